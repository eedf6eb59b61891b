"""Quality rules as a bitmask ledger: measure once, keep failure bits, apply any policy later."""

from __future__ import annotations

import re
from collections import Counter

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType

from ringlink.llm.common import lean, shield

_SYMBOL = re.compile(r"[#*$%&|<>]")
_SPACE = re.compile("[\x20\x09-\x0d]")
MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines")
SCHEMA = "doc_id long, " + ", ".join(f"{m} long" for m in MEASURES)


def measure(text: str | None) -> tuple[int, ...]:
    """The measures of one whole text; null counts as empty."""
    text = text or ""
    words = text.encode("utf-8", "surrogatepass").split()
    n = len(words)
    lines = [x for x in text.split("\n") if _SPACE.sub("", x)]
    repeated = 0
    if n >= 3:
        windows = list(zip(words, words[1:], words[2:]))
        if len(set(windows)) < n - 2:
            twice = {k for k, v in Counter(windows).items() if v > 1}
            until = 0
            for i, window in enumerate(windows):
                if window in twice:
                    repeated += i + 3 - max(i, until)
                    until = i + 3
    return n, len(text) - len(_SPACE.findall(text)), len(_SYMBOL.findall(text)), len(lines) - len(set(lines)), repeated, len(lines)


def _measured(batches):
    for batch in batches:
        rows = list(zip(*map(measure, batch.column("text").to_pylist()), strict=True)) or [[]] * len(MEASURES)
        yield pa.RecordBatch.from_arrays([batch.column("doc_id").cast(pa.int64()), *(pa.array(x, pa.int64()) for x in rows)], names=["doc_id", *MEASURES])


def rules() -> list[tuple[str, Column]]:
    """(name, failed) in the order of the ledger's bits; never null."""
    c = F.col
    return [
        ("too_short", c("n_words") < 50),
        ("repeated_windows", 100 * c("n_repeat_words") > 50 * c("n_words")),
        ("symbols", 10 * c("n_symbols") > 5 * c("n_words")),
        ("duplicate_lines", (c("n_lines") >= 4) & (100 * c("n_dup_lines") > 50 * c("n_lines"))),
        ("word_length", (c("word_chars") > 20 * c("n_words")) | (c("word_chars") < 2 * c("n_words"))),
        ("nearly_empty", c("n_words") < 5),
    ]


#: Versions of the policy: the bits that reject a document. "corpus" keeps short documents, which are mostly clean.
POLICIES = {"base": 0b000011, "v1": 0b011111, "corpus": 0b111110}


def ledger(docs: DataFrame) -> DataFrame:
    """doc_id, the measures and `failures`, one bit per rule; each rule is evaluated once."""
    return docs.select("doc_id", "text").mapInArrow(_measured, SCHEMA).withColumn("failures", failures())


def failures() -> Column:
    """One bit per rule that fails, from the measures."""
    bits = F.lit(0)
    for i, (_, failed) in enumerate(rules()):
        bits = bits.bitwiseOR(F.when(failed, F.lit(1 << i)).otherwise(F.lit(0)))
    return bits.cast("long")


def verdict(policy: str = "v1") -> Column:
    return F.col("failures").bitwiseAND(F.lit(POLICIES[policy])) == 0


def ablation(book: DataFrame, policy: str = "v1") -> DataFrame:
    """(rule, failed, only): how many documents each rule rejects, and how many it alone does."""
    mask = POLICIES[policy]
    names = [n for n, _ in rules()]
    pick = [F.struct(F.lit(n).alias("rule"), (F.col("failures").bitwiseAND(F.lit(1 << i)) != 0).cast("long").alias("failed"), (F.col("failures").bitwiseAND(F.lit(mask)) == (1 << i)).cast("long").alias("only")) for i, n in enumerate(names) if mask >> i & 1]
    return book.select(F.explode(F.array(*pick)).alias("p")).groupBy("p.rule").agg(F.sum("p.failed").alias("failed"), F.sum("p.only").alias("only"))


def keep(docs: DataFrame, policy: str = "v1") -> DataFrame:
    """The rows of docs that the policy keeps, each judged by its own text, columns as they were.

    Texts pass the measuring once, with their row: nothing is joined or shuffled. Null text counts as empty.
    """
    rows, back = shield(docs, "text")

    def run(batches):
        for b in batches:
            cols = list(zip(*map(measure, b.column("text").to_pylist()), strict=True)) or [[]] * len(MEASURES)
            yield pa.RecordBatch.from_arrays([*b.columns, *(pa.array(x, pa.int64()) for x in cols)], names=[*b.schema.names, *MEASURES])

    schema = StructType([*rows.schema.fields, *(StructField(m, LongType()) for m in MEASURES)])
    return rows.mapInArrow(lean(run), schema).withColumn("failures", failures()).where(verdict(policy)).select(*back)


def digest(docs: DataFrame) -> DataFrame:
    book = ledger(docs)
    base = F.col("failures").bitwiseAND(F.lit(POLICIES["base"])) != 0
    return book.select("doc_id", *MEASURES[:5], base.alias("base_failed"), verdict().alias("kept"), "failures")
