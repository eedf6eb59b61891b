"""Registers of persons, products and documents, dealt to parties with known overlap."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ringlink.spec import LinkageSpec

# The syllables of the derived person register.
HEAD = ["ba", "ce", "di", "fo", "gu", "ha", "je", "ki", "lo", "mu", "na", "pe", "ri", "so", "tu", "va"]
TAIL = ["ber", "cal", "din", "fos", "gar", "hen", "jul", "kam", "lin", "mor", "nel", "pat", "ros", "sten", "tol", "vik"]


def _digit(text: Column, at: int) -> Column:
    return F.conv(F.substring(text, at, 1), 16, 10).cast("int")


def _pick(words: list[str], digit: Column) -> Column:
    return F.element_at(F.array(*map(F.lit, words)), digit + 1)


def deal(rows: DataFrame, parties: int) -> DataFrame:
    """rows (entity, ...) -> one row per party that holds it, with party and rid.

    Key modulo P+1 = 0 is in every register, = i in that of party i alone, so half of each register is shared.
    """
    r = F.pmod(F.col("entity"), F.lit(parties + 1)).cast("int")
    holders = F.when(r == 0, F.sequence(F.lit(1), F.lit(parties))).otherwise(F.array(r))
    letters = F.array(*(F.lit(chr(65 + i)) for i in range(parties)))
    dealt = rows.withColumn("party", F.explode(holders))
    return dealt.withColumn("rid", F.concat_ws("-", F.element_at(letters, F.col("party")), F.col("entity").cast("string")))


def make_register(people: DataFrame, parties: int) -> DataFrame:
    """people (entity, nation) -> party, entity, given, surname, suburb, postcode, rid."""
    e, n = F.md5(F.concat(F.lit("e"), F.col("entity").cast("string"))), F.md5(F.concat(F.lit("n"), F.col("nation").cast("string")))
    named = people.select(
        "entity",
        F.concat(_pick(HEAD, _digit(e, 1)), _pick(TAIL, _digit(e, 2))).alias("given"),
        F.concat(_pick(TAIL, _digit(e, 3)), _pick(HEAD, _digit(e, 4)), _pick(TAIL, _digit(e, 5))).alias("surname"),
        F.concat(_pick(TAIL, _digit(n, 1)), _pick(HEAD, _digit(n, 2)), F.lit("ton")).alias("suburb"),
        (F.lit(20000) + F.col("nation") * 389 + _digit(e, 6)).cast("string").alias("postcode"),
    )
    return deal(named, parties)


def keyed_people(keys: DataFrame) -> DataFrame:
    """keys (entity) -> people (entity, nation) for keys without a nation of their own."""
    h = F.conv(F.substring(F.md5(F.concat(F.lit("nat"), F.col("entity").cast("string"))), 1, 8), 16, 10).cast("long")
    return keys.select("entity", (h % 25).cast("int").alias("nation"))


def product_register(part: DataFrame, parties: int) -> DataFrame:
    """Products as records: few names, so blocks are skewed and many entities agree on all attributes."""
    rows = part.select(F.col("p_partkey").alias("entity"), F.col("p_name").alias("name"), F.col("p_brand").alias("brand"), F.col("p_type").alias("kind"), F.col("p_size").cast("string").alias("size"))
    return deal(rows, parties)


def document_register(docs: DataFrame, parties: int, signs: int = 200) -> DataFrame:
    """Documents as records, one party each: the first `signs` signs of the collapsed, lower-cased text, and the language."""
    text = F.lower(F.trim(F.regexp_replace(F.coalesce("text", F.lit("")), "[ \\t\\r\\n]+", " ")))
    party = (F.pmod("doc_id", F.lit(parties)) + 1).cast("int")
    letters = F.array(*(F.lit(chr(65 + i)) for i in range(parties)))
    rows = docs.select(party.alias("party"), F.col("doc_id").alias("entity"), F.substring(text, 1, signs).alias("head"), F.coalesce("lang", F.lit("")).alias("lang"))
    return rows.withColumn("rid", F.concat_ws("-", F.element_at(letters, F.col("party")), F.col("entity").cast("string")))


def true_sets(register: DataFrame, spec: LinkageSpec) -> DataFrame:
    """cand of every entity that all parties hold, whatever blocking does to it."""
    held = register.groupBy("entity").agg(F.count("*").alias("n"), F.array_join(F.array_sort(F.collect_list("rid")), ",").alias("cand"))
    return held.where(F.col("n") == spec.parties).select("cand")


def size_series(people: DataFrame, sizes: tuple[int, ...], parties: int) -> DataFrame:
    """size, party, n, shared: register sizes for growing key ranges, counted without building the records."""
    held = deal(people.select("entity"), parties).select("party", "entity")
    steps = held.withColumn("size", F.explode(F.array(*map(F.lit, sizes)))).where("entity <= size")
    shared = F.count_if(F.pmod("entity", F.lit(parties + 1)) == 0)
    return steps.groupBy("size", "party").agg(F.count("*").alias("n"), shared.alias("shared"))
