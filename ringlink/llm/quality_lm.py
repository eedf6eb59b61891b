"""Quality by perplexity: an interpolated modified Kneser-Ney character n-gram model of trusted text.

A character is a UTF-16 unit, so that a gram of four is one long. Counts, contexts and probabilities are tables in
shards, met by joins; no table of grams is broadcast or reaches the driver. Texts are scored in blocks: a block's
distinct grams ask the shards once, and the answers return to the block.
"""

from __future__ import annotations

import functools
import json

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ringlink.llm.common import hot_join, settle

ORDER = 4
BITS = 16
#: Units worked on at once, whatever a text's length.
WINDOW = 1_000_000
_PACK = zstandard.ZstdCompressor(level=9)
_OPEN = zstandard.ZstdDecompressor()


def _units(text: str | None) -> np.ndarray:
    return np.frombuffer((" " * (ORDER - 1) + (text or "") + " ").encode("utf-16-le", "surrogatepass"), np.uint16)


def _grams(units: np.ndarray) -> np.ndarray:
    """The gram of four that ends at each unit from the fourth on."""
    u, n = units.astype(np.uint64), len(units) - ORDER + 1
    return functools.reduce(lambda g, i: (g << np.uint64(BITS)) | u[i : i + n], range(1, ORDER), u[:n])


def _windows(texts):
    """(place, grams) of the texts, by windows of a long text."""
    for i, t in enumerate(texts):
        u = _units(t)
        for at in range(0, len(u) - ORDER + 1, WINDOW):
            yield i, _grams(u[at : at + WINDOW + ORDER - 1])


def _batched(texts):
    """(places, lengths, grams) of texts until a window is full."""
    where, grams, size = [], [], 0
    for i, g in _windows(texts):
        where.append(i), grams.append(g)
        size += len(g)
        if size >= WINDOW:
            yield where, grams
            where, grams, size = [], [], 0
    if where:
        yield where, grams


def _distinct(texts) -> tuple[np.ndarray, np.ndarray]:
    """The texts' distinct grams, in order, and their counts."""
    seen, n = np.zeros(0, np.uint64), np.zeros(0, np.int64)
    for _, grams in _batched(texts):
        new, m = np.unique(np.concatenate(grams), return_counts=True)
        both, at = np.unique(np.concatenate([seen, new]), return_inverse=True)
        n, seen = np.bincount(at, np.concatenate([n, m]), len(both)).astype(np.int64), both
    return seen, n


def _orders(grams: np.ndarray) -> list[np.ndarray]:
    """By order from 0 to 4 the grams that scoring `grams` may need: endings and contexts."""
    out = [grams]
    for k in range(ORDER - 1, -1, -1):
        out.append(np.unique(np.concatenate([out[-1] & np.uint64((1 << BITS * k) - 1), out[-1] >> np.uint64(BITS)])))
    return out[::-1]


def _pack(a: np.ndarray) -> bytes:
    return _PACK.compress(a.tobytes())


def _open(b: bytes, kind) -> np.ndarray:
    return np.frombuffer(_OPEN.decompress(b), kind)


def _packed(batches):
    """(block, piece): rows of a block that are read together, compressed."""
    held: dict = {}
    size = 0
    for b in batches:
        for block, *row in zip(*(b.column(c).to_pylist() for c in ("block", "doc_id", "lang", "text")), strict=True):
            held.setdefault(block, []).append(row)
            size += len(row[2] or "") + 40
            if size > 4 * WINDOW:
                yield _pieces(held)
                held, size = {}, 0
    yield _pieces(held)


def _pieces(held: dict) -> pa.RecordBatch:
    packed = [_PACK.compress(json.dumps(rows, ensure_ascii=False).encode("utf-8", "surrogatepass")) for rows in held.values()]
    return pa.RecordBatch.from_arrays([pa.array(list(held), pa.int64()), pa.array(packed, pa.binary())], names=["block", "piece"])


def _by_lang(pieces: pa.Table) -> dict:
    """lang -> (doc_ids, texts) of a block; null is the language ''."""
    out: dict = {}
    for piece in pieces.column("piece").to_pylist():
        for i, lang, text in json.loads(_OPEN.decompress(piece).decode("utf-8", "surrogatepass")):
            ids, langs, texts = out.setdefault(lang or "", ([], [], []))
            ids.append(i), langs.append(lang), texts.append(text)
    return out


def _half(block: int, lang: str, other: bool = False) -> str:
    """The key of a model: the half of the blocks that it learns from, and the language."""
    return f"{(block + other) % 2}:{lang}"


def _table(rows: list, schema: pa.Schema) -> pa.Table:
    return pa.table([pa.array([r[i] for r in rows], f.type) for i, f in enumerate(schema)], schema=schema)


MET = "block long, lang string, k int, shard int, grams binary, n binary"
_MET = pa.schema([("block", pa.int64()), ("lang", pa.string()), ("k", pa.int32()), ("shard", pa.int32()), ("grams", pa.binary()), ("n", pa.binary())])


def _mixed(g: np.ndarray) -> np.ndarray:
    return (g ^ (g >> np.uint64(17)) ^ (g >> np.uint64(31))) & np.uint64((1 << 40) - 1)


def _shard_of(gram, shards: int):
    """The column counterpart of `_mixed`, modulo shards."""
    return ((gram.bitwiseXOR(F.shiftrightunsigned(gram, 17)).bitwiseXOR(F.shiftrightunsigned(gram, 31))).bitwiseAND(F.lit((1 << 40) - 1)) % shards).cast("int")


def _gathering(shards: int):
    def gather(key, pieces: pa.Table, marks: pa.Table) -> pa.Table:
        """A block's counts over trusted texts (n given), and what it asks of each shard (n null)."""
        rows, good, block = [], set(marks.column("doc_id").to_pylist()), key[0].as_py()
        for lang, (ids, _, texts) in _by_lang(pieces).items():
            trusted, n = _distinct(t for i, t in zip(ids, texts, strict=True) if i in good)
            if len(trusted):
                rows.append((block, _half(block, lang), ORDER, -1, _pack(trusted), _pack(n)))
            others, _ = _distinct(t for i, t in zip(ids, texts, strict=True) if i not in good)
            for k, grams in enumerate(_orders(np.union1d(trusted, others))):
                at = _mixed(grams) % np.uint64(shards)
                rows += [(block, _half(block, lang, other=True), k, int(s), _pack(grams[at == s]), None) for s in np.unique(at)]
        return _table(rows, _MET)

    return gather


def _counted(batches):
    for b in batches:
        for lang, grams, n in zip(*(b.column(c).to_pylist() for c in ("lang", "grams", "n")), strict=True):
            g, m = _open(grams, np.int64), _open(n, np.int64)
            yield pa.RecordBatch.from_arrays([pa.array([lang] * len(g), pa.string()), pa.array(g), pa.array(m)], names=["lang", "gram", "n"])


def model(counts: DataFrame) -> DataFrame:
    """(lang, k, gram, p, back) of the grams of order k from 0 to 4 of trusted text, from the counts (lang, gram, n) of four units.

    p is the probability of a gram's last unit after those before it, null where the gram is a context only; back is
    its weight of the lower order as a context, null where it is none. Orders below the highest count distinct left
    neighbours; each order of each language has three discounts from its counts of counts. Order 0 spreads over the
    language's units and one for all it lacks.
    """
    level = counts.select("lang", F.lit(ORDER).alias("k"), "gram", "n")
    tables = [level]
    for k in range(ORDER - 1, 0, -1):
        tables.append(tables[-1].groupBy("lang", F.lit(k).alias("k"), F.col("gram").bitwiseAND(F.lit((1 << BITS * k) - 1)).alias("gram")).agg(F.count("*").alias("n")))
    every = settle(functools.reduce(DataFrame.union, tables).withColumn("lk", F.concat(F.col("k"), F.lit(":"), F.col("lang"))))
    of = every.groupBy(F.col("lk").alias("of_lk")).agg(F.count("*").alias("types"), *(F.count_if(F.col("n") == i).alias(f"t{i}") for i in (1, 2, 3, 4)))
    y = F.coalesce(F.try_divide(F.col("t1"), F.col("t1") + 2 * F.col("t2")), F.lit(0.0))
    d = lambda i: F.greatest(F.lit(0.05), F.least(F.lit(i - 0.05), F.coalesce(i - (i + 1) * y * F.try_divide(f"t{i + 1}", f"t{i}"), F.lit(i * 0.5))))
    of = settle(of.select("of_lk", (1 / (F.col("types") + 1)).alias("flat"), *(d(i).alias(f"d{i}") for i in (1, 2, 3))))
    cut = hot_join(every, of, "lk", "of_lk").withColumn("d", F.when(F.col("n") == 1, F.col("d1")).when(F.col("n") == 2, F.col("d2")).otherwise(F.col("d3")))
    cut = settle(cut.select("lang", "k", "gram", "n", "d", "flat", F.shiftrightunsigned("gram", BITS).alias("ctx")))
    ctx = settle(cut.groupBy("lang", "k", "ctx").agg(F.sum("n").alias("of_ctx"), (F.sum("d") / F.sum("n")).alias("back"), F.max("flat").alias("flat")))
    own = cut.join(ctx.drop("flat"), ["lang", "k", "ctx"]).select("lang", "k", "gram", ((F.col("n") - F.col("d")) / F.col("of_ctx")).alias("own"), "back", "flat")
    own = settle(own)
    orders = [ctx.where("k = 1").select("lang", F.lit(0).alias("k"), F.lit(0).cast("long").alias("gram"), F.col("flat").alias("p"))]
    for k in range(1, ORDER + 1):
        low = orders[-1].select("lang", F.col("gram").alias("short"), F.col("p").alias("low"))
        short = F.col("gram").bitwiseAND(F.lit((1 << BITS * (k - 1)) - 1))
        high = own.where(F.col("k") == k)
        if k == 1:
            orders.append(high.select("lang", "k", "gram", (F.col("own") + F.col("back") * F.col("flat")).alias("p")))
        else:
            orders.append(settle(high.withColumn("short", short).join(low, ["lang", "short"]).select("lang", "k", "gram", (F.col("own") + F.col("back") * F.col("low")).alias("p"))))
    grams = functools.reduce(DataFrame.union, orders).withColumn("back", F.lit(None).cast("double"))
    contexts = ctx.select("lang", (F.col("k") - 1).alias("k"), F.col("ctx").alias("gram"), F.lit(None).cast("double").alias("p"), "back")
    return settle(grams.union(contexts).groupBy("lang", "k", "gram").agg(F.max("p").alias("p"), F.max("back").alias("back")))


ANSWER = "block long, lang string, k int, grams binary, p binary, back binary"
_ANSWER = pa.schema([("block", pa.int64()), ("lang", pa.string()), ("k", pa.int32()), ("grams", pa.binary()), ("p", pa.binary()), ("back", pa.binary())])


def _answer(asked: pa.Table, shard: pa.Table) -> pa.Table:
    """What a shard knows of the grams that blocks ask for; NaN: nothing."""
    known: dict = {}
    lang, k = (shard.column(c).to_pandas().to_numpy() for c in ("lang", "k"))
    gram = shard.column("gram").to_numpy().view(np.uint64)
    p, back = (shard.column(c).to_pandas().to_numpy(np.float32) for c in ("p", "back"))
    for key in set(zip(lang, k, strict=True)):
        at = np.nonzero((lang == key[0]) & (k == key[1]))[0]
        at = at[np.argsort(gram[at])]
        known[key] = gram[at], p[at], back[at]
    rows = []
    for block, lang_, k_, packed in zip(*(asked.column(c).to_pylist() for c in ("block", "lang", "k", "grams")), strict=True):
        if (lang_, k_) not in known:
            continue
        have, p_, back_ = known[lang_, k_]
        grams = _open(packed, np.uint64)
        at = np.minimum(np.searchsorted(have, grams), len(have) - 1)
        found = have[at] == grams
        if found.any():
            at = at[found]
            rows.append((block, lang_, k_, _pack(grams[found]), _pack(p_[at]), _pack(back_[at]) if k_ < ORDER else None))
    return _table(rows, _ANSWER)


def resolve(grams: np.ndarray, answers: dict) -> np.ndarray | None:
    """The probability of each of the grams of four, from answers {k: (grams, p, back)} in order; None without a model.

    An unseen gram takes the next lower order at its context's weight, or at weight 1 where the context is unseen too.
    """
    if 0 not in answers:
        return None
    asked = _orders(grams)
    low, back = np.full(len(asked[0]), np.nan), None
    for k, g in enumerate(asked):
        p, b = np.full(len(g), np.nan), np.ones(len(g))
        if k in answers:
            have, p_, b_ = answers[k]
            at = np.minimum(np.searchsorted(have, g), len(have) - 1)
            found = have[at] == g
            p[found] = p_[at[found]]
            b[found] = np.nan_to_num(b_[at[found]], nan=1.0) if b_ is not None else 1.0
        if k:
            before = asked[k - 1]
            short, ctx = g & np.uint64((1 << BITS * (k - 1)) - 1), g >> np.uint64(BITS)
            p = np.where(np.isnan(p), back[np.searchsorted(before, ctx)] * low[np.searchsorted(before, short)], p)
        low, back = p, b
    return low


SCORED = "doc_id long, lang string, perplexity double"
_SCORED = pa.schema([("doc_id", pa.int64()), ("lang", pa.string()), ("perplexity", pa.float64())])


def _scoring(key, pieces: pa.Table, answers: pa.Table) -> pa.Table:
    known: dict = {}
    for lang, k, *packed in zip(*(answers.column(c).to_pylist() for c in ("lang", "k", "grams", "p", "back")), strict=True):
        known.setdefault((lang, k), []).append([None if x is None else _open(x, t) for x, t in zip(packed, (np.uint64, np.float32, np.float32), strict=True)])
    merged: dict = {}
    for (lang, k), parts in known.items():
        grams = np.concatenate([x[0] for x in parts])
        at = np.argsort(grams)
        merged.setdefault(lang, {})[k] = (grams[at], *(None if parts[0][i] is None else np.concatenate([x[i] for x in parts])[at] for i in (1, 2)))
    out: list = []
    for lang, (ids, langs, texts) in _by_lang(pieces).items():
        total, size = np.zeros(len(ids)), np.zeros(len(ids))
        model_ = merged.get(_half(key[0].as_py(), lang, other=True), {})
        if 0 in model_:
            for where, grams in _batched(texts):
                g, at = np.unique(np.concatenate(grams), return_inverse=True)
                log = np.log(resolve(g, model_))[at]
                lengths = [len(x) for x in grams]
                np.add.at(total, where, np.add.reduceat(log, np.cumsum([0, *lengths[:-1]])))
                np.add.at(size, where, lengths)
        out += [(i, x, float(np.exp(-t / n)) if n else None) for i, x, t, n in zip(ids, langs, total, size, strict=True)]
    return _table(out, _SCORED)


def score(docs: DataFrame, labels: DataFrame, quantile: float = 0.995, block: int = 12_000_000) -> DataFrame:
    """doc_id, lang, perplexity, threshold, kept of docs (doc_id, text, lang), one row each.

    Trusted text: documents labelled quality 1, all of them. Two models learn from the trusted texts of one half of the
    blocks each, and score the other half, so no text is scored by what it taught and trusted texts are measured as
    all others are. A document is rejected where its perplexity is over its language's trusted `quantile`; without a
    trusted document of its language in the other half it has no perplexity and stays. Null and empty texts are
    scored as one space; a null language is the language ''. Rows are dealt to blocks of about `block` characters by
    a hash of id and text; a text longer than that is a block's by itself, worked on in windows. Rows equal in both
    meet in one block. A shard holds what a thousand blocks add to the model; its copies serve eight blocks each.
    """
    d = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", "lang")
    # labels grow with the documents: no broadcast; only ids move
    good = labels.where("quality = 1").select(F.col("doc_id").cast("long").alias("doc_id")).distinct().hint("shuffle_hash")
    blocks = 2 + (d.agg(F.sum(F.length("text"))).first()[0] or 0) // (2 * block) * 2  # even: two halves
    shards, salts = 1 + blocks // 1000, 1 + blocks // 8
    placed = d.withColumn("block", F.pmod(F.xxhash64("doc_id", "text"), F.lit(blocks)))
    marks = placed.select("doc_id", "block").join(good, "doc_id", "left_semi").distinct()
    pieces = placed.mapInArrow(_packed, "block long, piece binary").groupBy("block")
    met = settle(pieces.cogroup(marks.groupBy("block")).applyInArrow(_gathering(shards), MET))
    counts = settle(met.where("n IS NOT NULL").select("lang", "grams", "n").mapInArrow(_counted, "lang string, gram long, n long").groupBy("lang", "gram").agg(F.sum("n").alias("n")))
    asked = met.where("n IS NULL").withColumn("salt", F.pmod("block", F.lit(salts)).cast("int")).drop("n")
    copied = model(counts).withColumn("shard", _shard_of(F.col("gram"), shards)).withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    answers = asked.groupBy("shard", "salt").cogroup(copied.groupBy("shard", "salt")).applyInArrow(_answer, ANSWER)
    scored = settle(pieces.cogroup(answers.groupBy("block")).applyInArrow(_scoring, SCORED).withColumn("_lang", F.coalesce("lang", F.lit(""))))
    limits = scored.join(good, "doc_id", "left_semi").groupBy(F.col("_lang").alias("_of")).agg(F.percentile_approx("perplexity", quantile, 10_000).alias("threshold"))
    out = hot_join(scored, settle(limits), "_lang", "_of")
    return out.select("doc_id", "lang", "perplexity", "threshold", F.coalesce(F.col("perplexity") <= F.col("threshold"), F.lit(True)).alias("kept"))
