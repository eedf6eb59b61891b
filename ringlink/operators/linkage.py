"""The protocol from register to matches."""

from __future__ import annotations

from functools import reduce
from itertools import combinations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ringlink.operators import blocking, blockwise, compare, ring
from ringlink.operators.encoding import encode_register
from ringlink.operators.exchange import exchange_segments, record_tokens
from ringlink.plans.physical import settle
from ringlink.spec import LinkageSpec

MODES = {"approx": None, "approx_filtered": "prefix", "final": "final", "bound": "bound"}


def counts(view: DataFrame, spec: LinkageSpec, mode: str = "approx", order: str = "id") -> DataFrame:
    if mode == "bound":
        return compare.bounded_counts(view, spec)
    return compare.partial_counts(view, spec, MODES[mode], order)


def classify(totals: DataFrame, spec: LinkageSpec, key: str, initiator: str = "one") -> DataFrame:
    """r1..rP, c, x, sim of the closed rings whose P-way Dice, unmasked by their initiator, reaches s_t."""
    num, den = spec.threshold
    read = ring.unmask(totals, key, initiator)
    hit = read.where((F.col("x") > 0) & (den * spec.parties * F.col("c") >= num * F.col("x")))
    ids = [f"r{j}" for j in range(1, spec.parties + 1)]
    return hit.select(*ids, *(c for c in totals.columns if c.startswith("name")), "c", "x", F.round(spec.parties * F.col("c") / F.col("x"), 6).alias("sim"))


def readable(matches: DataFrame, tokens: DataFrame, spec: LinkageSpec) -> DataFrame:
    """cand, c, x, sim: each owner reads its own tokens in the results handed out."""
    ids = [f"r{j}" for j in range(1, spec.parties + 1)]
    rows = matches.select("c", "x", "sim", candidate_id(spec).alias("_id"), F.posexplode(F.array(*ids)).alias("_at", "token"))
    found = rows.join(tokens.select((F.col("party") - 1).alias("_at"), "token", "rid"), ["_at", "token"])
    whole = found.groupBy("_id").agg(F.first("c").alias("c"), F.first("x").alias("x"), F.first("sim").alias("sim"), F.array_sort(F.collect_list(F.struct("_at", "rid"))).alias("m"))
    return whole.select(F.concat_ws(",", "m.rid").alias("cand"), "c", "x", "sim")


def named_matches(matches: DataFrame, spec: LinkageSpec) -> DataFrame:
    """cand, c, x, sim of matches that carry what each owner calls its record: no match is joined or grouped."""
    return matches.select(F.concat_ws(",", *(f"name{j}" for j in range(1, spec.parties + 1))).alias("cand"), "c", "x", "sim")


def candidate_id(spec: LinkageSpec) -> Column:
    return ring.candidate(spec)


def link_encoded(encoded: DataFrame, spec: LinkageSpec, mode: str = "approx", key: str = "k1", initiator: str = "one", order: str = "id") -> DataFrame:
    """cand, c, x, sim from encoded records (party, rid, bkv, b0.., x_own): exchange, counts, ring, classification.

    With the order `id`, approx and approx_filtered have all holders' counts of a candidate in one row and leave out
    sets that cannot reach s_t; the other modes go through the view.
    """
    encoded = settle(encoded)
    if mode in ("approx", "approx_filtered") and order == "id":
        joint = compare.joint_counts(encoded, spec, MODES[mode], "dice")
        return named_matches(classify(ring.joint_totals(joint, spec, key, initiator), spec, key, initiator), spec)
    view = settle(exchange_segments(encoded, spec))
    totals = ring.ring_totals(counts(view, spec, mode, order), spec, key, initiator)
    return readable(classify(totals, spec, key, initiator), record_tokens(encoded, spec), spec)


def link(register: DataFrame, spec: LinkageSpec, mode: str = "approx", key: str = "k1", initiator: str = "one", most: float | None = None, finer: str | None = None) -> DataFrame:
    """The whole protocol. mode: approx, approx_filtered, final or bound.

    With `most`, blocks of more candidate sets are cut by the attribute `finer` first (nothing is dropped).
    """
    encoded = encode_register(register, spec)
    if most is not None:
        encoded = blocking.split_blocks(encoded.join(register.select("party", "rid", F.col(finer).alias("_finer")), ["party", "rid"]), spec.parties, most, "_finer").drop("_finer")
    return link_encoded(encoded, spec, mode, key, initiator)


def link_subsets(register: DataFrame, spec: LinkageSpec, least: int) -> DataFrame:
    """subset, cand, sim: matches of every choice of `least` parties or more, each choice by central Dice of its filters."""
    encoded = settle(encode_register(register, spec))
    out = []
    for size in range(least, spec.parties + 1):
        for chosen in combinations(range(1, spec.parties + 1), size):
            dealt = reduce(DataFrame.unionByName, (encoded.where(F.col("party") == p).withColumn("party", F.lit(i)) for i, p in enumerate(chosen, 1)))
            found = central(dealt, spec, size)
            out.append(found.select(F.lit("+".join(map(str, chosen))).alias("subset"), "cand", "sim"))
    return reduce(DataFrame.unionByName, out)


def central(encoded: DataFrame, spec: LinkageSpec, parties: int | None = None, kind: str = "dice", keep_all: bool = False) -> DataFrame:
    """cand, c, x, sim of what one trusted party finds with whole filters in its hands."""
    from ringlink.operators.encoding import bit_columns

    p = parties or spec.parties
    bits = bit_columns(spec)
    num, den = spec.threshold
    if kind in blockwise.KINDS and not keep_all:
        sets, sizes = blockwise.sets_reaching(encoded, p, bits, spec.threshold, kind), [f"x{j}" for j in range(1, p + 1)]
        cand, c = F.concat_ws(",", *(f"rid{j}" for j in range(1, p + 1))).alias("cand"), F.col("c1")
        sim = compare.counted_similarity(c, sizes, kind)
    else:
        groups, sizes = [[f"{b}_{j}" for b in bits] for j in range(1, p + 1)], [f"x_own_{j}" for j in range(1, p + 1)]
        sets = blocking.enumerate_candidates(encoded, p, (*bits, "x_own"), None if keep_all else lambda j: _reaches(groups[:j], num, den))
        cand, c, sim = blocking.named(p), compare._fold(groups, "and"), compare.similarity(groups, sizes, kind)
    x = reduce(lambda a, b: a + b, (F.col(s) for s in sizes)).cast("long").alias("x")
    rows = sets.select(cand, c.cast("long").alias("c"), x, sim.alias("sim"))
    if not keep_all:
        rows = rows.where(den * p * F.col("c") >= num * F.col("x")).where("x > 0") if kind == "dice" else rows.where(F.col("sim") * den >= num - 1e-12)
    return rows.withColumn("sim", F.round("sim", 6))


def _reaches(groups: list[list[str]], num: int, den: int) -> Column:
    """Whether a prefix of a set can still reach a jaccard of num/den: common bits shrink and bits of any grow with every record."""
    return den * compare._fold(groups, "and") >= num * (1 - 1e-9) * compare._fold(groups, "or")


def best_per_record(matches: DataFrame, parties: int) -> DataFrame:
    """Matches that are the best of each of their records; ties go to the smaller `cand`.

    Each record's best is an aggregate (map-side combined), met again by an equi-join: no record's matches are sorted.
    """
    rank = F.struct((-F.col("sim")).alias("s"), F.col("cand").alias("k"))
    parts = matches.select("cand", rank.alias("rank"), F.explode(F.split("cand", ",")).alias("rid"))
    best = parts.groupBy("rid").agg(F.min("rank").alias("top"))
    won = best.groupBy(F.col("top.k").alias("cand")).agg(F.count("*").alias("wins")).where(F.col("wins") == parties).select("cand")
    return matches.join(won, "cand", "left_semi")


def top_matches(matches: DataFrame, blocks: DataFrame, k: int) -> DataFrame:
    """bkv, rank, cand, sim: the k best matches of each block. blocks: rid, bkv of the first party."""
    rows = matches.withColumn("rid", F.substring_index("cand", ",", 1)).join(blocks, "rid")
    place = F.row_number().over(W.partitionBy("bkv").orderBy(F.desc("sim"), "cand"))
    return rows.withColumn("rank", place).where(F.col("rank") <= k).select("bkv", "rank", "cand", "sim")
