"""Quality, pruning, cost and privacy measures."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ringlink.operators.encoding import record_grams
from ringlink.operators.exchange import word_columns
from ringlink.spec import LinkageSpec


def fill_ratio(encoded: DataFrame, spec: LinkageSpec) -> DataFrame:
    return encoded.groupBy("party").agg(F.count("*").alias("n"), F.round(F.sum("x_own") / (F.count("*") * spec.bits), 6).alias("fill"))


# Quality


def quality(matches: DataFrame, truth: DataFrame) -> DataFrame:
    """tp, fp, fn, precision, recall, f1 over whole sets; both sides have a unique `cand`."""
    both = matches.select("cand", F.lit(1).alias("m")).join(truth.select("cand", F.lit(1).alias("t")), "cand", "full_outer")
    n = both.agg(F.count_if(F.col("m").isNotNull() & F.col("t").isNotNull()).alias("tp"), F.count_if(F.col("t").isNull()).alias("fp"), F.count_if(F.col("m").isNull()).alias("fn"))
    r = lambda a, b: F.round(F.try_divide(a, b), 6)
    return n.withColumns({"precision": r(F.col("tp"), F.col("tp") + F.col("fp")), "recall": r(F.col("tp"), F.col("tp") + F.col("fn")), "f1": r(2 * F.col("tp"), 2 * F.col("tp") + F.col("fp") + F.col("fn"))})


def pairs_of(sets: DataFrame) -> DataFrame:
    """cand of every pair of records inside the sets, each pair once."""
    rows = sets.select(F.split("cand", ",").alias("r"))
    one = rows.select("r", F.posexplode("r").alias("i", "a")).select("a", F.explode(F.slice("r", F.col("i") + 2, F.size("r"))).alias("b"))
    return one.select(F.concat_ws(",", "a", "b").alias("cand")).distinct()


def within_blocks(truth: DataFrame, rows: DataFrame) -> DataFrame:
    """The true sets whose records share one block: what blocking leaves to be found. rows: rid, bkv."""
    parts = truth.select("cand", F.explode(F.split("cand", ",")).alias("rid")).join(rows.select("rid", "bkv"), "rid")
    return parts.groupBy("cand").agg(F.countDistinct("bkv").alias("blocks")).where("blocks = 1").select("cand")


# Pruning


def reduction_ratio(register: DataFrame, candidates: DataFrame) -> DataFrame:
    """candidates, rr from one row `candidates`: the share of the parties' full product that blocking leaves out."""
    n = register.groupBy("party").agg(F.count("*").alias("n"))
    full = n.agg(F.aggregate(F.collect_list("n"), F.lit(1.0), lambda a, x: a * x).alias("full"))  # a row a party
    return candidates.crossJoin(full).select("candidates", F.round(1 - F.col("candidates") / F.col("full"), 6).alias("rr"))  # one row each


def filter_reduction(kept: DataFrame, candidates: DataFrame, spec: LinkageSpec) -> DataFrame:
    """holder, kept, before, rr_f: each holder's ratio; holder 0 is their mean, -1 what is left of all of them together."""
    ids = [f"r{j}" for j in range(1, spec.parties + 1)]
    held = kept.groupBy("holder").agg(F.count("*").alias("kept"))
    every = kept.sparkSession.range(1, spec.parties + 1).select(F.col("id").cast("int").alias("holder"))
    per = every.join(held, "holder", "left").select("holder", F.coalesce("kept", F.lit(0)).cast("double").alias("kept"))
    mean = per.agg(F.lit(0).alias("holder"), F.avg("kept").alias("kept"))
    joint = kept.groupBy(*ids).agg(F.count("*").alias("n")).agg(F.lit(-1).alias("holder"), F.count_if(F.col("n") == spec.parties).cast("double").alias("kept"))
    rows = per.unionByName(mean).unionByName(joint).crossJoin(candidates)  # one row
    return rows.select("holder", F.round("kept", 6).alias("kept"), F.col("candidates").alias("before"), F.round(1 - F.try_divide("kept", "candidates"), 6).alias("rr_f"))


# Privacy


def suspicion(view: DataFrame, world: DataFrame, spec: LinkageSpec) -> DataFrame:
    """holder, owner, rid, n_g, p_s: how many records of the global database have each masked piece, and one over it (0 for none).

    The global side is counted first, so a frequent pattern is one row of the join.
    """
    words = word_columns(spec)
    known = world.groupBy("holder", *words).agg(F.count("*").alias("n_g"))
    rows = view.join(known, ["holder", *words], "left")
    return rows.select("holder", "owner", "rid", F.coalesce("n_g", F.lit(0)).cast("long").alias("n_g"), F.round(F.coalesce(1 / F.col("n_g"), F.lit(0.0)), 6).alias("p_s"))


def disclosure(view: DataFrame, spec: LinkageSpec) -> DataFrame:
    """dr_mean, dr_mark, dr_max where the global database is each owner's register itself: n_g is the size of a pattern's group."""
    groups = view.groupBy("holder", "owner", *word_columns(spec)).agg(F.count("*").alias("n"))
    return groups.agg(F.round(F.count("*") / F.sum("n"), 6).alias("dr_mean"), F.round(F.count_if(F.col("n") == 1) / F.sum("n"), 6).alias("dr_mark"), F.max(F.round(1 / F.col("n"), 6)).alias("dr_max"))


def disclosure_external(view: DataFrame, world: DataFrame, spec: LinkageSpec) -> DataFrame:
    """holder, dr_mean, dr_mark, dr_max against a global database that differs from the registers."""
    p = suspicion(view, world, spec)
    return p.groupBy("holder").agg(F.round(F.avg(F.when(F.col("n_g") > 0, 1 / F.col("n_g")).otherwise(0.0)), 6).alias("dr_mean"), F.round(F.count_if(F.col("n_g") == 1) / F.count("*"), 6).alias("dr_mark"), F.max("p_s").alias("dr_max"))


def frequency_attack(view: DataFrame, world: DataFrame, spec: LinkageSpec) -> DataFrame:
    """holder, patterns, hits, records: an attacker lines up patterns and global patterns by falling frequency.

    A hit is a pattern whose global namesake has the same rank; records counts the records that hits give away. Ties
    go by the pattern's words. Ranks come from counts of groups, one row a pattern.
    """
    words = word_columns(spec)

    def ranked(rows: DataFrame, name: str) -> DataFrame:
        groups = rows.groupBy("holder", *words).agg(F.count("*").alias(name))
        return groups.withColumn("rank", F.row_number().over(W.partitionBy("holder").orderBy(F.desc(name), *words)))

    mine, theirs = ranked(view, "n"), ranked(world, "g")
    met = mine.join(theirs, ["holder", "rank", *words], "left")
    return met.groupBy("holder").agg(F.count("*").alias("patterns"), F.count("g").alias("hits"), F.coalesce(F.sum(F.when(F.col("g").isNotNull(), F.col("n"))), F.lit(0)).alias("records"))


def bit_sensitivity(register: DataFrame, spec: LinkageSpec) -> DataFrame:
    """place, dist (distinct grams that set it), freq (records that have it), s = 1/min(dist, freq), null where never set.

    Distinct grams are few, so records are counted by gram first; only the pairs (record, place) of rare collisions
    need the distinct count.
    """
    from ringlink.operators.encoding import hash_positions

    grams = record_grams(register, spec).select("party", "rid", "gram").distinct()
    place = grams.select("gram").distinct().select("gram", F.explode(F.array_distinct(hash_positions(F.col("gram"), spec.bits, spec.hashes, spec.secret, spec.scheme))).alias("place"))
    dist = place.groupBy("place").agg(F.count("*").alias("dist"))
    freq = grams.join(place, "gram").select("party", "rid", "place").distinct().groupBy("place").agg(F.count("*").alias("freq"))
    every = register.sparkSession.range(spec.bits).select(F.col("id").alias("place"))
    rows = every.join(dist, "place", "left").join(freq, "place", "left")
    return rows.select("place", F.coalesce("dist", F.lit(0)).cast("long").alias("dist"), F.coalesce("freq", F.lit(0)).cast("long").alias("freq"), F.round(1 / F.least("dist", "freq"), 6).alias("s"))


def simulate_parameters(register: DataFrame, specs: list[LinkageSpec]) -> DataFrame:
    """l, k, q, unset, s_max, s_mean, s_one: the spread of bit sensitivity for each choice of parameters, before agreeing on one."""
    out = []
    for s in specs:
        one = bit_sensitivity(register, s)
        out.append(one.agg(F.lit(s.bits).alias("l"), F.lit(s.hashes).alias("k"), F.lit(s.q).alias("q"), F.count_if(F.col("freq") == 0).alias("unset"), F.max("s").alias("s_max"), F.round(F.avg("s"), 6).alias("s_mean"), F.count_if(F.col("s") == 1).alias("s_one")))
    return reduce(DataFrame.unionByName, out)


def initiator_view(partials: DataFrame, spec: LinkageSpec) -> DataFrame:
    """cand, rest_c, rest_x, c_high, x_low, x_high, shares_bits: what party 1 learns of the others in its rings.

    The ranges are those it can give without looking at bits: the others' pieces have (P-1)*l/P places together; a
    record with a gram has a bit at least and l at most.
    """
    ids = [f"r{j}" for j in range(1, spec.parties + 1)]
    rest = F.col("holder") > 1
    p = spec.parties
    rows = partials.groupBy(*ids).agg(F.sum(F.when(rest, F.col("c")).otherwise(0)).alias("rest_c"), F.sum(F.when(rest, F.col("x")).otherwise(0)).alias("rest_x"))
    return rows.select(F.concat_ws(",", *ids).alias("cand"), "rest_c", "rest_x", F.lit((p - 1) * spec.width).alias("c_high"), F.lit(p - 1).alias("x_low"), F.lit((p - 1) * spec.bits).alias("x_high"), (F.col("rest_c") > 0).alias("shares_bits"))


# Cost


def message_ledger(view: DataFrame, partials: DataFrame, spec: LinkageSpec) -> DataFrame:
    """step, messages, bytes of the exchange (pieces to others), the ring (two longs a hop) and the results, as counted."""
    ids = [f"r{j}" for j in range(1, spec.parties + 1)]
    size = -(-spec.width // 8) + 32 + 32  # piece and two tokens
    sent = view.where("holder <> owner").agg(F.lit("exchange").alias("step"), F.countDistinct("holder", "owner").alias("messages"), (F.count("*") * size).alias("bytes"))
    closed = partials.groupBy(*ids).agg(F.count("*").alias("n")).where(F.col("n") == spec.parties).agg(F.count("*").alias("n"))
    ring = closed.select(F.lit("ring").alias("step"), (F.col("n") * spec.parties).alias("messages"), (F.col("n") * spec.parties * 16).alias("bytes"))
    results = closed.select(F.lit("results").alias("step"), (F.col("n") * (spec.parties - 1)).alias("messages"), (F.col("n") * (spec.parties - 1) * 8).alias("bytes"))
    return sent.unionByName(ring).unionByName(results)


def ledger_model(spec: LinkageSpec, rows_per_party: int, candidates: int) -> dict[str, dict[str, int]]:
    """Messages and bytes of each step in closed form."""
    p = spec.parties
    return {
        "exchange": {"messages": p * (p - 1), "bytes": p * (p - 1) * rows_per_party * (-(-spec.width // 8) + 64)},
        "ring": {"messages": p * candidates, "bytes": 16 * p * candidates},
        "results": {"messages": (p - 1) * candidates, "bytes": 8 * (p - 1) * candidates},
    }


def cost_model(register: DataFrame, encoded: DataFrame, candidates: DataFrame, spec: LinkageSpec) -> DataFrame:
    """n, blocks, grams, hash_ops, hash_model, ands, ands_model: counted operations beside the closed forms.

    hash_ops counts k digests for every gram of every record; the model has the mean number of grams. ands counts the
    ANDs over candidates of all holders; the model has blocks of equal size.
    """
    grams = record_grams(register, spec).select("party", "rid", "gram").distinct().agg(F.count("*").alias("grams"))
    size = encoded.agg(F.count("*").alias("all"), F.countDistinct("bkv").alias("blocks"))
    rows = size.crossJoin(grams).crossJoin(candidates)  # one row each
    n, b, p = F.col("all") / spec.parties, F.col("blocks"), spec.parties
    mean = F.col("grams") / F.col("all")
    r = lambda c, name: F.round(c, 3).alias(name)
    return rows.select(r(n, "n"), b.alias("blocks"), r(mean, "grams"), (F.col("grams") * spec.hashes).alias("hash_ops"), r(n * p * mean * spec.hashes, "hash_model"), r(F.col("candidates") * p * (p - 1), "ands"), r(b * F.pow(n / b, F.lit(float(p))) * p * (p - 1), "ands_model"))


def memory_model(view: DataFrame, partials: DataFrame, spec: LinkageSpec) -> DataFrame:
    """holder, piece_bytes, list_bytes: what each holder keeps, its pieces with two tokens, and its list of candidates."""
    pieces = view.groupBy("holder").agg((F.count("*") * (8 * spec.words + 64 + 4)).alias("piece_bytes"))
    lists = partials.groupBy("holder").agg((F.count("*") * (32 * spec.parties + 16)).alias("list_bytes"))
    return pieces.join(lists, "holder", "left").select("holder", "piece_bytes", F.coalesce("list_bytes", F.lit(0)).cast("long").alias("list_bytes"))
