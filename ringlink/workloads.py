"""The experiments: series of registers linked in one plan each, and the worked examples."""

from __future__ import annotations

from dataclasses import replace
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ringlink.operators import baselines, blocking, compare, linkage, measures, registers
from ringlink.operators import corruption as C
from ringlink.operators import encoding as E
from ringlink.operators import exchange as X
from ringlink.plans.physical import settle
from ringlink.spec import LinkageSpec

RATES = (0, 20, 40)


def spec_for(parties: int) -> LinkageSpec:
    """Surname blocks for three parties, given name and surname beyond, where surname blocks would explode."""
    return LinkageSpec(parties=parties, block_keys=("surname",) if parties == 3 else ("given", "surname"))


def series(parts: list[tuple[str, DataFrame]]) -> DataFrame:
    """Registers side by side: `series` names each, record ids carry it, so one plan links them all and none meets another."""
    named = (df.withColumn("series", F.lit(name)).withColumn("rid", F.concat_ws(":", F.lit(name), "rid")) for name, df in parts)
    return reduce(DataFrame.unionByName, named)


def of_series(cand: str = "cand"):
    return F.substring_index(cand, ":", 1).cast("int")


def in_series(spec: LinkageSpec) -> LinkageSpec:
    return replace(spec, block_keys=("series", *spec.block_keys))  # series names are digits, which Soundex leaves alone


def by_rate(register: DataFrame, parties: int, rates=RATES) -> DataFrame:
    return series([(str(r), C.corrupt_register(register, parties, r).drop("corrupted")) for r in rates])


def _scored(matches: DataFrame, truth: DataFrame, mode: str, spec: LinkageSpec) -> DataFrame:
    both = matches.select("cand", F.lit(1).alias("m")).join(truth.select("cand", F.lit(1).alias("t")), "cand", "full_outer").withColumn("rate", of_series())
    n = both.groupBy("rate").agg(F.count_if(F.col("m").isNotNull() & F.col("t").isNotNull()).alias("tp"), F.count_if(F.col("t").isNull()).alias("fp"), F.count_if(F.col("m").isNull()).alias("fn"))
    r = lambda a, b, name: F.round(F.try_divide(a, b), 6).alias(name)
    tp, fp, fn = F.col("tp"), F.col("fp"), F.col("fn")
    return n.select(F.lit(mode).alias("mode"), F.lit(spec.parties).alias("parties"), "rate", "tp", "fp", "fn", r(tp, tp + fp, "precision"), r(tp, tp + fn, "recall"), r(2 * tp, 2 * tp + fp + fn, "f1"))


def quality_grid(register: DataFrame, spec: LinkageSpec, rates=RATES) -> DataFrame:
    """mode, parties, rate, tp, fp, fn, precision, recall, f1: both matchers and the exact one, all on the same blocks."""
    s, dirty = in_series(spec), by_rate(register, spec.parties, rates)
    truth = registers.true_sets(dirty.withColumn("entity", F.concat_ws(":", "series", "entity")), spec)
    encoded = settle(E.encode_register(dirty, s))
    found = [(mode, linkage.link_encoded(encoded, s, mode)) for mode in ("approx", "approx_filtered")]
    found.append(("exact", baselines.equal_filters(encoded, s)))
    return reduce(DataFrame.unionByName, (_scored(m, truth, mode, spec) for mode, m in found))


def candidate_series(people: DataFrame, sizes: tuple[int, ...], parties=(3, 5, 7)) -> DataFrame:
    """size, parties, keys, candidates: counted from block sizes, never enumerated."""
    out = []
    for p in parties:
        reg = registers.make_register(people, p)
        for keys in (("surname",), ("given", "surname")):
            rows = reg.select("party", "entity", blocking.block_key(keys).alias("key")).withColumn("size", F.explode(F.array(*map(F.lit, sizes)))).where("entity <= size")
            by = rows.groupBy("size", "key").agg(*(F.count_if(F.col("party") == j).alias(f"n{j}") for j in range(1, p + 1)))
            sets = reduce(lambda a, b: a * b, (F.col(f"n{j}").cast("double") for j in range(1, p + 1)))
            out.append(by.groupBy("size").agg(F.sum(sets).alias("candidates")).select("size", F.lit(p).alias("parties"), F.lit("+".join(keys)).alias("keys"), "candidates"))
    return reduce(DataFrame.unionByName, out)


def rr_f_series(people: DataFrame, sizes: tuple[int, ...], spec: LinkageSpec) -> DataFrame:
    """size, holder, before, kept, rr_f of the filter for growing registers."""
    s = in_series(spec)
    reg = series([(str(n), registers.make_register(people.where(F.col("entity") <= n), spec.parties)) for n in sizes])
    encoded = settle(E.encode_register(reg, s))
    view = settle(X.exchange_segments(encoded, s))
    token = E.tokenise(F.col("rid"), "rid", s.secret)
    first = encoded.where("party = 1").select(token.alias("r1"), of_series("rid").alias("size"))
    kept = compare.partial_counts(view, s, "prefix").join(first, "r1").groupBy("size", "holder").agg(F.count("*").alias("kept"))
    before = blocking.block_sizes(encoded, s.parties).groupBy(F.substring_index("bkv", "|", 1).cast("int").alias("size")).agg(F.sum("sets").cast("long").alias("before"))
    every = before.withColumn("holder", F.explode(F.sequence(F.lit(1), F.lit(s.parties))))
    n = F.coalesce("kept", F.lit(0)).cast("long")
    return every.join(kept, ["size", "holder"], "left").select("size", "holder", "before", n.alias("kept"), F.round(1 - n / F.col("before"), 6).alias("rr_f"))


def threshold_sweep(register: DataFrame, spec: LinkageSpec, tenths=(0, 6, 7, 8)) -> DataFrame:
    """s_m, kept, matches, tp, recall: candidates that all holders keep and what is found of the truth, as s_m grows."""
    truth = settle(registers.true_sets(register, spec))
    encoded = settle(E.encode_register(register, spec))
    out = []
    for t in tenths:
        s = replace(spec, seg_threshold=(t, 10))
        if t:
            kept = compare.joint_counts(encoded, s, "prefix").agg(F.count("*").alias("kept"))
        else:  # no set fails: counted from blocks
            kept = blocking.candidate_count(encoded, s.parties).select(F.col("candidates").cast("long").alias("kept"))
        found = linkage.link_encoded(encoded, s, "approx_filtered")
        hits = found.select("cand", F.lit(1).alias("m")).join(truth.select("cand", F.lit(1).alias("t")), "cand", "full_outer")
        n = hits.agg(F.count("m").alias("matches"), F.count_if(F.col("m").isNotNull() & F.col("t").isNotNull()).alias("tp"), F.count("t").alias("truth"))
        out.append(kept.crossJoin(n).select(F.lit(t).alias("tenths"), "kept", "matches", "tp", F.round(F.try_divide("tp", "truth"), 6).alias("recall")))  # one row each
    return reduce(DataFrame.unionByName, out)


def disclosure_grid(people: DataFrame, grid: list[tuple[int, int, int]]) -> DataFrame:
    """parties, l, k, dr_mean, dr_mark, dr_max for each (parties, length, hashes)."""
    out = []
    for p, length, hashes in grid:
        s = LinkageSpec(parties=p, length=length, hashes=hashes)
        view = X.exchange_segments(E.encode_register(registers.make_register(people, p), s), s)
        out.append(measures.disclosure(view, s).select(F.lit(p).alias("parties"), F.lit(s.bits).alias("l"), F.lit(hashes).alias("k"), "dr_mean", "dr_mark", "dr_max"))
    return reduce(DataFrame.unionByName, out)


def tradeoff_sweep(register: DataFrame, specs: list[LinkageSpec]) -> DataFrame:
    """l, k, fill, dr_mean, f1: privacy against quality as the parameters move. register is the corrupted one."""
    out = []
    for s in specs:
        encoded = settle(E.encode_register(register, s))
        view = X.exchange_segments(encoded, s)
        q = measures.quality(linkage.central(encoded, s), registers.true_sets(register, s)).select("f1")
        fill = encoded.agg(F.round(F.sum("x_own") / (F.count("*") * s.bits), 6).alias("fill"))
        one = fill.crossJoin(measures.disclosure(view, s).select("dr_mean")).crossJoin(q)  # one row each
        out.append(one.select(F.lit(s.bits).alias("l"), F.lit(s.hashes).alias("k"), "fill", "dr_mean", "f1"))
    return reduce(DataFrame.unionByName, out)


def cost_compare(register: DataFrame, spec: LinkageSpec) -> DataFrame:
    """mode, parties, candidates, bytes that travel after the hand-over of pieces: two longs a hop against whole conjunctions."""
    encoded = settle(E.encode_register(register, spec))
    view = settle(X.exchange_segments(encoded, spec))
    p, ids = spec.parties, [f"r{j}" for j in range(1, spec.parties + 1)]
    every = blocking.candidate_count(encoded, p).select(F.col("candidates").cast("long").alias("n"))
    kept = compare.partial_counts(view, spec, "prefix").groupBy(*ids).agg(F.count("*").alias("h")).where(F.col("h") == p).agg(F.count("*").alias("n"))
    exact = 8 * spec.words * p + 8 * spec.words * p * p  # pieces put together, the whole sent to each party
    rows = [("approx", every, 16 * p), ("approx_filtered", kept, 16 * p), ("exact", every, exact)]
    return reduce(DataFrame.unionByName, (df.select(F.lit(m).alias("mode"), F.lit(p).alias("parties"), F.col("n").alias("candidates"), (F.col("n") * size).alias("bytes")) for m, df, size in rows))


# Worked examples

PEOPLE = [
    (1, "A-1", "petra", "hansen", "norton", "27601", "bk1"), (1, "A-2", "martin", "kelly", "durham", "27701", "bk1"),
    (2, "B-1", "marta", "holm", "dunville", "27702", "bk1"), (2, "B-2", "petra", "hanson", "norton", "27601", "bk1"),
    (3, "C-1", "petra", "hansen", "norton", "27601", "bk1"), (3, "C-2", "oskar", "lind", "wilson", "27893", "bk2"),
]
BITS = [(1, "A1", "101101101100"), (1, "A2", "010010010011"), (2, "B1", "101101101000"), (2, "B2", "011010011100"), (3, "C1", "101101111100"), (3, "C2", "010010000011"), (3, "C3", "100101101101")]


def running_example(spark: SparkSession) -> DataFrame:
    """cand, c1..c3, c, x, sim, is_match of six records in two blocks: four candidates, one match."""
    s = LinkageSpec(parties=3, block_keys=("block",), block_fn="exact")
    reg = spark.createDataFrame(PEOPLE, "party int, rid string, given string, surname string, suburb string, postcode string, block string")
    encoded = settle(E.encode_register(reg, s))
    view = X.split_segments(encoded, s).withColumnsRenamed({"party": "owner", "piece": "holder"}).withColumn("slot", X.slot())
    view = settle(view.withColumn("x_own", F.when(F.col("holder") == F.col("owner"), F.col("x_own"))))
    rows = compare.partial_counts(view, s).groupBy(F.concat_ws(",", "r1", "r2", "r3").alias("cand"))
    n = rows.agg(*(F.sum(F.when(F.col("holder") == h, F.col("c"))).alias(f"c{h}") for h in (1, 2, 3)), F.sum("c").alias("c"), F.sum("x").alias("x"))
    return n.select("*", F.round(3 * F.col("c") / F.col("x"), 4).alias("sim"), (15 * F.col("c") >= 4 * F.col("x")).alias("is_match"))


def bits_view(spark: SparkSession, spec: LinkageSpec) -> DataFrame:
    """The pieces of the seven short filters of the filter example, as the holders have them."""
    rows = [(p, r, "b", int(b[i * 4 : i * 4 + 4][::-1], 2), b[i * 4 : i * 4 + 4].count("1"), b.count("1"), i + 1) for p, r, b in BITS for i in range(3)]
    df = spark.createDataFrame(rows, "owner int, rid string, bkv string, w0 long, seg_ones int, x_all int, holder int")
    return df.withColumn("slot", X.slot()).withColumn("x_own", F.when(F.col("holder") == F.col("owner"), F.col("x_all")))


def filter_example(spark: SparkSession) -> DataFrame:
    """tenths, holder, before, kept: 2 x 2 x 3 record sets, those left by the filter at s_m .8 and .6, and (holder 0) the
    sets that remain if the one pair A2, B1 alone is dropped: 12 to 9."""
    base = LinkageSpec(parties=3, length=12)
    view = bits_view(spark, base)
    pair = compare.partial_counts(view, base).where("holder = 1 and not (r1 = 'A2' and r2 = 'B1')").agg(F.count("*").alias("kept"))
    out = [pair.select(F.lit(0).alias("tenths"), F.lit(0).alias("holder"), F.lit(12).cast("long").alias("before"), "kept")]
    every = spark.range(1, 4).select(F.col("id").cast("int").alias("holder"))
    for t in (6, 8):
        kept = compare.partial_counts(view, replace(base, seg_threshold=(t, 10)), "prefix").groupBy("holder").agg(F.count("*").alias("n"))
        out.append(every.join(kept, "holder", "left").select(F.lit(t).alias("tenths"), "holder", F.lit(12).cast("long").alias("before"), F.coalesce("n", F.lit(0)).cast("long").alias("kept")))
    return reduce(DataFrame.unionByName, out)


def two_strings(spark: SparkSession, one: str = "peter", two: str = "pete", bits: int = 14, hashes: int = 2) -> DataFrame:
    """p1, p2, x1, x2, c, dice of two short strings."""
    df = spark.createDataFrame([(one, two)], "a string, b string").select(*(E.bloom_positions(F.col(n), bits, hashes).alias(n) for n in "ab"))
    c, x1, x2 = F.size(F.array_intersect("a", "b")), F.size("a"), F.size("b")
    return df.select(E.listed(F.col("a")).alias("p1"), E.listed(F.col("b")).alias("p2"), x1.alias("x1"), x2.alias("x2"), c.alias("c"), F.round(2 * c / (x1 + x2), 4).alias("dice"))


def example_sets(register: DataFrame, spec: LinkageSpec) -> DataFrame:
    """The running example's columns for every candidate of a register, by the ids that the owners use."""
    joint, p = compare.joint_counts(settle(E.encode_register(register, spec)), spec), spec.parties
    num, den = spec.threshold
    total = lambda k: reduce(lambda a, b: a + b, (F.col(f"{k}{h}") for h in range(1, p + 1))).alias(k)
    rows = joint.select(F.concat_ws(",", *(f"name{j}" for j in range(1, p + 1))).alias("cand"), *(f"c{h}" for h in range(1, p + 1)), total("c"), total("x"))
    return rows.select("*", F.round(F.try_divide(p * F.col("c"), F.col("x")), 4).alias("sim"), (den * p * F.col("c") >= num * F.col("x")).alias("is_match"))


def filtered_sets(register: DataFrame, spec: LinkageSpec, tenths=(6, 8)) -> DataFrame:
    """The filter example's columns for a register: the sets that each holder keeps and (holder 0) those that all keep."""
    encoded = settle(E.encode_register(register, spec))
    view, out = settle(X.exchange_segments(encoded, spec)), []
    before = blocking.candidate_count(encoded, spec.parties).select(F.col("candidates").cast("long").alias("before"))
    every = register.sparkSession.range(0, spec.parties + 1).select(F.col("id").cast("int").alias("holder"))
    for t in tenths:
        s = replace(spec, seg_threshold=(t, 10))
        each = compare.partial_counts(view, s, "prefix").groupBy("holder").agg(F.count("*").alias("n"))
        all_ = compare.joint_counts(encoded, s, "prefix").agg(F.lit(0).alias("holder"), F.count("*").alias("n"))
        rows = every.join(each.unionByName(all_), "holder", "left").crossJoin(before)  # one row
        out.append(rows.select(F.lit(t).alias("tenths"), "holder", "before", F.coalesce("n", F.lit(0)).cast("long").alias("kept")))
    return reduce(DataFrame.unionByName, out)


def string_pairs(df: DataFrame, one: str, two: str, bits: int = 14, hashes: int = 2) -> DataFrame:
    """The columns of `two_strings` beside df's others, for each row's two strings."""
    kept = [c for c in df.columns if c not in (one, two)]
    rows = df.select(*kept, *(E.bloom_positions(F.col(n), bits, hashes).alias(f"_{i}") for i, n in enumerate((one, two))))
    c, x1, x2 = F.size(F.array_intersect("_0", "_1")), F.size("_0"), F.size("_1")
    return rows.select(*kept, E.listed(F.col("_0")).alias("p1"), E.listed(F.col("_1")).alias("p2"), x1.alias("x1"), x2.alias("x2"), c.alias("c"), F.round(F.try_divide(2 * c, x1 + x2), 4).alias("dice"))


def embedding_filters(vectors: DataFrame, spec: LinkageSpec) -> DataFrame:
    """Vectors as encoded records: the bit of a dimension is set where its value is above 0; blocks are labels."""
    held = vectors.where("label is not null and embedding is not null")
    party = (F.pmod("vec_id", F.lit(spec.parties)) + 1).cast("int")
    letters = F.array(*(F.lit(chr(65 + i)) for i in range(spec.parties)))
    rows = held.select(party.alias("party"), F.concat_ws("-", F.element_at(letters, party), F.col("vec_id").cast("string")).alias("rid"), F.col("label").cast("string").alias("bkv"), "embedding")
    cols = []
    for k, b in enumerate(E.bit_columns(spec)):
        base = (k // spec.words) * spec.width + (k % spec.words) * 63
        size = min(63, spec.width - (k % spec.words) * 63)
        cols.append(F.expr(f"aggregate(sequence(0, {size - 1}), 0L, (m, i) -> m | if(coalesce(get(embedding, i + {base}), 0) > 0, shiftleft(1L, i), 0L))").alias(b))
    out = rows.select("party", "rid", "bkv", *cols)
    return out.withColumn("x_own", E.ones(E.bit_columns(spec)))
