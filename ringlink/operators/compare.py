"""Similarities of record sets, and the counts that the holders make of their pieces."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ringlink.operators import blockwise
from ringlink.operators.encoding import bit_columns, ones, tokenise
from ringlink.operators.exchange import word_columns
from ringlink.spec import LinkageSpec


def _fold(groups: list[list[str]], how: str) -> Column:
    """Bits set in the AND (or OR) of filters given as lists of word columns."""
    sign = {"and": " & ", "or": " | "}[how]
    return F.expr(" + ".join(f"bit_count({sign.join(cols)})" for cols in zip(*groups, strict=True)))


def similarity(groups: list[list[str]], sizes: list[str], kind: str = "dice") -> Column:
    """Multi-party similarity of filters (word columns) with `sizes` bits: dice, jaccard, overlap, cosine; null where a divisor is 0."""
    common = _fold(groups, "and")
    if kind == "jaccard":
        return F.try_divide(common, _fold(groups, "or"))
    return counted_similarity(common, sizes, kind)


def counted_similarity(common: Column, sizes: list[str], kind: str = "dice") -> Column:
    """dice, overlap or cosine of filters with `sizes` bits, `common` of them in all."""
    p = len(sizes)
    if kind == "overlap":
        return F.try_divide(common, F.least(*sizes))
    if kind == "cosine":
        return F.try_divide(common, F.pow(reduce(lambda a, b: a * b, (F.col(s).cast("double") for s in sizes)), F.lit(1 / p)))
    return F.try_divide(p * common, reduce(lambda a, b: a + b, (F.col(s) for s in sizes)))


def dice_pairs(encoded: DataFrame, spec: LinkageSpec, one: int = 1, two: int = 2) -> DataFrame:
    """rid1, rid2, c, x1, x2, dice of the pairs of two parties in one block."""
    bits = bit_columns(spec)
    side = lambda j, k: encoded.where(F.col("party") == j).select("bkv", F.col("rid").alias(f"rid{k}"), *(F.col(b).alias(f"{b}_{k}") for b in bits), F.col("x_own").alias(f"x{k}"))
    pairs = side(one, 1).join(side(two, 2), "bkv")
    groups = [[f"{b}_{k}" for b in bits] for k in (1, 2)]
    return pairs.select("rid1", "rid2", _fold(groups, "and").alias("c"), "x1", "x2", F.round(similarity(groups, ["x1", "x2"]), 6).alias("dice"))


def _chain(view: DataFrame, spec: LinkageSpec, stage, order: str) -> DataFrame:
    """holder, bkv, s1..sP (tokens by slot), o1..oP (owners, where the order varies), the ANDed words, ones, x.

    One plan serves all holders, as the holder is part of the join key; stage(n) may drop prefixes after the n-th merge.
    """
    words = word_columns(spec)
    if order == "small_first":
        sizes = view.groupBy("holder", "bkv", "owner").agg(F.count("*").alias("n"))
        rank = F.row_number().over(W.partitionBy("holder", "bkv").orderBy(F.col("holder") != F.col("owner"), "n", "owner"))
        view = view.drop("slot").join(sizes.withColumn("slot", rank).drop("n"), ["holder", "bkv", "owner"])
    acc = None
    for n in range(1, spec.parties + 1):
        part = view.where(F.col("slot") == n)
        who = [F.col("owner").alias(f"o{n}")] if order == "small_first" else []
        if acc is None:
            acc = part.select("holder", "bkv", F.col("rid").alias("s1"), *who, *words, F.col("seg_ones").alias("ones"), F.col("x_own").alias("x"))
            continue
        right = part.select("holder", "bkv", F.col("rid").alias(f"s{n}"), *who, *(F.col(w).alias(f"v{w}") for w in words), "seg_ones")
        held = [c for c in acc.columns if c[0] in "so" and c[1:].isdigit()]
        acc = acc.join(right, ["holder", "bkv"]).select("holder", "bkv", *held, f"s{n}", *([f"o{n}"] if who else []), *(F.expr(f"{w} & v{w} AS {w}") for w in words), (F.col("ones") + F.col("seg_ones")).alias("ones"), "x")
        if (keep := stage(n)) is not None:
            acc = acc.where(keep)
    return acc


def _by_owner(j: int, spec: LinkageSpec, order: str) -> Column:
    """Party j's token in a chain's row."""
    if order == "small_first":
        return F.coalesce(*(F.when(F.col(f"o{n}") == j, F.col(f"s{n}")) for n in range(1, spec.parties + 1)))
    h = F.col("holder")
    if j == 1:
        return F.when(h == 1, F.col("s1")).otherwise(F.col("s2"))
    if j == spec.parties:
        return F.when(h == j, F.col("s1")).otherwise(F.col(f"s{j}"))
    return F.when(h == j, F.col("s1")).when(h > j, F.col(f"s{j + 1}")).otherwise(F.col(f"s{j}"))


def partial_counts(view: DataFrame, spec: LinkageSpec, prune: str | None = None, order: str = "id", words: bool = False) -> DataFrame:
    """holder, r1..rP, c, x: each holder ANDs its pieces over every candidate of a block.

    prune: None (all candidates), `prefix` (after every merge, pieces merged times common bits over their bits must
    reach s_m, or the prefix leaves before the next join multiplies it), `final` (that test once, after the last
    merge) or `bound` (a prefix leaves only where no further record can bring the piece to s_t). Pieces without a
    bit count as alike. order: the other owners ascending (`id`) or those with the smallest block first (`small_first`).
    """
    (num, den), (goal, of) = spec.prune, spec.threshold
    common = ones(word_columns(spec))

    def stage(n: int) -> Column | None:
        if prune == "prefix" or prune == "final" and n == spec.parties:
            return den * n * common >= num * F.col("ones")
        if prune == "bound":
            return of * spec.parties * common >= goal * (F.col("ones") + (spec.parties - n) * common)
        return None

    if prune not in (None, "prefix", "final", "bound"):
        raise ValueError(f"unknown filter {prune}")
    acc = _chain(view, spec, stage, order)
    return acc.select("holder", *(_by_owner(j, spec, order).alias(f"r{j}") for j in range(1, spec.parties + 1)), common.cast("long").alias("c"), F.col("x").cast("long").alias("x"), *(word_columns(spec) if words else []))


def counts_for(candidates: DataFrame, view: DataFrame, spec: LinkageSpec) -> DataFrame:
    """holder, r1..rP, c, x of the given candidates (r1..rP) at every holder."""
    ids, words = [f"r{j}" for j in range(1, spec.parties + 1)], word_columns(spec)
    acc = candidates.select(*ids, F.explode(F.sequence(F.lit(1), F.lit(spec.parties))).alias("holder"))
    for j in range(1, spec.parties + 1):
        part = view.where(F.col("owner") == j).select("holder", F.col("rid").alias(f"r{j}"), *(F.col(w).alias(f"v{w}") for w in words), F.col("x_own").alias("xj"))
        joined = acc.join(part, ["holder", f"r{j}"])
        merged = [F.col(f"v{w}").alias(w) if j == 1 else F.col(w).bitwiseAND(F.col(f"v{w}")).alias(w) for w in words]
        acc = joined.select("holder", *ids, *merged, (F.col("xj") if j == 1 else F.coalesce("x", "xj")).alias("x"))
    return acc.select("holder", *ids, ones(words).cast("long").alias("c"), F.col("x").cast("long").alias("x"))


def bounded_counts(view: DataFrame, spec: LinkageSpec) -> DataFrame:
    """partial counts of the candidates that some holder's bound lets pass: no match is lost.

    A set's similarity is a mediant of its pieces' similarities, so one piece at least reaches s_t if the set does;
    a candidate that fails everywhere is no match, one that passes anywhere is counted by all.
    """
    ids = [f"r{j}" for j in range(1, spec.parties + 1)]
    return counts_for(partial_counts(view, spec, "bound").select(*ids).distinct(), view, spec)


def side_by_side(encoded: DataFrame, spec: LinkageSpec) -> DataFrame:
    """party, bkv, r (tokens), rid, b0.., n1..nP (each piece's bits), x_own: the pieces of one record in one row.

    Columns of piece h are what holder h gets of that owner, so that all holders' counts of a candidate can stand in
    one row and no candidate has to be brought together again.
    """
    bits, w = bit_columns(spec), spec.words
    sizes = (ones(bits[h * w : (h + 1) * w]).alias(f"n{h + 1}") for h in range(spec.parties))
    return encoded.select("party", tokenise(F.col("bkv"), "bkv", spec.secret).alias("bkv"), tokenise(F.col("rid"), "rid", spec.secret).alias("r"), "rid", *bits, *sizes, "x_own")


def joint_counts(encoded: DataFrame, spec: LinkageSpec, prune: str | None = None, matches: str | None = None) -> DataFrame:
    """r1..rP, name1..nameP (tokens and ids), c1..cP, x1..xP of the candidates: holder h's count and own size as ch, xh.

    One chain of joins over the blocks; sums over holders are sums of columns, nothing is grouped by candidate.
    prune `prefix`: only candidates that every holder keeps by the tests of `partial_counts`; each is applied as soon
    as its prefix stands. matches: what is left out because no match can come of it: `equal` (filters differ, by what
    each prefix has in common) or `dice` (s_t not reached; these sets are found pairs first, by `blockwise`).
    """
    p, w, bits = spec.parties, spec.words, bit_columns(spec)
    num, den = spec.prune
    if matches == "dice":
        rows = side_by_side(encoded, spec).withColumn("name", F.col("rid"))
        return blockwise.sets_reaching(rows, p, bits, spec.threshold, "dice", p, ("r", "name"), spec.prune if prune == "prefix" else None)
    piece = [bits[h * w : (h + 1) * w] for h in range(p)]
    rows, sized = side_by_side(encoded, spec), range(1, p + 1) if prune == "prefix" else ()
    held = lambda m, h: [f"q{m}_{b}" for b in piece[h]]  # noqa: E731  # piece h of parties 1..m, merged
    # never true, but a condition with it stays where it is: moved into the joins, the planner would infer constraints
    # for every choice of merged or unmerged columns
    every, acc = lambda tests: reduce(lambda a, b: a & b, tests) | (F.spark_partition_id() < 0), None
    for j in range(1, p + 1):
        part = rows.where(F.col("party") == j).select("bkv", F.col("r").alias(f"r{j}"), F.col("rid").alias(f"name{j}"), *(F.col(b).alias(f"v{b}") for b in bits), *(F.col(f"n{h}").alias(f"n{h}_{j}") for h in sized), F.col("x_own").alias(f"x{j}"))
        kept = [f"q{m}_{b}" for m in range(1, j) for h in range(j, p) for b in piece[h]] if prune == "prefix" else []
        if acc is None:
            acc = part.withColumnsRenamed({f"v{b}": b for b in bits})
        else:
            acc = acc.join(part, "bkv")
        tests = []
        if prune == "prefix" and j > 1:  # holder j merges its own piece first, then those of 1, 2, ..
            for m in range(2, j):
                both = " + ".join(f"bit_count({q} & v{b})" for q, b in zip(held(m - 1, j - 1), piece[j - 1], strict=True))
                total = " + ".join(f"n{j}_{i}" for i in [j, *range(1, m)])
                tests.append(F.expr(f"{den * m} * ({both}) >= {num} * ({total})"))
        if j > 1:
            ids = [c for i in range(1, j + 1) for c in (f"r{i}", f"name{i}", f"x{i}", *(f"n{h}_{i}" for h in sized))]
            if tests:
                acc = acc.where(every(tests))
            old = [c for c in acc.columns if c.startswith("q") and c in kept]
            acc = acc.select("bkv", *ids, *(F.expr(f"{b} & v{b} AS {b}") for b in bits), *old)
            tests = []
            if prune == "prefix":
                tests += [F.expr(f"{den * j} * ({' + '.join(f'bit_count({b})' for b in piece[h - 1])}) >= {num} * ({' + '.join(f'n{h}_{i}' for i in range(1, j + 1))})") for h in range(1, j + 1)]
            common, sizes = " + ".join(f"bit_count({b})" for b in bits), [f"x{i}" for i in range(1, j + 1)]
            if matches == "equal":
                tests += [F.expr(f"{common} = {x}") for x in sizes]
            if tests:
                acc = acc.where(every(tests))
        if prune == "prefix" and j < p:
            acc = acc.select("*", *(F.col(b).alias(f"q{j}_{b}") for h in range(j + 1, p) for b in piece[h]))
    each = (F.expr("bigint(" + " + ".join(f"bit_count({b})" for b in piece[h]) + ")").alias(f"c{h + 1}") for h in range(p))
    return acc.select(*(f"r{j}" for j in range(1, p + 1)), *(f"name{j}" for j in range(1, p + 1)), *each, *(F.col(f"x{j}").cast("long").alias(f"x{j}") for j in range(1, p + 1)))


def kept_counts(encoded: DataFrame, spec: LinkageSpec) -> DataFrame:
    """holder, r1..rP, c, x, as `partial_counts` with the filter `prefix` and the order `id` has them.

    A record crosses the network once, all its pieces in one array that no holder's chain can narrow, so each party's
    part is shuffled once and read by every chain; each drops its prefixes early. Nothing is settled: a party's part is
    encoded where it is dealt out. The number of partitions is given, as candidates say more than bytes.
    """
    p, w, bits, words = spec.parties, spec.words, bit_columns(spec), word_columns(spec)
    (num, den), rows, everyone = spec.prune, side_by_side(encoded, spec), range(1, p + 1)
    n = int(encoded.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = {j: rows.where(F.col("party") == j).select("bkv", "r", F.array(*bits, F.col("x_own").cast("long")).alias("all")).repartition(n, "bkv") for j in everyone}

    def piece(h: int, j: int, names: list[str]) -> DataFrame:
        held = [F.col("all")[(h - 1) * w + k].alias(name) for k, name in enumerate(names)]
        return dealt[j].select("bkv", F.col("r").alias(f"r{j}"), *held, F.col("all")[len(bits)].alias("x")).withColumn("seg_ones", ones(names))

    def chain(h: int) -> DataFrame:
        acc, ids = piece(h, h, words).withColumnRenamed("seg_ones", "ones"), [f"r{h}"]
        for at, j in enumerate((j for j in everyone if j != h), 2):
            ids.append(f"r{j}")
            right = piece(h, j, [f"v{x}" for x in words]).drop("x")
            acc = acc.join(right, "bkv").select("bkv", *ids, *(F.expr(f"{x} & v{x} AS {x}") for x in words), (F.col("ones") + F.col("seg_ones")).alias("ones"), "x")
            acc = acc.where(den * at * ones(words) >= num * F.col("ones"))
        return acc.select(F.lit(h).alias("holder"), *(f"r{j}" for j in everyone), ones(words).cast("long").alias("c"), "x")

    return reduce(DataFrame.unionByName, map(chain, everyone))


def by_holder(joint: DataFrame, spec: LinkageSpec) -> DataFrame:
    """joint counts as rows holder, r1..rP, c, x, as `partial_counts` has them."""
    each = F.array(*(F.struct(F.lit(h).alias("holder"), F.col(f"c{h}").alias("c"), F.col(f"x{h}").alias("x")) for h in range(1, spec.parties + 1)))
    ids = [f"r{j}" for j in range(1, spec.parties + 1)]
    return joint.select(*ids, F.explode(each).alias("h")).select("h.holder", *ids, "h.c", "h.x")
