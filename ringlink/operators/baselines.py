"""What the distributed matcher is compared with: exact matchers, clear-text references, filters on sizes."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ringlink.operators import blocking, compare
from ringlink.operators.encoding import bit_columns, clean, encode_register, qgrams
from ringlink.plans.physical import settle
from ringlink.spec import LinkageSpec


def _and(columns) -> Column:
    return reduce(lambda a, b: a & b, columns)


def exact_conjunction(register: DataFrame, spec: LinkageSpec) -> DataFrame:
    """cand of the compared exact matcher: holders AND their pieces, the whole conjunction is put together again, and
    every party tests whether its own filter lies inside it.

    A party's filter lies inside the conjunction if both have equally many bits, so holders' counts stand for the bits,
    and a set leaves the chain as soon as two filters in it differ. What the whole conjunctions would cost is
    `workloads.cost_compare`'s to count.
    """
    sets = compare.joint_counts(settle(encode_register(register, spec)), spec, matches="equal")
    return sets.select(F.concat_ws(",", *(f"name{j}" for j in range(1, spec.parties + 1))).alias("cand"))


def equal_filters(encoded: DataFrame, spec: LinkageSpec) -> DataFrame:
    """What the exact conjunction finds, by one equi-join on block and whole filter."""
    bits, out = bit_columns(spec), None
    for j in range(1, spec.parties + 1):
        part = encoded.where(F.col("party") == j).select("bkv", *bits, F.col("rid").alias(f"r{j}"))
        out = part if out is None else out.join(part, ["bkv", *bits])
    return out.select(blocking.named(spec.parties))


def register_conjunction(encoded: DataFrame, spec: LinkageSpec) -> DataFrame:
    """party, rid of the records whose bits all lie in the conjunction of the parties' whole registers (each the OR of its records)."""
    bits = bit_columns(spec)
    registers = encoded.groupBy("party").agg(*(F.bit_or(b).alias(b) for b in bits))
    common = registers.agg(*(F.bit_and(b).alias(f"c{b}") for b in bits))  # one row
    inside = _and(F.col(b).bitwiseAND(F.col(f"c{b}")) == F.col(b) for b in bits)
    return encoded.crossJoin(F.broadcast(common)).where(inside).select("party", "rid")


def clear_exact(register: DataFrame, spec: LinkageSpec) -> DataFrame:
    """cand of the records that agree on all attributes, compared in the clear."""
    out = None
    for j in range(1, spec.parties + 1):
        part = register.where(F.col("party") == j).select(*spec.qids, F.col("rid").alias(f"r{j}"))
        out = part if out is None else out.join(part, list(spec.qids))
    return out.select(blocking.named(spec.parties))


def clear_qgrams(register: DataFrame, spec: LinkageSpec) -> DataFrame:
    """cand, c, x, sim by Dice on the q-grams themselves: what hashing alone loses shows against the central reference."""
    grams = F.array_distinct(F.flatten(F.array(*(qgrams(clean(F.col(c)), spec.q, spec.pad) for c in spec.qids))))
    rows = register.select("party", "rid", blocking.block_key(spec.block_keys, spec.block_fn).alias("bkv"), grams.alias("grams"))
    sets = blocking.enumerate_candidates(rows, spec.parties, ("grams",))
    lists = [F.col(f"grams_{j}") for j in range(1, spec.parties + 1)]
    c, x = F.size(reduce(F.array_intersect, lists)), reduce(lambda a, b: a + b, map(F.size, lists))
    num, den = spec.threshold
    rows = sets.select(blocking.named(spec.parties), c.cast("long").alias("c"), x.cast("long").alias("x")).where(den * spec.parties * F.col("c") >= num * F.col("x")).where("x > 0")
    return rows.withColumn("sim", F.round(spec.parties * F.col("c") / F.col("x"), 6))


def length_filter(encoded: DataFrame, spec: LinkageSpec) -> DataFrame:
    """candidates, kept, share: how little the sizes of half-full filters rule out. A set passes if its smallest size allows s_t."""
    num, den = spec.threshold
    sets = blocking.enumerate_candidates(encoded, spec.parties, ("x_own",))
    sizes = [F.col(f"x_own_{j}") for j in range(1, spec.parties + 1)]
    passes = den * spec.parties * F.least(*sizes) >= num * reduce(lambda a, b: a + b, sizes)
    n = sets.agg(F.count("*").alias("candidates"), F.count_if(passes).alias("kept"))
    return n.withColumn("share", F.round(F.try_divide("kept", "candidates"), 6))


def range_partners(encoded: DataFrame, spec: LinkageSpec, step: int = 8) -> DataFrame:
    """rid1, rid2 of the pairs of two parties whose sizes allow s_t for two: a range join made an equi-join.

    Partners of a filter with x bits have between x*s/(2-s) and x*(2-s)/s bits; each row is copied to the steps that
    range touches, each partner stands in one, so every pair meets once.
    """
    num, den = spec.threshold
    low, high = F.ceil(F.col("x1") * num / (2 * den - num)).cast("long"), F.floor(F.col("x1") * (2 * den - num) / num).cast("long")
    one = encoded.where("party = 1").select("bkv", F.col("rid").alias("rid1"), F.col("x_own").alias("x1")).withColumns({"lo": low, "hi": high})
    one = one.withColumn("bin", F.explode(F.sequence(F.floor(F.col("lo") / step), F.floor(F.col("hi") / step))))
    two = encoded.where("party = 2").select("bkv", F.col("rid").alias("rid2"), F.col("x_own").alias("x2"), F.floor(F.col("x_own") / step).alias("bin"))
    return one.join(two, ["bkv", "bin"]).where("x2 between lo and hi").select("rid1", "rid2", "x1", "x2")
