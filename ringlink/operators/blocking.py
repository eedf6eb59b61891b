"""Block functions, blocks common to all parties, candidate counts and the guard against oversize blocks."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def block_key(keys: tuple[str, ...], fn: str = "soundex") -> Column:
    """The parts' block values joined by bars. fn: soundex, exact, prefix:n, none (one block of all); null counts as empty."""
    if fn == "none":
        return F.lit("")
    name, _, n = fn.partition(":")
    forms = {"soundex": F.soundex, "exact": lambda c: c, "prefix": lambda c: F.substring(c, 1, int(n or 1))}
    return F.concat_ws("|", *(forms[name](F.coalesce(F.col(k), F.lit(""))) for k in keys))


def block_counts(rows: DataFrame) -> DataFrame:
    """party, bkv, n of rows (party, bkv)."""
    return rows.groupBy("party", "bkv").agg(F.count("*").alias("n"))


def shared_block_keys(rows: DataFrame, parties: int) -> DataFrame:
    """bkv, n1..nP of the blocks that every party has."""
    by = rows.groupBy("bkv").agg(*(F.count_if(F.col("party") == j).alias(f"n{j}") for j in range(1, parties + 1)))
    return by.where(reduce(lambda a, b: a & b, (F.col(f"n{j}") > 0 for j in range(1, parties + 1))))


def block_sizes(rows: DataFrame, parties: int) -> DataFrame:
    """bkv, sets, rows of the blocks that all parties have; sets is the product of the parties' counts.

    The product is a double beyond 2^53: an exact one can pass 38 digits for many parties.
    """
    shared = shared_block_keys(rows, parties)
    sets = reduce(lambda a, b: a * b, (F.col(f"n{j}").cast("double") for j in range(1, parties + 1)))
    total = reduce(lambda a, b: a + b, (F.col(f"n{j}") for j in range(1, parties + 1)))
    return shared.select("bkv", sets.alias("sets"), total.alias("rows"))


def candidate_count(rows: DataFrame, parties: int) -> DataFrame:
    """candidates: how many record sets the blocks give, without building one."""
    return block_sizes(rows, parties).agg(F.coalesce(F.sum("sets"), F.lit(0.0)).alias("candidates"))


def guard_blocks(rows: DataFrame, parties: int, most: float) -> DataFrame:
    """bkv, sets, action for each common block: `keep`, or `split` where it gives more than `most` sets."""
    return block_sizes(rows, parties).select("bkv", "sets", F.when(F.col("sets") > most, "split").otherwise("keep").alias("action"))


def split_blocks(rows: DataFrame, parties: int, most: float, finer: str) -> DataFrame:
    """rows whose oversize blocks are cut by the column `finer`: no record is dropped, but sets that differ in `finer` part."""
    over = guard_blocks(rows, parties, most).where("action = 'split'").select("bkv", F.lit(True).alias("_over"))
    marked = rows.join(over, "bkv", "left")
    return marked.withColumn("bkv", F.when(F.col("_over"), F.concat_ws("/", "bkv", finer)).otherwise(F.col("bkv"))).drop("_over")


def union_passes(matches: list[DataFrame]) -> DataFrame:
    """Matches of several block keys, each set once."""
    return reduce(DataFrame.unionByName, matches).dropDuplicates(["cand"])


def enumerate_candidates(rows: DataFrame, parties: int, carry: tuple[str, ...] = (), stage=None) -> DataFrame:
    """r1..rP and the carried columns as name_j: a chain of equi-joins over the blocks, one record of each party.

    stage(j) may give a test that the prefixes of parties 1..j must pass before the next join multiplies them.
    """
    out = None
    for j in range(1, parties + 1):
        part = rows.where(F.col("party") == j).select("bkv", F.col("rid").alias(f"r{j}"), *(F.col(c).alias(f"{c}_{j}") for c in carry))
        out = part if out is None else out.join(part, "bkv")
        if stage is not None and 1 < j < parties:
            out = out.where(stage(j) | (F.spark_partition_id() < 0))  # never true: it keeps the test out of the join's condition
    return out


def named(parties: int) -> Column:
    return F.concat_ws(",", *(f"r{j}" for j in range(1, parties + 1))).alias("cand")
