"""Physical choices that stay lossless: settled tables, broadcasts behind a size check, salted joins."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def settle(df: DataFrame) -> DataFrame:
    """Write df to the shared checkpoint folder and read it from there, so several readers do not compute it again.

    The folder is spark.checkpoint.dir; one of our own is set only where that is unset on a local master.
    """
    spark = df.sparkSession
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        named = spark.conf.get("spark.checkpoint.dir", None)
        local = sc.master == "local" or sc.master.startswith("local[")
        sc.setCheckpointDir(named or (tempfile.mkdtemp(prefix="ringlink-") if local else spark.conf.get("spark.sql.warehouse.dir") + "/_shared"))
    return df.checkpoint(eager=True)


def small(df: DataFrame, rows: int) -> DataFrame:
    """df marked for broadcast if it has `rows` rows or fewer, else as it is: the join then shuffles."""
    return F.broadcast(df) if df.limit(rows + 1).count() <= rows else df


def salted_join(left: DataFrame, right: DataFrame, on: list[str], salts: int = 8, how: str = "inner") -> DataFrame:
    """An equi-join whose left rows of one key are dealt over `salts` tasks; the right side is copied to each.

    inner, left and left_semi keep their meaning, since each left row meets each right row of its key exactly once.
    """
    if how not in ("inner", "left", "left_semi", "left_anti"):
        raise ValueError("the copied side must not be preserved")
    dealt = left.withColumn("_salt", F.pmod(F.xxhash64(*left.columns), F.lit(salts)).cast("int"))
    copied = right.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return dealt.join(copied, [*on, "_salt"], how).drop("_salt")


def candidate_executor(total: int, largest: int, most: int = 100_000_000, block: int = 1_000_000) -> str:
    """How to enumerate: `chain` of joins, `split` blocks by a finer key first, or `refuse` (count only)."""
    if total > 100 * most:
        return "refuse"
    return "split" if largest > block else "chain"
