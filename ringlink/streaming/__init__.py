"""Arrivals as streams: encoding, windows, late rows, incremental linkage, a monitor of rare patterns."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ringlink.operators import compare, linkage, ring
from ringlink.operators.encoding import encode_register
from ringlink.operators.exchange import exchange_segments, record_tokens
from ringlink.spec import LinkageSpec

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def arrivals(spark: SparkSession, folder: str, files: int = 1) -> DataFrame:
    """The events of a folder of Parquet files as a stream."""
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files).parquet(folder)


def arriving_records(events: DataFrame, people: DataFrame, parties: int) -> DataFrame:
    """Events joined to the register of persons (static): party, rid, entity, attributes, ts. Rows without a person wait for none."""
    party = (F.pmod("event_id", F.lit(parties)) + 1).cast("int")
    return events.select(party.alias("party"), F.concat_ws("-", "user_id", "event_id").alias("rid"), F.col("user_id").alias("entity"), "ts").join(people, "entity")


def windowed(events: DataFrame, parties: int, kind: str = "tumbling", late: str | None = "1 hour") -> DataFrame:
    """party, start, end, n per window of arrivals; kind: tumbling (1 day), sliding (1 day, every 12 hours), session (gap of 6 hours).

    The same plan serves a batch; on a stream rows later than the watermark are dropped.
    """
    party = (F.pmod("event_id", F.lit(parties)) + 1).cast("int").alias("party")
    rows = (events.withWatermark("ts", late) if late else events).select("ts", party)
    span = {"tumbling": F.window("ts", "1 day"), "sliding": F.window("ts", "1 day", "12 hours"), "session": F.session_window("ts", "6 hours")}[kind]
    return rows.groupBy("party", span.alias("w")).agg(F.count("*").alias("n")).select("party", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def late_rows(events: DataFrame, allowed: str = "1 hour") -> DataFrame:
    """Batch form of the watermark: events of a day older than the latest time seen before them less `allowed`.

    Events arrive dealt over 97 senders, one sender after the other (event_id % 97, then event_id).
    """
    from pyspark.sql import Window as W

    seen = F.max("ts").over(W.partitionBy(F.col("ts").cast("date")).orderBy(F.col("event_id") % 97, "event_id").rowsBetween(W.unboundedPreceding, -1))
    return events.withColumn("seen", seen).where(F.col("ts") < F.col("seen") - F.expr(f"INTERVAL {allowed}")).select("event_id", "ts", "seen")


def first_arrivals(events: DataFrame, within: str = "1 day") -> DataFrame:
    """One event per user and type within the watermark; later copies are dropped with their state."""
    return events.withWatermark("ts", within).dropDuplicatesWithinWatermark(["user_id", "event_type"])


def matched_arrivals(one: DataFrame, two: DataFrame, within: str = "1 hour") -> DataFrame:
    """Stream-stream join: arrivals of two parties in one block within an interval. Sides: bkv, rid, ts."""
    a = one.select(F.col("bkv").alias("b1"), F.col("rid").alias("rid1"), F.col("ts").alias("t1")).withWatermark("t1", within)
    b = two.select(F.col("bkv").alias("b2"), F.col("rid").alias("rid2"), F.col("ts").alias("t2")).withWatermark("t2", within)
    near = F.expr(f"t2 BETWEEN t1 - INTERVAL {within} AND t1 + INTERVAL {within}")
    return a.join(b, (F.col("b1") == F.col("b2")) & near).select(F.col("b1").alias("bkv"), "rid1", "rid2", "t1", "t2")


def incremental_link(spec: LinkageSpec, stored: DataFrame, sink: Callable[[DataFrame], None], party: int = 1) -> Callable[[DataFrame, int], None]:
    """A foreachBatch function: new records of one party against the stored encoded records of the others.

    Only blocks that the batch touches are read: the stored side is cut by a semi-join on the batch's block keys before
    any record set is built.
    """

    def each(batch: DataFrame, _: int) -> None:
        new = encode_register(batch.withColumn("party", F.lit(party)), spec)
        new = new.persist()
        try:
            touched = stored.where(F.col("party") != party).join(new.select("bkv").distinct(), "bkv", "left_semi")
            rows = new.unionByName(touched)
            view = exchange_segments(rows, spec)
            totals = ring.ring_totals(compare.partial_counts(view, spec), spec, "k1")
            sink(linkage.readable(linkage.classify(totals, spec, "k1"), record_tokens(rows, spec), spec))
        finally:
            new.unpersist()

    return each


def rare_blocks(rows: DataFrame, most: int = 3) -> DataFrame:
    """bkv, n, rare: a running count of each block with an alarm while it is rarer than `most`; state is one number a block."""

    def count(key, frames, state):
        n = state.get[0] if state.exists else 0
        n += sum(len(f) for f in frames)
        state.update((n,))
        yield pd.DataFrame({"bkv": [key[0]], "n": [n], "rare": [n < most]})

    return rows.groupBy("bkv").applyInPandasWithState(count, "bkv string, n long, rare boolean", "n long", "update", "NoTimeout")


def run_to_table(stream: DataFrame, folder: str, mode: str = "append") -> DataFrame:
    """The stream run to the end of what is there (available-now trigger) with a checkpoint, its result as a table.

    append writes Parquet; update and complete go through foreachBatch, each batch under its number, so a batch that
    is run again replaces itself.
    """
    spark = stream.sparkSession
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{folder}/_state").trigger(availableNow=True)
    if mode == "append":
        writer.format("parquet").option("path", f"{folder}/rows").start().awaitTermination()
        return spark.read.parquet(f"{folder}/rows")
    writer.foreachBatch(lambda df, i: df.write.mode("overwrite").parquet(f"{folder}/rows/batch={i}")).start().awaitTermination()
    return spark.read.parquet(f"{folder}/rows")
