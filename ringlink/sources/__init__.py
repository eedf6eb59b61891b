"""Registers and pieces in files and tables, and a message channel as a data source."""

from __future__ import annotations

import json
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

REGISTER = "party int, rid string, entity long, given string, surname string, suburb string, postcode string"


def read_register(spark: SparkSession, path: str, kind: str = "parquet", schema: str = REGISTER) -> DataFrame:
    """A party's delivery with the agreed schema, never an inferred one. kind: parquet, csv, json, orc, text (tab-separated)."""
    if kind == "text":
        fields = [f.strip().split(" ") for f in schema.split(",")]
        cut = F.split("value", "\t")
        return spark.read.text(path).select(*(F.when(cut[i] != "\\N", cut[i]).cast(t).alias(n) for i, (n, t) in enumerate(fields)))
    reader = spark.read.schema(schema)
    if kind == "csv":  # an empty field is null, a quoted one an empty value
        reader = reader.option("header", True).option("emptyValue", "").option("nullValue", "\\N").option("mode", "FAILFAST")
    return reader.format(kind).load(path)


def write_register(df: DataFrame, path: str, kind: str = "parquet") -> None:
    if kind == "text":
        cols = [F.coalesce(F.col(c).cast("string"), F.lit("\\N")) for c in df.columns]
        df.select(F.concat_ws("\t", *cols).alias("value")).write.text(path)
        return
    writer = df.write.format(kind)
    if kind == "csv":
        writer = writer.option("header", True).option("emptyValue", "").option("nullValue", "\\N")
    writer.save(path)


def write_pieces(view: DataFrame, path: str) -> None:
    """Pieces by holder: each holder reads its own folder, and the scan prunes the others."""
    view.write.partitionBy("holder").parquet(path)


def save_pieces(view: DataFrame, table: str, buckets: int = 8) -> None:
    """Pieces bucketed and sorted by (holder, block token): the holders' joins on them need no shuffle."""
    view.write.bucketBy(buckets, "holder", "bkv").sortBy("holder", "bkv").mode("overwrite").saveAsTable(table)


class Inbox(DataSource):
    """Messages of one receiver, read from a folder of JSON lines: sender, receiver, body. Option `receiver` names it.

    A party's reader opens only files named for it (`to-<receiver>*.jsonl`), one partition a file.
    """

    @classmethod
    def name(cls) -> str:
        return "inbox"

    def schema(self) -> str:
        return "sender int, receiver int, body string"

    def reader(self, schema) -> DataSourceReader:
        return InboxReader(self.options["path"], int(self.options["receiver"]))


class InboxReader(DataSourceReader):
    def __init__(self, path: str, receiver: int) -> None:
        self.path, self.receiver = path, receiver

    def partitions(self):
        return [InputPartition(str(f)) for f in sorted(Path(self.path).glob(f"to-{self.receiver}-*.jsonl"))] or [InputPartition(None)]

    def read(self, partition):
        if partition.value is None:
            return
        with open(partition.value) as lines:
            for line in lines:
                m = json.loads(line)
                if m["receiver"] != self.receiver:
                    raise ValueError("a message for another party in this inbox")
                yield m["sender"], m["receiver"], m["body"]


def post(transcript: DataFrame, path: str) -> None:
    """Ring messages (sender, receiver, ...) as JSON lines, a file for each receiver and task."""
    Path(path).mkdir(parents=True, exist_ok=True)

    def send(rows):
        import uuid

        out: dict = {}
        for r in rows:
            out.setdefault(r["receiver"], []).append(json.dumps({"sender": r["sender"], "receiver": r["receiver"], "body": r["body"]}))
        for receiver, lines in out.items():
            Path(path, f"to-{receiver}-{uuid.uuid4().hex}.jsonl").write_text("\n".join(lines) + "\n")

    body = F.to_json(F.struct(*(c for c in transcript.columns if c not in ("sender", "receiver"))))
    transcript.select("sender", "receiver", body.alias("body")).foreachPartition(send)


def null_policy(register: DataFrame, qids: tuple[str, ...], policy: str = "empty") -> DataFrame:
    """Missing attributes: `empty` counts them as empty values, `skip` drops such records, `count` adds how many are missing."""
    if policy == "empty":
        return register.na.fill("", list(qids))
    if policy == "skip":
        return register.na.drop(subset=list(qids))
    missing = [F.col(c).isNull().cast("int") for c in qids]
    return register.withColumn("missing", sum(missing[1:], missing[0]))


def hash_sample(df: DataFrame, key: str, share: float, seed: str = "") -> DataFrame:
    """A share of the rows by a keyed digest: the same rows on every run and in every engine."""
    h = F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}|"), F.col(key).cast("string"))), 1, 8), 16, 10).cast("long")
    return df.where(h < int(share * (1 << 32)))
