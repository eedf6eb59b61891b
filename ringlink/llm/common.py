"""What the corpus operators share: tables, durable intermediate results, connected components."""

from __future__ import annotations

import ctypes
import gc
import tempfile

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or one of our own where it is unset."""
    sc = spark.sparkContext
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named:
        named = sc.getCheckpointDir()
    if not named:
        local = sc.master.startswith("local[") or sc.master == "local"
        named = tempfile.mkdtemp(prefix="ringlink-") if local else spark.conf.get("spark.sql.warehouse.dir") + "/_shared"
    if sc.getCheckpointDir() is None:
        sc.setCheckpointDir(named)
    return named


def settle(df: DataFrame) -> DataFrame:
    """Write df to the shared checkpoint folder now and read it from there: the lineage is cut, a lost executor loses nothing."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def stored(df: DataFrame, path: str) -> DataFrame:
    """df as a Parquet table in the shared folder: its size is then known to the planner."""
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def remove(spark: SparkSession, *paths: str) -> None:
    """Delete what is no longer read."""
    sc = spark.sparkContext
    for p in paths:
        path = sc._jvm.org.apache.hadoop.fs.Path(p)
        path.getFileSystem(sc._jsc.hadoopConfiguration()).delete(path, True)


def hot_join(left: DataFrame, right: DataFrame, on: str, key: str, rows: int = 200_000, salts: int = 16) -> DataFrame:
    """left outer join of left.on = right.key, right unique by key and settled, where one key may hold much of left.

    A right side of `rows` rows or fewer, counted, is broadcast; beyond it, it is copied to `salts` tasks a key.
    """
    if right.count() <= rows:
        return left.join(F.broadcast(right), F.col(on) == F.col(key), "left")
    dealt = left.withColumn("_salt", (F.rand() * salts).cast("int"))
    copied = right.withColumn("_copy", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return dealt.join(copied, (F.col(on) == F.col(key)) & (F.col("_salt") == F.col("_copy")), "left").drop("_salt", "_copy")


def shield(docs: DataFrame, *used: str) -> tuple[DataFrame, list]:
    """docs whose columns other than `used` have names that clash with none of ours, and the columns that undo it."""
    names = {c: c if c in used else f"_other{i}" for i, c in enumerate(docs.columns)}
    back = [F.col(f"`{n}`").alias(c) for c, n in names.items()]
    return docs.select(*(F.col(f"`{c}`").alias(n) for c, n in names.items())), back


#: Functions that empty what this process keeps between tasks.
KEPT: list = []


def lean(run, drop: bool = True):
    """A mapInArrow function that hands memory back to the system when its task ends, as Spark keeps Python workers for
    later stages; with `drop` it first empties what other operators' tasks keep in this worker."""

    def out(batches):
        if drop:
            for empty in KEPT:
                empty()
            _trim()
        yield from run(batches)
        _trim()

    return out


def _trim() -> None:
    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # not the GNU library
        pass


class Forest:
    """Union-find over hashable nodes; the smallest node of a tree is its root."""

    def __init__(self) -> None:
        self.up: dict = {}

    def find(self, a):
        up = self.up
        root = a
        while (nxt := up.get(root, root)) != root:
            root = nxt
        while a != root:
            up[a], a = root, up.get(a, root)
        return root

    def link(self, a, b) -> bool:
        a, b = self.find(a), self.find(b)
        if a == b:
            return False
        if b < a:
            a, b = b, a
        self.up[b] = a
        self.up.setdefault(a, a)
        return True


EDGE = "a long, b long"
#: Links that one task may hold: nodes are then fewer than `_contract` gathers before it hands out stars.
ONE_TASK = 200_000


def _contract(batches):
    """Each partition's links become stars around the smallest node that they reach."""
    forest, seen = Forest(), 0
    for batch in batches:
        for a, b in zip(batch.column("a").to_pylist(), batch.column("b").to_pylist(), strict=True):
            forest.link(a, b)
        seen += batch.num_rows
        if len(forest.up) > 500_000:  # bounded: what was gathered goes out as stars, later rounds join it
            yield _stars(forest)
            forest = Forest()
    yield _stars(forest)


def _stars(forest: Forest) -> pa.RecordBatch:
    pairs = [(r, n) for n in list(forest.up) if (r := forest.find(n)) != n]
    return pa.RecordBatch.from_arrays([pa.array([p[0] for p in pairs], pa.int64()), pa.array([p[1] for p in pairs], pa.int64())], names=["a", "b"])


def components(edges: DataFrame) -> DataFrame:
    """(node, component) of each node of the links (a, b): component is the smallest node reachable.

    Links are first contracted partition by partition, then large and small stars alternate until
    nothing changes. Each round takes minima by aggregation (map-side combined) and hands them back by an
    equi-join whose two sides AQE may split, so a node with very many neighbours is no single task's work.
    No link, label or component reaches the driver: only a checksum of the links does, to see the end.
    """
    one_way = edges.select(F.col("a").cast("long").alias("a"), F.col("b").cast("long").alias("b")).where("a <> b")
    e = settle(one_way.mapInArrow(_contract, EDGE).distinct())
    if e.count() <= ONE_TASK:  # counted: one task's union-find ends it, beyond that the rounds do
        e = settle(e.repartition(1).mapInArrow(_contract, EDGE))
        return _labelled(e)
    mark = None
    while True:
        both = e.select("a", "b").union(e.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
        large = both.join(low, "a").where("b > a").select(F.col("m").alias("a"), "b").where("a <> b").distinct()
        down = large.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
        least = down.groupBy("a").agg(F.min("b").alias("m"))
        small = down.join(least, "a").select(F.explode(F.array(F.struct(F.col("m").alias("a"), F.col("a").alias("b")), F.struct(F.col("m").alias("a"), F.col("b").alias("b")))).alias("p")).select("p.a", "p.b").where("a <> b").distinct()
        e = settle(small)
        now = e.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")), F.countDistinct("b")).first()
        if now == mark or now[0] == now[2] and not e.alias("x").join(e.select(F.col("b").alias("n")).distinct(), F.col("x.a") == F.col("n"), "left_semi").take(1):
            break
        mark = now
    return _labelled(e)


def _labelled(stars: DataFrame) -> DataFrame:
    return stars.select(F.col("b").alias("node"), F.col("a").alias("component")).union(stars.select(F.col("a").alias("node"), F.col("a").alias("component")).distinct())
