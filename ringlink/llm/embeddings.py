"""Embedding near-dedup by an epsilon grid order join."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, FloatType

from ringlink.llm.common import Forest, components, settle

LEADING = 8
PLACED = "label string, dim int, cell array<int>, box array<double>, rep long, m long, v binary"
BLOCK = "label string, dim int, block long, c0 int, c1 int, low array<double>, high array<double>, reps array<long>, ms array<long>, vectors binary"


def _units(raw: np.ndarray) -> np.ndarray:
    a = raw.astype(np.float64)
    return a / np.linalg.norm(a, axis=1, keepdims=True)


def _axes(vectors: DataFrame, sample: int) -> dict[int, np.ndarray]:
    """Leading principal axes for each length among at most `sample` vectors; other lengths take their first components.

    Any orthonormal axes give a projection that lengthens no distance, so they change the time alone.
    """
    by: dict = {}
    for r in vectors.select("dim", "v").orderBy(F.xxhash64("v")).limit(sample).collect():
        by.setdefault(r["dim"], []).append(np.frombuffer(bytes(r["v"]), np.float64))
    out = {}
    for dim, rows in by.items():
        u = _units(np.array(rows))
        if len(u) > 1:
            out[dim] = np.linalg.svd(u - u.mean(0), full_matrices=False)[2][:LEADING]
    return out


def _placed(axes: dict, eps: float):
    def run(batches):
        for b in batches:
            rows = {"cell": [], "box": []}
            for dim, v in zip(b.column("dim").to_pylist(), b.column("v").to_pylist(), strict=True):
                u = _units(np.frombuffer(v, np.float64)[None, :])[0]
                a = axes.get(dim)
                p = (a @ u) if a is not None else u[:LEADING]
                p = np.concatenate([p, np.zeros(max(0, LEADING - len(p)))])
                rows["cell"].append(np.floor(p / eps).astype(int).tolist()), rows["box"].append(p.tolist())
            yield pa.RecordBatch.from_arrays([b.column("label"), b.column("dim"), pa.array(rows["cell"], pa.list_(pa.int32())), pa.array(rows["box"], pa.list_(pa.float64())), b.column("rep"), b.column("m"), b.column("v")], names=["label", "dim", "cell", "box", "rep", "m", "v"])

    return run


def _blocks(size: int):
    """The sorted sequence cut in blocks of `size` vectors of one label and length; ids are unique over tasks."""

    def run(batches):
        from pyspark import TaskContext

        base, n, held, now = TaskContext.get().partitionId() << 32, 0, [], None

        def out():
            boxes = np.array([h[1] for h in held])
            c0 = [h[0][0] for h in held]
            row = {"label": now[0], "dim": now[1], "block": base + n, "c0": min(c0), "c1": max(c0), "low": boxes.min(0).tolist(), "high": boxes.max(0).tolist(), "reps": [h[2] for h in held], "ms": [h[3] for h in held], "vectors": b"".join(h[4] for h in held)}
            schema = pa.schema([("label", pa.string()), ("dim", pa.int32()), ("block", pa.int64()), ("c0", pa.int32()), ("c1", pa.int32()), ("low", pa.list_(pa.float64())), ("high", pa.list_(pa.float64())), ("reps", pa.list_(pa.int64())), ("ms", pa.list_(pa.int64())), ("vectors", pa.binary())])
            return pa.RecordBatch.from_pylist([row], schema=schema)

        for b in batches:
            cols = [b.column(c).to_pylist() for c in ("label", "dim", "cell", "box", "rep", "m", "v")]
            for label, dim, cell, box, rep, m, v in zip(*cols, strict=True):
                if held and ((label, dim) != now or len(held) >= size):
                    yield out()
                    n, held = n + 1, []
                now = (label, dim)
                held.append((cell, box, rep, m, v))
        if held:
            yield out()

    return run


def meet(A, B, bounds_a, bounds_b, least: float, eps: float, leaf: int, same: bool, at: int = 0, bt: int = 0, skipped: list | None = None):
    """Pairs (i, j) of two sequence intervals with cosine `least` or more; i < j where both are one interval.

    The intervals are halved in turn; halves whose boxes on the leading dimensions lie over eps apart are skipped.
    """
    gap = np.maximum(0, np.maximum(bounds_a.min(0) - bounds_b.max(0), bounds_b.min(0) - bounds_a.max(0)))
    if (gap**2).sum() > (eps + 1e-9) ** 2:
        if skipped is not None:
            skipped.append(len(A) * len(B))
        return
    if len(A) <= leaf and len(B) <= leaf:
        i, j = np.nonzero(A @ B.T >= least)
        if same and at == bt:
            i, j = i[i < j], j[i < j]
        yield i + at, j + bt
        return
    m, k = (len(A) + 1) // 2, (len(B) + 1) // 2
    halves = [(A[:m], A[m:]), (B[:k], B[k:]), (bounds_a[:m], bounds_a[m:]), (bounds_b[:k], bounds_b[k:])]
    if same and at == bt:
        todo = [(0, 0), (1, 1), (0, 1)]
    elif len(A) >= len(B):
        for x in (0, 1):
            yield from meet(halves[0][x], B, halves[2][x], bounds_b, least, eps, leaf, same, at + m * x, bt, skipped)
        return
    else:
        for y in (0, 1):
            yield from meet(A, halves[1][y], bounds_a, halves[3][y], least, eps, leaf, same, at, bt + k * y, skipped)
        return
    for x, y in todo:
        yield from meet(halves[0][x], halves[1][y], halves[2][x], halves[3][y], least, eps, leaf, same, at + m * x, bt + k * y, skipped)


def _joined(axes: dict, least: float, eps: float, leaf: int = 128):
    """Rows sorted by `one`, the block itself first, then its partners: links of each class (a, null, n), and tree edges (a, b)."""

    def load(r):
        raw = np.frombuffer(r["vectors"], np.float64).reshape(-1, r["dim"])
        u = _units(raw)
        a = axes.get(r["dim"])
        return np.array(r["reps"], np.int64), np.array(r["ms"], np.int64), u, u @ a.T if a is not None else u[:, :LEADING]

    def run(batches):
        mine, name = None, None
        for batch in batches:
            for r in batch.to_pylist():
                theirs = load(r)
                if r["own"]:
                    mine, name = theirs, r["one"]
                elif r["one"] != name:
                    raise ValueError("a block came without its own vectors")
                i, j = [np.zeros(0, int)], [np.zeros(0, int)]
                for x, y in meet(mine[2], theirs[2], mine[3], theirs[3], least, eps, leaf, r["own"]):
                    i.append(x), j.append(y)
                i, j = np.concatenate(i), np.concatenate(j)
                n_a = np.bincount(i, weights=theirs[1][j], minlength=len(mine[0])).astype(np.int64)
                n_b = np.bincount(j, weights=mine[1][i], minlength=len(theirs[0])).astype(np.int64)
                forest = Forest()
                tree = [(a, b) for a, b in zip(mine[0][i].tolist(), theirs[0][j].tolist(), strict=True) if forest.link(a, b)]
                ids, n = np.concatenate([mine[0][n_a > 0], theirs[0][n_b > 0]]), np.concatenate([n_a[n_a > 0], n_b[n_b > 0]])
                yield pa.RecordBatch.from_arrays([pa.array([*ids.tolist(), *(a for a, _ in tree)], pa.int64()), pa.array([None] * len(ids) + [b for _, b in tree], pa.int64()), pa.array([*n.tolist(), *[0] * len(tree)], pa.int64())], names=["a", "b", "n"])

    return run


def _vectors(vectors: DataFrame) -> DataFrame:
    """vec_id, label, dim, v: the vectors that can link. v is the bytes of the components as doubles; -0 counts as 0."""
    e = F.col("embedding").cast("array<double>")
    fine = F.col("label").isNotNull() & (F.size(e) > 0) & F.forall(e, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists(e, lambda x: x != 0)
    rows = vectors.where(F.coalesce(fine, F.lit(False))).select(F.col("vec_id").cast("long").alias("vec_id"), F.col("label").cast("string").alias("label"), F.transform(e, lambda x: x + F.lit(0.0)).alias("e"))

    def packed(batches):
        for b in batches:
            e = b.column("e")
            flat, at = e.flatten().to_numpy(zero_copy_only=False), np.concatenate([[0], np.cumsum(e.value_lengths().to_numpy())])
            v = [flat[x:y].tobytes() for x, y in zip(at[:-1], at[1:], strict=True)]
            yield pa.RecordBatch.from_arrays([b.column("vec_id"), b.column("label"), pa.array(np.diff(at), pa.int32()), pa.array(v, pa.binary())], names=["vec_id", "label", "dim", "v"])

    return rows.mapInArrow(packed, "vec_id long, label string, dim int, v binary")


def near_duplicates(vectors: DataFrame, least: float = 0.93, sample: int = 4096, block: int = 2048) -> DataFrame:
    """(vec_id, n_links, component_id, kept) of vectors (vec_id, embedding, label), one row per row.

    Vectors link when labels are equal and not null, lengths are equal and their cosine (double precision) is `least` or
    more. Null, zero and non-finite vectors link with nothing. Equal vectors of a label are one class, counted and
    never paired; rows with one vec_id are one vector where they are equal. Classes are sorted by label, length and
    grid cell on the leading dimensions (epsilon grid order) into a range-partitioned sequence, cut in blocks of
    `block`. Blocks whose cells and boxes are within epsilon meet, each in the task of one of the two, and are joined
    by recursive halving. Only the sample of `sample` vectors for the axes reaches the driver. An empty table gives no rows.
    """
    spark = vectors.sparkSession
    eps = float(np.sqrt(2 - 2 * least))
    good = settle(_vectors(vectors))
    once = good.groupBy("label", "dim", "v", "vec_id").agg(F.lit(1).alias("_one"))
    classes = settle(once.groupBy("label", "dim", "v").agg(F.min("vec_id").alias("rep"), F.count("*").alias("m")))
    axes = _axes(classes, sample)
    placed = classes.select("label", "dim", "rep", "m", "v").mapInArrow(_placed(axes, eps), PLACED)
    order = ["label", "dim", "cell", "rep"]
    blocks = settle(placed.repartitionByRange(*order).sortWithinPartitions(*order).mapInArrow(_blocks(block), BLOCK))
    found = settle(_met(spark, blocks, eps).mapInArrow(_joined(axes, least, eps), "a long, b long, n long"))
    counts = found.where("b is null").groupBy("a").agg(F.sum("n").alias("n"))
    groups = components(found.where("b is not null").select("a", "b"))
    named = classes.join(counts, F.col("rep") == F.col("a"), "left").join(groups, F.col("rep") == F.col("node"), "left")
    named = named.select("label", "dim", "v", (F.coalesce("n", F.lit(0)) + F.col("m") - 1).alias("links"), F.coalesce("component", "rep").alias("group"))
    each = once.join(named, ["label", "dim", "v"]).groupBy("vec_id").agg(F.sum("links").alias("links"), F.min("group").alias("group"))
    out = vectors.select(F.col("vec_id").cast("long").alias("vec_id")).join(each.withColumnRenamed("vec_id", "_v"), F.col("vec_id") == F.col("_v"), "left")
    group = F.coalesce("group", "vec_id")
    return out.select("vec_id", F.coalesce("links", F.lit(0)).cast("long").alias("n_links"), group.alias("component_id"), (F.col("vec_id") == group).alias("kept"))


def _met(spark: SparkSession, blocks: DataFrame, eps: float) -> DataFrame:
    """own, one and the columns of a block: each block itself, then the blocks within epsilon of it, sorted into its task.

    Cells that differ by one at most in the first dimension are met by an equi-join of block outlines; the boxes then
    decide. A pair is dealt to either of its blocks by digest, so no block has all of its partners.
    """
    outline = blocks.select("label", "dim", "block", "c0", "c1", "low", "high")
    left = outline.select("label", "dim", F.col("block").alias("x"), F.col("low").alias("lx"), F.col("high").alias("hx"), F.explode(F.sequence(F.col("c0") - 1, F.col("c1") + 1)).alias("c"))
    right = outline.select("label", "dim", F.col("block").alias("y"), F.col("low").alias("ly"), F.col("high").alias("hy"), F.explode(F.sequence("c0", "c1")).alias("c"))
    apart = F.expr("aggregate(zip_with(zip_with(lx, hy, (l, h) -> l - h), zip_with(ly, hx, (l, h) -> l - h), (a, b) -> pow(greatest(a, b, 0D), 2)), 0D, (s, x) -> s + x)")
    pairs = left.join(right, ["label", "dim", "c"]).where("x < y").where(apart <= (eps + 1e-9) ** 2).select("x", "y").distinct()
    turn = F.pmod(F.xxhash64("x", "y"), F.lit(2)) == 0
    pairs = pairs.select(F.when(turn, F.col("x")).otherwise(F.col("y")).alias("one"), F.when(turn, F.col("y")).otherwise(F.col("x")).alias("two"))
    cols = ["block", "dim", "reps", "ms", "vectors"]
    own = blocks.select(F.lit(True).alias("own"), F.col("block").alias("one"), *cols)
    others = pairs.join(blocks.select(*cols), F.col("two") == F.col("block")).select(F.lit(False).alias("own"), "one", *cols)
    return own.unionByName(others).repartition("one").sortWithinPartitions("one", F.desc("own"), "block")
