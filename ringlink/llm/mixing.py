"""Mixing sources to target weights by entropy balancing."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ringlink.llm.common import hot_join, settle, shared_dir, stored

WEIGHTS = (5, 2, 1)


def sizes(text: Column) -> Column:
    """Words parted by ASCII white space; null has none."""
    return F.size(F.regexp_extract_all(F.coalesce(text, F.lit("")), F.lit(r"[^\x20\x09-\x0D]+"), F.lit(0))).cast("long")


def _ranked(sources: DataFrame) -> DataFrame:
    """sources with `rank` from 0 in code point order, null last: ranges sorted apart, their counts added up."""
    parts = settle(sources.withColumn("_last", F.col("source").isNull()).repartitionByRange("_last", "source").sortWithinPartitions("_last", "source").withColumn("_p", F.spark_partition_id()).withColumn("_i", F.monotonically_increasing_id()))
    counts = {r["_p"]: (r["n"], r["low"]) for r in parts.groupBy("_p").agg(F.count("*").alias("n"), F.min("_i").alias("low")).collect()}  # a row a partition
    before, total = F.lit(0).cast("long"), 0
    for p in sorted(counts):
        before = F.when(F.col("_p") == p, F.lit(total - counts[p][1])).otherwise(before)
        total += counts[p][0]
    return parts.withColumn("rank", F.col("_i") + before).drop("_last", "_p", "_i")


def targets(totals: DataFrame, share: float = 1.5, most: float = 2.0, weights: tuple[int, ...] = WEIGHTS) -> DataFrame:
    """totals (source, size) with `target`: `share` of all sizes by weight, `most` times a source's size at most.

    What a full source cannot take is shared by weight among the rest, until none is above. A round needs two sums.
    """
    w = F.element_at(F.array(*(F.lit(float(x)) for x in weights)), (F.col("rank") % len(weights) + 1).cast("int"))
    rows = _ranked(totals).withColumn("weight", w)
    whole = rows.agg(F.coalesce(F.sum("size"), F.lit(0))).first()[0] * share
    rows = settle(rows.select("source", "size", "weight", F.lit(None).cast("double").alias("target")))
    while True:
        full, open_ = rows.agg(F.sum("target"), F.sum(F.when(F.col("target").isNull(), F.col("weight")))).first()
        if not open_:
            return rows.select("source", "size", "target")
        unit = (whole - (full or 0.0)) / open_
        over = F.col("target").isNull() & (F.col("weight") * unit > F.col("size") * most)
        if rows.where(over).isEmpty():
            return rows.select("source", "size", F.coalesce("target", F.col("weight") * unit).alias("target"))
        rows = settle(rows.withColumn("target", F.when(over, F.col("size") * most).otherwise(F.col("target"))))


def _rate(most: float) -> str:
    """A document's rate: the base rate 1 tilted by exp(dual * z), z its size over its source's mean size, bounded by `most`."""
    return f"{most} / (1 + ({most} - 1) * exp(-greatest(least(dual * z, 700D), -700D)))"


def balance(cells: DataFrame, aims: DataFrame, most: float = 2.0, exact: float = 1e-7, steps: int = 200) -> DataFrame:
    """source, dual of the convex dual of the sources' token constraints, by distributed Newton steps.

    cells: (source, size, n), the documents counted by size; aims: (source, size, target), one row a source. The entropy
    of the rates against 1, with rates between 0 and `most`, is least where each is a tilt of 1 by the exponential of
    its constraint's dual times the document's tokens. A step's gradient and curvature are sums over all cells, kept
    by source; the step is halved into the bracket of the root that earlier steps left, so it always ends. The driver
    sees the greatest relative error alone. A source at its bound has an infinite dual, an empty one the dual 0.
    """
    mean = cells.groupBy("source").agg((F.sum(F.col("size") * F.col("n")) / F.sum("n")).alias("mean"))
    c = cells.alias("c").join(mean.alias("m"), F.expr("c.source <=> m.source")).select("c.source", "c.size", "c.n", F.expr("if(mean > 0, c.size / mean, 0)").alias("z"))
    c = settle(c.where("size > 0"))
    free = "size > 0 AND target < %s * size" % most
    state = settle(aims.select("source", "size", "target", F.expr(f"if({free} OR size = 0, 0D, double('infinity'))").alias("dual"), F.lit(-1e6).alias("low"), F.lit(1e6).alias("high"), F.expr(free).alias("open")))
    w = _rate(most)
    for _ in range(steps):
        live = state.where("open").select(F.col("source").alias("s"), "dual")
        if live.isEmpty():
            break  # on settled rows: no step is computed again
        sums = c.join(live, F.expr("source <=> s")).withColumn("w", F.expr(w)).groupBy("s").agg(F.expr("sum(size * n * w)").alias("got"), F.expr(f"sum(size * n * z * w * (1 - w / {most}))").alias("slope"))
        step = state.alias("a").join(sums.alias("b"), F.expr("a.source <=> b.s AND a.open"), "left").withColumn("gradient", F.expr("got - target"))
        lower, upper = F.expr("if(gradient < 0, greatest(low, dual), low)"), F.expr("if(gradient > 0, least(high, dual), high)")
        step = step.withColumn("low", F.when(F.col("gradient").isNull(), F.col("low")).otherwise(lower)).withColumn("high", F.when(F.col("gradient").isNull(), F.col("high")).otherwise(upper))
        newton = "dual - greatest(least(try_divide(gradient, slope), 4D), -4D)"
        inside = F.expr(f"CASE WHEN gradient IS NULL OR gradient = 0 THEN dual WHEN ({newton}) > low AND ({newton}) < high THEN {newton} WHEN gradient > 0 THEN greatest(dual - 4, (low + dual) / 2) ELSE least(dual + 4, (dual + high) / 2) END")
        step = step.select("source", "size", "target", inside.alias("dual"), "low", "high", F.expr(f"open AND abs(gradient) > {exact} * target").alias("open"))
        state = settle(step.withColumn("open", F.coalesce("open", F.lit(False))))
    return state.select("source", "dual")


def _plan(narrow: DataFrame, share: float, most: float) -> DataFrame:
    """source, source_size, target, dual, mean, cut: one row a source, a stored table.

    Rates become whole copies: a document takes its rate's whole part, and one more where its priority, a hash of the
    row over the broken part, lies under its source's cut. The cut is found by four rounds of histograms of 256 cells a
    source, so the copies meet the target to about a document without sorting a source.
    """
    cells = settle(narrow.groupBy("source", "size").agg(F.count("*").alias("n")))
    totals = cells.groupBy("source").agg(F.sum(F.col("size") * F.col("n")).alias("size"), F.sum("n").alias("docs"))
    aims = settle(targets(totals.select("source", "size"), share, most))
    dual = balance(cells, aims, most)
    plan = aims.alias("a").join(dual.alias("d"), F.expr("a.source <=> d.source")).join(totals.alias("t"), F.expr("a.source <=> t.source"))
    plan = plan.select("a.source", F.col("a.size").alias("source_size"), "a.target", "d.dual", F.expr("t.size / docs").alias("mean"))
    plan = settle(plan)
    spark = narrow.sparkSession
    rated = _rated(narrow, plan, spark, most).select("key", "size", "whole", "p")
    rated = settle(rated.groupBy("key", "p").agg(F.sum(F.col("whole") * F.col("size")).alias("sure"), F.sum("size").alias("size")))  # by priority cell: bounded, not by document
    sure = rated.groupBy(F.col("key").alias("k")).agg(F.sum("sure").alias("sure"))
    state = plan.withColumn("key", _key("source")).join(sure, F.col("key") == F.col("k"), "left").select("key", "source", "source_size", "target", "dual", "mean", (F.col("target") - F.coalesce("sure", F.lit(0))).alias("need"), F.lit(0).cast("long").alias("cut"))
    for shift in (24, 16, 8, 0):
        wide = state.select(F.col("key").alias("k"), "cut", "need")
        at = rated.join(wide, F.col("key") == F.col("k")).withColumn("cell", F.expr(f"shiftright(p - cut, {shift})")).where("p >= cut AND cell < 256 AND p < 4294967295")
        hist = at.groupBy("k", "cell").agg(F.sum("size").alias("size"))
        cells_ = hist.groupBy("k").agg(F.array_sort(F.collect_list(F.struct("cell", "size"))).alias("h"))  # 256 cells at most
        last = "h.size / 2 < left" if shift == 0 else "h.size <= left"
        walk = f"aggregate(h, named_struct('left', double(need), 'cell', 0L, 'open', true), (a, h) -> if(a.open AND {last.replace('left', 'a.left')}, named_struct('left', a.left - h.size, 'cell', bigint(h.cell) + 1, 'open', true), named_struct('left', a.left, 'cell', if(a.open, bigint(h.cell), a.cell), 'open', false)))"
        moved = state.join(cells_, F.col("key") == F.col("k"), "left").withColumn("_w", F.expr(walk))
        full = "coalesce(if(_w.open, 256L, _w.cell), 256L)" if shift else "coalesce(_w.cell, 0L)"
        state = settle(moved.select("key", "source", "source_size", "target", "dual", "mean", F.expr("coalesce(_w.left, need)").alias("need"), F.expr(f"least(cut + shiftleft({full}, {shift}), 4294967295L)").alias("cut")))
    return state.select("key", "source_size", "target", "dual", "mean", "cut")


def _key(source: str) -> Column:
    """A source as a value that is never null."""
    return F.concat(F.when(F.col(source).isNull(), "n").otherwise("s"), F.coalesce(F.col(source).cast("string"), F.lit("")))


def _rated(rows: DataFrame, plan: DataFrame, spark, most: float) -> DataFrame:
    """rows (source, size, u) with the plan's columns, whole (copies for sure) and p, the priority for one more (32 bits, low first)."""
    import uuid

    if "key" not in plan.columns:
        plan = plan.withColumn("key", _key("source")).drop("source")
    plan = stored(plan.withColumnRenamed("key", "_k"), f"{shared_dir(spark)}/mix-{uuid.uuid4().hex}")
    out = hot_join(rows.withColumn("key", _key("source")), plan, "key", "_k").withColumn("z", F.expr("if(mean > 0, size / mean, 0)"))
    out = out.withColumn("rate", F.expr(f"CASE WHEN dual = double('infinity') THEN {most} ELSE {_rate(most)} END"))
    out = out.withColumn("whole", F.floor(F.col("rate") + 1e-9).cast("long")).withColumn("part", F.greatest(F.col("rate") - F.col("whole"), F.lit(0.0)))
    return out.withColumn("p", F.expr("if(part <= 1e-9 OR size = 0, 4294967295L, least(4294967294L, bigint(u / 16777216D / part * 268435456D)))"))


def _narrow(docs: DataFrame) -> DataFrame:
    u = F.shiftrightunsigned(F.xxhash64("doc_id", "source", F.lit("mix")), 40)
    return docs.withColumn("size", sizes(F.col("text"))).withColumn("u", u)


def _taken(rows: DataFrame, plan: DataFrame, most: float) -> DataFrame:
    out = _rated(rows, plan, rows.sparkSession, most)
    copies = F.least(F.col("whole") + F.expr("int(p < cut)"), F.lit(int(most))).cast("int")
    return out.withColumn("copies", copies).withColumn("taken", (F.col("copies") * F.col("size")).cast("long"))


def mix(docs: DataFrame, share: float = 1.5, most: float = 2.0) -> DataFrame:
    """docs (doc_id, text, source) with its columns and, named _size, _source_size, _target, _copies, _taken, the mix.

    Sizes count ASCII-space separated words (null: 0); a document without words has its base rate 1. Repeated rows
    share a hash. Nulls in doc_id or source are values of their own. An empty table gives no rows.
    """
    from ringlink.llm.common import shield

    rows, back = shield(docs, "doc_id", "text", "source")
    rows = _narrow(rows)
    plan = _plan(settle(rows.select("source", "size", "u")), share, most)
    out = _taken(rows, plan, most)
    return out.select(*back, *(F.col(c).alias(f"_{c}") for c in ("size", "source_size", "target", "copies", "taken")))


def digest(docs: DataFrame) -> DataFrame:
    """doc_id, size, source_size, target, taken, copies of every row of docs; null text has size 0, an empty table no rows.

    Texts are read once: sizes are settled before the mix is planned.
    """
    rows = settle(_narrow(docs.select("doc_id", "text", "source")).select("doc_id", "source", "size", "u"))
    out = _taken(rows, _plan(rows, 1.5, 2.0), 2.0)
    return out.select("doc_id", "size", F.col("source_size").cast("long").alias("source_size"), "target", "taken", "copies")
