"""Queries of the engine around the linkage: sources, joins, aggregates, windows, sets, functions, streams, UDFs."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ringlink import functions as fn
from ringlink import sources, streaming
from ringlink.operators import encoding as E
from ringlink.operators import exchange as X
from ringlink.operators import registers as R
from ringlink.oracles import filters, held, key, place, reg, spec_key, standard
from ringlink.plans.physical import salted_join, settle, small
from ringlink.spec import LinkageSpec

S3 = LinkageSpec()


def _t(name):
    return lambda k, d: k.read.parquet(f"{d}/{name}.parquet")


customer, orders, nation, region, events, part, supplier, lineitem, pages, conversations = map(_t, "customer orders nation region events part supplier lineitem pages conversations".split())


def people(k, d, p=3):
    return R.make_register(customer(k, d).select(F.col("c_custkey").alias("entity"), F.col("c_nationkey").alias("nation")), p)


def _scratch(k) -> str:
    """A folder of its own in the session's shared checkpoint folder, or in a temporary one where none is named."""
    import tempfile

    named = k.conf.get("spark.checkpoint.dir", None) or k.sparkContext.getCheckpointDir() or tempfile.mkdtemp(prefix="ringlink-")
    return f"{named.removeprefix('file:')}/{uuid.uuid4().hex}"


def _round_trip(kind):
    def run(k, d):
        rows = people(k, d).select("party", "rid", "entity", F.when(F.col("entity") % 7 != 0, F.col("given")).alias("given"), F.when(F.col("entity") % 11 == 0, F.lit('a "b", c')).otherwise(F.col("surname")).alias("surname"), "suburb", "postcode")
        path = _scratch(k)
        sources.write_register(rows, path, kind)
        return sources.read_register(k, path, kind)

    return run


_TRIP = f"WITH {reg()} SELECT party, rid, entity, CASE WHEN entity % 7 <> 0 THEN given END AS given, CASE WHEN entity % 11 = 0 THEN 'a \"b\", c' ELSE surname END AS surname, suburb, postcode FROM reg"


def _sources() -> dict:
    def pieces(k, d):
        path = _scratch(k)
        sources.write_pieces(X.exchange_segments(E.encode_register(people(k, d), S3), S3), path)
        return k.read.parquet(path).where("holder = 2").groupBy("owner").agg(F.count("*").alias("rows"), F.sum("seg_ones").alias("ones"))

    def bucketed(k, d):
        name = f"pieces_{uuid.uuid4().hex}"
        sources.save_pieces(X.exchange_segments(E.encode_register(people(k, d), S3), S3), name)
        t = k.table(name)
        a, b = t.where("owner = 1").select("holder", "bkv", F.col("rid").alias("r1")), t.where("owner = 2").select("holder", "bkv", F.col("rid").alias("r2"))
        out = settle(a.join(b, ["holder", "bkv"]).groupBy("holder").agg(F.count("*").alias("pairs")))
        k.sql(f"DROP TABLE {name}")
        return out

    def inbox(k, d):
        from ringlink.operators import compare, ring

        view = settle(X.exchange_segments(E.encode_register(people(k, d), S3), S3))
        path = _scratch(k)
        sources.post(ring.ring_transcript(compare.partial_counts(view, S3, "prefix"), S3, "k1").select("sender", "receiver", "cand", "masked_c"), path)
        k.dataSource.register(sources.Inbox)
        read = k.read.format("inbox").option("receiver", 2).load(path)
        return read.groupBy("sender", "receiver").agg(F.countDistinct(F.get_json_object("body", "$.cand")).alias("messages"))

    def in_memory(k, d):
        """Rows given in the program and in SQL text, met by customers."""
        rows = k.createDataFrame([(1, "x"), (2, None)], "a int, b string").union(k.sql("SELECT * FROM VALUES (3, 'y') v(a, b)"))
        return customer(k, d).select("c_custkey", (F.col("c_custkey") % 3 + 1).cast("int").alias("a")).join(F.broadcast(rows), "a").select("c_custkey", "a", "b")

    def bernoulli(k, d):
        """Whether a sample of a fifth has as many keys as it should, within five standard deviations, none twice."""
        keys = customer(k, d).select("c_custkey")
        n = keys.sample(0.2, 7).agg(F.count("c_custkey").alias("n"), F.countDistinct("c_custkey").alias("d"))
        both = n.crossJoin(keys.agg(F.count("*").alias("all")))  # one row each
        return both.select(((F.abs(F.col("n") - 0.2 * F.col("all")) <= 5 * F.sqrt(0.16 * F.col("all")) + 1) & (F.col("n") == F.col("d"))).alias("plausible"))

    def missing(k, d):
        rows = people(k, d).withColumn("given", F.when(F.col("entity") % 5 != 0, F.col("given"))).withColumn("suburb", F.when(F.col("entity") % 7 != 0, F.col("suburb")))
        n = sources.null_policy(rows, S3.qids, "count").groupBy("missing").agg(F.count("*").alias("n")).select(F.concat(F.lit("missing "), F.col("missing")).alias("policy"), "n")
        kept = sources.null_policy(rows, S3.qids, "skip").agg(F.lit("skip").alias("policy"), F.count("*").alias("n"))
        filled = sources.null_policy(rows, S3.qids).agg(F.lit("empty").alias("policy"), F.count_if(F.col("given") == "").alias("n"))
        return n.unionByName(kept).unionByName(filled)

    return {
        "scan_prune": (lambda k, d: orders(k, d).where((F.col("o_totalprice") > 250000) & (F.col("o_orderstatus") == "F")).select("o_orderkey", "o_custkey"), "SELECT o_orderkey, o_custkey FROM orders WHERE o_totalprice>250000 AND o_orderstatus='F'"),
        **{f"roundtrip_{kind}": (_round_trip(kind), _TRIP) for kind in ("csv", "json", "orc", "text", "parquet")},
        "in_memory": (in_memory, "SELECT c_custkey, (c_custkey%3+1)::INT AS a, b FROM customer JOIN (VALUES (1,'x'),(2,NULL),(3,'y')) v(a,b) ON v.a=c_custkey%3+1"),
        "pieces_partitioned": (pieces, f"WITH {reg()}, {filters('reg', spec_key(3))} SELECT party AS owner, count(*) AS rows, sum(len(list_filter(v, lambda q: q//167=1)))::BIGINT AS ones FROM e GROUP BY party"),
        "pieces_bucketed": (bucketed, f"WITH {reg()} SELECT h::INT AS holder, count(*) AS pairs FROM reg a JOIN reg b ON {key().replace('surname', 'a.surname')}={key().replace('surname', 'b.surname')}, range(1,4) t(h) WHERE a.party=1 AND b.party=2 GROUP BY h"),
        "inbox": (inbox, f"{standard(3)}, {held(3, 167)} SELECT 1 AS sender, 2 AS receiver, count(*) AS messages FROM kept WHERE holder=1"),
        "projection": (lambda k, d: part(k, d).select("*", (F.col("p_retailprice") * 2).alias("twice")).withColumnRenamed("p_name", "name").drop("p_type").withColumn("p_size", F.col("p_size") + 1), "SELECT p_partkey, p_name AS name, p_brand, p_size+1 AS p_size, p_retailprice, p_retailprice*2 AS twice FROM part"),
        "predicates": (lambda k, d: part(k, d).where((F.col("p_size").between(5, 20) | F.col("p_brand").isin("Brand#1", "Brand#2")) & ~F.col("p_name").like("small%") & F.col("p_name").rlike("[aeiou]n") & ~F.col("p_type").eqNullSafe(None)).select("p_partkey", F.when(F.col("p_size") < 10, "low").when(F.col("p_size") < 30, "mid").otherwise("high").alias("class")), "SELECT p_partkey, CASE WHEN p_size<10 THEN 'low' WHEN p_size<30 THEN 'mid' ELSE 'high' END AS class FROM part WHERE (p_size BETWEEN 5 AND 20 OR p_brand IN ('Brand#1','Brand#2')) AND NOT p_name LIKE 'small%' AND regexp_matches(p_name,'[aeiou]n') AND p_type IS DISTINCT FROM NULL"),
        "null_policy": (missing, f"WITH {reg()}, m AS (SELECT (entity % 5=0)::INT+(entity % 7=0)::INT AS n, entity FROM reg) SELECT 'missing '||n::VARCHAR AS policy, count(*) AS n FROM m GROUP BY n UNION ALL SELECT 'skip', count(*) FILTER (n=0) FROM m UNION ALL SELECT 'empty', count(*) FILTER (entity % 5=0) FROM m"),
        "dedup": (lambda k, d: events(k, d).dropDuplicates(["user_id", "event_type"]).select("user_id", "event_type"), "SELECT DISTINCT user_id, event_type FROM events"),
        "hash_sample": (lambda k, d: sources.hash_sample(customer(k, d), "c_custkey", 0.25).select("c_custkey"), "SELECT c_custkey FROM customer WHERE ('0x'||substr(md5('|'||c_custkey::VARCHAR),1,8))::BIGINT < 1073741824"),
        "sample_bernoulli": (bernoulli, "SELECT true AS plausible"),
        "sample_stratified": (lambda k, d: people(k, d).sampleBy("party", {1: 1.0, 2: 0.0}, 7).groupBy("party").agg(F.count("*").alias("n")), f"WITH {reg()} SELECT party, count(*) AS n FROM reg WHERE party=1 GROUP BY party"),
    }


def _joins() -> dict:
    co = lambda k, d, hint=None: (lambda o, c: o.join(c.hint(hint) if hint else c, o.o_custkey == c.c_custkey))(orders(k, d).select("o_orderkey", "o_custkey"), customer(k, d).select("c_custkey", "c_nationkey"))
    inner = "SELECT o_orderkey, o_custkey, c_custkey, c_nationkey FROM orders JOIN customer ON o_custkey=c_custkey"
    a = lambda k, d: people(k, d).where("party = 1").select("entity", "rid")
    b = lambda k, d: people(k, d).where("party = 2").select("entity", F.col("rid").alias("rid2"))
    sides = f"WITH {reg()}, a AS (SELECT entity, rid FROM reg WHERE party=1), b AS (SELECT entity, rid AS rid2 FROM reg WHERE party=2)"

    def asof(k, d):
        """Each event with the last order of its user before it: one pass over both, merged by user and time."""
        o = orders(k, d).select(F.col("o_custkey").alias("user_id"), F.col("o_orderdate").alias("at"), "o_orderkey")
        e = events(k, d).select("user_id", F.col("ts").alias("at"), "event_id")
        both = o.select("user_id", "at", "o_orderkey", F.lit(None).cast("long").alias("event_id"), F.lit(0).alias("side")).unionByName(e.select("user_id", "at", F.lit(None).cast("long").alias("o_orderkey"), "event_id", F.lit(1).alias("side")))
        last = F.last("o_orderkey", True).over(W.partitionBy("user_id").orderBy("at", "side", "o_orderkey").rowsBetween(W.unboundedPreceding, 0))
        return both.withColumn("last_order", last).where("side = 1").select("event_id", "last_order")

    def salted(k, d):
        rows, names = events(k, d).select("event_id", "event_type"), events(k, d).groupBy("event_type").agg(F.count("*").alias("n"))
        return salted_join(rows, names, ["event_type"], 4)

    def lateral(k, d):
        customer(k, d).createOrReplaceTempView("_customer")
        orders(k, d).createOrReplaceTempView("_orders")
        return k.sql("SELECT c_custkey, n, top FROM _customer, LATERAL (SELECT count(*) AS n, max(o_totalprice) AS top FROM _orders WHERE o_custkey = c_custkey) WHERE c_custkey < 200")

    def interval(k, d):
        e = events(k, d).where("event_type = 'error'").select("user_id", "event_id", "ts")
        c = events(k, d).where("event_type = 'click'").select(F.col("user_id").alias("u2"), F.col("event_id").alias("e2"), F.col("ts").alias("t2"))
        return e.join(c, (F.col("user_id") == F.col("u2")) & F.col("t2").between(F.col("ts") - F.expr("INTERVAL 1 HOUR"), F.col("ts"))).select("event_id", "e2")

    return {
        **{f"join_{n}": (lambda k, d, h=h: co(k, d, h), inner) for n, h in (("inner", None), ("merge", "merge"), ("shuffle_hash", "shuffle_hash"))},
        "join_broadcast": (lambda k, d: customer(k, d).join(small(nation(k, d), 10_000), F.col("c_nationkey") == F.col("n_nationkey")).join(small(region(k, d), 10_000), F.col("n_regionkey") == F.col("r_regionkey")).groupBy("r_name").agg(F.count("*").alias("n")), "SELECT r_name, count(*) AS n FROM customer JOIN nation ON c_nationkey=n_nationkey JOIN region ON n_regionkey=r_regionkey GROUP BY r_name"),
        "join_theta": (lambda k, d: supplier(k, d).alias("a").join(supplier(k, d).alias("b"), (F.col("a.s_nationkey") == F.col("b.s_nationkey")) & (F.col("a.s_acctbal") < F.col("b.s_acctbal"))).select(F.col("a.s_suppkey").alias("low"), F.col("b.s_suppkey").alias("high")), "SELECT a.s_suppkey AS low, b.s_suppkey AS high FROM supplier a JOIN supplier b ON a.s_nationkey=b.s_nationkey AND a.s_acctbal<b.s_acctbal"),
        "join_cross": (lambda k, d: nation(k, d).crossJoin(F.broadcast(region(k, d))).select("n_name", "r_name"), "SELECT n_name, r_name FROM nation, region"),
        "join_semi": (lambda k, d: customer(k, d).join(orders(k, d), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey"), "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)"),
        "join_anti": (lambda k, d: customer(k, d).join(orders(k, d), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey"), "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey=c_custkey)"),
        **{f"join_{n}": (lambda k, d, h=h: a(k, d).join(b(k, d), "entity", h), f"{sides} SELECT * FROM a {s} JOIN b USING (entity)") for n, h, s in (("left", "left", "LEFT"), ("right", "right", "RIGHT"), ("full", "full_outer", "FULL"))},
        "join_self": (lambda k, d: a(k, d).join(b(k, d), "entity").join(people(k, d).where("party = 3").select("entity", F.col("rid").alias("rid3")), "entity"), f"{sides} SELECT a.entity, rid, rid2, c.rid3 FROM a JOIN b USING (entity) JOIN (SELECT entity, rid AS rid3 FROM reg WHERE party=3) c USING (entity)"),
        "join_asof": (asof, "SELECT event_id, (SELECT o_orderkey FROM orders WHERE o_custkey=user_id AND o_orderdate<=ts ORDER BY o_orderdate DESC, o_orderkey DESC LIMIT 1) AS last_order FROM events"),
        "join_interval": (interval, "SELECT e.event_id, c.event_id AS e2 FROM events e JOIN events c ON e.user_id=c.user_id AND e.event_type='error' AND c.event_type='click' AND c.ts BETWEEN e.ts-INTERVAL 1 HOUR AND e.ts"),
        "join_lateral": (lateral, "SELECT c_custkey, n, top FROM customer, LATERAL (SELECT count(*) AS n, max(o_totalprice) AS top FROM orders WHERE o_custkey=c_custkey) WHERE c_custkey<200"),
        "join_explode": (lambda k, d: conversations(k, d).select("conv_id", "turn", F.explode(F.split("text", " ")).alias("word")).groupBy("word").agg(F.count("*").alias("n")), "SELECT word, count(*) AS n FROM (SELECT unnest(string_split(text,' ')) AS word FROM conversations) GROUP BY word"),
        "join_salted": (salted, "SELECT event_id, event_type, count(*) OVER (PARTITION BY event_type) AS n FROM events"),
    }


def _aggregates() -> dict:
    o = orders
    money = lambda: F.col("o_totalprice").cast("decimal(18,2)")
    price = "o_totalprice::DECIMAL(18,2)"
    grouped = lambda k, d: o(k, d).select("o_orderstatus", "o_orderpriority", F.year("o_orderdate").alias("y"))
    sql_sets = lambda s: f"SELECT o_orderstatus, o_orderpriority, count(*) AS n, grouping(o_orderstatus)::INT AS g FROM orders GROUP BY {s}"

    def sets(k, d, how):
        o(k, d).createOrReplaceTempView("_orders")
        return k.sql(f"SELECT o_orderstatus, o_orderpriority, count(*) AS n, int(grouping(o_orderstatus)) AS g FROM _orders GROUP BY {how}")

    words = lambda k, d: E.encode_register(people(k, d), S3)
    bits = f"WITH {reg()}, {filters('reg', spec_key(3))}"
    return {
        "agg_basic": (lambda k, d: o(k, d).groupBy("o_orderstatus").agg(F.sum(money()).cast("double").alias("total"), F.count("*").alias("n"), F.min("o_totalprice").alias("low"), F.max("o_totalprice").alias("high"), F.round(F.avg("o_totalprice"), 4).alias("mean"), F.round(F.stddev("o_totalprice"), 3).alias("sd")), f"SELECT o_orderstatus, sum({price})::DOUBLE AS total, count(*) AS n, min(o_totalprice) AS low, max(o_totalprice) AS high, round(avg(o_totalprice),4) AS mean, round(stddev(o_totalprice),3) AS sd FROM orders GROUP BY 1"),
        "agg_distinct": (lambda k, d: o(k, d).groupBy("o_orderstatus").agg(F.countDistinct("o_custkey").alias("customers"), F.countDistinct("o_orderpriority").alias("priorities")), "SELECT o_orderstatus, count(DISTINCT o_custkey) AS customers, count(DISTINCT o_orderpriority) AS priorities FROM orders GROUP BY 1"),
        "agg_approx_distinct": (lambda k, d: o(k, d).agg(F.countDistinct("o_custkey").alias("n"), F.approx_count_distinct("o_custkey", 0.02).alias("a"), F.hll_sketch_estimate(F.hll_sketch_agg("o_custkey", 14)).alias("h")).select((F.abs(F.col("a") / F.col("n") - 1) < 0.1).alias("approx"), (F.abs(F.col("h") / F.col("n") - 1) < 0.05).alias("sketch")), "SELECT true AS approx, true AS sketch"),
        "agg_bits": (lambda k, d: words(k, d).groupBy("party").agg(F.bit_or("b0").alias("any"), F.bit_and("b0").alias("every"), F.bit_count(F.bit_xor("b0")).alias("odd")), f"{bits}, w AS (SELECT party, rid, sum(CASE WHEN p<63 THEN 1::BIGINT<<(p%63) ELSE 0 END)::BIGINT AS b0 FROM pos GROUP BY party, rid) SELECT party, bit_or(b0) AS any, bit_and(b0) AS every, bit_count(bit_xor(b0))::INT AS odd FROM w GROUP BY party"),
        "agg_collect": (lambda k, d: o(k, d).groupBy("o_custkey").agg(F.concat_ws(",", F.array_sort(F.collect_list("o_orderkey")).cast("array<string>")).alias("keys"), F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("dearest"), F.min_by("o_orderkey", F.struct("o_orderdate", "o_orderkey")).alias("first")), "SELECT o_custkey, string_agg(o_orderkey::VARCHAR, ',' ORDER BY o_orderkey) AS keys, arg_max(o_orderkey, (o_totalprice, o_orderkey)) AS dearest, arg_min(o_orderkey, (o_orderdate, o_orderkey)) AS first FROM orders GROUP BY 1"),
        "agg_percentile": (lambda k, d: o(k, d).groupBy("o_orderstatus").agg(F.round(F.percentile("o_totalprice", 0.5), 4).alias("median"), F.round(F.percentile("o_totalprice", 0.95), 4).alias("p95")), "SELECT o_orderstatus, round(quantile_cont(o_totalprice,0.5),4) AS median, round(quantile_cont(o_totalprice,0.95),4) AS p95 FROM orders GROUP BY 1"),
        "agg_rollup": (lambda k, d: grouped(k, d).rollup("o_orderstatus", "y").agg(F.count("*").alias("n")), "SELECT o_orderstatus, year(o_orderdate)::INT AS y, count(*) AS n FROM orders GROUP BY ROLLUP (o_orderstatus, year(o_orderdate))"),
        "agg_cube": (lambda k, d: grouped(k, d).cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n")), "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)"),
        "agg_sets": (lambda k, d: sets(k, d, "GROUPING SETS ((o_orderstatus, o_orderpriority), (o_orderpriority), ())"), sql_sets("GROUPING SETS ((o_orderstatus, o_orderpriority), (o_orderpriority), ())")),
        "agg_pivot": (lambda k, d: grouped(k, d).groupBy("y").pivot("o_orderstatus", ["F", "O", "P"]).count(), "SELECT year(o_orderdate)::INT AS y, nullif(count(*) FILTER (o_orderstatus='F'),0) AS F, nullif(count(*) FILTER (o_orderstatus='O'),0) AS O, nullif(count(*) FILTER (o_orderstatus='P'),0) AS P FROM orders GROUP BY 1"),
        "agg_unpivot": (lambda k, d: part(k, d).select("p_partkey", F.col("p_size").cast("double").alias("size"), F.col("p_retailprice").alias("price")).unpivot("p_partkey", ["size", "price"], "name", "value"), "SELECT p_partkey, 'size' AS name, p_size::DOUBLE AS value FROM part UNION ALL SELECT p_partkey, 'price', p_retailprice FROM part"),
        "agg_filter_having": (lambda k, d: o(k, d).groupBy("o_custkey").agg(F.count_if(F.col("o_orderstatus") == "F").alias("done"), F.count("*").alias("n")).where("n >= 12"), "SELECT o_custkey, count(*) FILTER (o_orderstatus='F') AS done, count(*) AS n FROM orders GROUP BY 1 HAVING count(*)>=12"),
        "agg_histogram": (lambda k, d: words(k, d).groupBy(F.width_bucket("x_own", F.lit(200), F.lit(320), F.lit(12)).cast("int").alias("bucket")).agg(F.count("*").alias("n")), f"{bits} SELECT CASE WHEN x<200 THEN 0 WHEN x>=320 THEN 13 ELSE (x-200)//10+1 END::INT AS bucket, count(*) AS n FROM e GROUP BY 1"),
    }


def _windows() -> dict:
    by = lambda: W.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    cents = lambda: F.round(F.col("o_totalprice") * 100).cast("long")
    c, w = "round(o_totalprice*100)::BIGINT", "PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey"
    rows = lambda k, d, *cols: orders(k, d).select("o_orderkey", *cols)
    return {
        "win_running": (lambda k, d: rows(k, d, F.sum(cents()).over(by().rowsBetween(W.unboundedPreceding, 0)).alias("running")), f"SELECT o_orderkey, (sum({c}) OVER ({w} ROWS UNBOUNDED PRECEDING))::BIGINT AS running FROM orders"),
        "win_rank": (lambda k, d: (lambda v: rows(k, d, F.rank().over(v).alias("r"), F.dense_rank().over(v).alias("dr"), F.row_number().over(v.orderBy("o_orderpriority", "o_orderkey")).alias("rn"), F.round(F.percent_rank().over(v), 6).alias("pr")))(W.partitionBy("o_custkey").orderBy("o_orderpriority")), "SELECT o_orderkey, (rank() OVER v)::INT AS r, (dense_rank() OVER v)::INT AS dr, (row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority, o_orderkey))::INT AS rn, round(percent_rank() OVER v,6) AS pr FROM orders WINDOW v AS (PARTITION BY o_custkey ORDER BY o_orderpriority)"),
        "win_ntile": (lambda k, d: rows(k, d, F.ntile(4).over(by()).alias("q")), f"SELECT o_orderkey, (ntile(4) OVER ({w}))::INT AS q FROM orders"),
        "win_lag": (lambda k, d: rows(k, d, F.lag("o_orderkey").over(by()).alias("before"), F.lead("o_orderkey", 2).over(by()).alias("after2")), f"SELECT o_orderkey, lag(o_orderkey) OVER ({w}) AS before, lead(o_orderkey,2) OVER ({w}) AS after2 FROM orders"),
        "win_first_last": (lambda k, d: rows(k, d, F.first("o_orderkey").over(by()).alias("first"), F.last("o_orderkey").over(by().rowsBetween(W.unboundedPreceding, W.unboundedFollowing)).alias("last")), f"SELECT o_orderkey, first_value(o_orderkey) OVER ({w}) AS first, last_value(o_orderkey) OVER ({w} ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS last FROM orders"),
        "win_range": (lambda k, d: rows(k, d, F.count("*").over(W.partitionBy("o_custkey").orderBy(F.unix_date(F.to_date("o_orderdate"))).rangeBetween(-90, 0)).alias("recent")), "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderdate::DATE - DATE '1970-01-01' RANGE BETWEEN 90 PRECEDING AND CURRENT ROW) AS recent FROM orders"),
        "sort_topk": (lambda k, d: orders(k, d).orderBy(F.desc("o_totalprice"), "o_orderkey").limit(25).select("o_orderkey", "o_totalprice"), "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25"),
        "sort_within": (lambda k, d: orders(k, d).repartition(4, "o_custkey").sortWithinPartitions("o_custkey", "o_orderkey").groupBy("o_custkey").agg(F.first("o_orderkey").alias("any_key")).select("o_custkey", (F.col("any_key") >= 0).alias("ok")), "SELECT DISTINCT o_custkey, true AS ok FROM orders"),
    }


def _sets() -> dict:
    a, b = (lambda k, d, j=j: people(k, d).where(F.col("party") == j).select("given", "suburb") for j in (1, 2))
    sides = f"WITH {reg()}, a AS (SELECT given, suburb FROM reg WHERE party=1), b AS (SELECT given, suburb FROM reg WHERE party=2)"
    ops = {"union": ("unionByName", "UNION ALL"), "intersect": ("intersect", "INTERSECT"), "intersect_all": ("intersectAll", "INTERSECT ALL"), "except": ("subtract", "EXCEPT"), "except_all": ("exceptAll", "EXCEPT ALL")}
    return {f"set_{n}": (lambda k, d, m=m: getattr(a(k, d), m)(b(k, d)), f"{sides} SELECT * FROM a {s} SELECT * FROM b") for n, (m, s) in ops.items()}


def _functions() -> dict:
    c = F.col

    def levenshtein(k, d):
        p = people(k, d)
        one, two = p.where("party = 1").select("entity", "rid", c("surname").alias("a"), c("suburb").alias("s")), p.where("party = 2").select("rid", c("surname").alias("b"), c("suburb").alias("s"), c("postcode"))
        met = one.join(two.withColumnRenamed("rid", "rid2"), "s").where("substring(a, 1, 3) = substring(b, 1, 3)")
        return met.select("rid", "rid2", fn.edit_similarity("a", "b").alias("sim"))

    return {
        "fn_string": (lambda k, d: part(k, d).select("p_partkey", F.upper("p_name").alias("u"), F.trim(F.concat(F.lit(" "), "p_name", F.lit("  "))).alias("t"), F.regexp_replace("p_name", "[aeiou]", "_").alias("r"), F.translate("p_name", "abc", "xyz").alias("tr"), F.concat_ws("-", "p_brand", "p_type").alias("cw"), F.length("p_name").alias("n"), F.split("p_name", " ")[0].alias("w1"), F.soundex("p_name").alias("sx"), F.overlay("p_name", F.lit("ZZ"), 2).alias("ov"), F.replace("p_brand", F.lit("#"), F.lit("")).alias("rp"), F.lpad(c("p_size").cast("string"), 4, "0").alias("lp")), f"SELECT p_partkey, upper(p_name) AS u, trim(' '||p_name||'  ',' ') AS t, regexp_replace(p_name,'[aeiou]','_','g') AS r, translate(p_name,'abc','xyz') AS tr, concat_ws('-',p_brand,p_type) AS cw, length(p_name)::INT AS n, string_split(p_name,' ')[1] AS w1, {key(('p_name',))} AS sx, substr(p_name,1,1)||'ZZ'||substr(p_name,4) AS ov, replace(p_brand,'#','') AS rp, lpad(p_size::VARCHAR,4,'0') AS lp FROM part"),
        "fn_hash": (lambda k, d: part(k, d).select("p_partkey", F.md5("p_name").alias("m"), F.sha1("p_name").alias("s1"), F.sha2("p_name", 256).alias("s2"), F.conv(F.substring(F.md5("p_name"), 1, 8), 16, 10).cast("long").alias("h")), "SELECT p_partkey, md5(p_name) AS m, sha1(p_name) AS s1, sha256(p_name) AS s2, ('0x'||substr(md5(p_name),1,8))::BIGINT AS h FROM part"),
        "fn_xxhash": (lambda k, d: part(k, d).select((F.xxhash64("p_name") == F.xxhash64(F.concat(F.lit(""), "p_name"))).alias("same")).groupBy("same").agg(F.count("*").alias("n")), "SELECT true AS same, count(*) AS n FROM part"),
        "fn_bits": (lambda k, d: part(k, d).select("p_partkey", c("p_partkey").bitwiseAND(F.lit(255)).alias("a"), c("p_partkey").bitwiseOR(c("p_size").cast("long")).alias("o"), c("p_partkey").bitwiseXOR(F.lit(85)).alias("x"), F.shiftleft("p_partkey", 3).alias("l"), F.shiftright("p_partkey", 2).alias("r"), F.bit_count("p_partkey").alias("n"), F.getbit("p_partkey", F.lit(1)).cast("int").alias("b1")), "SELECT p_partkey, p_partkey & 255 AS a, p_partkey | p_size AS o, xor(p_partkey,85) AS x, p_partkey << 3 AS l, p_partkey >> 2 AS r, bit_count(p_partkey)::INT AS n, ((p_partkey >> 1) & 1)::INT AS b1 FROM part"),
        "fn_math": (lambda k, d: part(k, d).select("p_partkey", F.round(F.log(c("p_size")), 6).alias("ln"), F.round(F.exp(c("p_size") / 50), 6).alias("ex"), F.pow("p_size", F.lit(2)).alias("sq"), F.ceil(c("p_retailprice") / 7).alias("up"), F.floor(c("p_retailprice") / 7).alias("down"), F.pmod(c("p_size") - 25, F.lit(7)).alias("pm"), F.try_divide("p_retailprice", c("p_size") - 1).alias("td")), "SELECT p_partkey, round(ln(p_size),6) AS ln, round(exp(p_size/50),6) AS ex, pow(p_size,2) AS sq, ceil(p_retailprice/7)::BIGINT AS up, floor(p_retailprice/7)::BIGINT AS down, ((p_size-25)%7+7)%7 AS pm, CASE WHEN p_size<>1 THEN p_retailprice/(p_size-1) END AS td FROM part"),
        "fn_array": (lambda k, d: part(k, d).withColumn("w", F.split("p_name", " ")).withColumn("g", E.qgrams(c("p_name"), 2, distinct=False)).select("p_partkey", F.concat_ws(",", F.array_sort(F.array_distinct("g"))).alias("gs"), F.concat_ws(",", F.array_sort(F.array_intersect("g", F.array(F.lit("sm"), F.lit("ri"))))).alias("gi"), F.size(F.array_except("w", F.array(F.lit("small")))).alias("ex"), F.exists("w", lambda x: F.length(x) > 5).alias("any"), F.forall("w", lambda x: F.length(x) > 3).alias("all"), F.aggregate("w", F.lit(0), lambda a, x: a + F.length(x)).alias("len"), F.concat_ws(",", F.zip_with("w", F.reverse("w"), lambda a, b: F.concat(a, b))).alias("zip"), F.size(F.flatten(F.array("w", "g"))).alias("n"), F.element_at("w", -1).alias("last"), F.concat_ws(",", F.array_union("w", F.array(F.lit("x")))).alias("u")), "SELECT p_partkey, array_to_string(list_sort(list_distinct(g)),',') AS gs, array_to_string(list_sort(list_intersect(list_distinct(g),['sm','ri'])),',') AS gi, len(list_distinct(list_filter(w, lambda x: x<>'small')))::INT AS ex, len(list_filter(w, lambda x: length(x)>5))>0 AS any, len(list_filter(w, lambda x: length(x)<=3))=0 AS all, list_sum(list_transform(w, lambda x: length(x)))::INT AS len, array_to_string(list_transform(range(1,len(w)+1), lambda i: w[i]||w[len(w)+1-i]),',') AS zip, (len(w)+len(g))::INT AS n, w[-1] AS last, array_to_string(w,',')||',x' AS u FROM (SELECT p_partkey, string_split(p_name,' ') AS w, list_transform(range(1,length(p_name)), lambda i: substr(p_name,i::INT,2)) AS g FROM part)"),
        "fn_map": (lambda k, d: part(k, d).withColumn("m", F.map_from_arrays(F.array(F.lit("brand"), F.lit("type")), F.array("p_brand", "p_type"))).select("p_partkey", c("m")["brand"].alias("b"), F.size(F.map_filter("m", lambda a, v: v.like("%ECONOMY%"))).alias("n"), F.concat_ws(",", F.map_keys("m")).alias("keys")), "SELECT p_partkey, p_brand AS b, (p_brand LIKE '%ECONOMY%')::INT+(p_type LIKE '%ECONOMY%')::INT AS n, 'brand,type' AS keys FROM part"),
        "fn_date": (lambda k, d: orders(k, d).select("o_orderkey", F.to_date("o_orderdate").alias("day"), F.date_trunc("month", "o_orderdate").cast("date").alias("month"), F.datediff(F.lit("2001-01-01"), "o_orderdate").alias("age"), F.dayofweek("o_orderdate").alias("dow"), F.date_format("o_orderdate", "yyyy-MM").alias("ym")), "SELECT o_orderkey, o_orderdate::DATE AS day, date_trunc('month',o_orderdate)::DATE AS month, (DATE '2001-01-01'-o_orderdate::DATE)::INT AS age, (dayofweek(o_orderdate)+1)::INT AS dow, strftime(o_orderdate,'%Y-%m') AS ym FROM orders"),
        "fn_json": (lambda k, d: events(k, d).select("event_id", F.from_json("props", "k int")["k"].alias("k"), F.get_json_object("props", "$.k").alias("ks"), F.to_json(F.struct("user_id", "event_type")).alias("j")), "SELECT event_id, (props->>'k')::INT AS k, props->>'k' AS ks, '{\"user_id\":'||user_id::VARCHAR||',\"event_type\":\"'||event_type||'\"}' AS j FROM events"),
        "fn_levenshtein": (levenshtein, f"WITH {reg()} SELECT a.rid, b.rid AS rid2, round(1-levenshtein(a.surname,b.surname)/greatest(length(a.surname),length(b.surname)),6) AS sim FROM reg a JOIN reg b ON a.suburb=b.suburb AND a.party=1 AND b.party=2 AND substr(a.surname,1,3)=substr(b.surname,1,3)"),
    }


def _streams() -> dict:
    """Batch forms with a DuckDB counterpart, and streams run to the end of their files."""

    def streamed(build, mode="append"):
        def run(k, d):
            folder = _scratch(k)
            events(k, d).repartitionByRange(4, "ts").sortWithinPartitions("ts").write.parquet(f"{folder}/in")
            return streaming.run_to_table(build(k, d, streaming.arrivals(k, f"{folder}/in")), f"{folder}/out", mode)

        return run

    def encode(k, d, s):
        people = customer(k, d).select(F.col("c_custkey").alias("entity"), F.col("c_nationkey").alias("nation"))
        people = people.select("entity", F.size(E.bloom_positions(F.concat_ws(" ", "entity", "nation"), 501, 20)).alias("ones"))
        return streaming.arriving_records(s, settle(people), 3).select("party", "rid", "ones")  # each person hashed once, not at each arrival

    windows = {
        "tumbling": "SELECT (event_id % 3+1)::INT AS party, date_trunc('day',ts) AS start, date_trunc('day',ts)+INTERVAL 1 DAY AS end, count(*) AS n FROM events GROUP BY ALL",
        "sliding": "SELECT (event_id % 3+1)::INT AS party, s AS start, s+INTERVAL 1 DAY AS end, count(*) AS n FROM (SELECT event_id, unnest([time_bucket(INTERVAL 12 HOUR, ts), time_bucket(INTERVAL 12 HOUR, ts)-INTERVAL 12 HOUR]) AS s FROM events) GROUP BY ALL",
        "session": "SELECT party, min(ts) AS start, max(ts)+INTERVAL 6 HOUR AS end, count(*) AS n FROM (SELECT party, ts, sum(new) OVER (PARTITION BY party ORDER BY ts, event_id) AS g FROM (SELECT (event_id % 3+1)::INT AS party, ts, event_id, CASE WHEN ts>=lag(ts) OVER (PARTITION BY event_id % 3 ORDER BY ts, event_id)+INTERVAL 6 HOUR THEN 1 ELSE 0 END AS new FROM events)) GROUP BY party, g",
    }
    first = lambda k, d, s: streaming.first_arrivals(s, "1000 days").select("user_id", "event_type")
    blocks = lambda k, d, s: streaming.rare_blocks(s.select(F.col("event_type").alias("bkv")))
    return {
        **{f"win_{n}": (lambda k, d, n=n: streaming.windowed(events(k, d), 3, n, None), q) for n, q in windows.items()},
        "late_rows": (lambda k, d: streaming.late_rows(events(k, d)), "SELECT event_id, ts, seen FROM (SELECT event_id, ts, max(ts) OVER (PARTITION BY ts::DATE ORDER BY event_id % 97, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS seen FROM events) WHERE ts<seen-INTERVAL 1 HOUR"),
        "stream_encode": (streamed(encode), f"WITH g AS (SELECT DISTINCT event_id, substr(v,i::INT,2) AS gram, user_id FROM (SELECT event_id, user_id, c_custkey::VARCHAR||' '||c_nationkey::VARCHAR AS v FROM events JOIN customer ON user_id=c_custkey), range(1,30) t(i) WHERE i<=length(v)-1) SELECT (event_id % 3+1)::INT AS party, user_id::VARCHAR||'-'||event_id::VARCHAR AS rid, count(DISTINCT {place(501)})::INT AS ones FROM g, range(0,20) t(i) GROUP BY event_id, user_id"),
        "stream_dedup": (streamed(first), "SELECT DISTINCT user_id, event_type FROM events"),
        "stream_monitor": (lambda k, d: streamed(blocks, "update")(k, d).groupBy("bkv").agg(F.max("n").alias("n")), "SELECT event_type AS bkv, count(*) AS n FROM events GROUP BY 1"),
        "stream_complete": (lambda k, d: streamed(lambda k, d, s: s.groupBy("event_type").agg(F.count("*").alias("n")), "complete")(k, d).groupBy("event_type").agg(F.max("n").alias("n")), "SELECT event_type, count(*) AS n FROM events GROUP BY 1"),
    }


def _udfs() -> dict:
    words = lambda k, d: E.encode_register(people(k, d), S3)

    def popcount(k, d):
        w = words(k, d).select("party", "rid", "b0", "b1")
        return w.select("party", "rid", fn.popcount_and("b0", "b1").alias("udf"), F.bit_count(F.col("b0").bitwiseAND(F.col("b1"))).alias("native")).agg(F.count("*").alias("rows"), F.count_if(F.col("udf") == F.col("native")).alias("same"))

    def union(k, d):
        return words(k, d).groupBy("party").agg(fn.bf_union("b0").alias("udf")).join(words(k, d).groupBy("party").agg(F.bit_or("b0").alias("native")), "party").select("party", (F.col("udf") == F.col("native")).alias("same"))

    def candidates(k, d):
        s = LinkageSpec(block_keys=("given", "surname"))
        rows = E.encode_register(people(k, d), s)
        # JSON arrays of mixed kind are written by hand: [["rid", [words]], ...]
        entry = "concat('[\"', rid, '\",[', concat_ws(',', cast(array(" + ",".join(E.bit_columns(s)) + ") as array<string>)), ']]')"
        held = rows.select("bkv", "party", F.expr(entry).alias("e")).groupBy("bkv", "party").agg(F.concat_ws(",", F.collect_list("e")).alias("es"))
        whole = held.groupBy("bkv").agg(F.concat(F.lit("{"), F.concat_ws(",", F.collect_list(F.expr("concat('\"', party, '\":[', es, ']')"))), F.lit("}")).alias("members"))
        whole.createOrReplaceTempView("_blocks")
        k.udtf.register("block_candidates", fn.BlockCandidates)
        return k.sql("SELECT c.cand, c.c FROM _blocks b, LATERAL block_candidates(b.members, 3) c")

    def functions(k, d):
        fn.register_functions(k)
        part(k, d).createOrReplaceTempView("_part")
        return k.sql("SELECT p_partkey, round(bf_dice(bf_encode(p_name, 501, 20), bf_encode(p_type, 501, 20)), 6) AS dice, size(bf_segment(bf_encode(p_name, 501, 20), 2, 167)) AS ones2 FROM _part")

    enc = lambda c: f"(SELECT list(DISTINCT ('0x'||substr(md5('|'||i::VARCHAR||'|'||substr(lower({c}),j::INT,2)),1,8))::BIGINT % 501) FROM range(0,20) t(i), range(1,60) r(j) WHERE j<length({c}))"
    return {
        "udf_popcount": (popcount, f"WITH {reg()} SELECT count(*) AS rows, count(*) AS same FROM reg"),
        "udaf_union": (union, "SELECT party::INT AS party, true AS same FROM range(1,4) t(party)"),
        "udtf_candidates": (candidates, f"WITH {reg()}, {filters('reg', key(('given', 'surname')))} SELECT a.rid||','||b.rid||','||c.rid AS cand, len(list_intersect(list_intersect(a.v,b.v),c.v))::INT AS c FROM e a JOIN e b ON a.b=b.b AND b.party=2 JOIN e c ON a.b=c.b AND c.party=3 WHERE a.party=1 AND len(list_intersect(list_intersect(a.v,b.v),c.v))>0"),
        "sql_functions": (functions, f"SELECT p_partkey, round(2*len(list_intersect(a,b))/(len(a)+len(b)),6) AS dice, len(list_filter(a, lambda q: q//167=1))::INT AS ones2 FROM (SELECT p_partkey, {enc('p_name')} AS a, {enc('p_type')} AS b FROM part)"),
        "arrow_encoder": (lambda k, d: fn.encode_in_pandas(people(k, d), S3), f"WITH {reg()}, {filters('reg', spec_key(3))} SELECT party, rid, x::INT AS x_own FROM e"),
    }


def _all() -> dict:
    return _sources() | _joins() | _aggregates() | _windows() | _sets() | _functions() | _streams() | _udfs()


def queries() -> dict:
    return {n: q for n, (q, _) in _all().items()}


def oracle_sql() -> dict[str, str]:
    return {n: s for n, (_, s) in _all().items() if s}
