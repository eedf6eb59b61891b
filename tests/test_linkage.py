from dataclasses import replace

import pytest
from pyspark.sql import functions as F

from ringlink import catalog, streaming
from ringlink import workloads as K
from ringlink.operators import baselines as B
from ringlink.operators import blocking, compare, measures, ring
from ringlink.operators import corruption as C
from ringlink.operators import encoding as E
from ringlink.operators import exchange as X
from ringlink.operators import linkage as L
from ringlink.operators import registers as R
from ringlink.spec import LinkageSpec, expected_fill, fit_length, optimal_hashes

S = LinkageSpec()


def _people(spark, n=300):
    return spark.range(n).selectExpr("id AS entity", "cast(id % 25 AS int) AS nation")


def _rows(df, *cols):
    return sorted(tuple(r) for r in df.select(*cols).collect())


@pytest.fixture(scope="module")
def encoded(spark):
    return E.settle(E.encode_register(C.corrupt_register(R.make_register(_people(spark), 3), 3, 40), S))


@pytest.fixture(scope="module")
def view(spark, encoded):
    return E.settle(X.exchange_segments(encoded, S))


def test_parameters():
    assert [fit_length(500, p) for p in (3, 5, 7)] == [501, 500, 504]
    assert abs(expected_fill(500, 20, optimal_hashes(500, 20)) - 0.5) < 1e-9
    for wrong in ({"parties": 2}, {"length": 0}, {"threshold": (3, 2)}, {"encoding": "x"}, {"weights": (1, 2)}, {"pad": "__"}, {"scheme": "y"}):
        with pytest.raises(ValueError):
            LinkageSpec(**wrong)
    with pytest.raises(ValueError):
        fit_length(500, 3, strict=True)
    assert sum(replace(S, weights=(2, 3, 1, 2)).bits_by_qid) == 501


def test_positions_of_the_fixture(spark):
    row = spark.range(1).select(*(F.array_sort(E.hash_positions(F.lit("pe"), 501, 3, scheme=s)).alias(s) for s in ("independent", "double"))).first()
    assert (row["independent"], row["double"]) == ([210, 422, 453], [78, 196, 461])


def test_worked_examples(spark):
    got = {r["cand"]: (r["c1"], r["c2"], r["c3"], r["c"], r["x"], r["sim"], r["is_match"]) for r in K.running_example(spark).collect()}
    assert got == {
        "A-1,B-1,C-1": (45, 45, 47, 137, 758, 0.5422, False), "A-1,B-2,C-1": (81, 75, 78, 234, 751, 0.9348, True),
        "A-2,B-1,C-1": (31, 38, 40, 109, 755, 0.4331, False), "A-2,B-2,C-1": (40, 49, 55, 144, 748, 0.5775, False),
    }
    assert tuple(K.two_strings(spark).first()) == ("0 1 2 4 8 10 13", "2 4 8 10 13", 7, 5, 5, 0.8333)
    sent, total = ring.ring_sum(spark.createDataFrame([(1, 11), (2, 7), (3, 15)], "party int, value long"), 3, 1, 20)
    assert [r["message"] for r in sent.orderBy("hop").collect()] == [31, 38, 53] and total.first()["total"] == 33
    kept = {(r["tenths"], r["holder"]): r["kept"] for r in K.filter_example(spark).collect()}
    assert kept[0, 0] == 9 and [kept[8, h] for h in (1, 2, 3)] == [1, 2, 2] and all(kept[6, h] >= 1 for h in (1, 2, 3))
    view = K.bits_view(spark, LinkageSpec(length=12))
    for tenths, want in ((8, set()), (6, {("A1", "B1", "C1")})):
        s = LinkageSpec(length=12, seg_threshold=(tenths, 10))
        rows = compare.partial_counts(view, s, "prefix").groupBy("r1", "r2", "r3").agg(F.count("*").alias("n"), F.sum("c").alias("c"), F.sum("x").alias("x")).where("n = 3 and 15 * c >= 4 * x")
        assert set(_rows(rows, "r1", "r2", "r3")) == want  # the filter at .8 loses the only match


def test_registers(spark):
    reg = R.make_register(_people(spark, 1500), 3)
    assert reg.count() == 2250 and R.true_sets(reg, S).count() == 375
    row = reg.where("entity = 8").first()
    assert row["suburb"].endswith("ton") and any(row["suburb"].startswith(t) for t in R.TAIL)
    assert {r["party"] for r in reg.where("entity = 5").collect()} == {1}


def test_golden_totals(spark):
    d = "/root/testdata/sf0.01"
    found = L.link(catalog.register(spark, d), S)
    truth = R.true_sets(catalog.register(spark, d), S)
    rows = catalog.register(spark, d).select("party", blocking.block_key(("surname",)).alias("bkv"))
    assert blocking.candidate_count(rows, 3).first()["candidates"] == 15724
    q = measures.quality(found, truth).first()
    assert (q["tp"], q["fp"], q["fn"]) == (375, 51, 0)


def test_distributed_equals_central(spark, encoded, view):
    central = _rows(L.central(encoded, S), "cand", "c", "x", "sim")
    assert central and _rows(L.link_encoded(encoded, S), "cand", "c", "x", "sim") == central
    assert _rows(L.link_encoded(encoded, S, "bound"), "cand", "c", "x", "sim") == central
    for who in ("rotate", "external"):
        assert _rows(L.link_encoded(encoded, S, initiator=who), "cand", "c", "x", "sim") == central
    filtered = _rows(L.link_encoded(encoded, S, "approx_filtered"), "cand", "c", "x", "sim")
    assert set(filtered) <= set(central)


def test_filter_against_brute_force(spark, view):
    pieces: dict = {}
    for r in view.collect():
        pieces.setdefault((r["holder"], r["bkv"]), {}).setdefault(r["owner"], []).append((r["rid"], tuple(r[f"w{k}"] for k in range(S.words))))
    pop = lambda ws: sum(w.bit_count() for w in ws)
    for num, den in ((0, 1), (3, 5), (4, 5)):
        s, want = replace(S, seg_threshold=(num, den)), set()
        for (h, _), by in pieces.items():
            order = [h] + [j for j in (1, 2, 3) if j != h]
            front = [({h: rid}, ws, pop(ws)) for rid, ws in by.get(h, [])]
            for n, j in enumerate(order[1:], 2):
                nxt = []
                for ids, ws, ones in front:
                    for rid, other in by.get(j, []):
                        both, total = tuple(a & b for a, b in zip(ws, other, strict=True)), ones + pop(other)
                        if den * n * pop(both) >= num * total:
                            nxt.append((ids | {j: rid}, both, total))
                front = nxt
            want |= {(h, *(ids[j] for j in (1, 2, 3)), pop(ws)) for ids, ws, _ in front}
        got = {tuple(r) for r in compare.partial_counts(view, s, "prefix").select("holder", "r1", "r2", "r3", "c").collect()}
        assert got == want
    assert compare.partial_counts(view, S).count() == compare.partial_counts(view, replace(S, seg_threshold=(0, 1)), "prefix").count()


def test_ring_hides_and_returns(spark, view):
    counts = E.settle(compare.partial_counts(view, S))
    plain = {r["cand"]: (r["c"], r["x"]) for r in counts.groupBy(ring.candidate(S).alias("cand")).agg(F.sum("c").alias("c"), F.sum("x").alias("x")).collect()}
    for who in ("one", "rotate", "external"):
        totals = ring.ring_totals(counts, S, "k", who)
        assert {r["cand"]: (r["c"], r["x"]) for r in ring.unmask(totals, "k", who).collect()} == plain
        sent = ring.ring_transcript(counts, S, "k", who)
        assert sent.count() == 3 * len(plain) and sent.agg(F.min("masked_c")).first()[0] >= 0
        assert sent.where(F.col("masked_c") < 501).count() == 0  # no message shows a count
    last = ring.ring_transcript(counts, S, "k").where("hop = 3").select("cand", "masked_c")
    assert last.exceptAll(ring.ring_totals(counts, S, "k").select("cand", "masked_c")).isEmpty()
    wrong = {r["cand"]: r["c"] for r in ring.unmask(ring.ring_totals(counts, S, "k"), "other").collect()}
    assert all(wrong[c] != plain[c][0] for c in wrong)


def test_exchange_shows_no_more_than_a_piece(spark, encoded, view):
    assert not {"entity", "given", "surname", "suburb", "postcode"} & set(view.columns)
    assert view.where("holder <> owner and x_own is not null").isEmpty()
    assert X.exposure_audit(view, S).agg(F.max("max_bits")).first()[0] <= S.width
    assert not {r["rid"] for r in view.select("rid").distinct().collect()} & {r["rid"] for r in encoded.select("rid").collect()}


def test_exact_matchers_agree(spark, encoded):
    dirty = C.corrupt_register(R.make_register(_people(spark), 3), 3, 40)
    exact = _rows(B.exact_conjunction(dirty, S), "cand")
    assert exact == _rows(B.equal_filters(encoded, S), "cand")
    assert set(_rows(B.clear_exact(dirty, S), "cand")) <= set(exact) <= set(_rows(L.central(encoded, S), "cand"))


def test_corruption(spark):
    reg = R.make_register(_people(spark, 1500), 3)
    a = C.corruption_audit(reg, C.corrupt_register(reg, 3, 20), 3).first()
    assert 0.15 < a["share"] < 0.25 and a["min_clean"] >= 1 and a["wrong"] == 0
    rows = C.corrupt_register(reg, 3, 40).where("corrupted").collect()
    assert all(r["postcode"].isdigit() or not r["postcode"] for r in rows)
    assert C.corrupt_register(reg, 3, 0).where("corrupted").isEmpty()
    one = spark.createDataFrame([("phone",)], "v string")
    assert {one.select(F.expr(C.ocr_confuse("v", str(i))).alias("v")).first()["v"] for i in range(40)} > {"ph0ne"}
    assert one.select(F.expr(C.phonetic_rewrite("v", "0")).alias("v")).first()["v"] == "fone"


def test_skew_split_keeps_all_records(spark, encoded):
    cut = blocking.split_blocks(encoded.withColumn("f", F.substring("rid", -1, 1)), 3, 1, "f")
    assert cut.count() == encoded.count()
    assert blocking.guard_blocks(encoded, 3, 1).where("action = 'split'").count() > 0


def test_nulls_blanks_and_empty_registers(spark):
    schema = "party int, rid string, entity long, given string, surname string, suburb string, postcode string"
    rows = [(p, f"{'ABC'[p - 1]}-1", 1, None, "", None, " ") for p in (1, 2, 3)]
    assert L.link(spark.createDataFrame(rows, schema), S).isEmpty()  # no gram, no similarity
    assert L.link(spark.createDataFrame([], schema), S).isEmpty()


def test_measures(spark, encoded, view):
    s = measures.bit_sensitivity(R.make_register(_people(spark, 8), 3), S)
    assert s.count() == 501 and all(r["s"] is None if r["freq"] == 0 else r["s"] == round(1 / min(r["dist"], r["freq"]), 6) for r in s.collect())
    noisy = E.perturb(encoded, S, (5, 100))
    assert noisy.agg(F.avg("flipped")).first()[0] == pytest.approx(25, abs=3)
    same = measures.disclosure_external(view, view, S).agg(F.avg("dr_mean")).first()[0]
    assert 0 < same <= 1
    sweep = K.disclosure_grid(_people(spark, 1500), [(3, 100, 3), (7, 100, 3), (20, 100, 3)]).orderBy("parties").collect()
    assert [r["dr_mean"] for r in sweep] == sorted((r["dr_mean"] for r in sweep), reverse=True)


def test_quality_trends(spark):
    rows = {(r["mode"], r["rate"]): r for r in K.quality_grid(R.make_register(_people(spark, 600), 3), S).collect()}
    for mode in ("approx", "approx_filtered", "exact"):
        assert rows[mode, 0]["recall"] >= rows[mode, 20]["recall"] >= rows[mode, 40]["recall"]
    assert rows["approx", 40]["f1"] > rows["exact", 40]["f1"] and rows["exact", 0]["f1"] == 1
    assert rows["approx_filtered", 0]["precision"] >= rows["approx", 0]["precision"]


def test_incremental_link_equals_batch(spark, tmp_path):
    reg = R.make_register(_people(spark), 3)
    stored = E.settle(E.encode_register(reg, S))
    found: list = []
    each = streaming.incremental_link(S, stored, lambda df: found.extend(r["cand"] for r in df.collect()))
    mine = reg.where("party = 1")
    mine.repartition(3).write.parquet(f"{tmp_path}/in")
    stream = spark.readStream.schema(mine.schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in")
    stream.writeStream.foreachBatch(each).option("checkpointLocation", f"{tmp_path}/state").trigger(availableNow=True).start().awaitTermination()
    assert sorted(found) == [r[0] for r in _rows(L.link(reg, S), "cand")]


def test_stream_join_and_late_rows(spark, tmp_path):
    for name, rows in (("a", [("x", "A-1", "2024-01-01 00:00:00")]), ("b", [("x", "B-1", "2024-01-01 00:30:00"), ("x", "B-2", "2024-01-01 03:00:00")])):
        spark.createDataFrame(rows, "bkv string, rid string, ts string").withColumn("ts", F.to_timestamp("ts")).write.parquet(f"{tmp_path}/{name}")
    read = lambda n: spark.readStream.schema("bkv string, rid string, ts timestamp").parquet(f"{tmp_path}/{n}")
    out = streaming.run_to_table(streaming.matched_arrivals(read("a"), read("b")), f"{tmp_path}/out")
    assert _rows(out, "rid1", "rid2") == [("A-1", "B-1")]


def test_no_shuffle_on_bucketed_pieces(spark, view):
    from ringlink import sources

    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        sources.save_pieces(view, "pieces_plan_test", 4)
        t = spark.table("pieces_plan_test")
        plan = t.where("owner = 1").join(t.where("owner = 2").select("holder", "bkv", F.col("rid").alias("r2")), ["holder", "bkv"])
        assert "Exchange" not in plan._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.sql("DROP TABLE IF EXISTS pieces_plan_test")
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


def test_joint_counts_equal_the_holders_own(spark, encoded, view):
    cols = ("holder", "r1", "r2", "r3", "c", "x")
    assert _rows(compare.by_holder(compare.joint_counts(encoded, S), S), *cols) == _rows(compare.partial_counts(view, S), *cols)
    for t in ((3, 5), (4, 5)):
        s = replace(S, seg_threshold=t)
        kept = compare.partial_counts(view, s, "prefix").groupBy("r1", "r2", "r3").agg(F.count("*").alias("n")).where("n = 3")
        assert _rows(compare.joint_counts(encoded, s, "prefix"), "r1", "r2", "r3") == _rows(kept, "r1", "r2", "r3")
    counts, joint = compare.partial_counts(view, S), compare.joint_counts(encoded, S)
    for who in ("one", "rotate", "external"):
        cols = ("cand", "first", "hop", "sender", "receiver", "masked_c", "masked_x")
        assert _rows(ring.joint_transcript(joint, S, "k", who), *cols) == _rows(ring.ring_transcript(counts, S, "k", who), *cols)


def test_prefixes_of_seven_parties(spark):
    s = replace(K.spec_for(7), seg_threshold=(3, 5))
    encoded = E.settle(E.encode_register(C.corrupt_register(R.make_register(_people(spark, 120), 7), 7, 40), s))
    ids = [f"r{j}" for j in range(1, 8)]
    kept = compare.partial_counts(E.settle(X.exchange_segments(encoded, s)), s, "prefix").groupBy(*ids).agg(F.count("*").alias("n")).where("n = 7")
    rows = _rows(compare.joint_counts(encoded, s, "prefix"), *ids)
    assert rows and rows == _rows(kept, *ids)


def test_no_candidate_is_shuffled(spark, encoded):
    for mode in ("approx", "approx_filtered"):
        plan = L.link_encoded(encoded, S, mode)._jdf.queryExecution().executedPlan().toString()
        moved = [line for line in plan.splitlines() if "Exchange" in line and "AdaptiveSparkPlan" not in line]
        assert moved and all("hashpartitioning(bkv" in line for line in moved)


def test_bounds_lose_no_match(spark, encoded):
    for kind in ("dice", "jaccard", "overlap", "cosine"):
        s = replace(S, threshold=(3, 5))
        every = L.central(encoded, s, kind=kind, keep_all=True)
        want = every.where("x > 0 and 15 * c >= 3 * x") if kind == "dice" else every.where("sim >= 0.6")
        got = L.central(encoded, s, kind=kind)
        assert _rows(got, "cand", "c", "x", "sim") == _rows(want, "cand", "c", "x", "sim")


@pytest.mark.parametrize("name", ["in_memory", "ring_example", "two_strings", "running_example", "filter_example", "sample_bernoulli"])
def test_examples_read_a_table(spark, monkeypatch, name):
    from pyspark.sql.readwriter import DataFrameReader

    read, was = [], DataFrameReader.parquet
    monkeypatch.setattr(DataFrameReader, "parquet", lambda self, *paths, **more: read.extend(paths) or was(self, *paths, **more))
    assert not catalog.queries()[name](spark, "/root/testdata/sf0.001").isEmpty() and read


def test_sample_is_plausible_at_any_size(spark):
    assert catalog.queries()["sample_bernoulli"](spark, "/root/testdata/sf0.1").first()["plausible"]


def test_stream_hashes_persons_once(spark, monkeypatch):
    seen, was = [], streaming.run_to_table
    monkeypatch.setattr(streaming, "run_to_table", lambda stream, *more: seen.append(stream) or was(stream, *more))
    rows = catalog.queries()["stream_encode"](spark, "/root/testdata/sf0.001").count()
    assert rows and "md5" not in seen[0]._jdf.queryExecution().logical().toString()


def test_filter_zero_joins_once_for_all_holders(spark, tmp_path):
    spark.range(1, 301).selectExpr("id AS c_custkey", "int(id % 25) AS c_nationkey").write.parquet(f"{tmp_path}/customer.parquet")
    out, zero = catalog.queries()["filter_zero"](spark, str(tmp_path)), replace(S, seg_threshold=(0, 5))
    want = catalog._candidate_rows(compare.partial_counts(catalog.settled_view(spark, str(tmp_path), zero), zero, "prefix"), zero)
    assert sorted(map(tuple, out.collect())) == sorted(map(tuple, want.collect())) != []
    joins = [r for r in out._jdf.queryExecution().sparkPlan().toString().splitlines() if "Join" in r]
    assert len(joins) == 2 and not any("holder" in r for r in joins)


def test_filter_loose_moves_a_record_once(spark, tmp_path):
    spark.range(300).selectExpr("id AS c_custkey", "int(id % 25) AS c_nationkey").write.parquet(f"{tmp_path}/customer.parquet")
    out, loose = catalog.queries()["filter_loose"](spark, str(tmp_path)), replace(S, seg_threshold=(3, 5))
    want = catalog._candidate_rows(compare.partial_counts(catalog.settled_view(spark, str(tmp_path), loose), loose, "prefix"), loose)
    assert out.dtypes == want.dtypes and sorted(map(tuple, out.collect())) == sorted(map(tuple, want.collect())) != []
    plan = out._jdf.queryExecution().executedPlan().toString().partition("== Initial Plan ==")[0]
    moved = [r for r in plan.splitlines() if "Exchange hashpartitioning(" in r and "Reused" not in r and "hashpartitioning(party" not in r]
    assert len(moved) == 3 and all("hashpartitioning(bkv" in r for r in moved)  # one for each party, none for a holder


def test_holders_chains_of_seven_parties(spark):
    s = replace(K.spec_for(7), seg_threshold=(3, 5))
    encoded = E.settle(E.encode_register(C.corrupt_register(R.make_register(_people(spark, 120), 7), 7, 40), s))
    cols = ("holder", *(f"r{j}" for j in range(1, 8)), "c", "x")
    want = _rows(compare.partial_counts(E.settle(X.exchange_segments(encoded, s)), s, "prefix"), *cols)
    assert want and _rows(compare.kept_counts(encoded, s), *cols) == want


def _brute(rows, p, kind, num, den):
    """cand of the sets of one block that reach num/den, each tried."""
    from itertools import product

    out = set()
    for block in {r["bkv"] for r in rows}:
        for chosen in product(*([r for r in rows if r["bkv"] == block and r["party"] == j] for j in range(1, p + 1))):
            sets = [{(k, i) for k in range(9) for i in range(63) if r[f"b{k}"] >> i & 1} for r in chosen]
            c, x = len(set.intersection(*sets)), [len(s) for s in sets]
            over = {"dice": (p * c, sum(x)), "overlap": (c, min(x)), "cosine": (c, (x[0] * x[1] * x[p - 1]) ** (1 / p) if p == 3 else (x[0] * x[1]) ** 0.5)}[kind]
            if over[1] and den * over[0] >= num * over[1] - 1e-9:
                out.add(",".join(r["rid"] for r in chosen))
    return sorted(out)


@pytest.mark.parametrize(("kind", "p"), [("dice", 3), ("overlap", 3), ("cosine", 3), ("dice", 2)])
def test_sets_are_found_pairs_first_whatever_the_tiles(spark, monkeypatch, kind, p):
    from ringlink.operators import blockwise

    register = C.corrupt_register(R.make_register(_people(spark, 90), 3), 3, 40)
    encoded = E.settle(E.encode_register(register.withColumn("surname", F.substring("surname", 1, 1)), S).unionByName(E.encode_register(register.limit(2), S).select("party", F.lit("A-empty").alias("rid"), F.lit("B000").alias("bkv"), *(F.lit(0).cast("long").alias(b) for b in E.bit_columns(S)), F.lit(0).alias("x_own")).limit(1)))
    want = _brute(encoded.collect(), p, kind, 4, 5)
    assert len(want) > 5
    for first, others, cells in ((1024, 16384, 1 << 18), (2, 3, 4)):
        monkeypatch.setattr(blockwise, "FIRST", first)
        monkeypatch.setattr(blockwise, "OTHERS", others)
        monkeypatch.setattr(blockwise, "CELLS", cells)
        found = L.central(encoded, S, p, kind)
        assert sorted(r["cand"] for r in found.collect()) == want
        plan = found._jdf.queryExecution().optimizedPlan().toString()
        assert plan.count("Join") == 1  # with the sizes of blocks; no join multiplies records by a block


def test_filtered_matches_of_many_parties_need_no_chain_of_joins(spark):
    s = replace(S, parties=4, seg_threshold=(3, 4), threshold=(7, 10))
    encoded = E.settle(E.encode_register(R.make_register(_people(spark, 60), 4).withColumn("surname", F.substring("surname", 1, 1)), s))
    joint = compare.joint_counts(encoded, s, "prefix", "dice")
    assert joint._jdf.queryExecution().optimizedPlan().toString().count("Join") == 1
    view = E.settle(X.exchange_segments(encoded, s))
    totals = ring.ring_totals(compare.partial_counts(view, s, "prefix"), s, "k1")
    want = _rows(L.readable(L.classify(totals, s, "k1"), X.record_tokens(encoded, s), s), "cand", "c", "x", "sim")
    assert want and _rows(L.link_encoded(encoded, s, "approx_filtered"), "cand", "c", "x", "sim") == want
    assert len(_rows(L.link_encoded(encoded, s), "cand")) > len(want)
