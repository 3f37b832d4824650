"""Invariance under pieces, plans, rejections, layouts, measures and streams."""

from __future__ import annotations

import datetime as dt

import pytest
from pyspark.sql import functions as F

from chronofold.baselines import naive, paths
from chronofold.functions.instants import FROM, TO, on_axis
from chronofold.functions.user import register
from chronofold.operators import cohort as co
from chronofold.operators import same_base as sb
from chronofold.operators.canonical import canonical_equal, coalesce_intervals, keys_correct, stitch_edges
from chronofold.operators.partials import DELTA, broken
from chronofold.plans import measures, sizing
from chronofold.plans.query import PlanRejected, Query, closed, explain_plan, plan, validate
from chronofold.plans.runner import IncompletePartials, evaluate, merge_durable, missing_pieces, run_fanout, run_fanout_durable, run_mono, run_piece
from chronofold.sources import layout as ly
from chronofold.sources.files import load_changes, write_result
from chronofold.spec import Cohort, HistorySpec, QueryWindow
from chronofold.workloads.histories import HISTORIES

SPEC = HistorySpec(("k",), ("g", "x", "y"), integer=True)
W = QueryWindow(17, 173)


@pytest.fixture(scope="module")
def randoms(spark):
    """Rows of 40 keys on 0..200 with gaps, ties, equal neighbours and nulls, by hashes."""
    n = spark.range(40 * 8).select((F.col("id") % 40).alias("k"), F.floor(F.col("id") / 40).alias("i"))
    h = lambda s, m: F.pmod(F.xxhash64("k", "i", F.lit(s)), F.lit(m))
    rows = n.select("k", F.concat(F.lit("g"), h(1, 3)).alias("g"), F.when(h(2, 20) > 0, h(3, 5)).cast("int").alias("x"), F.when(h(4, 20) > 0, h(5, 5)).cast("int").alias("y"), (F.col("i") * 25 + h(6, 12)).alias(FROM), (F.col("i") * 25 + h(6, 12) + 1 + h(7, 13)).alias(TO))
    return rows.cache()


QUERIES = {
    "predicate": Query("predicate", SPEC, W, phi="x < 3", payload=("x",)),
    "minus": Query("boolean", SPEC, W, phi="x < 3", other="y < 2", op="minus"),
    "gated": Query("boolean", SPEC, W, phi="x < 3", other="y < 2", op="or").then_gate("x = 4"),
    "duration": Query("duration", SPEC, W, x="x", group=("g",)),
    "count": Query("count", SPEC, W, phi="x < 3", group=("g",)),
    "threshold": Query("count", SPEC, W, phi="x < 3", group=("g",)).then_threshold(4),
    "pairwise": Query("pairwise", SPEC, W, x="x", left=1, right=2, cohort=Cohort((1, 2)), emit="both"),
    "better": Query("better", SPEC, W, x="x", reference=3, cohort=Cohort(tuple(range(20)))),
    "ranked": Query("ranked", SPEC, W, x="x", k=3, cohort=Cohort(tuple(range(20)))),
}
GRIDS = [ly.ChunkGrid.uniform(7), ly.ChunkGrid.uniform(50, 3), ly.ChunkGrid.explicit([20, 21, 100])]


def brute(rows, name: str):
    """Answers instant by instant."""
    at = {}
    for r in rows:
        for t in range(max(r[FROM], W.start), min(r[TO], W.end)):
            at.setdefault(t, {})[r["k"]] = r
    small = lambda r: r["x"] is not None and r["x"] < 3
    out = {}
    for t in range(W.start, W.end):
        here = at.get(t, {})
        if name == "count":
            for g in {r["g"] for r in here.values()}:
                if n := sum(small(r) for r in here.values() if r["g"] == g):
                    out[t, g] = n
        elif name == "ranked":
            order = sorted((r["x"], k) for k, r in here.items() if k < 20 and r["x"] is not None)
            out.update({(t, i + 1): o[::-1] for i, o in enumerate(order[:3])})
        elif name == "better" and 3 in here and here[3]["x"] is not None:
            out[t, 3] = sum(r["x"] is not None and r["x"] < here[3]["x"] for k, r in here.items() if k < 20)
        elif name == "minus":
            out.update({(t, k): True for k, r in here.items() if small(r) and not (r["y"] is not None and r["y"] < 2)})
    return out


@pytest.mark.parametrize("name", ["count", "ranked", "better", "minus"])
def test_against_every_instant(spark, randoms, name):
    found = {}
    for r in run_mono(QUERIES[name], randoms).collect():
        for t in range(r[FROM], r[TO]):
            match name:
                case "count":
                    found[t, r["g"]] = r["active"]
                case "ranked":
                    found[t, r["rank"]] = (r["key"], r["x"])
                case "better":
                    found[t, 3] = r["better"]
                case "minus":
                    found[t, r["k"]] = True
    assert found == brute(randoms.collect(), name)


@pytest.mark.parametrize("name", QUERIES)
@pytest.mark.parametrize("grid", GRIDS, ids=["narrow", "wide", "uneven"])
def test_chunks_do_not_matter(spark, randoms, name, grid):
    mono = run_mono(QUERIES[name], randoms)
    pieces = evaluate(QUERIES[name], ly.segments(randoms, grid, ["k"], W))
    assert canonical_equal(mono, pieces) == (0, 0)


def test_variants_agree(spark, randoms):
    seg = ly.segments(randoms, GRIDS[0], ["k"], W)
    for shards in (2, 5):
        assert canonical_equal(co.ranked_timeline(seg, "k", "x", 2), co.ranked_timeline(seg, "k", "x", 2, shards=shards)) == (0, 0)
    assert canonical_equal(co.ranked_timeline(seg, "k", "x", 2, True), co.ranked_timeline(seg, "k", "x", 2, True, strategy="sweep")) == (0, 0)
    a = sb.count_timeline(seg, "x < 3", ["g"])
    assert canonical_equal(a, sb.count_timeline(seg, "x < 3", ["g"], "step")) == (0, 0)
    assert canonical_equal(a, sb.count_timeline(seg, "x < 3", ["g"], cluster_first=True)) == (0, 0)
    assert broken(sb.count_deltas(seg, "x < 3", ["g"]), DELTA, ["g"]).isEmpty()
    raw = sb.predicate_window(seg, ["k"], "x < 3", ("x",), canon=False)
    edges = spark.range(0, 210, 7).select(F.col("id").alias("at"))
    assert canonical_equal(coalesce_intervals(raw, ["k"], ["x"]), coalesce_intervals(stitch_edges(raw, ["k"], ["x"], edges), ["k"], ["x"])) == (0, 0)
    assert naive.ranked_per_shard(seg, "k", "x", 1, 4).count() > co.winner_timeline(seg, "k", "x").count()
    assert co.choose_strategy(seg) == "native" and co.choose_strategy(seg, limit=1) == "sweep"


def test_closed_pieces_and_cohorts(spark, randoms):
    seg = ly.segments(randoms, GRIDS[0], ["k"], W)
    whole = run_mono(Query("predicate", SPEC, W, phi="true", payload=SPEC.payload), randoms)
    assert closed(seg, whole, ["k"], True)
    assert not closed(seg.where("chunk <> 4"), whole, ["k"], True)
    co.assert_cohort_closed(seg, seg.where("k < 3"), "k")
    with pytest.raises(ValueError, match="cohort"):
        co.assert_cohort_closed(seg.where("k <> 2"), seg.where("k < 3"), "k")


@pytest.fixture(scope="module")
def stored(spark, randoms, tmp_path_factory):
    return ly.build_clipped_layout(randoms, GRIDS[1], str(tmp_path_factory.mktemp("layout")), SPEC, buckets=16)


@pytest.mark.parametrize("name", QUERIES)
def test_stored_layout(spark, randoms, stored, name):
    assert canonical_equal(run_mono(QUERIES[name], randoms), run_fanout(QUERIES[name], stored, spark)) == (0, 0)


@pytest.mark.parametrize("name", ["gated", "duration", "threshold", "better", "ranked"])
def test_durable_pieces(spark, randoms, stored, name, tmp_path):
    q = QUERIES[name]
    hist = sizing.key_byte_histogram(stored.scan(spark), ["k"], 10.0)
    shards = sizing.plan_shards(hist, 400.0)
    p = plan(q, stored, spark, shards)
    assert "partial" in explain_plan(p)
    with pytest.raises(IncompletePartials):
        merge_durable(q, p, spark, str(tmp_path))
    run_piece(q, stored, spark, str(tmp_path), p.pieces[0], 0)
    run_piece(q, stored, spark, str(tmp_path), p.pieces[0], 1)  # a repeated piece counts once
    assert len(missing_pieces(spark, p, str(tmp_path))) == len(p.pieces) - 1
    assert canonical_equal(run_mono(q, randoms), run_fanout_durable(q, stored, spark, str(tmp_path), shards)) == (0, 0)


def test_rejections():
    bad = {
        "TEMPORAL_JOIN": Query("temporal_join", SPEC, W), "SEQUENCE": Query("sequence", SPEC, W), "SLIDING": Query("sliding", SPEC, W), "UNSUPPORTED": Query("magic", SPEC, W),
        "DYNAMIC_COHORT": Query("ranked", SPEC, W, x="x", cohort=Cohort((1,), dynamic=True)), "NO_TIE_RULE": Query("ranked", SPEC, W, x="x", cohort=Cohort((1,), tie=None)),
        "NO_SHARD_PLACEMENT": Query("ranked", SPEC, W, x="x", cohort=Cohort((1,)), shards=0), "NO_BARRIER": Query("count", SPEC, W, barrier=False),
        "NOT_FULL_STATE": Query("predicate", HistorySpec(("k",), ("x",), full_state=False), W, phi="x < 3"),
    }
    for code, query in bad.items():
        with pytest.raises(PlanRejected) as e:
            validate(query)
        assert e.value.code == code
    with pytest.raises(PlanRejected):
        Query("duration", SPEC, W, x="x").then_threshold(3)
    with pytest.raises(PlanRejected):
        Query("count", SPEC, W).then_gate("x = 1")


def explained(df) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def test_plans(spark, randoms, stored):
    one = explained(run_fanout(QUERIES["duration"], stored, spark))
    assert one.count("Exchange hashpartitioning") == 1 and "PartitionFilters" in one and "chunk" in one.split("PartitionFilters")[1][:120]
    assert "SinglePartition" not in explained(run_fanout(QUERIES["threshold"], stored, spark))
    assert "WindowGroupLimit" in explained(run_fanout(QUERIES["ranked"], stored, spark))
    canon = explained(coalesce_intervals(randoms, ["k"], ["x"]))
    assert canon.count("Exchange hashpartitioning") == 1


def test_sizing(spark, randoms, stored):
    found = {r.width: r.layout_rows for r in sizing.row_amplification(randoms, {"seven": GRIDS[0], "fifty": GRIDS[1]}).collect()}
    assert found["fifty"] == stored.scan(spark).count() < found["seven"]
    assert sizing.storage_safe_width(randoms, {"seven": GRIDS[0], "fifty": GRIDS[1]}, 0.5) == "fifty"
    assert sizing.storage_safe_width(randoms, {"seven": GRIDS[0]}, 0.01) is None
    assert round(sizing.predict_amplification(4.8, 30.44, 1), 3) == 1.125
    shards = sizing.plan_shards(sizing.key_byte_histogram(stored.scan(spark), ["k"], 10.0), 300.0).collect()
    assert all(r.over or r.bytes <= 300 for r in shards)
    best, record = sizing.calibrate_ceiling([1, 2, 4], lambda b: {"q": b < 3})
    assert best == 2 and [r["ok"] for r in record] == [True, True, False]
    assert sizing.amortized_queries(10, 3, 1) == 5


def test_append_goes_on_from_the_old_end(spark, tmp_path):
    spec = HistorySpec(("k",), ("v",), 20, integer=True)
    from chronofold.sources.history import from_change_log

    log = spark.createDataFrame([("a", 1, 1), ("b", 2, 1), ("a", 12, 2), ("a", 25, 3), ("c", 31, 9)], "k string, at long, v int")
    grid = ly.ChunkGrid.uniform(15)
    built = ly.build_clipped_layout(from_change_log(log.where("at < 20"), ["k"], "at", ["v"], horizon=20), grid, str(tmp_path), spec, buckets=4)
    ly.append_period(spark, built, log.where("at >= 20"), "at", 40)
    whole = ly.clip_to_chunks(from_change_log(log, ["k"], "at", ["v"], horizon=40), grid, ["k"], 4)
    assert canonical_equal(whole.select("k", "v", FROM, TO, "chunk", "is_head"), built.scan(spark).select("k", "v", FROM, TO, "chunk", "is_head")) == (0, 0)


def test_measures(spark, randoms):
    assert measures.cost_scan(0) == 10 / 1024 / 1024 * 5 and measures.cost_scan(1 << 40) == 5
    prices = {"gb_second": 1.0, "read": 2.0, "write": 3.0, "queue": 4.0, "commit": 5.0}
    assert measures.cost_serverless(measures.Usage(1, 1, 1, 1, 1), prices) == 15
    assert round(measures.break_even(201, 0.0011)) == 250
    assert measures.cost_curve({"a": 2}, {"fixed": 7}, [3]) == [{"queries": 3, "a": 6, "fixed": 7}]
    points = measures.frontier({("a", "w"): (1, 1), ("b", "w"): (2, 2)})
    assert [p["best"] for p in points] == [True, False]
    a = run_mono(QUERIES["duration"], randoms)
    assert measures.relative_error(a, a, ["g"], "twa") == 0
    found = run_mono(QUERIES["predicate"], randoms)
    right, n = keys_correct(found.where("k <> 5"), found, ["k"])
    assert right == n - 1


def test_other_paths_agree(spark, randoms):
    randoms.createOrReplaceTempView("randoms")
    d = HISTORIES["supp"]
    w = d.windows["w3"]
    h = d.build(spark, "/root/testdata/sf0.001")
    h.createOrReplaceTempView("supp_source")
    mono = run_mono(Query("predicate", d.spec, w, phi="price < 10000", payload=("price",)), h)
    assert canonical_equal(mono, paths.sql_windows(spark, "supp_source", w, ["supp_key"], "price < 10000", ["price"])) == (0, 0)
    top = co.ranked_timeline(ly.segments(h, d.grid, ["supp_key"], w), "supp_key", "price", 2)
    assert canonical_equal(top, paths.coupled_rank(h, "supp_key", "price", 2, w, ly.ChunkGrid.calendar("WEEK"))) == (0, 0)
    assert canonical_equal(top, paths.exchanged_rank(h, "supp_key", "price", 2, w, ly.ChunkGrid.calendar("WEEK"))) == (0, 0)
    r = paths.coupled_input(h, w, ly.ChunkGrid.calendar("WEEK")).first()
    assert r.reducer_rows > r.source_rows


def test_sql_surface_and_files(spark, tmp_path):
    register(spark, 10)
    assert [tuple(r) for r in spark.sql("SELECT * FROM chunk_pieces(5, 25)").collect()] == [(0, 5, 10), (1, 10, 20), (2, 20, 25)]
    assert spark.sql("SELECT twa(x, d) AS t FROM VALUES (10.0D, 3L), (20.0D, 1L), (NULL, 9L) AS v(x, d)").first().t == 12.5
    assert spark.sql("SELECT overlap_us(TIMESTAMP_NTZ'2024-01-01', TIMESTAMP_NTZ'2024-01-03', TIMESTAMP_NTZ'2024-01-02', TIMESTAMP_NTZ'2024-02-01') AS n").first().n == 86_400_000_000
    (tmp_path / "c.csv").write_text("a,1\nb,x\n")
    from pyspark.sql import types as T

    schema = T.StructType([T.StructField("k", T.StringType()), T.StructField("v", T.IntegerType())])
    got = load_changes(spark, str(tmp_path / "c.csv"), "csv", schema).cache()
    assert [r._corrupt for r in got.orderBy("k").collect()] == [None, "b,x"]
    write_result(spark.range(3).toDF("n"), str(tmp_path / "out"), "q")
    assert spark.read.parquet(str(tmp_path / "out/manifest")).first().rows == 3


def test_stream_gives_what_the_batch_gives(spark, data, tmp_path):
    from chronofold.sources.history import from_change_log
    from chronofold.streaming.ingest import closed_intervals, sealed_chunks

    events = spark.read.parquet(f"{data}/events.parquet").select("user_id", F.col("ts").cast("timestamp").alias("ts"), "event_id", "event_type").where("event_id < 300")
    source = tmp_path / "in"
    for i in range(3):
        events.where(f"event_id % 3 = {i}").coalesce(1).write.mode("append").parquet(str(source))
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 3).parquet(str(source))
    closed_intervals(stream, "user_id", "ts", ["event_type"], ["event_id"], "1 hour").writeStream.format("memory").queryName("closed").outputMode("append").trigger(availableNow=True).option("checkpointLocation", str(tmp_path / "cp")).start().awaitTermination(120)
    found = spark.table("closed")
    batch = from_change_log(events, ["user_id"], "ts", ["event_type"], ["event_id"]).where(F.col(TO).isNotNull())
    only_stream, only_batch = canonical_equal(found, batch.select(*found.columns))
    assert only_stream == 0 and found.count() > 0.8 * batch.count() and only_batch == batch.count() - found.count()
    assert sealed_chunks(ly.ChunkGrid.calendar("DAY"), dt.datetime(2024, 1, 3, 5)) == ly.ChunkGrid.calendar("DAY").id_of(dt.datetime(2024, 1, 2))


@pytest.mark.parametrize("parts", [3, 160])
def test_conservation_of_more_time_than_a_bigint_holds(spark, tmp_path, parts):
    """160 parts from year 100 to the horizon have more than 2^63 microseconds."""
    from chronofold.workloads.queries import layout_conservation

    start = dt.datetime(100, 1, 15)
    line = "id AS l_partkey, 1L AS l_suppkey, 1L AS l_orderkey, 1 AS l_linenumber, 1.0D AS l_extendedprice, 0.0D AS l_discount, 0.0D AS l_tax, 1.0D AS l_quantity"
    spark.range(parts).selectExpr(*line.split(", "), "TIMESTAMP_NTZ'0100-01-15' AS l_shipdate").write.parquet(str(tmp_path / "lineitem.parquet"))
    found = layout_conservation(spark, str(tmp_path))
    row = found.first()
    want = parts * ((HISTORIES["part"].horizon - start) // dt.timedelta(microseconds=1))
    assert (int(row.duration_us), row.heads) == (want, parts)
    assert dict(found.dtypes)["duration_us"] == ("bigint" if want < 2**63 else "decimal(38,0)") and (parts == 3) == (want < 2**63)


def executed(plan):
    """Every operator of a plan that has run, in its final form."""
    kind = plan.getClass().getSimpleName()
    if kind == "AdaptiveSparkPlanExec":
        yield from executed(plan.executedPlan())
    elif kind.endswith("QueryStageExec"):
        yield from executed(plan.plan())
    else:
        yield plan
        children = plan.children()
        for i in range(children.size()):
            yield from executed(children.apply(i))


def widest(df):
    """(rows that the largest operator made, names of the operators), after a run."""
    df.collect()
    found = list(executed(df._jdf.queryExecution().executedPlan()))
    rows = [p.metrics().apply("numOutputRows").value() for p in found if p.metrics().contains("numOutputRows")]
    return max(rows), {p.getClass().getSimpleName() for p in found}


@pytest.mark.parametrize("descending", [False, True])
def test_ranks_of_many_segments(spark, descending):
    """Some 3,000 cuts of two chunks, rows that last for a few or most of them, gaps, ties and nulls; native as the sweep."""
    h = lambda s, m: F.pmod(F.xxhash64("k", "i", F.lit(s)), F.lit(m))
    n = spark.range(60 * 40).select((F.col("id") % 60).alias("k"), F.floor(F.col("id") / 60).alias("i"))
    start = F.col("i") * 100 + h(1, 40)
    rows = n.where("k >= 3 OR i = 0").select(F.col("k"), F.when(h(2, 9) > 0, h(3, 12)).cast("int").alias("x"), start.alias(FROM), F.when(F.col("k") < 3, 4000 - F.col("k")).otherwise(start + 1 + h(4, 60)).alias(TO), F.concat(F.lit("g"), F.col("k") % 2).alias("g"))
    seg = ly.clip_to_chunks(rows.where(F.col(FROM) < F.col(TO)), ly.ChunkGrid.uniform(2500), ["k"]).cache()
    for family, k in (([], 3), (["g"], 70)):
        native, sweep = (co.ranked_timeline(seg, "k", "x", k, descending, family, strategy=s) for s in ("native", "sweep"))
        assert canonical_equal(native, sweep) == (0, 0)


def test_ranks_do_not_pair_members_with_cuts(spark):
    """2,000 members hold all through 2,000 cuts that two others make."""
    long = spark.range(2000).select(F.col("id").alias("k"), F.col("id").alias("x"), F.lit(0).cast("long").alias(FROM), F.lit(2000).cast("long").alias(TO))
    short = spark.range(2000).select((F.col("id") % 2 + 5000).alias("k"), (F.col("id") % 7 - 3).alias("x"), F.col("id").alias(FROM), (F.col("id") + 1).alias(TO))
    rows, _ = widest(co.ranked_timeline(long.unionByName(short), "k", "x", 3))
    assert rows < 2000 * 3 * 12


@pytest.mark.parametrize("name", ["q10_user_origin", "q09_user", "q10_user", "layout_q09_user", "layout_q10_user"])
def test_ranks_of_all_users_are_not_broadcast(spark, data, name):
    from chronofold.workloads.queries import QUERIES as named

    rows, operators = widest(named[name](spark, data))
    assert "BroadcastExchangeExec" not in operators


@pytest.mark.parametrize(("kind", "descending"), [("int", False), ("decimal(18,2)", True), ("double", True)])
def test_rows_without_a_rank_are_not_ranked(spark, kind, descending):
    """400 members that mostly last through stretches, three chunks, ties, nulls, gaps and rows of no length; a family is ranked whole."""
    h = lambda s, m: F.pmod(F.xxhash64("k", "i", F.lit(s)), F.lit(m))
    n = spark.range(400 * 3).select((F.col("id") % 400).alias("k"), F.floor(F.col("id") / 400).alias("i"))
    x = F.when(h(2, 9) > 0, h(3, 200)) if kind != "double" else F.when(h(2, 9) > 1, h(3, 200) / 7).when(h(2, 9) > 0, F.lit(float("nan")))
    rows = n.select("k", x.cast(kind).alias("x"), (F.col("i") * 1000 + h(1, 50)).alias(FROM), (F.col("i") * 1000 + h(1, 50) + h(4, 950)).alias(TO), F.lit("g").alias("g"))
    seg = ly.clip_to_chunks(rows.where(F.col(FROM) < F.col(TO)), ly.ChunkGrid.uniform(1100), ["k"]).cache()
    whole = co.ranked_timeline(seg, "k", "x", 3, descending, ["g"]).drop("g")
    assert canonical_equal(co.ranked_timeline(seg, "k", "x", 3, descending), whole) == (0, 0)
    plain = seg.where("x IS NOT NULL").select("chunk", F.col("k").alias("key"), "x", FROM, TO)
    assert co.within_reach(plain, 1, descending).count() * 2 < plain.count()
    nobody = plain.where(F.col(TO) - F.col(FROM) < 20)
    assert co.within_reach(nobody, 3, descending).count() == nobody.count()


@pytest.mark.parametrize("name", ["layout_q09_user", "layout_q10_user"])
def test_ranks_from_a_layout_take_less_than_its_rows(spark, data, name):
    """No operator makes more rows than the layout has: few users' rows can be among the best at all."""
    from chronofold.workloads.queries import QUERIES as named
    from chronofold.workloads.stored import stored

    folder = data.replace("sf0.001", "sf0.01")
    rows, _ = widest(named[name](spark, folder))
    assert rows <= stored(spark, folder, "user").scan(spark).count()


@pytest.mark.parametrize(("kind", "descending"), [("int", False), ("decimal(38,2)", True)])
def test_few_rows_are_ranked_where_planned(spark, monkeypatch, kind, descending):
    """As by nodes of segments, by member and by value: three chunks, ties, gaps, rows of no length or without an end, instants or numbers."""
    h = lambda s, m: F.pmod(F.xxhash64("k", "i", F.lit(s)), F.lit(m))
    n = spark.range(90 * 30).select((F.col("id") % 90).alias("k"), F.floor(F.col("id") / 90).alias("i"))
    big = F.lit(0) if kind == "int" else F.lit("123456789012345678901234567890123456").cast("decimal(36,0)")
    start = F.col("i") * 100 + h(1, 40)
    rows = n.where("k >= 4 OR i = 0").select("k", (big + F.when(h(2, 9) > 0, h(3, 6))).cast(kind).alias("x"), start.alias(FROM), F.when(F.col("k") < 4, 2500 + F.col("k")).when(F.col("k") % 9 > 0, start + h(4, 60)).alias(TO))
    seg = ly.clip_to_chunks(rows.where("coalesce(valid_from < valid_to, true)").fillna(3000, [TO]), ly.ChunkGrid.uniform(1100), ["k"])
    seg = seg.unionByName(seg.limit(9).withColumn(TO, F.col(FROM))).unionByName(seg.limit(9).withColumn(TO, F.lit(None).cast("long"))).cache()
    at = {c: F.timestamp_add("MICROSECOND", F.col(c), F.to_timestamp_ntz(F.lit("2024-01-01 00:00:00.000001"))) for c in (FROM, TO)}
    for rows, identity in ((seg, "entity"), (seg, "value"), (seg.withColumns(at), "entity"), (seg.where("x IS NULL"), "entity")):
        run = lambda: co.ranked_timeline(rows, "k", "x", 3, descending, identity=identity)  # noqa: B023, E731
        few = run()
        with monkeypatch.context() as m:
            m.setattr(co, "FEW_ROWS", -1)
            nodes = run()
        assert few.dtypes == nodes.dtypes
        assert canonical_equal(few, nodes) == (0, 0)


def test_ranks_from_a_layout_need_no_exchange_if_few_rows_are_left(spark, data):
    """And the chunks' first and last instants come from the manifest."""
    from chronofold.workloads.queries import QUERIES as named
    from chronofold.workloads.stored import stored

    folder = data.replace("sf0.001", "sf0.01")
    assert "ShuffleExchangeExec" not in widest(named["layout_q10_user"](spark, folder))[1]
    layout, window = stored(spark, folder, "user"), HISTORIES["user"].windows["cut"]
    rows = ly.read_layout(spark, layout, window)
    assert layout.spans(spark, window) == co.spans_of(rows, on_axis(rows, FROM), on_axis(rows, TO))


def test_day_chunks_do_not_depend_on_the_zone(spark):
    """Also on a day that the session's zone never had, before 1970, and at both midnights."""
    zone = spark.conf.get("spark.sql.session.timeZone")
    at = [dt.datetime(2011, 12, 30), dt.datetime(2011, 12, 30, 23, 59, 59, 999999), dt.datetime(2011, 12, 31), dt.datetime(1969, 12, 31, 12), dt.datetime(1950, 1, 1)]
    rows = spark.createDataFrame([(t,) for t in at], "t timestamp_ntz")
    spark.conf.set("spark.sql.session.timeZone", "Pacific/Apia")
    try:
        for grid in (ly.ChunkGrid.calendar("DAY"), ly.ChunkGrid.calendar("WEEK"), ly.ChunkGrid.uniform(dt.timedelta(days=2), dt.datetime(1971, 1, 3))):
            found = rows.select("t", grid.of(F.col("t")).alias("o"), grid.last(F.col("t")).alias("l"), grid.start(grid.of(F.col("t"))).alias("s")).collect()
            for r in found:
                assert (r.o, r.l) == (grid.id_of(r.t), grid.id_of(r.t - dt.timedelta(microseconds=1)))
                assert grid.id_of(r.s) == r.o and r.s <= r.t and grid.id_of(r.s - dt.timedelta(microseconds=1)) == r.o - 1
    finally:
        spark.conf.set("spark.sql.session.timeZone", zone)


def test_the_sweep_goes_to_workers_without_this_package():
    import subprocess
    import sys

    from pyspark import cloudpickle

    run = "import sys, pickle; f = pickle.load(sys.stdin.buffer); print(f([(7, 1, 0, 9), (8, 0, 2, 4)]))"
    said = subprocess.run([sys.executable, "-I", "-c", run], input=cloudpickle.dumps(co.sweeper(1, False)), capture_output=True, cwd="/", check=True)
    assert said.stdout.split() == b"[(1, 7, 1, 0, 2), (1, 8, 0, 2, 4), (1, 7, 1, 4, 9)]".split()
    frame = subprocess.run([sys.executable, "-I", "-c", run.split("; print")[0]], input=cloudpickle.dumps(co._sweep(["chunk"], 1, False)), capture_output=True, cwd="/")
    assert frame.returncode == 0, frame.stderr
