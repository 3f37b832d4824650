"""Hand-checked micro-histories, and the wrong answers of broken fan-outs."""

from __future__ import annotations

import datetime as dt

import pytest
from pyspark.sql import functions as F

from chronofold.baselines import mq5_faults, naive
from chronofold.functions.instants import FROM, TO
from chronofold.functions.predicates import Pred
from chronofold.operators import cohort as co
from chronofold.operators import interval_algebra as ia
from chronofold.operators import joins
from chronofold.operators import same_base as sb
from chronofold.operators.canonical import coalesce_intervals
from chronofold.operators.gate import gated_difference
from chronofold.sources import history as hs
from chronofold.sources.layout import ChunkGrid, clip_to_chunks, segments
from chronofold.spec import HistorySpec, QueryWindow

D = dt.datetime
MONTH = ChunkGrid.calendar("MONTH")
TEN = ChunkGrid.uniform(10)


def table(spark, rows, schema):
    return spark.createDataFrame(rows, schema)


def ints(spark, rows, payload="x int"):
    return table(spark, rows, f"k string, {payload}, {FROM} long, {TO} long")


def got(df, *columns):
    return sorted(tuple(r) for r in df.select(*columns).collect())


@pytest.fixture(scope="module")
def prices(spark):
    return table(spark, [("A", 10, D(2025, 3, 18), D(2025, 5, 3)), ("A", 20, D(2025, 5, 3), D(2025, 6, 1))], f"k string, x int, {FROM} timestamp_ntz, {TO} timestamp_ntz")


SPRING = QueryWindow(D(2025, 4, 1), D(2025, 6, 1))
DAY = 86_400_000_000


def test_average_adds_sums_and_divides_once(spark, prices):
    seg = segments(prices, MONTH, ["k"], SPRING)
    r = sb.duration_aggregate(seg, "x", digits=6).first()
    assert (r.weighted_sum, r.duration_us, r.twa) == (900 * DAY, 61 * DAY, 14.754098)
    assert round(naive.mean_of_means(seg, "x").first().twa, 6) == 14.677419
    assert naive.mean_of_means(naive.whole_rows_by_start(prices, MONTH, QueryWindow(D(2025, 3, 1), D(2025, 6, 1))), "x").first().twa == 15.0


def test_rows_enter_each_chunk_they_touch(spark, prices):
    rows = clip_to_chunks(prices.where("x = 10"), MONTH, ["k"])
    assert got(rows, FROM, TO, "is_head") == [(D(2025, 3, 18), D(2025, 4, 1), True), (D(2025, 4, 1), D(2025, 5, 1), False), (D(2025, 5, 1), D(2025, 5, 3), False)]
    exact = table(spark, [("B", 1, D(2025, 4, 1), D(2025, 5, 1))], f"k string, x int, {FROM} timestamp_ntz, {TO} timestamp_ntz")
    assert clip_to_chunks(exact, MONTH, ["k"]).count() == 1
    assert naive.start_chunk_only(prices, MONTH, SPRING).where("x = 10").count() == 0


def test_threshold_after_the_sum(spark):
    rows = ints(spark, [(f"a{i}", 1, 0, 10) for i in range(100)])
    full = sb.count_timeline(rows, "x = 1")
    assert got(full, FROM, TO, "active") == [(0, 10, 100)]
    assert got(sb.threshold_windows(full, [], 80), FROM, TO) == [(0, 10)]
    assert naive.threshold_per_shard(rows, ["k"], "x = 1", [], 80, 2).count() == 0


def test_canonical_form(spark):
    rows = ints(spark, [("K", 1, 0, 5), ("K", 1, 5, 9), ("K", 2, 9, 12), ("K", 2, 13, 15)])
    assert got(coalesce_intervals(rows, ["k"], ["x"]), "x", FROM, TO) == [(1, 0, 9), (2, 9, 12), (2, 13, 15)]
    once = coalesce_intervals(rows, ["k"])
    assert got(once, FROM, TO) == [(0, 12), (13, 15)] == got(coalesce_intervals(once, ["k"]), FROM, TO)


def test_null_is_false(spark):
    rows = table(spark, [("K", 3, None, 0, 10)], f"k string, price int, stable boolean, {FROM} long, {TO} long")
    assert sb.boolean_window(rows, ["k"], Pred.col("price") < 5, "stable", "minus").count() == 1
    assert rows.where("price < 5 AND NOT stable").count() == 0


def test_better_count_keeps_zeros(spark):
    rows = ints(spark, [("R", 5, 0, 10), ("c1", 3, 2, 6), ("c2", 7, 0, 10)])
    assert got(co.count_better_than(rows, "k", "R", "x"), FROM, TO, "better") == [(0, 2, 0), (2, 6, 1), (6, 10, 0)]
    assert got(naive.better_without_cover(rows, "k", "R", "x"), FROM, TO, "better") == [(2, 6, 1)]


@pytest.mark.parametrize("shards", [1, 2, 7])
def test_better_count_over_shards(spark, shards):
    rows = ints(spark, [("R", 5, 0, 10), ("c1", 3, 2, 6), ("c3", 4, 4, 8)])
    assert got(co.count_better_than(rows, "k", "R", "x", shards=shards), FROM, TO, "better") == [(0, 2, 0), (2, 4, 1), (4, 6, 2), (6, 8, 1), (8, 10, 0)]


@pytest.mark.parametrize("strategy", ["native", "sweep"])
def test_ranks(spark, strategy):
    ties = ints(spark, [("b", 4, 0, 10), ("a", 4, 0, 10), ("c", 9, 0, 10)])
    assert got(co.ranked_timeline(ties, "k", "x", 2, strategy=strategy), "rank", "key") == [(1, "a"), (2, "b")]
    few = ints(spark, [("a", 1, 0, 4), ("b", 2, 0, 8)])
    assert got(co.winner_timeline(few, "k", "x", strategy=strategy), FROM, TO, "key") == [(0, 4, "a"), (4, 8, "b")]
    assert got(co.ranked_timeline(few, "k", "x", 3, strategy=strategy), FROM, TO, "rank", "key") == [(0, 4, 1, "a"), (0, 4, 2, "b"), (4, 8, 1, "b")]
    assert got(co.ranked_timeline(few, "k", "x", 1, strategy=strategy, identity="value"), FROM, TO, "x") == [(0, 4, 1), (4, 8, 2)]


def test_pairs_only_where_both_hold(spark):
    rows = ints(spark, [("l", 1, 0, 5), ("r", 2, 3, 8)])
    assert got(co.pairwise_compare(rows, "k", "l", "r", "x"), FROM, TO) == [(3, 5)]
    assert got(co.pairwise_compare(rows, "k", "l", "r", "x", "gt", "both"), FROM, TO, "holds") == [(3, 5, False)]


def test_gated_difference(spark):
    rows = [("7", p, True, f, t) for p, f, t in ((5, 0, 6), (12, 6, 9), (5, 9, 14), (15, 14, 16), (5, 16, 20))]
    rows += [("8", 5, True, 0, 20), ("9", 5, True, 0, 10), ("9", 50, False, 25, 30)]
    h = table(spark, rows, f"k string, price int, brand boolean, {FROM} long, {TO} long")
    cut = clip_to_chunks(h, TEN, ["k"])
    want = [("7", 0, 6), ("7", 9, 14), ("7", 16, 20), ("9", 0, 10)]
    assert got(gated_difference(cut, ["k"], "brand", "price > 10", "price > 10"), "k", FROM, TO) == want
    assert ("7", 0, 20) in got(mq5_faults.intersection_fault(h, ["k"], "brand", "price > 10"), "k", FROM, TO)
    assert got(coalesce_intervals(naive.gate_per_chunk(cut, ["k"], "brand AND price <= 10", "price > 10"), ["k"]), "k", FROM, TO) != want


def test_groups_change_with_rows(spark):
    rows = table(spark, [("a", "g1", 0, 5), ("a", "g2", 5, 10)], f"k string, g string, {FROM} long, {TO} long")
    assert got(sb.count_timeline(rows, None, ["g"]), "g", FROM, TO, "active") == [("g1", 0, 5, 1), ("g2", 5, 10, 1)]


def test_change_log(spark):
    log = table(spark, [("a", 5, 1, "old"), ("a", 5, 2, "new"), ("a", 9, 1, "end"), (None, 1, 1, "x")], "k string, at long, n int, v string")
    rows = hs.from_change_log(log, ["k"], "at", ["v"], ["n"], horizon=100)
    assert got(rows, "v", FROM, TO) == [("end", 9, 100), ("new", 5, 9)]
    assert got(hs.restrict_window(rows, QueryWindow(90, 120)), "v", FROM, TO) == [("end", 90, 100)]
    deleted = table(spark, [("a", 1, "x", "insert"), ("a", 4, None, "delete"), ("a", 7, "y", "insert")], "k string, at long, v string, op string")
    assert got(hs.from_change_log(deleted, ["k"], "at", ["v"], horizon=9, op="op"), "v", FROM, TO) == [("x", 1, 4), ("y", 7, 9)]
    assert got(hs.from_change_log(log.where("n = 1"), ["k"], "at", ["n"], horizon=100, compact=True), FROM, TO) == [(5, 100)]


def test_full_state_and_checks(spark):
    log = table(spark, [("k", 1, ["a", "b"], 1, 1), ("k", 2, ["a"], 2, None), ("k", 3, ["b"], None, None)], "k string, at long, changed array<string>, a int, b int")
    assert [tuple(r) for r in hs.fill_full_state(log, ["k"], "at", ["a", "b"], changed="changed").orderBy("at").select("a", "b").collect()] == [(1, 1), (2, 1), (2, None)]
    assert [r.b for r in hs.fill_full_state(log, ["k"], "at", ["a", "b"]).orderBy("at").collect()] == [1, 1, 1]
    bad = ints(spark, [("a", 1, 0, 5), ("a", 2, 3, 8), ("b", 1, 5, 5), (None, 1, 0, 1), ("c", 1, 0, None), ("c", 1, 4, 6)])
    assert sorted(r.problem for r in hs.validate_history(bad, HistorySpec(("k",), ("x",), integer=True)).collect()) == ["empty interval", "null key", "overlap", "overlap"]


def test_overlap_pairs_once(spark):
    a, b = ints(spark, [("k", 1, 5, 28)]), ints(spark, [("k", 2, 8, 35)])
    assert joins.overlap_join(a, b, TEN.of, ["k"]).count() == 1


def test_interval_sets(spark):
    a, b = ints(spark, [("k", 1, 0, 10)]), ints(spark, [("k", 1, 4, 6), ("k", 1, 8, 12)])
    assert got(ia.union(a, b, ["k"]), FROM, TO) == [(0, 12)]
    assert got(ia.intersect(a, b, ["k"]), FROM, TO) == [(4, 6), (8, 10)]
    assert got(ia.subtract(a, b, ["k"]), FROM, TO) == [(0, 4), (6, 8)]
    assert got(ia.complement(b, a, ["k"], F.lit(0).cast("long"), F.lit(20).cast("long")), FROM, TO) == [(0, 4), (6, 8), (12, 20)]


def test_explicit_grid_and_zeros(spark):
    rows = ints(spark, [("k", 1, 0, 50)])
    cut = clip_to_chunks(rows, ChunkGrid.explicit([10, 30]), ["k"])
    assert got(cut, "chunk", FROM, TO) == [(-1, 0, 10), (0, 10, 30), (1, 30, 50)]
    t = sb.count_timeline(ints(spark, [("k", 1, 2, 4)]), None, ["k"])
    whole = sb.with_zeros(t, rows, ["k"], F.lit(0).cast("long"), F.lit(6).cast("long"))
    assert got(whole, FROM, TO, "active") == [(0, 2, 0), (2, 4, 1), (4, 6, 0)]
