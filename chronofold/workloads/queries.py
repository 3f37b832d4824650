"""Every query of the engine's own inventory, with SQL where SQL can say it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..baselines import mq5_faults, naive, paths
from ..functions.instants import FROM, TO, length
from ..operators import cohort as co
from ..operators import gate, interval_algebra, joins
from ..operators import same_base as sb
from ..plans import sizing
from ..plans.query import Query
from ..plans.runner import run_fanout, run_fanout_durable
from ..sources import history as hs
from ..sources import layout as ly
from ..sources.files import load, props
from ..sources.folders import scratch
from ..streaming.ingest import session_counts, sliding_counts, tumbling_counts
from . import oracles as sql
from . import stored, studies
from .histories import HISTORIES
from .suite import SUITE, compositions, nth_key, segmented, smallest, suite

Run = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Run] = {}
ORACLES: dict[str, str] = {}

PART, CUST, USER = HISTORIES["part"], HISTORIES["cust"], HISTORIES["user"]
W12, CUT = PART.windows["w12"], PART.windows["cut"]
LOW, HIGH = f"TIMESTAMP '{W12.start}'", f"TIMESTAMP '{W12.end}'"


def query(oracle: str | None = None, name: str | None = None):
    def add(run: Run) -> Run:
        QUERIES[name or run.__name__] = run
        if oracle is not None:
            ORACLES[name or run.__name__] = oracle
        return run

    return add


# Histories.


def _history(name: str) -> None:
    d = HISTORIES[name]
    columns = ", ".join(d.spec.columns)
    query(f"WITH {sql.history(name)} SELECT {columns} FROM h", f"hist_{name}")(lambda spark, folder: d.build(spark, folder))


for _name in HISTORIES:
    _history(_name)

_PIVOT = ", ".join(f"CASE WHEN event_type = '{t}' THEN CAST(value AS DECIMAL(18,2)) END AS {t}_v" for t in ("click", "error", "purchase", "signup", "view"))


@query(
    f"WITH p AS (SELECT user_id, ts, event_id, {_PIVOT} FROM events) SELECT user_id, ts, event_id, "
    + ", ".join(f"last_value({t}_v IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS {t}_v" for t in ("click", "error", "purchase", "signup", "view"))
    + " FROM p"
)
def hist_sparse_filled(spark, folder):
    """A log that shows one column a row, filled to full-state rows."""
    names = [f"{t}_v" for t in ("click", "error", "purchase", "signup", "view")]
    shown = [f"CASE WHEN event_type = '{n[:-2]}' THEN CAST(value AS DECIMAL(18,2)) END AS {n}" for n in names]
    sparse = load(spark, folder, "events").selectExpr("user_id", "ts", "event_id", *shown)
    return hs.fill_full_state(sparse, ["user_id"], "ts", names, ["event_id"])


@query("SELECT conv_id, role, CAST(length(text) AS INT) AS n_chars, turn AS valid_from, coalesce(lead(turn) OVER (PARTITION BY conv_id ORDER BY turn), turn + 1) AS valid_to FROM conversations")
def hist_conv(spark, folder):
    """An integer axis: turns of a conversation."""
    turns = load(spark, folder, "conversations").select("conv_id", "role", F.char_length("text").cast("int").alias("n_chars"), "turn")
    rows = hs.from_change_log(turns, ["conv_id"], "turn", ["role", "n_chars"])
    return rows.withColumn(TO, F.coalesce(TO, F.col(FROM) + 1))


_DAILY = "SELECT DISTINCT user_id, date_trunc('day', ts) AS d, event_type FROM events"


@query(
    f"WITH u AS ({_DAILY}), s AS (SELECT user_id, d AS valid_from, d + INTERVAL 1 DAY AS valid_to, max(event_type) AS event_type FROM u GROUP BY user_id, d) "
    + sql.islands("s", ["user_id"], ["event_type"])
)
def snapshots_to_history(spark, folder):
    """Daily snapshots (a user's greatest event type of the day) as a history."""
    day = F.date_trunc("day", "ts").cast("timestamp_ntz")
    daily = load(spark, folder, "events").groupBy("user_id", day.alias("d")).agg(F.max("event_type").alias("event_type"))
    return hs.from_snapshots(daily, ["user_id"], "d", ["event_type"], F.expr("INTERVAL 1 DAY"))


@query("SELECT CAST(NULL AS BIGINT) AS part_key, TIMESTAMP '2000-01-01' AS valid_from, TIMESTAMP '2000-01-01' AS valid_to, '' AS problem WHERE false")
def history_violations(spark, folder):
    """None, for a history that is well formed."""
    return hs.validate_history(PART.build(spark, folder), PART.spec)


@query(f"WITH {sql.history('part')} SELECT part_key, price, score FROM h WHERE valid_from <= {LOW} AND valid_to > {LOW}")
def state_at_instant(spark, folder):
    return hs.state_at(PART.build(spark, folder), W12.start).select("part_key", "price", "score")


@query(f"{sql.clipped('part', CUT)} SELECT part_key, price, valid_from, valid_to FROM c")
def window_clip(spark, folder):
    return hs.restrict_window(PART.build(spark, folder), CUT).select("part_key", "price", FROM, TO)


@query(f"{sql.clipped('supp', HISTORIES['supp'].windows['w1'])} SELECT CAST(count(*) AS BIGINT) AS n FROM (SELECT supp_key, unnest(generate_series(valid_from, valid_to - INTERVAL 1 MICROSECOND, INTERVAL 1 DAY)) FROM c)")
def history_to_snapshots(spark, folder):
    """A row a day, counted."""
    d = HISTORIES["supp"]
    return hs.to_snapshots(hs.restrict_window(d.build(spark, folder), d.windows["w1"]), F.expr("INTERVAL 1 DAY")).agg(F.count(F.lit(1)).alias("n"))


# Layout and sizing.

_SPREAD = f"WITH {sql.history('part')}, g AS (SELECT h.*, unnest(generate_series(date_trunc('month', valid_from), date_trunc('month', valid_to - INTERVAL 1 MICROSECOND), INTERVAL 1 MONTH)) AS m FROM h), l AS (SELECT * REPLACE (greatest(valid_from, m) AS valid_from, least(valid_to, m + INTERVAL 1 MONTH) AS valid_to), valid_from >= m AS is_head FROM g)"


@query(f"{_SPREAD} SELECT CAST(year(m) * 12 + month(m) - 1 AS INT) AS chunk, CAST(count(*) AS BIGINT) AS n, CAST(sum(CASE WHEN is_head THEN 1 ELSE 0 END) AS BIGINT) AS heads, CAST(sum(date_diff('microsecond', valid_from, valid_to)) AS BIGINT) AS duration_us FROM l GROUP BY m")
def layout_rows_by_chunk(spark, folder):
    rows = ly.clip_to_chunks(PART.build(spark, folder), PART.grid, ["part_key"])
    return rows.groupBy("chunk").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("is_head").cast("long")).alias("heads"), F.sum(length(F.col(FROM), F.col(TO))).alias("duration_us"))


@query(f"WITH {sql.history('part')} SELECT CAST(sum(date_diff('microsecond', valid_from, valid_to)) AS BIGINT) AS duration_us, CAST(count(*) AS BIGINT) AS heads FROM h")
def layout_conservation(spark, folder):
    """Time and heads of the pieces are those of the source.  The time is summed as a decimal, since some 30,000 parts pass what a
    BIGINT holds; it is a BIGINT, as in SQL, where it fits one, and that decimal otherwise."""
    rows = ly.clip_to_chunks(PART.build(spark, folder), PART.grid, ["part_key"])
    duration, heads = rows.agg(F.sum(length(F.col(FROM), F.col(TO)).cast("decimal(20,0)")), F.sum(F.col("is_head").cast("long"))).first()
    if duration is None or -(2**63) <= duration < 2**63:
        return spark.createDataFrame([(None if duration is None else int(duration), heads)], "duration_us bigint, heads bigint")
    return spark.createDataFrame([(duration, heads)], "duration_us decimal(38,0), heads bigint")


_CALENDAR = {"month": ly.ChunkGrid.calendar("MONTH"), "quarter": ly.ChunkGrid.calendar("QUARTER"), "year": ly.ChunkGrid.calendar("YEAR")}
_SHORT = {"6h": 21_600_000_000, "day": 86_400_000_000, "week": 604_800_000_000}


def _amplified(name: str, spans: dict[str, str], grids: dict) -> None:
    rows = " UNION ALL ".join(f"SELECT '{w}' AS width, CAST(count(*) AS BIGINT) AS source_rows, CAST(sum({s}) AS BIGINT) AS layout_rows FROM h" for w, s in spans.items())
    text = f"WITH {sql.history(name)}, a AS ({rows}) SELECT width, source_rows, layout_rows, round(layout_rows / source_rows, 6) AS a_row FROM a"
    query(text, f"amplification_{name}")(lambda spark, folder: sizing.row_amplification(HISTORIES[name].build(spark, folder), grids))


_LAST = "valid_to - INTERVAL 1 MICROSECOND"
for _name in ("part", "supp", "cust"):
    _amplified(_name, {u: f"datediff('{u}', valid_from, {_LAST}) + 1" for u in _CALENDAR}, _CALENDAR)
_amplified("user", {w: f"CAST(floor(epoch_us({_LAST}) / {n}.0) - floor(epoch_us(valid_from) / {n}.0) AS BIGINT) + 1" for w, n in _SHORT.items()}, {w: ly.ChunkGrid("uniform", width=n) for w, n in _SHORT.items()})


@query(f"WITH {sql.history('part')} SELECT CAST(year(valid_from) * 12 + month(valid_from) - 1 AS INT) AS from_month, CAST(count(*) AS BIGINT) AS n FROM h GROUP BY ALL")
def from_month_source(spark, folder):
    """The unclipped source, written by start month and read back."""
    path = scratch(spark)
    ly.write_scd2(PART.build(spark, folder), path)
    return spark.read.parquet(path).groupBy("from_month").agg(F.count(F.lit(1)).alias("n"))


def _stored(spark: SparkSession, folder: str, name: str = "part", grid: ly.ChunkGrid | None = None) -> ly.Layout:
    return stored.stored(spark, folder, name, grid)


@query(sql.count("part", W12, "price < 10000", ["brand"], ["brand"], 8))
def layout_q06_part(spark, folder):
    """Q6 through a stored layout."""
    asked = Query("count", PART.spec, W12, phi="price < 10000", group=("brand",)).with_dims(PART.dim(spark, folder, "brand"), "part_key").then_threshold(8)
    return run_fanout(asked, _stored(spark, folder), spark)


@query(sql.duration("part", PART.windows["w3"], "price", []))
def durable_average(spark, folder):
    """Piece by piece with stored partials and a commit log."""
    asked = Query("duration", PART.spec, PART.windows["w3"], x="price", digits=6)
    return run_fanout_durable(asked, _stored(spark, folder, grid=ly.ChunkGrid.calendar("YEAR")), spark, scratch(spark))


@query(f"WITH {sql.history('cust')}, a AS (SELECT 'month' AS width, 1 AS o, sum(datediff('month', valid_from, {_LAST}) + 1) / count(*) AS a FROM h UNION ALL SELECT 'quarter', 2, sum(datediff('quarter', valid_from, {_LAST}) + 1) / count(*) FROM h UNION ALL SELECT 'year', 3, sum(datediff('year', valid_from, {_LAST}) + 1) / count(*) FROM h) SELECT coalesce(min_by(width, o) FILTER (a <= 1.25), 'whole') AS width FROM a")
def safe_width_cust(spark, folder):
    """Long lives: no calendar width is within a quarter more rows, so the window stays whole and keys are sharded."""
    found = sizing.storage_safe_width(CUST.build(spark, folder), _CALENDAR, 0.25)
    return spark.createDataFrame([(found or "whole",)], "width string")


@query()
def shard_plan_part(spark, folder):
    """Bucket ranges of each month within a ceiling of bytes."""
    rows = ly.clip_to_chunks(hs.restrict_window(PART.build(spark, folder), W12), PART.grid, ["part_key"], 64)
    return sizing.plan_shards(sizing.key_byte_histogram(rows, ["part_key"], 10.0, 64), 4096.0)


# The suite, by window and by chunk width.

for _name in SUITE:
    _q, _o = suite(_name)
    QUERIES |= _q
    ORACLES |= _o
for _w in ("w1", "w3", "w6"):
    _q, _o = suite("part", _w, f"_{_w}")
    QUERIES |= _q
    ORACLES |= _o
for _label, _factor in (("quarter", 0.25), ("half", 0.5), ("double", 2), ("fourfold", 4)):
    _q, _o = suite("part", "cut", f"_{_label}", PART.grid.scale(_factor))
    QUERIES |= _q
    ORACLES |= _o
for _w in ("cut", "empty", "inside"):
    _q, _o = suite("part", _w, f"_{_w}", None, (1, 2, 6, 10))
    QUERIES |= _q
    ORACLES |= _o
_q, _o = suite("user", "origin", "_origin", None, (6, 7, 8, 10))
QUERIES |= _q
ORACLES |= _o
_composed: dict[str, Query] = {}
_q, _o = compositions(_composed)
QUERIES |= _q
ORACLES |= _o
for _q, _o in (stored.layout_suite(ORACLES), stored.layout_compositions(_composed, ORACLES), stored.durable_families()):
    QUERIES |= _q
    ORACLES |= _o

# Variants of the operators.


@query(sql.count("part", W12, "price < 10000", ["brand"], ["brand"], 0))
def q06_part_smallest(spark, folder):
    """Any cheap part at all: counts grow with the keys, so the smallest tables ask for one."""
    timeline = sb.count_timeline(segmented("part", spark, folder, W12, ("brand",)), "price < 10000", ["brand"])
    return sb.threshold_windows(timeline, ["brand"], 0)


@query(sql.duration("part", W12, "price", ["region"], ["region"]))
def q02_time_varying_group(spark, folder):
    """A group that changes with a row's supplier."""
    return sb.duration_aggregate(segmented("part", spark, folder, W12, ("region",)), "price", ["region"], 6)


@query(sql.duration("cust", CUST.windows["w12"], "price", ["prio"]))
def q02_cust_by_prio(spark, folder):
    return sb.duration_aggregate(segmented("cust", spark, folder, CUST.windows["w12"]), "price", ["prio"], 6)


@query(sql.duration("part", W12, "price", []))
def q02_global(spark, folder):
    return sb.duration_aggregate(segmented("part", spark, folder, W12), "price", [], 6)


@query(f"{sql.clipped('cust', CUST.windows['w12'])} SELECT status, CAST(sum(date_diff('microsecond', valid_from, valid_to)) AS BIGINT) AS duration_us FROM c GROUP BY status")
def time_in_status(spark, folder):
    return sb.time_in_state(segmented("cust", spark, folder, CUST.windows["w12"]), ["status"])


_EXPOSED = f"{sql.clipped('supp', W12, ['region'])}, s AS (SELECT region, nation, CAST(sum(price * CAST(date_diff('microsecond', valid_from, valid_to) AS DECIMAL(20,0))) AS DECIMAL(38,2)) AS weighted_sum, CAST(sum(date_diff('microsecond', valid_from, valid_to)) AS BIGINT) AS duration_us, CAST(grouping(region) * 2 + grouping(nation) AS BIGINT) AS level FROM c GROUP BY {{0}}(region, nation)) SELECT *, round(CAST(weighted_sum AS DOUBLE) / duration_us, 6) AS twa FROM s"


@query(_EXPOSED.format("ROLLUP "))
def rollup_exposure(spark, folder):
    return sb.duration_rollup(segmented("supp", spark, folder, W12, ("region",)), "price", ["region", "nation"])


@query(_EXPOSED.format("CUBE "))
def cube_exposure(spark, folder):
    return sb.duration_rollup(segmented("supp", spark, folder, W12, ("region",)), "price", ["region", "nation"], cube=True)


for _unit in ("delta", "step"):
    query(sql.count("user", USER.windows["cut"], "value < 10", ["event_type"]), f"count_timeline_{_unit}")(lambda spark, folder, unit=_unit: sb.count_timeline(segmented("user", spark, folder, USER.windows["cut"]), "value < 10", ["event_type"], unit))


@query(sql.count("user", USER.windows["cut"], "value < 10", ["event_type"]))
def count_timeline_cluster_first(spark, folder):
    return sb.count_timeline(segmented("user", spark, folder, USER.windows["cut"]), "value < 10", ["event_type"], cluster_first=True)


@query(f"{sql.timeline('part', W12, 'price < 10000', ['brand'], ['brand'])}, i AS ({sql.islands('t', ['brand'], ['active'])}) SELECT brand, round(sum(CAST(active * date_diff('microsecond', valid_from, valid_to) AS DOUBLE)) / sum(date_diff('microsecond', valid_from, valid_to)), 6) AS mean_active FROM i GROUP BY brand")
def mean_count(spark, folder):
    """A second stage over a merged timeline, which is a history of its own."""
    t = sb.count_timeline(segmented("part", spark, folder, W12, ("brand",)), "price < 10000", ["brand"])
    d = length(F.col(FROM), F.col(TO))
    return t.groupBy("brand").agg(F.round(F.sum((F.col("active") * d).cast("double")) / F.sum(d), 6).alias("mean_active"))


@query(f"{sql.timeline('part', W12, 'price < 10000', ['brand'], ['brand'])} SELECT brand, max(active) AS active, arg_min(valid_from, (-active, valid_from)) AS valid_from FROM t GROUP BY brand")
def count_peaks(spark, folder):
    return sb.count_peak(sb.count_timeline(segmented("part", spark, folder, W12, ("brand",)), "price < 10000", ["brand"]), ["brand"])


_OPS = {"lt": "<", "le": "<=", "gt": ">", "ge": ">=", "eq": "=", "ne": "<>"}
_TWO = f"{sql.clipped('user', USER.windows['cut'])}, p AS (" + " UNION ALL ".join(f"SELECT '{n}' AS cmp, l.user_id AS left_key, r.user_id AS right_key, greatest(l.valid_from, r.valid_from) AS valid_from, least(l.valid_to, r.valid_to) AS valid_to, l.value {o} r.value AS holds FROM c l, c r WHERE l.user_id = {nth_key('user', 0)} AND r.user_id = {nth_key('user', 1)} AND l.valid_from < r.valid_to AND r.valid_from < l.valid_to" for n, o in _OPS.items()) + f") {sql.islands('p', ['cmp', 'left_key', 'right_key'], ['holds'])}"


@query(_TWO)
def q07_all_comparators(spark, folder):
    seg = segmented("user", spark, folder, USER.windows["cut"])
    a, b = smallest("user", spark, folder, 2)
    out = None
    for name in _OPS:
        one = co.pairwise_compare(seg, "user_id", a, b, "value", name, "both").withColumn("cmp", F.lit(name))
        out = one if out is None else out.unionByName(one)
    return out


@query(sql.better("part", W12, "brand = 'Brand#7'", nth_key("part", 0), "price", "<", ["brand"]))
def q08_sharded(spark, folder):
    seg = segmented("part", spark, folder, W12, ("brand",)).where("brand = 'Brand#7'")
    return co.count_better_than(seg, "part_key", smallest("part", spark, folder, 1)[0], "price", shards=3)


@query(sql.ranked("part", W12, "true", "price", 1, ["brand"], ["brand"]))
def q09_family_all_brands(spark, folder):
    """Every brand's winner at once."""
    return co.winner_timeline(segmented("part", spark, folder, W12, ("brand",)), "part_key", "price", family=["brand"])


_TOP3 = sql.ranked("part", W12, "brand = 'Brand#7'", "price", 3, ["brand"])


@query(_TOP3)
def q10_sharded(spark, folder):
    seg = segmented("part", spark, folder, W12, ("brand",)).where("brand = 'Brand#7'")
    return co.ranked_timeline(seg, "part_key", "price", 3, shards=4)


@query(_TOP3)
def q10_sweep(spark, folder):
    seg = segmented("part", spark, folder, W12, ("brand",)).where("brand = 'Brand#7'")
    return co.ranked_timeline(seg, "part_key", "price", 3, strategy="sweep")


@query(sql.ranked("part", W12, "brand = 'Brand#7'", "score", 3, ["brand"], (), True))
def q10_ties_descending(spark, folder):
    """Many members tie on a score of fifty values; the smaller key goes first."""
    seg = segmented("part", spark, folder, W12, ("brand",)).where("brand = 'Brand#7'")
    return co.ranked_timeline(seg, "part_key", "score", 3, descending=True)


# Baselines.


@query(f"{sql.clipped('part', W12)} SELECT round(avg(a), 6) AS twa FROM (SELECT sum(price * CAST(date_diff('microsecond', valid_from, valid_to) AS DECIMAL(20,0)))::DOUBLE / sum(date_diff('microsecond', valid_from, valid_to)) AS a FROM (SELECT c.price, unnest(generate_series(date_trunc('month', valid_from), date_trunc('month', valid_to - INTERVAL 1 MICROSECOND), INTERVAL 1 MONTH)) AS m, greatest(valid_from, m) AS valid_from, least(valid_to, m + INTERVAL 1 MONTH) AS valid_to FROM c) GROUP BY m)")
def naive_twa(spark, folder):
    """Wrong on purpose: the mean of months' means."""
    return naive.mean_of_means(segmented("part", spark, folder, W12), "price").select(F.round("twa", 6).alias("twa"))


_WINNER = sql.ranked("part", W12, "true", "price", 1)


@query(_WINNER)
def coupled_winner(spark, folder):
    """Rows dealt to weeks at query time, over all parts."""
    return paths.coupled_rank(PART.build(spark, folder), "part_key", "price", 1, W12, ly.ChunkGrid.calendar("WEEK"))


@query(_WINNER)
def independent_winner(spark, folder):
    return co.winner_timeline(segmented("part", spark, folder, W12), "part_key", "price")


@query(_WINNER)
def exchanged_winner(spark, folder):
    return paths.exchanged_rank(PART.build(spark, folder), "part_key", "price", 1, W12, ly.ChunkGrid.calendar("WEEK"))


@query(sql.predicate("part", W12, "price < 10000", ["price"]))
def engine_scd2_q1(spark, folder):
    path = scratch(spark)
    ly.write_scd2(PART.build(spark, folder), path)
    return paths.engine_on_scd2(spark, path, Query("predicate", PART.spec, W12, phi="price < 10000", payload=("price",)), PART.grid)


@query(f"{sql.clipped('supp', W12)}, s AS (SELECT supp_key, CAST(sum(price * CAST(date_diff('microsecond', valid_from, valid_to) AS DECIMAL(20,0))) AS DECIMAL(38,2)) AS weighted_sum, CAST(sum(date_diff('microsecond', valid_from, valid_to)) AS BIGINT) AS duration_us FROM c GROUP BY supp_key) SELECT *, round(CAST(weighted_sum AS DOUBLE) / duration_us, 6) AS twa FROM s")
def native_sequence_average(spark, folder):
    return paths.native_sequences(HISTORIES["supp"].build(spark, folder), ["supp_key"], "price", W12)


for _fault in ("intersection_fault", "bridged_fault"):
    query(None, f"mq5_{_fault}")(lambda spark, folder, f=_fault: getattr(mq5_faults, f)(segmented("cust", spark, folder, CUST.windows["w12"]), ["cust_key"], "prio = '1-URGENT'", "price > 450000"))


@query()
def mq5_unclipped_fault(spark, folder):
    h = CUST.build(spark, folder)
    return mq5_faults.unclipped_fault(h, segmented("cust", spark, folder, CUST.windows["w12"]), ["cust_key"], "prio = '1-URGENT'", "price > 450000")


# Interval sets, keys, joins.


def _sets(spark, folder):
    seg = segmented("part", spark, folder, W12)
    return sb.predicate_window(seg, ["part_key"], "price < 10000"), sb.predicate_window(seg, ["part_key"], "score >= 25")


_ALGEBRA = {"union": ("or", "price < 10000 OR score >= 25"), "intersect": ("and", "price < 10000 AND score >= 25"), "subtract": ("minus", "price < 10000 AND NOT score >= 25")}
for _k, (_, _phi) in _ALGEBRA.items():
    query(sql.predicate("part", W12, _phi), f"interval_{_k}")(lambda spark, folder, k=_k: getattr(interval_algebra, k)(*_sets(spark, folder), ["part_key"]))


@query(f"{sql.clipped('part', W12)}, z AS (SELECT DISTINCT part_key, {LOW} AS f0, {HIGH} AS t0 FROM c), y AS ({sql.islands('c', ['part_key'], (), 'price < 10000')}), q AS (SELECT part_key, f0 AS tick FROM z UNION SELECT part_key, t0 FROM z UNION SELECT part_key, valid_from FROM y UNION SELECT part_key, valid_to FROM y), g AS (SELECT part_key, tick AS valid_from, lead(tick) OVER (PARTITION BY part_key ORDER BY tick) AS valid_to FROM q), r AS (SELECT * FROM g WHERE valid_to IS NOT NULL AND NOT EXISTS (SELECT 1 FROM y WHERE y.part_key = g.part_key AND y.valid_from <= g.valid_from AND g.valid_from < y.valid_to)) {sql.islands('r', ['part_key'])}")
def interval_complement(spark, folder):
    seg = segmented("part", spark, folder, W12)
    return interval_algebra.complement(sb.predicate_window(seg, ["part_key"], "price < 10000"), seg, ["part_key"], W12.low, W12.high)


_SETS_SQL = f"{sql.clipped('part', W12)}, a AS (SELECT part_key, bool_or(price < 10000) AS ever, bool_and(price < 10000) AS always FROM c GROUP BY part_key) SELECT 'ever' AS kind, part_key FROM a WHERE ever UNION ALL SELECT 'never', part_key FROM a WHERE NOT ever UNION ALL SELECT 'always', part_key FROM a WHERE always"


@query(_SETS_SQL)
def set_ops_keys(spark, folder):
    seg = segmented("part", spark, folder, W12)
    parts = [f(seg, ["part_key"], "price < 10000").withColumn("kind", F.lit(n)) for n, f in (("ever", gate.keys_ever), ("never", gate.keys_never), ("always", gate.keys_always))]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


@query("SELECT l.l_orderkey, l.l_linenumber, l.l_shipdate, o.o_totalprice, l.l_extendedprice FROM lineitem l ASOF LEFT JOIN (SELECT o_orderkey AS k, o_orderdate, max(o_totalprice) AS o_totalprice FROM orders GROUP BY ALL) o ON l.l_orderkey = o.k AND l.l_shipdate >= o.o_orderdate")
def asof_order_at_shipping(spark, folder):
    """Each line with its order as it was at shipping."""
    lines = load(spark, folder, "lineitem", ["l_orderkey", "l_linenumber", "l_shipdate", "l_extendedprice"])
    orders = load(spark, folder, "orders").groupBy("o_orderkey", "o_orderdate").agg(F.max("o_totalprice").alias("o_totalprice")).withColumnRenamed("o_orderkey", "l_orderkey")
    return joins.asof_join(lines, orders, ["l_orderkey"], "l_shipdate", "o_orderdate", ["o_totalprice"])


@query(f"WITH {sql.history('supp').replace('b AS', 'b1 AS').replace('FROM b WHERE', 'FROM b1 WHERE').replace('h AS (', 'h1 AS (')}, {sql.history('cust')} SELECT CAST(count(*) AS BIGINT) AS pairs, CAST(sum(date_diff('microsecond', greatest(a.valid_from, b.valid_from), least(a.valid_to, b.valid_to))) AS BIGINT) AS overlap_us FROM h1 a JOIN h b ON a.supp_key = b.cust_key AND a.valid_from < b.valid_to AND b.valid_from < a.valid_to")
def overlap_join_pairs(spark, folder):
    """Rows of two histories that overlap on one key, each pair once."""
    a = HISTORIES["supp"].build(spark, folder).select(F.col("supp_key").alias("k"), FROM, TO)
    b = CUST.build(spark, folder).select(F.col("cust_key").alias("k"), FROM, TO)
    pairs = joins.overlap_join(a, b, ly.ChunkGrid.calendar("YEAR").of, ["k"])
    return pairs.agg(F.count(F.lit(1)).alias("pairs"), F.sum(length(F.col(FROM), F.col(TO))).alias("overlap_us"))


@query("SELECT CAST(count(*) AS BIGINT) AS pairs FROM orders a JOIN orders b ON a.o_custkey = b.o_custkey AND abs(datediff('day', a.o_orderdate, b.o_orderdate)) <= 10")
def range_join_orders(spark, folder):
    o = load(spark, folder, "orders", ["o_custkey", "o_orderdate"])
    day = F.unix_date(F.col("o_orderdate").cast("date"))
    return joins.range_join(o, o, day, day, 10, ["o_custkey"]).agg(F.count(F.lit(1)).alias("pairs"))


@query(f"WITH {sql.history('user')} SELECT e.event_id, h.event_type AS state FROM events e JOIN h ON e.user_id = h.user_id AND h.valid_from <= e.ts AND e.ts < h.valid_to")
def point_lookup(spark, folder):
    """Each event with the state that it begins."""
    points = load(spark, folder, "events", ["event_id", "user_id", "ts"])
    states = USER.build(spark, folder).select("user_id", F.col("event_type").alias("state"), FROM, TO)
    return joins.point_in_interval(points, states, "ts", ly.ChunkGrid.calendar("DAY").of, ["user_id"]).select("event_id", "state")


# Around the operators.


@query("SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events WHERE CAST(json_extract(props, '$.k') AS BIGINT) % 2 = 0")
def json_filter_events(spark, folder):
    return props(load(spark, folder, "events")).where("props.k % 2 = 0").select("event_id", "props.k")


@query("SELECT event_type, time_bucket(INTERVAL 1 HOUR, ts) AS w_from, time_bucket(INTERVAL 1 HOUR, ts) + INTERVAL 1 HOUR AS w_to, CAST(count(*) AS BIGINT) AS n FROM events GROUP BY ALL")
def tumbling_hours(spark, folder):
    return tumbling_counts(load(spark, folder, "events"), "ts", "1 hour", ["event_type"])


@query("WITH s AS (SELECT time_bucket(INTERVAL 30 MINUTE, ts) AS b FROM events), w AS (SELECT unnest([b, b - INTERVAL 30 MINUTE]) AS w_from FROM s) SELECT w_from, w_from + INTERVAL 1 HOUR AS w_to, CAST(count(*) AS BIGINT) AS n FROM w GROUP BY ALL")
def sliding_hours(spark, folder):
    return sliding_counts(load(spark, folder, "events"), "ts", "1 hour", "30 minutes")


@query("WITH s AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS z FROM events), i AS (SELECT *, sum(z) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM s) SELECT user_id, min(ts) AS w_from, max(ts) + INTERVAL 6 HOUR AS w_to, CAST(count(*) AS BIGINT) AS n FROM i GROUP BY user_id, k")
def sessions(spark, folder):
    return session_counts(load(spark, folder, "events"), "ts", "6 hours", ["user_id"])


@query("SELECT user_id, CAST(sum(CASE WHEN event_type = 'click' THEN 1 ELSE 0 END) AS BIGINT) AS click, CAST(sum(CASE WHEN event_type = 'view' THEN 1 ELSE 0 END) AS BIGINT) AS view FROM events GROUP BY user_id")
def pivot_events(spark, folder):
    counts = load(spark, folder, "events", ["user_id", "event_type"]).groupBy("user_id").pivot("event_type", ["click", "view"]).count()
    return counts.select("user_id", *(F.coalesce(c, F.lit(0)).alias(c) for c in ("click", "view")))


@query(f"{sql.clipped('supp', W12, ['region'])} SELECT region, CAST(count(DISTINCT supp_key) AS BIGINT) AS n_keys FROM c GROUP BY region")
def distinct_keys_by_region(spark, folder):
    return sb.distinct_keys(segmented("supp", spark, folder, W12, ("region",)), ["supp_key"], ["region"])


@query()
def temporal_index_counts(spark, folder):
    return paths.event_list_counts(USER.build(spark, folder), USER.windows["cut"], 3_600_000_000)



QUERIES |= studies.QUERIES
ORACLES |= studies.ORACLES
