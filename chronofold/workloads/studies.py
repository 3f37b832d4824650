"""Measures of the method on the given tables: what is read, exchanged and left apart, and which programs are right."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..baselines import mq5_faults, paths
from ..functions.instants import FROM, TO, length, micros
from ..operators.canonical import keys_correct
from ..plans.query import Query
from ..plans.runner import evaluate
from ..sources import layout as ly
from ..sources.files import load
from ..sources.folders import scratch
from ..sources.history import restrict_window
from . import oracles as sql
from .histories import HISTORIES
from .stored import stored
from .suite import SUITE, nth_key, segmented, smallest

Run = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Run] = {}
ORACLES: dict[str, str] = {}
PART, CUST = HISTORIES["part"], HISTORIES["cust"]
W12, CUT = PART.windows["w12"], PART.windows["cut"]
FACTORS = {"quarter": 0.25, "half": 0.5, "one": 1, "double": 2, "fourfold": 4}
_LAST = "valid_to - INTERVAL 1 MICROSECOND"


def query(oracle: str | None = None, name: str | None = None):
    def add(run: Run) -> Run:
        QUERIES[name or run.__name__] = run
        if oracle is not None:
            ORACLES[name or run.__name__] = oracle
        return run

    return add


# Raw rows and canonical rows by chunk factor.


def _chunk_of(factor: float, at: str) -> str:
    if float(factor).is_integer():
        return f"CAST(floor((year({at}) * 12 + month({at}) - 1) / {factor}.0) AS BIGINT)"
    return f"CAST(floor(epoch_us({at}) / {int(30 * 86_400_000_000 * factor)}.0) AS BIGINT)"


def _fragments(name: str, phi: str, payload: list[str]) -> None:
    raw = " UNION ALL ".join(f"SELECT '{n}' AS factor, CAST(sum({_chunk_of(f, _LAST)} - {_chunk_of(f, 'valid_from')} + 1) AS BIGINT) AS raw_rows FROM c WHERE coalesce({phi}, false)" for n, f in FACTORS.items())
    text = f"{sql.clipped('part', CUT)}, r AS ({raw}), i AS (SELECT CAST(count(*) AS BIGINT) AS canonical_rows FROM ({sql.islands('c', ['part_key'], payload, f'coalesce({phi}, false)')})) SELECT factor, raw_rows, canonical_rows FROM r, i"

    @query(text, f"fragments_{name}")
    def run(spark, folder):
        """What pieces give before and after joining: the first follows the chunks, the second doesn't."""
        out = None
        for n, f in FACTORS.items():
            seg = segmented("part", spark, folder, CUT, (), PART.grid.scale(f))
            asked = Query("predicate", PART.spec, CUT, phi=phi, payload=tuple(payload))
            raw = seg.where(phi).agg(F.count(F.lit(1)).alias("raw_rows"))
            one = raw.crossJoin(evaluate(asked, seg).agg(F.count(F.lit(1)).alias("canonical_rows"))).select(F.lit(n).alias("factor"), "raw_rows", "canonical_rows")  # one row by one row
            out = one if out is None else out.unionByName(one)
        return out


_CHEAP, _STABLE = SUITE["part"]["cheap"], SUITE["part"]["stable"]
_fragments("q1", _CHEAP, ["price"])
_fragments("q3", f"({_CHEAP}) AND ({_STABLE})", [])
_fragments("q4", f"({_CHEAP}) OR ({_STABLE})", [])
_fragments("q5", f"({_CHEAP}) AND NOT ({_STABLE})", [])


# Input of one month, moved later.


@query(
    f"WITH {sql.history('part')}, m AS (SELECT unnest(generate_series(TIMESTAMP '{W12.start}', TIMESTAMP '{W12.end}' - INTERVAL 1 MONTH, INTERVAL 1 MONTH)) AS m) "
    "SELECT CAST(year(m) * 12 + month(m) - 1 AS INT) AS month, CAST(count(*) FILTER (h.valid_from < m + INTERVAL 1 MONTH) AS BIGINT) AS unclipped_rows, "
    "CAST(count(*) FILTER (h.valid_from < m + INTERVAL 1 MONTH AND h.valid_to > m) AS BIGINT) AS clipped_rows FROM m, h GROUP BY m"
)
def preparation_sweep(spark, folder):
    """Rows that a piece of one month reads, by the month: of the unclipped source every earlier month's, of the layout its own."""
    source = scratch(spark)
    ly.write_scd2(PART.build(spark, folder), source)
    first, last = PART.grid.chunks_for(W12)
    months = spark.range(first, last + 1).select(F.col("id").cast("int").alias("month"))
    started = spark.read.parquet(source).groupBy("from_month").agg(F.count(F.lit(1)).alias("n"))
    before = months.join(started, F.col("from_month") <= F.col("month")).groupBy("month").agg(F.sum("n").alias("unclipped_rows"))  # months by months
    own = stored(spark, folder, "part").scan(spark).groupBy(F.col("chunk").cast("int").alias("month")).agg(F.count(F.lit(1)).alias("clipped_rows"))
    return before.join(own, "month", "left").select("month", "unclipped_rows", F.coalesce("clipped_rows", F.lit(0)).alias("clipped_rows"))


_WEEK = 604_800_000_000


@query(f"{sql.clipped('part', W12)} SELECT CAST(count(*) AS BIGINT) AS source_rows, CAST(sum(CAST(floor(epoch_us({_LAST}) / {_WEEK}.0) AS BIGINT) - CAST(floor(epoch_us(valid_from) / {_WEEK}.0) AS BIGINT) + 1) AS BIGINT) AS reducer_rows FROM c")
def coupled_inflation(spark, folder):
    """How copies inflate what a coupled plan sends to its reducers."""
    return paths.coupled_input(PART.build(spark, folder), W12, ly.ChunkGrid.calendar("WEEK"))


@query()
def programs_keys_correct(spark, folder):
    """Keys whose intervals are right, for the engine and three programs that are wrong on purpose, against the interval algebra."""
    from ..operators import gate, interval_algebra
    from ..operators.same_base import predicate_window

    keys, brand, over = ["cust_key"], "prio = '1-URGENT'", "price > 450000"
    w = CUST.windows["w12"]
    seg = segmented("cust", spark, folder, w).cache()
    history = CUST.build(spark, folder)
    evidence = predicate_window(seg, keys, over, canon=False)
    right = gate.key_domain_gate(interval_algebra.subtract(predicate_window(seg, keys, brand), predicate_window(seg, keys, over), keys), evidence, keys)
    programs = {
        "engine": evaluate(Query("boolean", CUST.spec, w, phi=brand, other=over, op="minus").then_gate(over), seg),
        "common part taken away": mq5_faults.intersection_fault(seg, keys, brand, over),
        "whole lives": mq5_faults.unclipped_fault(history, seg, keys, brand, over),
        "gaps bridged": mq5_faults.bridged_fault(seg, keys, brand, over),
    }
    found = [(n, *keys_correct(p.select(*keys, FROM, TO), right.select(*keys, FROM, TO), keys)) for n, p in programs.items()]
    seg.unpersist()
    return spark.createDataFrame(found, "program string, correct long, keys long")


# The suite as SQL over the unclipped source and over the layout.


def _view(spark: SparkSession, folder: str, clipped: bool, dims: tuple) -> str:
    rows = stored(spark, folder, "part").scan(spark).drop("chunk", "bucket", "is_head") if clipped else PART.build(spark, folder)
    for x in dims:
        rows = rows.join(PART.dim(spark, folder, x), PART.dims[x][0], "left")
    name = "clipped_part" if clipped else "unclipped_part"
    rows.createOrReplaceTempView(name)
    return name


def views(spark: SparkSession, folder: str, source: str, layout: ly.Layout) -> dict[str, str]:
    """Names of views over the stored unclipped source and the layout, with brands."""
    brand = PART.dim(spark, folder, "brand")
    for tag, rows in (("unclipped", spark.read.parquet(source).drop("from_month")), ("clipped", layout.scan(spark).drop("chunk", "bucket", "is_head"))):
        rows.join(brand, "part_key", "left").createOrReplaceTempView(f"{tag}_source")
    return {"unclipped": "unclipped_source", "clipped": "clipped_source"}


def sql_runs(spark: SparkSession, folder: str, w) -> dict[int, Callable[[str], DataFrame]]:
    """The ten queries as SQL on a view with brands."""
    s = SUITE["part"]
    where, c = s["cohort"][1], s["c"]
    a, b = smallest("part", spark, folder, 2)
    phis = {1: _CHEAP, 3: f"({_CHEAP}) AND ({_STABLE})", 4: f"({_CHEAP}) OR ({_STABLE})", 5: f"({_CHEAP}) AND NOT coalesce({_STABLE}, false)"}
    runs = {i: lambda v, phi=phi, i=i: paths.sql_windows(spark, v, w, ["part_key"], phi, ["price"] if i == 1 else []) for i, phi in phis.items()}
    runs |= {2: lambda v: paths.sql_average(spark, v, w, "price", "brand"), 6: lambda v: paths.sql_threshold(spark, v, w, _CHEAP, "brand", c)}
    runs |= {7: lambda v: paths.sql_pairwise(spark, v, w, "part_key", "price", a, b), 8: lambda v: paths.sql_better(spark, v, w, "part_key", "price", where, a)}
    return runs | {i: lambda v, k=k: paths.sql_ranked(spark, v, w, "part_key", "price", where, k) for i, k in ((9, 1), (10, 3))}


def _sql_suite(tag: str, clipped: bool) -> None:
    w, s = W12, SUITE["part"]
    key, x, where, c = "part_key", "price", s["cohort"][1], s["c"]
    both = {3: f"({_CHEAP}) AND ({_STABLE})", 4: f"({_CHEAP}) OR ({_STABLE})", 5: f"({_CHEAP}) AND NOT coalesce({_STABLE}, false)"}

    def at(dims: tuple, make) -> Run:
        return lambda spark, folder: make(spark, folder, _view(spark, folder, clipped, dims))

    runs = {1: (at((), lambda sp, f, v: paths.sql_windows(sp, v, w, [key], _CHEAP, [x])), sql.predicate("part", w, _CHEAP, [x]))}
    for i, phi in both.items():
        runs[i] = (at((), lambda sp, f, v, phi=phi: paths.sql_windows(sp, v, w, [key], phi)), sql.predicate("part", w, phi))
    runs[2] = (at(("brand",), lambda sp, f, v: paths.sql_average(sp, v, w, x, "brand")), sql.duration("part", w, x, ["brand"], ["brand"]))
    runs[6] = (at(("brand",), lambda sp, f, v: paths.sql_threshold(sp, v, w, _CHEAP, "brand", c)), sql.count("part", w, _CHEAP, ["brand"], ["brand"], c))
    runs[7] = (at(("brand",), lambda sp, f, v: paths.sql_pairwise(sp, v, w, key, x, *smallest("part", sp, f, 2))), sql.pairwise("part", w, nth_key("part", 0), nth_key("part", 1), x, "<", ["brand"]))
    runs[8] = (at(("brand",), lambda sp, f, v: paths.sql_better(sp, v, w, key, x, where, smallest("part", sp, f, 1)[0])), sql.better("part", w, where, nth_key("part", 0), x, "<", ["brand"]))
    for i, k in ((9, 1), (10, 3)):
        runs[i] = (at(("brand",), lambda sp, f, v, k=k: paths.sql_ranked(sp, v, w, key, x, where, k)), sql.ranked("part", w, where, x, k, ["brand"]))
    for i, (run, text) in runs.items():
        query(text, f"sql_{tag}_q{i}")(run)


_sql_suite("scd2", False)
_sql_suite("clipped", True)


@query(sql.count("part", W12, _CHEAP, ["brand"], ["brand"], 8))
def engine_scd2_by_chunk_q6(spark, folder):
    """The engine on the unclipped source chunk by chunk: each month's piece reads its own and every earlier month's rows."""
    source = scratch(spark)
    ly.write_scd2(PART.build(spark, folder), source)
    asked = Query("count", PART.spec, W12, phi=_CHEAP, group=("brand",)).with_dims(PART.dim(spark, folder, "brand"), "part_key").then_threshold(8)
    return evaluate(asked, paths.scd2_by_chunk(spark, source, W12, PART.grid))


# Operators around the method.


@query(f"{sql.clipped('part', W12, ['brand'])}, m AS (SELECT * FROM c WHERE brand = 'Brand#7'), q AS (SELECT valid_from AS tick FROM m UNION SELECT valid_to FROM m), g AS (SELECT tick AS valid_from, lead(tick) OVER (ORDER BY tick) AS valid_to FROM q), o AS (SELECT g.valid_from, g.valid_to, m.part_key, row_number() OVER (PARTITION BY g.valid_from ORDER BY m.price, m.part_key) AS rank FROM g JOIN m ON m.valid_from <= g.valid_from AND g.valid_from < m.valid_to WHERE g.valid_to IS NOT NULL) SELECT valid_from, valid_to, string_agg(CAST(part_key AS VARCHAR), ',' ORDER BY rank) AS ranked FROM o WHERE rank <= 3 GROUP BY valid_from, valid_to")
def ranked_lists(spark, folder):
    """The best three of every segment as one row."""
    from ..operators.cohort import ranked_lists as lists

    whole = restrict_window(PART.build(spark, folder), W12).join(PART.dim(spark, folder, "brand"), "part_key").where("brand = 'Brand#7'")
    return lists(whole, "part_key", "price", 3).select(FROM, TO, F.array_join(F.transform("members", lambda m: m["key"].cast("string")), ",").alias("ranked"))


_DAYS = "CAST(date_diff('microsecond', valid_from, valid_to) AS BIGINT) / 86400000000.0"


@query(f"WITH {sql.history('part')}, z AS (SELECT CASE WHEN {_DAYS} < 0 THEN 0 WHEN {_DAYS} >= 400 THEN 9 ELSE CAST(floor({_DAYS} / 50) AS BIGINT) + 1 END AS bucket FROM h) SELECT bucket, CAST(count(*) AS BIGINT) AS n FROM z GROUP BY bucket")
def lifetime_histogram(spark, folder):
    """Lives in eight classes of fifty days, and those beyond."""
    days = length(F.col(FROM), F.col(TO)) / 86_400_000_000.0
    return PART.build(spark, folder).select(F.width_bucket(days, F.lit(0.0), F.lit(400.0), F.lit(8)).alias("bucket")).groupBy("bucket").agg(F.count(F.lit(1)).alias("n"))


_RANKS = "rank() OVER w AS r, dense_rank() OVER w AS dr, round(percent_rank() OVER w, 9) AS pr, round(cume_dist() OVER w, 9) AS cd, CAST(ntile(4) OVER (PARTITION BY brand ORDER BY score, part_key) AS INT) AS quartile"


@query(f"{sql.clipped('part', W12, ['brand'])}, a AS (SELECT part_key, brand, score FROM c WHERE valid_from = TIMESTAMP '{W12.start}') SELECT part_key, brand, CAST(r AS INT) AS r, CAST(dr AS INT) AS dr, pr, cd, quartile FROM (SELECT *, {_RANKS} FROM a WINDOW w AS (PARTITION BY brand ORDER BY score))")
def rank_variants(spark, folder):
    """Ranks with ties, shares and quarters of the parts of each brand at one instant."""
    from pyspark.sql import Window

    at = segmented("part", spark, folder, W12, ("brand",)).where(F.col(FROM) == W12.low).select("part_key", "brand", "score")
    by = Window.partitionBy("brand").orderBy("score")
    quarter = F.ntile(4).over(Window.partitionBy("brand").orderBy("score", "part_key"))
    return at.select("part_key", "brand", F.rank().over(by).alias("r"), F.dense_rank().over(by).alias("dr"), F.round(F.percent_rank().over(by), 9).alias("pr"), F.round(F.cume_dist().over(by), 9).alias("cd"), quarter.alias("quartile"))


@query("SELECT event_id, CAST(count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 21600000000 PRECEDING AND CURRENT ROW) AS BIGINT) AS recent FROM events")
def changes_of_six_hours(spark, folder):
    """Changes of a user in the six hours up to each: a frame by time, not by rows."""
    from pyspark.sql import Window

    events = load(spark, folder, "events", ["event_id", "user_id", "ts"])
    by = Window.partitionBy("user_id").orderBy(micros(F.col("ts").cast("timestamp_ntz"))).rangeBetween(-21_600_000_000, 0)
    return events.select("event_id", F.count(F.lit(1)).over(by).alias("recent"))


@query("SELECT 'set' AS kind, k FROM (SELECT l_suppkey AS k FROM lineitem INTERSECT SELECT s_suppkey FROM supplier WHERE s_nationkey < 5) UNION ALL SELECT 'all', k FROM (SELECT l_suppkey AS k FROM lineitem INTERSECT ALL SELECT s_suppkey FROM supplier WHERE s_nationkey < 5)")
def keys_in_both(spark, folder):
    a = load(spark, folder, "lineitem", ["l_suppkey"]).toDF("k")
    b = load(spark, folder, "supplier").where("s_nationkey < 5").select(F.col("s_suppkey").alias("k"))
    return a.intersect(b).select(F.lit("set").alias("kind"), "k").unionByName(a.intersectAll(b).select(F.lit("all").alias("kind"), "k"))


_GATE = f"{sql.clipped('part', W12)} SELECT DISTINCT a.part_key FROM c a JOIN c b ON a.part_key = b.part_key WHERE a.price < 10000 AND b.price > 90000"
for _hint in ("shuffle_hash", "merge", "broadcast"):

    def _hinted(spark, folder, hint=_hint):
        """One gate by each way to join; the hint suits key sets of a middling, a large and a small proven size."""
        seg = segmented("part", spark, folder, W12)
        dear = seg.where("price > 90000").select("part_key").distinct()
        return seg.where("price < 10000").select("part_key").join(dear.hint(hint), "part_key").distinct()

    query(_GATE, f"gate_by_{_hint}")(_hinted)


@query(f"{sql.clipped('part', W12, ['brand'])}, w1 AS (SELECT brand, CAST(count(*) AS BIGINT) AS cheap FROM c WHERE price < 3000 GROUP BY brand), w2 AS (SELECT brand, CAST(count(*) AS BIGINT) AS dear FROM c WHERE price > 104000 GROUP BY brand) SELECT coalesce(w1.brand, w2.brand) AS brand, cheap, dear FROM w1 FULL JOIN w2 ON w1.brand = w2.brand")
def cheap_and_dear(spark, folder):
    """Both sides' groups, also those of one side alone."""
    seg = restrict_window(PART.build(spark, folder), W12).join(PART.dim(spark, folder, "brand"), "part_key", "left")
    a = seg.where("price < 3000").groupBy("brand").agg(F.count(F.lit(1)).alias("cheap"))
    b = seg.where("price > 104000").groupBy("brand").agg(F.count(F.lit(1)).alias("dear"))
    return a.join(b, "brand", "full")


@query("SELECT event_type, upper(substr(event_type, 1, 1)) || substr(event_type, 2) AS title, CAST(sum(len(event_type)) AS BIGINT) AS letters, CAST(count(*) FILTER (regexp_matches(event_type, '^[a-l]')) AS BIGINT) AS early, max(user_id) AS last_user FROM events GROUP BY event_type")
def text_and_map_functions(spark, folder):
    """String functions, and a map built and read back."""
    e = load(spark, folder, "events", ["event_type", "user_id"])
    m = e.select("event_type", F.create_map("event_type", "user_id").alias("m"))
    return m.groupBy("event_type").agg(F.initcap("event_type").alias("title"), F.sum(F.length("event_type")).alias("letters"), F.count(F.when(F.col("event_type").rlike("^[a-l]"), 1)).alias("early"), F.max(F.element_at("m", F.col("event_type"))).alias("last_user"))


@query(sql.predicate("part", W12, _CHEAP, ["price"]))
def layout_source_q1(spark, folder):
    """Q1 through the layout's own data source."""
    from ..sources.source import read

    layout = stored(spark, folder, "part")
    return evaluate(Query("predicate", PART.spec, W12, phi=_CHEAP, payload=("price",)), read(spark, layout, W12))
