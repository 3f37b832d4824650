"""Other ways to the same answers: SQL on the unclipped source or the layout, the engine on the unclipped source, always-on
engines, and plans that move rows at query time."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.instants import FROM, TO, length
from ..operators.canonical import coalesce_intervals
from ..operators.cohort import ranked_timeline
from ..plans.query import Query
from ..plans.runner import evaluate
from ..sources.layout import ChunkGrid, Layout, read_scd2_for_chunk
from ..spec import QueryWindow


def _clip(view: str, window: QueryWindow) -> str:
    low, high = f"TIMESTAMP_NTZ '{window.start}'", f"TIMESTAMP_NTZ '{window.end}'"
    return f"SELECT * EXCEPT (valid_from, valid_to), greatest(valid_from, {low}) AS valid_from, least(coalesce(valid_to, {high}), {high}) AS valid_to FROM {view} WHERE valid_from < {high} AND coalesce(valid_to, {high}) > {low}"


def sql_windows(spark: SparkSession, view: str, window: QueryWindow, keys: Sequence[str], phi: str, payload: Sequence[str] = ()) -> DataFrame:
    """Hand-written SQL with its own overlap test and clipping.  Over a clipped layout's view it reads every chunk."""
    names, k = ", ".join([*keys, *payload]), ", ".join(keys)
    same = "".join(f" AND lag({c}) OVER w <=> {c}" for c in payload)
    return spark.sql(
        f"WITH c AS ({_clip(view, window)}), f AS (SELECT {names}, valid_from, valid_to, CASE WHEN lag(valid_to) OVER w = valid_from{same} THEN 0 ELSE 1 END AS n FROM c WHERE coalesce({phi}, false) WINDOW w AS (PARTITION BY {k} ORDER BY valid_from)), "
        f"i AS (SELECT *, sum(n) OVER (PARTITION BY {k} ORDER BY valid_from ROWS UNBOUNDED PRECEDING) AS island FROM f) SELECT {names}, min(valid_from) AS valid_from, max(valid_to) AS valid_to FROM i GROUP BY {names}, island"
    )


def sql_average(spark: SparkSession, view: str, window: QueryWindow, x: str, group: str) -> DataFrame:
    d = "CAST(timestampdiff(MICROSECOND, valid_from, valid_to) AS DECIMAL(20,0))"
    return spark.sql(
        f"WITH c AS ({_clip(view, window)}), s AS (SELECT {group}, CAST(sum({x} * {d}) AS DECIMAL(38,2)) AS weighted_sum, CAST(sum({d}) AS BIGINT) AS duration_us, min({x}) AS x_min, max({x}) AS x_max FROM c WHERE {x} IS NOT NULL GROUP BY {group}) "
        f"SELECT *, round(CAST(weighted_sum AS DOUBLE) / duration_us, 6) AS twa FROM s"
    )


def sql_threshold(spark: SparkSession, view: str, window: QueryWindow, phi: str, group: str, c: int) -> DataFrame:
    return spark.sql(
        f"WITH c AS ({_clip(view, window)}), e AS (SELECT {group}, valid_from AS ins, 1 AS d FROM c WHERE coalesce({phi}, false) UNION ALL SELECT {group}, valid_to, -1 FROM c WHERE coalesce({phi}, false)), "
        f"s AS (SELECT {group}, ins, sum(d) AS d FROM e GROUP BY {group}, ins), r AS (SELECT {group}, ins AS valid_from, lead(ins) OVER w AS valid_to, sum(d) OVER w AS n FROM s WINDOW w AS (PARTITION BY {group} ORDER BY ins)), "
        f"f AS (SELECT *, CASE WHEN lag(valid_to) OVER (PARTITION BY {group} ORDER BY valid_from) = valid_from THEN 0 ELSE 1 END AS z FROM r WHERE n > {c}), i AS (SELECT *, sum(z) OVER (PARTITION BY {group} ORDER BY valid_from ROWS UNBOUNDED PRECEDING) AS island FROM f) "
        f"SELECT {group}, min(valid_from) AS valid_from, max(valid_to) AS valid_to FROM i GROUP BY {group}, island"
    )


_ISLANDS = "SELECT {ids}, min(valid_from) AS valid_from, max(valid_to) AS valid_to FROM (SELECT *, sum(z) OVER (PARTITION BY {by} ORDER BY valid_from ROWS UNBOUNDED PRECEDING) AS island FROM (SELECT *, CASE WHEN lag(valid_to) OVER w = valid_from{same} THEN 0 ELSE 1 END AS z FROM {of} WINDOW w AS (PARTITION BY {by} ORDER BY valid_from))) GROUP BY {ids}, island"


def sql_pairwise(spark: SparkSession, view: str, window: QueryWindow, key: str, x: str, left, right) -> DataFrame:
    islands = _ISLANDS.format(ids="left_key, right_key", by="left_key, right_key", same="", of="p")
    return spark.sql(
        f"WITH c AS ({_clip(view, window)}), p AS (SELECT a.{key} AS left_key, b.{key} AS right_key, greatest(a.valid_from, b.valid_from) AS valid_from, least(a.valid_to, b.valid_to) AS valid_to "
        f"FROM c a JOIN c b ON a.valid_from < b.valid_to AND b.valid_from < a.valid_to WHERE a.{key} = {left!r} AND b.{key} = {right!r} AND a.{x} < b.{x}) {islands}"
    )


def _cuts(view: str, window: QueryWindow, where: str) -> str:
    return (
        f"WITH m AS (SELECT * FROM ({_clip(view, window)}) WHERE {where}), q AS (SELECT valid_from AS tick FROM m UNION SELECT valid_to FROM m), "
        f"g AS (SELECT tick AS valid_from, lead(tick) OVER (ORDER BY tick) AS valid_to FROM q)"
    )


def sql_better(spark: SparkSession, view: str, window: QueryWindow, key: str, x: str, where: str, reference) -> DataFrame:
    islands = _ISLANDS.format(ids="reference_key, better", by="reference_key", same=" AND lag(better) OVER w = better", of="n")
    return spark.sql(
        f"{_cuts(view, window, where)}, r AS (SELECT g.*, a.{key} AS reference_key, a.{x} AS rx FROM g JOIN m a ON a.valid_from <= g.valid_from AND g.valid_from < a.valid_to WHERE a.{key} = {reference!r} AND g.valid_to IS NOT NULL), "
        f"n AS (SELECT r.reference_key, r.valid_from, r.valid_to, count(o.{key}) AS better FROM r LEFT JOIN m o ON o.{key} <> r.reference_key AND o.valid_from <= r.valid_from AND r.valid_from < o.valid_to AND o.{x} < r.rx GROUP BY ALL) {islands}"
    ).select("reference_key", FROM, TO, "better")


def sql_ranked(spark: SparkSession, view: str, window: QueryWindow, key: str, x: str, where: str, k: int) -> DataFrame:
    islands = _ISLANDS.format(ids="rank, key, x", by="rank", same=" AND lag(key) OVER w = key AND lag(x) OVER w = x", of="z")
    return spark.sql(
        f"{_cuts(view, window, where)}, o AS (SELECT g.valid_from, g.valid_to, m.{key} AS key, m.{x} AS x, row_number() OVER (PARTITION BY g.valid_from ORDER BY m.{x}, m.{key}) AS rank FROM g JOIN m ON m.valid_from <= g.valid_from AND g.valid_from < m.valid_to WHERE g.valid_to IS NOT NULL), "
        f"z AS (SELECT * FROM o WHERE rank <= {k}) {islands}"
    ).select(FROM, TO, "rank", "key", "x")


def scd2_by_chunk(spark: SparkSession, path: str, window: QueryWindow, grid: ChunkGrid) -> DataFrame:
    """Segments from the unclipped source as chunk workers get them: each chunk reads every month up to it and keeps what overlaps."""
    first, last = grid.chunks_for(window)
    source = spark.read.parquet(path)
    out = None
    for c in range(first, last + 1):  # as many scans as the window has chunks, each over all earlier months
        low, high = (F.greatest(grid.start(F.lit(c)), window.low), F.least(grid.start(F.lit(c + 1)), window.high))
        rows = source.where((F.col("from_month") <= F.year(high) * 12 + F.month(high) - 1) & (F.col(FROM) < high) & (F.col(TO) > low))
        one = rows.withColumns({FROM: F.greatest(F.col(FROM), low), TO: F.least(F.col(TO), high)}).drop("from_month").withColumn("chunk", F.lit(c))
        out = one if out is None else out.unionByName(one)
    return out


def engine_on_scd2(spark: SparkSession, path: str, query: Query, grid: ChunkGrid) -> DataFrame:
    """The engine with the unclipped source: each chunk's input is every month up to it, tested for overlap, then cut."""
    from ..sources.layout import clip_to_chunks

    return evaluate(query, clip_to_chunks(read_scd2_for_chunk(spark, path, query.window), grid, query.spec.keys))


def layout_view(spark: SparkSession, layout: Layout, name: str) -> None:
    layout.scan(spark).drop("chunk", "bucket", "is_head").createOrReplaceTempView(name)


def native_sequences(history: DataFrame, keys: Sequence[str], x: str, window: QueryWindow) -> DataFrame:
    """An always-on store with temporal types: each key's whole sequence is one value, and its duration-weighted average within the
    window is computed inside it.  A key's sequence must fit a row."""
    instants = F.array_sort(F.collect_list(F.struct(F.col(FROM).alias("f"), F.col(TO).alias("t"), F.col(x).cast("decimal(18,2)").alias("x"))))
    values = history.groupBy(*keys).agg(instants.alias("seq"))
    cut = F.transform("seq", lambda s: F.struct(F.greatest(s["f"], window.low).alias("f"), F.least(s["t"], window.high).alias("t"), s["x"].alias("x")))
    cut = F.filter(cut, lambda s: (s["f"] < s["t"]) & s["x"].isNotNull())
    spans = F.transform(cut, lambda s: F.struct((s["x"] * length(s["f"], s["t"]).cast("decimal(20,0)")).cast("decimal(38,2)").alias("w"), length(s["f"], s["t"]).alias("d")))
    sums = values.select(*keys, spans.alias("s")).where(F.size("s") > 0)
    w = F.aggregate("s", F.lit(0).cast("decimal(38,2)"), lambda a, s: (a + s["w"]).cast("decimal(38,2)"))
    d = F.aggregate("s", F.lit(0).cast("long"), lambda a, s: a + s["d"])
    return sums.select(*keys, w.alias("weighted_sum"), d.alias("duration_us")).withColumn("twa", F.round(F.col("weighted_sum").cast("double") / F.col("duration_us"), 6))


def coupled_rank(history: DataFrame, key: str, x: str, k: int, window: QueryWindow, bucket: ChunkGrid) -> DataFrame:
    """No layout: rows are dealt to time buckets at query time, a copy for each they touch, and each bucket ranks what it got."""
    from ..sources.layout import segments

    return ranked_timeline(segments(history, bucket, [key], window), key, x, k)


def coupled_input(history: DataFrame, window: QueryWindow, bucket: ChunkGrid) -> DataFrame:
    """(source_rows, reducer_rows): how the coupled plan's copies inflate what crosses to the reducers."""
    from ..sources.history import restrict_window

    rows = restrict_window(history, window)
    return rows.agg(F.count(F.lit(1)).alias("source_rows"), F.sum((bucket.last(F.col(TO)) - bucket.of(F.col(FROM)) + 1).cast("long")).alias("reducer_rows"))


def exchanged_rank(history: DataFrame, key: str, x: str, k: int, window: QueryWindow, grid: ChunkGrid) -> DataFrame:
    """Coupled through the engine's own exchange: cuts of all time are joined to rows by range within a grid's cells, then ranked."""
    from ..operators.joins import point_in_interval
    from ..sources.history import restrict_window

    rows = restrict_window(history, window).where(F.col(x).isNotNull()).select(F.col(key).alias("key"), F.col(x).alias("x"), FROM, TO)
    cuts = rows.select(F.explode(F.array(FROM, TO)).alias("cut")).distinct()
    cell = grid.of(F.col("cut"))
    ends = cuts.withColumn("cell", cell)
    nxt = F.lead("cut").over(Window.partitionBy("cell").orderBy("cut"))
    firsts = ends.groupBy("cell").agg(F.min("cut").alias("first"))
    after = firsts.select((F.lead("first").over(Window.orderBy("cell"))).alias("after"), "cell")  # one row per cell
    cuts = ends.withColumn("nxt", nxt).join(after, "cell", "left").select("cut", F.coalesce("nxt", "after").alias("end")).where("end IS NOT NULL")
    at = point_in_interval(cuts, rows, "cut", grid.of)
    best = Window.partitionBy("cut").orderBy("x", "key")
    ranked = at.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).select("rank", "key", "x", F.col("cut").alias(FROM), F.col("end").alias(TO))
    return coalesce_intervals(ranked, ["rank"], ["key", "x"]).select(FROM, TO, "rank", "key", "x")


def event_list_counts(history: DataFrame, window: QueryWindow, width_us: int) -> DataFrame:
    """A temporal index kept in memory: prefix counts at the grid's instants.  Answers counts at those instants alone."""
    from ..functions.instants import from_micros, micros
    from ..sources.history import restrict_window

    rows = restrict_window(history, window)
    cells = rows.select(F.explode(F.array(F.struct(F.ceil(micros(F.col(FROM)) / width_us).cast("long").alias("c"), F.lit(1).alias("d")), F.struct(F.ceil(micros(F.col(TO)) / width_us).cast("long").alias("c"), F.lit(-1).alias("d")))).alias("e"))
    sums = cells.groupBy("e.c").agg(F.sum("e.d").alias("d"))
    run = F.sum("d").over(Window.orderBy("c").rowsBetween(Window.unboundedPreceding, 0))  # one row per grid instant of the window
    return sums.select(from_micros(F.col("c") * width_us).alias("ins"), run.cast("long").alias("active"))
