"""Running a query: in one process, in one fused plan over the layout, or piece by piece with stored partials."""

from __future__ import annotations

from collections.abc import Mapping
from concurrent.futures import ThreadPoolExecutor

from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.instants import FROM, TO
from ..functions.predicates import Pred, predicate
from ..operators import cohort as co
from ..operators import same_base as sb
from ..operators.canonical import coalesce_intervals
from ..operators.gate import key_domain_gate
from ..sources.history import restrict_window
from ..sources.layout import Layout, read_layout
from ..spec import QueryWindow
from .query import FAMILIES, PiecePlan, Query, plan, validate


class IncompletePartials(RuntimeError):
    """The merge was asked for before every piece was committed."""


def _prepared(query: Query, rows: DataFrame) -> DataFrame:
    for table, on in query.dims:
        rows = rows.join(table, on, "left")
    if query.family in ("pairwise", "better", "ranked"):
        key = query.spec.keys[0]
        rows = query.cohort.restrict(rows, key) if query.cohort is not None else rows
    return rows


def _phi(query: Query):
    if query.other is None:
        return query.phi
    x, y = Pred(predicate(query.phi)), Pred(predicate(query.other))
    return {"and": x & y, "or": x | y, "minus": x - y}[query.op]


def evaluate(query: Query, seg: DataFrame, spans: Mapping[int, tuple[int, int]] | None = None) -> DataFrame:
    """The canonical result of segments.  ``spans``: what a layout knows of its chunks (see Layout.spans)."""
    keys, key = list(query.spec.keys), query.spec.keys[0]
    seg = _prepared(query, seg)
    match query.family:
        case "predicate" | "boolean":
            return sb.predicate_window(seg, keys, _phi(query), query.payload)
        case "gated":
            window = sb.predicate_window(seg, keys, _phi(query), query.payload)
            return key_domain_gate(window, sb.predicate_window(seg, keys, query.evidence, canon=False), keys)
        case "duration":
            rows = seg.where(predicate(query.phi)) if query.phi is not None else seg
            return sb.duration_aggregate(rows, query.x, query.group, query.digits, query.spec.integer)
        case "count" | "threshold":
            timeline = sb.count_timeline(seg, _phi(query) if query.phi is not None else None, query.group, query.encoding)
            return timeline if query.family == "count" else sb.threshold_windows(timeline, list(query.group), query.threshold)
        case "pairwise":
            return co.pairwise_compare(seg, key, query.left, query.right, query.x, query.cmp, query.emit)
        case "better":
            return co.count_better_than(seg, key, query.reference, query.x, query.cmp, query.shards)
        case "ranked":
            family = [query.cohort.family] if query.cohort.family else []
            return co.ranked_timeline(seg, key, query.x, query.k, query.descending, family, query.shards, query.strategy, query.identity, spans)
    raise AssertionError(query.family)


def run_mono(query: Query, history: DataFrame) -> DataFrame:
    """The reference: one stretch of time, no pieces."""
    validate(query)
    return evaluate(query, restrict_window(history, query.window))


def run_fanout(query: Query, layout: Layout, spark: SparkSession) -> DataFrame:
    """One lazy plan over the chunks that matter; the shuffle before the merge is the barrier."""
    validate(query)
    keys = list(query.cohort.keys) if query.cohort is not None and query.cohort.keys and query.cohort.table is None else None
    spans = layout.spans(spark, query.window) if query.family == "ranked" else None
    return evaluate(query, read_layout(spark, layout, query.window, keys=keys), spans)


# Stored partials.


def partial(query: Query, seg: DataFrame) -> DataFrame:
    """What a piece leaves for the merge."""
    keys, key = list(query.spec.keys), query.spec.keys[0]
    seg = _prepared(query, seg)
    match query.family:
        case "predicate" | "boolean":
            return sb.predicate_window(seg, keys, _phi(query), query.payload)
        case "gated":
            w = sb.predicate_window(seg, keys, _phi(query), query.payload).withColumn("role", F.lit("window"))
            e = seg.where(predicate(query.evidence)).select(*keys, *query.payload, FROM, TO).withColumn("role", F.lit("evidence"))
            return w.unionByName(e)
        case "duration":
            rows = seg.where(predicate(query.phi)) if query.phi is not None else seg
            return sb.duration_partials(rows, query.x, query.group, integer=query.spec.integer, window_start=query.window.low)
        case "count" | "threshold":
            return sb.count_deltas(seg, _phi(query) if query.phi is not None else None, query.group, query.encoding)
        case "better":
            # the key's type goes along, so that the merge states it
            return co.better_deltas(seg, key, query.reference, query.x, query.cmp).withColumn("reference_key", F.lit(query.reference).cast(seg.schema[key].dataType))
        case _:
            return evaluate(query, seg)


def merge(query: Query, partials: DataFrame) -> DataFrame:
    """The final result of all pieces' partials."""
    keys = list(query.spec.keys)
    match query.family:
        case "predicate" | "boolean":
            return coalesce_intervals(partials, keys, query.payload)
        case "gated":
            window = coalesce_intervals(partials.where("role = 'window'"), keys, query.payload)
            return key_domain_gate(window, partials.where("role = 'evidence'"), keys)
        case "duration":
            return sb.finalize_durations(sb.merge_durations(partials, list(query.group)), list(query.group), query.digits)
        case "count" | "threshold":
            timeline = sb.merge_counts(partials, list(query.group))
            return timeline if query.family == "count" else sb.threshold_windows(timeline, list(query.group), query.threshold)
        case "pairwise":
            return coalesce_intervals(partials, ["left_key", "right_key"], ["holds"] if query.emit == "both" else [])
        case "better":
            return co.merge_better(partials, query.reference, partials.schema["reference_key"].dataType)
        case "ranked":
            family = [query.cohort.family] if query.cohort.family else []
            on = ["key", "x"] if query.identity == "entity" else ["x"]
            return coalesce_intervals(partials, [*family, "rank"], on).select(*family, FROM, TO, "rank", *on)
    raise AssertionError(query.family)


def run_piece(query: Query, layout: Layout, spark: SparkSession, run_dir: str, piece: tuple[int, int, int, int], attempt: int, span: QueryWindow | None = None, check: bool = False) -> None:
    """Compute one piece (of ``span`` alone, if given), store its partial under its attempt, then commit it.  ``check``: a cohort's
    piece must hold every row of the cohort that its chunk has."""
    n, chunk, low, high = piece
    seg = read_layout(spark, layout, span or query.window, (low, high)).where(F.col("chunk") == chunk)
    if check and query.cohort is not None:
        co.assert_cohort_closed(_prepared(query, seg), _prepared(query, read_layout(spark, layout, query.window).where(F.col("chunk") == chunk)), query.spec.keys[0])
    path = f"{run_dir}/partials/piece={n}/attempt={attempt}"
    partial(query, seg).write.mode("overwrite").parquet(path)
    rows = spark.read.parquet(path).count()
    # a folder of its own: pieces that commit at once must not share one
    spark.createDataFrame([(rows,)], "rows long").coalesce(1).write.mode("overwrite").parquet(f"{run_dir}/commits/piece={n}/attempt={attempt}")


def committed(spark: SparkSession, run_dir: str) -> DataFrame:
    """One attempt for each piece, however often it was run."""
    try:
        log = spark.read.schema("piece int, attempt int, rows long").parquet(f"{run_dir}/commits")
    except AnalysisException as e:
        if e.getCondition() != "PATH_NOT_FOUND":
            raise
        return spark.createDataFrame([], "piece int, attempt int, rows long")
    return log.groupBy("piece").agg(F.min_by("attempt", "attempt").alias("attempt"), F.min_by("rows", "attempt").alias("rows"))


def missing_pieces(spark: SparkSession, p: PiecePlan, run_dir: str) -> list[tuple[int, int, int, int]]:
    done = {r.piece for r in committed(spark, run_dir).collect()}  # pieces of a plan
    return [x for x in p.pieces if x[0] not in done]


def merge_durable(query: Query, p: PiecePlan, spark: SparkSession, run_dir: str) -> DataFrame:
    """The merge over committed attempts; raises if a piece is missing."""
    if lost := missing_pieces(spark, p, run_dir):
        raise IncompletePartials(f"{len(lost)} pieces are not committed")
    winners = committed(spark, run_dir).select("piece", "attempt")
    stored = spark.read.option("mergeSchema", "true").parquet(f"{run_dir}/partials")
    return merge(query, stored.join(F.broadcast(winners), ["piece", "attempt"]).drop("piece", "attempt"))


def run_fanout_durable(query: Query, layout: Layout, spark: SparkSession, run_dir: str, shards: DataFrame | None = None, attempt: int = 0, at_once: int = 16, check: bool = False) -> DataFrame:
    """Run what is missing, ``at_once`` pieces side by side, then merge; a second call after a crash runs only the rest."""
    p = plan(query, layout, spark, shards)
    with ThreadPoolExecutor(at_once) as pool:  # each submits its piece's jobs; the scheduler shares the cluster among them
        list(pool.map(lambda piece: run_piece(query, layout, spark, run_dir, piece, attempt, p.spans.get(piece[0]), check), missing_pieces(spark, p, run_dir)))
    return merge_durable(query, p, spark, run_dir)


__all__ = ["FAMILIES", "IncompletePartials", "committed", "evaluate", "merge", "merge_durable", "missing_pieces", "partial", "run_fanout", "run_fanout_durable", "run_mono", "run_piece"]
