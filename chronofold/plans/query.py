"""Logical queries: what is asked, whether it can be answered piecewise, and in which pieces."""

from __future__ import annotations

from collections.abc import Mapping, Sequence
from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame, SparkSession

from ..functions.predicates import Pred
from ..operators.partials import ALIGNED, DELTA, DURATION, STEP, WINDOW
from ..sources.layout import Layout
from ..spec import Cohort, HistorySpec, QueryWindow


@dataclass(frozen=True)
class Family:
    """What a plan fixes for a kind of query."""

    partial: str
    merge: str
    finalizer: str
    canon: str
    shards: str  # of keys, of candidates, or none


FAMILIES = {
    "predicate": Family(WINDOW, "interval union", "none", "keys, payload", "keys"),
    "boolean": Family(WINDOW, "interval union", "none", "keys, payload if kept", "keys"),
    "duration": Family(DURATION, "sums, least and greatest", "ratio", "group", "keys"),
    "count": Family(DELTA, "endpoint addition", "none", "group, count", "keys"),
    "threshold": Family(STEP, "endpoint addition, then threshold", "count > c", "group", "keys"),
    "pairwise": Family(ALIGNED, "interval union", "keep true", "pair, flag", "none"),
    "better": Family(ALIGNED, "endpoint addition over candidate shards", "where the reference is present", "reference, count", "candidates"),
    "ranked": Family(ALIGNED, "rank shards' best again", "rank <= k", "cohort, rank, member or value", "candidates"),
    "gated": Family(WINDOW, "interval union, twice", "semi-restriction to keys", "keys, payload", "keys"),
}

#: Kinds of analysis that don't close over a piece, and the code of their rejection.
OUTSIDE = {"temporal_join": "TEMPORAL_JOIN", "sequence": "SEQUENCE", "sliding": "SLIDING", "dynamic_cohort": "DYNAMIC_COHORT"}


class PlanRejected(ValueError):
    def __init__(self, code: str, why: str) -> None:
        super().__init__(f"{code}: {why}")
        self.code = code


@dataclass(frozen=True)
class Query:
    """A query over one history.  Build one by the class methods; ``then_*`` add what is computed once, at the end."""

    family: str
    spec: HistorySpec
    window: QueryWindow
    phi: Pred | Column | str | None = None
    other: Pred | Column | str | None = None
    op: str = "and"
    payload: tuple[str, ...] = ()
    x: str | Column | None = None
    group: Mapping[str, Column] | Sequence[str] = ()
    threshold: int | None = None
    evidence: Pred | Column | str | None = None
    cohort: Cohort | None = None
    left: object = None
    right: object = None
    reference: object = None
    cmp: str = "lt"
    emit: str = "true"
    k: int = 1
    descending: bool = False
    shards: int = 1
    strategy: str = "native"
    identity: str = "entity"
    encoding: str = "delta"
    digits: int | None = None
    barrier: bool = True
    dims: tuple = field(default=(), compare=False)

    def then_threshold(self, c: int) -> Query:
        if self.family not in ("count", "threshold"):
            raise PlanRejected("UNSUPPORTED", "a threshold follows a count timeline")
        return replace(self, family="threshold", threshold=c)

    def then_gate(self, evidence: Pred | Column | str) -> Query:
        if self.family not in ("predicate", "boolean"):
            raise PlanRejected("UNSUPPORTED", "a gate restricts a window result; to count over one, store the gated window first")
        return replace(self, family="gated", evidence=evidence)

    def with_dims(self, table: DataFrame, on: str) -> Query:
        """Attributes that don't vary in time, joined before any operator."""
        return replace(self, dims=(*self.dims, (table, on)))


def validate(query: Query) -> None:
    """Raises PlanRejected before any job runs."""
    if query.family in OUTSIDE:
        raise PlanRejected(OUTSIDE[query.family], "its result needs more than the pieces of one history")
    if query.family not in FAMILIES:
        raise PlanRejected("UNSUPPORTED", f"no operator {query.family}")
    if not query.spec.full_state:
        raise PlanRejected("NOT_FULL_STATE", "rows show changed columns only; rebuild them first")
    if not query.barrier:
        raise PlanRejected("NO_BARRIER", "a merge needs every piece")
    if query.cohort is not None and query.cohort.dynamic:
        raise PlanRejected("DYNAMIC_COHORT", "the cohort must be fixed before the query runs")
    if query.family in ("pairwise", "better", "ranked") and len(query.spec.keys) != 1:
        raise PlanRejected("UNSUPPORTED", "cohorts are of single-column keys")
    if query.family in ("pairwise", "better") and query.cohort is None:
        raise PlanRejected("NO_COHORT", "keys are compared within a cohort fixed before the query runs")
    if query.family in ("better", "ranked") and query.shards < 1:
        raise PlanRejected("NO_SHARD_PLACEMENT", "candidates need a fixed number of shards")
    if query.family == "ranked":
        if query.cohort is None or query.cohort.tie is None:
            raise PlanRejected("NO_TIE_RULE", "ranks need a total order")
    if query.family == "threshold" and query.threshold is None:
        raise PlanRejected("UNSUPPORTED", "a threshold query needs its threshold")


@dataclass(frozen=True)
class PiecePlan:
    """(piece, chunk, bucket_lo, bucket_hi) and what the family fixes; ``spans``: the stretch of time of pieces that are cut in time,
    too, as their one bucket is over the ceiling."""

    query: Query
    family: Family
    pieces: tuple[tuple[int, int, int, int], ...]
    pruned: int
    chunks: tuple[int, int]
    spans: Mapping[int, QueryWindow] = field(default_factory=dict)


def plan(query: Query, layout: Layout, spark: SparkSession, shards: DataFrame | None = None) -> PiecePlan:
    """Pieces of the chunks that the window touches; ``shards`` (see plan_shards) splits chunks by buckets.  Reads the manifest
    alone, whose rows follow the number of chunks."""
    validate(query)
    first, last = layout.grid.chunks_for(query.window)
    known = {r.chunk: r for r in layout.manifest(spark).select("chunk", "bucket_lo", "bucket_hi", "min_from", "max_to").collect()}
    split: dict[int, list[tuple[int, int, int]]] = {}
    if shards is not None and FAMILIES[query.family].shards == "keys":
        for r in shards.where(f"chunk BETWEEN {first} AND {last}").collect():
            split.setdefault(r.chunk, []).append((r.bucket_lo, r.bucket_hi, r.parts if "parts" in shards.columns else 1))
    pieces, spans = [], {}
    for c in (c for c in sorted(known) if first <= c <= last):
        for low, high, parts in split.get(c, [(known[c].bucket_lo, known[c].bucket_hi, 1)]):
            for span in stretches(max(known[c].min_from, query.window.start), min(known[c].max_to, query.window.end), parts) if parts > 1 else [None]:
                if span is not None:
                    spans[len(pieces)] = span
                pieces.append((len(pieces), c, low, high))
    return PiecePlan(query, FAMILIES[query.family], tuple(pieces), len(known) - len({p[1] for p in pieces}), (first, last), spans)


def stretches(start, end, parts: int) -> list[QueryWindow]:
    """[start, end) in at most ``parts`` stretches of about one length; every operator that is sharded by key may be cut anywhere
    in time, as its merge joins stretches that meet."""
    if not start < end:
        return [QueryWindow(start, end)]
    at = [start + (end - start) * i // parts for i in range(parts)] + [end]
    return [QueryWindow(a, b) for a, b in zip(at, at[1:]) if a < b]


def explain_plan(p: PiecePlan) -> str:
    f = p.family
    return "\n".join([f"family {p.query.family}: partial {f.partial}; merge {f.merge}; finally {f.finalizer}; canonical by {f.canon}", f"chunks {p.chunks[0]} to {p.chunks[1]}: {len(p.pieces)} pieces, {p.pruned} chunks pruned, shards of {f.shards}"])


def closed(pieces: DataFrame, whole: DataFrame, keys: Sequence[str], integer: bool = False) -> bool:
    """Whether segments of all pieces are those of the whole: the same time per key, no piece overlapping another."""
    from ..operators.canonical import canonical_equal, coalesce_intervals

    columns = [c for c in whole.columns if c in pieces.columns and c not in ("chunk", "bucket", "is_head", "valid_from", "valid_to", *keys)]
    a, b = (coalesce_intervals(x, keys, columns) for x in (pieces, whole))
    from pyspark.sql import functions as F

    from ..functions.instants import FROM, TO, length

    total = [x.agg(F.sum(length(F.col(FROM), F.col(TO), integer))).first()[0] for x in (pieces, whole)]
    return total[0] == total[1] and canonical_equal(a, b) == (0, 0)
