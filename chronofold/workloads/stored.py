"""The suite, the compositions and every family's stored partials over layouts written before the query."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from ..plans import sizing
from ..plans.query import FAMILIES, Query
from ..plans.runner import run_fanout, run_fanout_durable
from ..sources.folders import scratch
from ..sources.layout import ChunkGrid, Layout, build_clipped_layout
from ..spec import Cohort, QueryWindow
from . import oracles as sql
from .histories import HISTORIES
from .suite import SUITE, smallest

Run = Callable[[SparkSession, str], DataFrame]
#: Bytes of a piece of the durable queries, at about ten a row.
CEILING = 30_000.0
_BUILT: dict[tuple, Layout] = {}


def stored(spark: SparkSession, folder: str, name: str, grid: ChunkGrid | None = None, bucket_groups: int = 8) -> Layout:
    """The layout of a history, built once in an application."""
    d = HISTORIES[name]
    grid = grid or d.grid
    of = (spark.sparkContext.applicationId, folder, name, grid, bucket_groups)
    if of not in _BUILT:
        _BUILT[of] = build_clipped_layout(d.build(spark, folder), grid, scratch(spark), d.spec, bucket_groups=bucket_groups)
    return _BUILT[of]


def asked(name: str, spark: SparkSession, folder: str, window: QueryWindow, threshold: int | None = None) -> dict[int, Callable[[], Query]]:
    """Q1 to Q10 as planned queries."""
    d, s = HISTORIES[name], SUITE[name]
    spec, cheap, stable, x = d.spec, s["cheap"], s["stable"], s["x"]
    group, dim = s["group"]
    cohort_dim, where = s["cohort"]

    def grouped(query: Query) -> Query:
        return query.with_dims(d.dim(spark, folder, dim), d.dims[dim][0]) if dim else query

    def cohort() -> Cohort:
        return Cohort(table=d.dim(spark, folder, cohort_dim).where(where)) if cohort_dim else Cohort(None)

    def pair() -> Query:
        a, b = smallest(name, spark, folder, 2)
        return Query("pairwise", spec, window, x=x, left=a, right=b, cohort=Cohort((a, b)))

    return {
        1: lambda: Query("predicate", spec, window, phi=cheap, payload=(x,)), 2: lambda: grouped(Query("duration", spec, window, x=x, group=(group,), digits=6)),
        3: lambda: Query("boolean", spec, window, phi=cheap, other=stable, op="and"), 4: lambda: Query("boolean", spec, window, phi=cheap, other=stable, op="or"),
        5: lambda: Query("boolean", spec, window, phi=cheap, other=stable, op="minus"), 6: lambda: grouped(Query("count", spec, window, phi=cheap, group=(group,))).then_threshold(s["c"] if threshold is None else threshold),
        7: pair, 8: lambda: Query("better", spec, window, x=x, reference=smallest(name, spark, folder, 1)[0], cohort=cohort()),
        9: lambda: Query("ranked", spec, window, x=x, k=1, cohort=cohort()), 10: lambda: Query("ranked", spec, window, x=x, k=3, cohort=cohort()),
    }


def layout_suite(oracles: dict[str, str]) -> tuple[dict[str, Run], dict[str, str]]:
    """Each suite query through its stored layout; the SQL is that of the query without one."""
    out: dict[str, Run] = {}
    text: dict[str, str] = {}
    for name, s in SUITE.items():
        w = HISTORIES[name].windows[s["window"]]
        for i in range(1, 11):
            out[f"layout_q{i:02d}_{name}"] = lambda spark, folder, name=name, w=w, i=i: run_fanout(asked(name, spark, folder, w)[i](), stored(spark, folder, name), spark)
            text[f"layout_q{i:02d}_{name}"] = oracles[f"q{i:02d}_{name}"]
    return out, text


def layout_compositions(queries: dict[str, Query], oracles: dict[str, str]) -> tuple[dict[str, Run], dict[str, str]]:
    out = {f"layout_{n}": lambda spark, folder, q=q: run_fanout(q, stored(spark, folder, "cust"), spark) for n, q in queries.items()}
    return out, {f"layout_{n}": oracles[n] for n in queries}


def durable_families() -> tuple[dict[str, Run], dict[str, str]]:
    """Every family piece by piece, with text keys and pieces small enough that key shards and stretches of time come up."""
    d = HISTORIES["tag"]
    w, spec = d.windows["w3"], d.spec
    keys = tuple(f"K{i}" for i in range(1, 41))
    members = f"tag IN ({', '.join(repr(k) for k in keys)})"
    cohort = Cohort(keys)
    cheap, many = "price < 10000", "price > 60000"
    queries = {
        "predicate": (Query("predicate", spec, w, phi=cheap, payload=("price",)), sql.predicate("tag", w, cheap, ["price"])),
        "boolean": (Query("boolean", spec, w, phi=cheap, other="score >= 25", op="minus"), sql.predicate("tag", w, f"({cheap}) AND NOT score >= 25")),
        "gated": (Query("boolean", spec, w, phi=cheap, other="score >= 25", op="minus").then_gate(many), sql.difference_gated("tag", w, cheap, "score >= 25", many)),
        "duration": (Query("duration", spec, w, x="price", group=("score",), digits=6), sql.duration("tag", w, "price", ["score"])),
        "count": (Query("count", spec, w, phi=cheap, group=("score",)), sql.count("tag", w, cheap, ["score"])),
        "threshold": (Query("count", spec, w, phi=cheap, group=("score",)).then_threshold(3), sql.count("tag", w, cheap, ["score"], (), 3)),
        "pairwise": (Query("pairwise", spec, w, x="price", left="K1", right="K2", cohort=cohort, emit="both"), sql.pairwise("tag", w, "'K1'", "'K2'", "price", "<", (), True)),
        "better": (Query("better", spec, w, x="price", reference="K1", cohort=cohort), sql.better("tag", w, members, "'K1'", "price", "<")),
        "ranked": (Query("ranked", spec, w, x="price", k=3, cohort=cohort), sql.ranked("tag", w, members, "price", 3)),
    }
    assert queries.keys() == FAMILIES.keys()

    def run(query: Query) -> Run:
        def durable(spark: SparkSession, folder: str) -> DataFrame:
            layout = stored(spark, folder, "tag", ChunkGrid.calendar("QUARTER"))
            sizes = sizing.key_byte_histogram(layout.scan(spark), ["tag"], 10.0)
            shards = sizing.plan_shards(sizes, CEILING)
            return run_fanout_durable(query, layout, spark, scratch(spark), shards, check=query.cohort is not None)

        return durable

    return {f"durable_{n}": run(q) for n, (q, _) in queries.items()}, {f"durable_{n}": t for n, (_, t) in queries.items()}
