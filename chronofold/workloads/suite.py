"""The ten-query suite on each history, the six compositions, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from ..operators.gate import key_domain_gate
from ..operators.same_base import predicate_window
from ..plans.query import Query
from ..plans.runner import evaluate
from ..sources.layout import ChunkGrid, segments
from ..spec import Cohort, QueryWindow
from . import oracles as sql
from .histories import HISTORIES

Run = Callable[[SparkSession, str], DataFrame]

#: Per history: a cheap predicate, a stable one, the quantity, groups (with the static attribute they need), count threshold at
#: sf0.01 (counts grow with the keys, so other sizes scale it), and the cohort as SQL over attributes.
SUITE = {
    "part": {"window": "w12", "cheap": "price < 10000", "stable": "score >= 25", "x": "price", "group": ("brand", "brand"), "c": 8, "cohort": ("brand", "brand = 'Brand#7'"), "first": "SELECT p_partkey FROM {part} WHERE p_brand = 'Brand#7'"},
    "supp": {"window": "w12", "cheap": "price < 10000", "stable": "tax >= 0.04", "x": "price", "group": ("region", "region"), "c": 2, "cohort": ("region", "nation = 9"), "first": "SELECT s_suppkey FROM {supplier} WHERE s_nationkey = 9"},
    "cust": {"window": "w12", "cheap": "price > 400000", "stable": "prio = '1-URGENT'", "x": "price", "group": ("segment", "segment"), "c": 61, "cohort": ("segment", "nation = 7 AND segment = 'BUILDING'"), "first": "SELECT c_custkey FROM {customer} WHERE c_nationkey = 7 AND c_mktsegment = 'BUILDING'"},
    "user": {"window": "cut", "cheap": "value < 10", "stable": "event_type = 'view'", "x": "value", "group": ("event_type", None), "c": 6, "cohort": (None, "true"), "first": "SELECT DISTINCT user_id FROM {events}"},
}


def segmented(name: str, spark: SparkSession, folder: str, window: QueryWindow, dims: tuple = (), grid: ChunkGrid | None = None) -> DataFrame:
    """Segments of a window with static attributes."""
    d = HISTORIES[name]
    seg = segments(d.build(spark, folder), grid or d.grid, list(d.keys), window)
    for x in dims:
        seg = seg.join(d.dim(spark, folder, x), d.dims[x][0], "left")
    return seg


def smallest(name: str, spark: SparkSession, folder: str, n: int) -> list:
    """The smallest keys of a cohort: static attributes, resolved when the query is planned."""
    from ..sources.files import load

    query = SUITE[name]["first"]
    tables = {t: load(spark, folder, t) for t in ("part", "supplier", "customer", "events") if "{" + t + "}" in query}
    found = spark.sql(query, **tables)
    key = found.columns[0]
    keys = [r[0] for r in found.orderBy(key).limit(n).collect()]
    return keys + [-1] * (n - len(keys))  # an empty cohort compares keys that nothing has


def _plain(query: str) -> str:
    return query.format(**{t: t for t in ("part", "supplier", "customer", "events")})


def nth_key(name: str, n: int) -> str:
    inner = _plain(SUITE[name]["first"])
    return f"(SELECT k FROM (SELECT * FROM ({inner}) AS z(k)) ORDER BY k LIMIT 1 OFFSET {n})"


def _add(out: dict, oracle: dict, name: str, run: Run, text: str | None) -> None:
    out[name] = run
    if text is not None:
        oracle[name] = text


def suite(name: str, window_name: str | None = None, suffix: str = "", grid: ChunkGrid | None = None, only: tuple[int, ...] = tuple(range(1, 11))) -> tuple[dict[str, Run], dict[str, str]]:
    """q01 to q10 of a history, and their SQL."""
    d, s = HISTORIES[name], SUITE[name]
    w = d.windows[window_name or s["window"]]
    spec, key = d.spec, next(iter(d.keys))
    group, dim = s["group"]
    dims = (dim,) if dim else ()
    cohort_dim, cohort_where = s["cohort"]
    cohort_dims = (cohort_dim,) if cohort_dim else ()
    cheap, stable, x = s["cheap"], s["stable"], s["x"]
    out: dict[str, Run] = {}
    oracle: dict[str, str] = {}
    tag = f"{name}{suffix}"

    def same_base(query: Query, needs: tuple = ()) -> Run:
        return lambda spark, folder: evaluate(query, segmented(name, spark, folder, w, needs, grid))

    def aligned(**options) -> Run:
        def run(spark: SparkSession, folder: str) -> DataFrame:
            seg = segmented(name, spark, folder, w, cohort_dims, grid).where(cohort_where)
            first = smallest(name, spark, folder, 2)
            named = {"left": first[0], "right": first[1], "reference": first[0]}
            return evaluate(Query(spec=spec, window=w, x=x, **{k: named.get(v, v) if isinstance(v, str) else v for k, v in options.items()}), seg)

        return run

    texts = {
        1: (same_base(Query("predicate", spec, w, phi=cheap, payload=(x,))), lambda: sql.predicate(name, w, cheap, [x])),
        2: (same_base(Query("duration", spec, w, x=x, group=(group,), digits=6), dims), lambda: sql.duration(name, w, x, [group], dims)),
        3: (same_base(Query("boolean", spec, w, phi=cheap, other=stable, op="and")), lambda: sql.predicate(name, w, f"({cheap}) AND ({stable})")),
        4: (same_base(Query("boolean", spec, w, phi=cheap, other=stable, op="or")), lambda: sql.predicate(name, w, f"({cheap}) OR ({stable})")),
        5: (same_base(Query("boolean", spec, w, phi=cheap, other=stable, op="minus")), lambda: sql.predicate(name, w, f"({cheap}) AND NOT coalesce(({stable}), false)")),
        6: (same_base(Query("threshold", spec, w, phi=cheap, group=(group,), threshold=s["c"]), dims), lambda: sql.count(name, w, cheap, [group], dims, s["c"])),
        7: (aligned(family="pairwise", cohort=Cohort(None), left="left", right="right"), lambda: sql.pairwise(name, w, nth_key(name, 0), nth_key(name, 1), x, "<", cohort_dims)),
        8: (aligned(family="better", cohort=Cohort(None), reference="reference"), lambda: sql.better(name, w, cohort_where, nth_key(name, 0), x, "<", cohort_dims)),
        9: (aligned(family="ranked", cohort=Cohort(None), k=1), lambda: sql.ranked(name, w, cohort_where, x, 1, cohort_dims)),
        10: (aligned(family="ranked", cohort=Cohort(None), k=3), lambda: sql.ranked(name, w, cohort_where, x, 3, cohort_dims)),
    }
    for i in only:
        run, text = texts[i]
        _add(out, oracle, f"q{i:02d}_{tag}", run, text())
    return out, oracle


def compositions(asked: dict[str, Query] | None = None) -> tuple[dict[str, Run], dict[str, str]]:
    """Six compositions (also put in ``asked``) on the customers' rows seen as items: brand is the priority, class the status."""
    d = HISTORIES["cust"]
    w, spec, keys = d.windows["w12"], d.spec, list(d.keys)
    brand, cls = "prio = '1-URGENT'", "status = 'F'"
    out: dict[str, Run] = {}
    oracle: dict[str, str] = {}

    def add(name: str, query: Query, text: str) -> None:
        if asked is not None:
            asked[name] = query
        _add(out, oracle, name, lambda spark, folder: evaluate(query, segmented("cust", spark, folder, w)), text)

    add("mq1_item", Query("predicate", spec, w, phi=brand, payload=("prio",)), sql.predicate("cust", w, brand, ["prio"]))
    add("mq2_item", Query("predicate", spec, w, phi="true", payload=("status",)), sql.predicate("cust", w, "true", ["status"]))
    add("mq3_item", Query("boolean", spec, w, phi=brand, other=cls, op="and"), sql.predicate("cust", w, f"{brand} AND {cls}"))
    add("mq4_item", Query("boolean", spec, w, phi=brand, other=cls, op="or"), sql.predicate("cust", w, f"{brand} OR {cls}"))
    for name, low, high in (("mq5_item", 250000, 450000), ("mq5_item_one_threshold", 450000, 450000)):
        query = Query("boolean", spec, w, phi=brand, other=f"price > {low}", op="minus").then_gate(f"price > {high}")
        add(name, query, sql.difference_gated("cust", w, brand, f"price > {low}", f"price > {high}"))
    add("mq6_item", Query("count", spec, w, phi=cls, group=("prio",)).then_threshold(93), sql.count("cust", w, cls, ["prio"], (), 93))
    gate = f"{sql.clipped('cust', w)}, k AS (SELECT DISTINCT cust_key FROM c WHERE price > 450000), r AS (SELECT * FROM c WHERE {brand} AND cust_key IN (SELECT cust_key FROM k)) {sql.islands('r', keys)}"

    def gate_only(spark: SparkSession, folder: str) -> DataFrame:
        seg = segmented("cust", spark, folder, w)
        return key_domain_gate(predicate_window(seg, keys, brand), predicate_window(seg, keys, "price > 450000", canon=False), keys)

    _add(out, oracle, "gate_only", gate_only, gate)
    return out, oracle
