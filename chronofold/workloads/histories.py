"""Histories derived from the given tables; expressions are SQL that Spark and DuckDB both read."""

from __future__ import annotations

import datetime as dt
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession

from ..sources.files import load
from ..sources.history import from_change_log
from ..sources.layout import ChunkGrid
from ..spec import HistorySpec, QueryWindow

D = dt.datetime
MONEY = "DECIMAL(18,2)"


@dataclass(frozen=True)
class Derived:
    """How a history follows from a table: each change of a key ends its last row."""

    table: str
    keys: dict[str, str]
    at: str
    tie: tuple[str, ...]
    payload: dict[str, str]
    horizon: D
    grid: ChunkGrid
    windows: dict[str, QueryWindow]
    #: Static attributes: name to (joined on, query over {table} names).
    dims: dict[str, tuple[str, str]] = field(default_factory=dict)
    compact: bool = False

    @property
    def spec(self) -> HistorySpec:
        return HistorySpec(tuple(self.keys), tuple(self.payload), self.horizon)

    def changes(self, spark: SparkSession, folder: str) -> DataFrame:
        rows = load(spark, folder, self.table)
        ties = [f"{t} AS tie{i}" for i, t in enumerate(self.tie)]
        return rows.selectExpr(*(f"{e} AS {n}" for n, e in (self.keys | self.payload).items()), f"{self.at} AS at", *ties)

    def build(self, spark: SparkSession, folder: str) -> DataFrame:
        ties = [f"tie{i}" for i in range(len(self.tie))]
        return from_change_log(self.changes(spark, folder), list(self.keys), "at", list(self.payload), ties, self.horizon, self.compact)

    def dim(self, spark: SparkSession, folder: str, name: str) -> DataFrame:
        query = self.dims[name][1]
        tables = [t for t in ("region", "nation", "customer", "supplier", "part") if "{" + t + "}" in query]
        return spark.sql(query, **{t: load(spark, folder, t) for t in tables})


def _day(y: int, m: int, d: int = 1) -> D:
    return D(y, m, d)


_START = _day(1998, 3)
#: One, three, six and twelve months; and one that cuts chunks at both ends.
ORDER_WINDOWS = {"w1": QueryWindow(_START, _day(1998, 4)), "w3": QueryWindow(_START, _day(1998, 6)), "w6": QueryWindow(_START, _day(1998, 9)), "w12": QueryWindow(_START, _day(1999, 3)), "cut": QueryWindow(_day(1998, 3, 10), _day(1999, 2, 20)), "empty": QueryWindow(_day(1990, 1), _day(1991, 1)), "inside": QueryWindow(_day(1998, 5, 5), _day(1998, 5, 6))}
EVENT_WINDOWS = {"all": QueryWindow(_day(2024, 1, 5), _day(2024, 1, 25)), "cut": QueryWindow(D(2024, 1, 5, 7, 30), D(2024, 1, 24, 18, 45)), "origin": QueryWindow(_day(2024, 1, 1), _day(2024, 1, 8))}

_LINE = {"price": f"CAST(l_extendedprice AS {MONEY})", "disc": "CAST(l_discount AS DECIMAL(4,2))", "tax": "CAST(l_tax AS DECIMAL(4,2))", "score": "CAST(l_quantity AS INT)"}
_REGION = ("supp_key", "SELECT s_suppkey AS supp_key, n_regionkey AS region, s_nationkey AS nation FROM {supplier} JOIN {nation} ON s_nationkey = n_nationkey")
_HORIZON = _day(2002, 1)

HISTORIES = {
    "part": Derived("lineitem", {"part_key": "l_partkey"}, "l_shipdate", ("l_orderkey", "l_linenumber", "l_suppkey", "l_extendedprice"), _LINE | {"supp_key": "l_suppkey"}, _HORIZON, ChunkGrid.calendar("MONTH"), ORDER_WINDOWS, {"brand": ("part_key", "SELECT p_partkey AS part_key, p_brand AS brand FROM {part}"), "region": _REGION}),
    "tag": Derived("lineitem", {"tag": "concat('K', l_partkey)"}, "l_shipdate", ("l_orderkey", "l_linenumber", "l_suppkey", "l_extendedprice"), {"price": _LINE["price"], "score": _LINE["score"]}, _HORIZON, ChunkGrid.calendar("MONTH"), ORDER_WINDOWS),
    "supp": Derived("lineitem", {"supp_key": "l_suppkey"}, "l_shipdate", ("l_orderkey", "l_linenumber", "l_partkey", "l_extendedprice"), _LINE | {"part_key": "l_partkey"}, _HORIZON, ChunkGrid.calendar("MONTH"), ORDER_WINDOWS, {"region": _REGION}),
    "pair": Derived("lineitem", {"part_key": "l_partkey", "supp_key": "l_suppkey"}, "l_shipdate", ("l_orderkey", "l_linenumber", "l_extendedprice"), {"price": _LINE["price"], "score": _LINE["score"]}, _HORIZON, ChunkGrid.whole(), ORDER_WINDOWS),
    "cust": Derived("orders", {"cust_key": "o_custkey"}, "o_orderdate", ("o_orderkey",), {"price": f"CAST(o_totalprice AS {MONEY})", "prio": "o_orderpriority", "status": "o_orderstatus"}, _HORIZON, ChunkGrid.calendar("YEAR"), ORDER_WINDOWS, {"segment": ("cust_key", "SELECT c_custkey AS cust_key, c_mktsegment AS segment, c_nationkey AS nation FROM {customer}")}),
    "user": Derived("events", {"user_id": "user_id"}, "ts", ("event_id",), {"event_type": "event_type", "value": f"CAST(value AS {MONEY})", "props": "props"}, _day(2024, 1, 31), ChunkGrid.calendar("DAY"), EVENT_WINDOWS),
    "user_type": Derived("events", {"user_id": "user_id"}, "ts", ("event_id",), {"event_type": "event_type"}, _day(2024, 1, 31), ChunkGrid.calendar("DAY"), EVENT_WINDOWS, compact=True),
}
