"""What a history, a window and a cohort are."""

from __future__ import annotations

import datetime as dt
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .functions.instants import FROM, TO, instant

Instant = dt.datetime | int


@dataclass(frozen=True)
class HistorySpec:
    """Columns of a history, beside ``valid_from`` and ``valid_to``: rows of one key never overlap, and each shows every payload
    column (``full_state``).  ``integer``: the time axis counts steps."""

    keys: tuple[str, ...]
    payload: tuple[str, ...]
    horizon: Instant | None = None
    full_state: bool = True
    integer: bool = False

    @property
    def columns(self) -> tuple[str, ...]:
        return (*self.keys, *self.payload, FROM, TO)


@dataclass(frozen=True)
class QueryWindow:
    """[start, end)."""

    start: Instant
    end: Instant

    @property
    def low(self) -> Column:
        return instant(self.start)

    @property
    def high(self) -> Column:
        return instant(self.end)


@dataclass(frozen=True)
class Cohort:
    """Keys to compare, fixed by the query: a list, a table of keys over static attributes, or (keys None) the rows given.  With ``family`` the table also has
    a column that tells many cohorts apart."""

    keys: tuple | None = ()
    table: DataFrame | None = field(default=None, compare=False)
    family: str | None = None
    tie: str | None = "key"
    dynamic: bool = False

    def restrict(self, rows: DataFrame, key: str) -> DataFrame:
        """Rows of the cohort's keys; a listed cohort becomes a filter that reaches the scan."""
        if self.table is not None:
            columns = [key] + ([self.family] if self.family else [])
            return rows.join(self.table.select(*columns).distinct(), key)
        if self.keys is None:
            return rows
        return rows.where(F.col(key).isin(*self.keys)) if self.keys else rows.where(F.lit(False))
