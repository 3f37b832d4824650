"""Two-valued predicates: a null comparison is false, and so is its use under a negation's operand.

SQL's third value would lose rows in ``a and not b`` where b is null, which a map to {0, 1} must keep.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


class Pred:
    """A predicate over one full-state row; combine with ``&``, ``|``, ``-`` (and not) and ``~``."""

    def __init__(self, condition: Column) -> None:
        self.column = F.coalesce(condition, F.lit(False))

    @staticmethod
    def col(name: str) -> _Operand:
        return _Operand(F.col(name))

    @staticmethod
    def sql(text: str) -> Pred:
        return Pred(F.expr(text))

    def __and__(self, other: Pred) -> Pred:
        return Pred(self.column & other.column)

    def __or__(self, other: Pred) -> Pred:
        return Pred(self.column | other.column)

    def __sub__(self, other: Pred) -> Pred:
        return Pred(self.column & ~other.column)

    def __invert__(self) -> Pred:
        return Pred(~self.column)


class _Operand:
    def __init__(self, column: Column) -> None:
        self._column = column

    def __lt__(self, other):
        return Pred(self._column < other)

    def __le__(self, other):
        return Pred(self._column <= other)

    def __gt__(self, other):
        return Pred(self._column > other)

    def __ge__(self, other):
        return Pred(self._column >= other)

    def __eq__(self, other):
        return Pred(self._column == other)

    def __ne__(self, other):
        return Pred(self._column != other)

    __hash__ = None

    def between(self, low, high) -> Pred:
        return Pred(self._column.between(low, high))

    def isin(self, *values) -> Pred:
        return Pred(self._column.isin(*values))

    def like(self, pattern: str) -> Pred:
        return Pred(self._column.like(pattern))

    def rlike(self, pattern: str) -> Pred:
        return Pred(self._column.rlike(pattern))

    def is_null(self) -> Pred:
        return Pred(self._column.isNull())

    def same_as(self, other) -> Pred:
        """Null-safe equality."""
        return Pred(self._column.eqNullSafe(other))


def predicate(phi: Pred | Column | str) -> Column:
    """Any way to state a predicate as a two-valued column."""
    if isinstance(phi, Pred):
        return phi.column
    return Pred(F.expr(phi) if isinstance(phi, str) else phi).column
