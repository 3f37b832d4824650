"""Programs for the gated difference with the faults of interval-set programming, to be held against the right answer."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.instants import FROM, TO
from ..functions.predicates import predicate
from ..operators.canonical import coalesce_intervals
from ..operators.gate import key_domain_gate
from ..operators.interval_algebra import subtract


def intersection_fault(seg: DataFrame, keys: Sequence[str], keep, exceeding) -> DataFrame:
    """Takes away what all exceeding intervals of a key have in common, not what any has: with two or more, nothing."""
    a = coalesce_intervals(seg.where(predicate(keep)), keys)
    x = seg.where(predicate(exceeding)).select(*keys, FROM, TO)
    common = coalesce_intervals(x, keys).groupBy(*keys).agg(F.max(FROM).alias(FROM), F.min(TO).alias(TO)).where(F.col(FROM) < F.col(TO))
    return key_domain_gate(subtract(a, common, keys), x, keys)


def unclipped_fault(history: DataFrame, seg: DataFrame, keys: Sequence[str], keep, exceeding) -> DataFrame:
    """Takes the difference over the rows' whole lives and never cuts it back to the window's brand intervals."""
    inside = seg.where(predicate(keep)).select(*keys).distinct()
    lives = coalesce_intervals(history.where(predicate(keep)).join(inside, list(keys), "left_semi"), keys)
    x = seg.where(predicate(exceeding)).select(*keys, FROM, TO)
    return key_domain_gate(subtract(lives, x, keys), x, keys)


def bridged_fault(seg: DataFrame, keys: Sequence[str], keep, exceeding) -> DataFrame:
    """Fills the stretches between exceeding intervals whatever the brand is there: extends beyond the brand's intervals."""
    span = seg.where(predicate(keep)).groupBy(*keys).agg(F.min(FROM).alias(FROM), F.max(TO).alias(TO))
    x = seg.where(predicate(exceeding)).select(*keys, FROM, TO)
    return key_domain_gate(subtract(span, x, keys), x, keys)
