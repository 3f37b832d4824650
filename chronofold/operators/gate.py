"""Restriction of a window result to the keys of another."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.instants import FROM, TO, length
from ..functions.predicates import predicate
from .canonical import coalesce_intervals
from .same_base import Phi, predicate_window


def key_domain_gate(window: DataFrame, evidence: DataFrame, keys: Sequence[str]) -> DataFrame:
    """Rows of a complete window whose key has any row in a complete evidence window; applied once, after both."""
    return window.join(evidence.select(*keys).distinct(), list(keys), "left_semi")


def gated_difference(seg: DataFrame, keys: Sequence[str], keep: Phi, drop: Phi, evidence: Phi, payload: Sequence[str] = ()) -> DataFrame:
    """Where ``keep`` holds and ``drop`` does not, for keys that ever show ``evidence`` in the window."""
    from .same_base import boolean_window

    window = boolean_window(seg, keys, keep, drop, "minus", payload)
    return key_domain_gate(window, predicate_window(seg, keys, evidence, canon=False), keys)


def keys_ever(seg: DataFrame, keys: Sequence[str], phi: Phi) -> DataFrame:
    return seg.where(predicate(phi)).select(*keys).distinct()


def keys_never(seg: DataFrame, keys: Sequence[str], phi: Phi) -> DataFrame:
    return seg.groupBy(*keys).agg(F.max(predicate(phi).cast("int")).alias("_any")).where("_any = 0").select(*keys)


def keys_always(seg: DataFrame, keys: Sequence[str], phi: Phi) -> DataFrame:
    """Keys whose time under the predicate is all the time they are present."""
    d = length(F.col(FROM), F.col(TO))
    sums = seg.groupBy(*keys).agg(F.sum(d).alias("_all"), F.sum(F.when(predicate(phi), d).otherwise(0)).alias("_on"))
    return sums.where("_all = _on").select(*keys)


def merge_windows(parts: Sequence[DataFrame], keys: Sequence[str], on: Sequence[str] = ()) -> DataFrame:
    """Union of window partials of any pieces, in canonical form."""
    whole = parts[0]
    for p in parts[1:]:
        whole = whole.unionByName(p)
    return coalesce_intervals(whole, keys, on)
