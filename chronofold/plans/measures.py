"""Latency, cost and exactness measures.  Unit prices vary by place and time, so they are parameters."""

from __future__ import annotations

import statistics
import time
from collections.abc import Callable, Mapping, Sequence
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

TIB = 1 << 40
MIB = 1 << 20


def measure(run: Callable[[], object], warmup: int = 1, repeats: int = 5) -> float:
    """Median seconds of some runs after warm-ups that don't count."""
    for _ in range(warmup):
        run()
    taken = []
    for _ in range(repeats):
        began = time.perf_counter()
        run()
        taken.append(time.perf_counter() - began)
    return statistics.median(taken)


def consume(df: DataFrame) -> None:
    """Compute every row and column without bringing any to the driver."""
    df.write.format("noop").mode("overwrite").save()


def suite_mean(medians: Sequence[float]) -> float:
    return sum(medians) / len(medians)


@dataclass(frozen=True)
class Usage:
    """What a run is billed for."""

    gb_seconds: float = 0.0
    reads: int = 0
    writes: int = 0
    queue_requests: int = 0
    commits: int = 0
    scanned_bytes: int = 0
    logical_bytes: int = 0


@dataclass(frozen=True)
class Observed:
    """What the stages of a run did, from Spark's own status store."""

    seconds: float
    tasks: int
    task_seconds: float
    scanned_bytes: int
    scanned_rows: int
    shuffle_bytes: int
    shuffle_rows: int
    spilled_bytes: int
    peak_memory: int
    #: Task seconds of stages that read input, of those between two exchanges, and of those that end the run.
    split: dict[str, float]

    def usage(self, worker_gb: float) -> Usage:
        """Billing units, with a task as one function of ``worker_gb`` of memory that is started by one queue request, reads its
        input in one request, writes its exchange in one, and commits once."""
        return Usage(self.task_seconds * worker_gb, self.tasks, self.tasks, self.tasks, self.tasks, self.scanned_bytes)


def observe(spark: SparkSession, run: Callable[[], object]) -> Observed:
    """Run and report the stages that it added.  Other work of the application must not run meanwhile."""
    store, gateway = spark.sparkContext._jsc.sc().statusStore(), spark.sparkContext._gateway
    none = gateway.new_array(spark.sparkContext._jvm.double, 0)

    def stages() -> dict:
        spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty()
        found = store.stageList(None, False, False, none, None)
        return {(s.stageId(), s.attemptId()): s for s in (found.apply(i) for i in range(found.size()))}

    before = stages().keys()
    began = time.perf_counter()
    run()
    seconds = time.perf_counter() - began
    new = [s for k, s in stages().items() if k not in before and s.numCompleteTasks()]
    split = {"scan": 0.0, "exchange": 0.0, "end": 0.0}
    for s in new:
        split["scan" if s.inputBytes() else "exchange" if s.shuffleWriteBytes() else "end"] += s.executorRunTime() / 1000
    total = lambda f: sum(getattr(s, f)() for s in new)
    return Observed(
        seconds, total("numCompleteTasks"), total("executorRunTime") / 1000, total("inputBytes"), total("inputRecords"), total("shuffleWriteBytes"), total("shuffleWriteRecords"),
        total("memoryBytesSpilled") + total("diskBytesSpilled"), max((s.peakExecutionMemory() for s in new), default=0), split,
    )


def fits(spark: SparkSession, run: Callable[[], object], memory: int) -> bool:
    """Whether a run neither spills nor has a stage of more than ``memory`` bytes of execution memory: the probe of a piece ceiling
    (see ``calibrate_ceiling``)."""
    seen = observe(spark, run)
    return seen.spilled_bytes == 0 and seen.peak_memory <= memory


def cold_and_warm(run: Callable[[], object], repeats: int = 5) -> tuple[float, float]:
    """Seconds of the first run of its kind in an application, and the median of later ones."""
    began = time.perf_counter()
    run()
    return time.perf_counter() - began, measure(run, 0, repeats)


def cost_serverless(u: Usage, prices: Mapping[str, float]) -> float:
    """Functions by memory and time, object requests, queue and commit registry, in USD."""
    return u.gb_seconds * prices["gb_second"] + u.reads * prices["read"] + u.writes * prices["write"] + u.queue_requests * prices["queue"] + u.commits * prices["commit"]


def cost_scan(scanned_bytes: int, usd_per_tib: float = 5.0, least: int = 10 * MIB) -> float:
    """A query service billed by scanned bytes, with a minimum."""
    return max(scanned_bytes, least) / TIB * usd_per_tib


def cost_logical(u: Usage, usd_per_tib: float) -> float:
    """One billed by the bytes of the columns' values rather than of the files."""
    return u.logical_bytes / TIB * usd_per_tib


def break_even(monthly_usd: float, per_query_usd: float, hours: float = 730.0) -> float:
    """Queries an hour at which a fixed price equals paying by query."""
    return monthly_usd / hours / per_query_usd


def cost_curve(per_query: Mapping[str, float], fixed: Mapping[str, float], queries: Sequence[int]) -> list[dict]:
    """Cost of each path by number of queries: straight lines, and flat ones."""
    return [{"queries": n} | {p: c * n for p, c in per_query.items()} | dict(fixed) for n in queries]


def frontier(points: Mapping[tuple[str, str], tuple[float, float]]) -> list[dict]:
    """Rows (path, window, seconds, usd, best) where best: no other path of the window is both faster and cheaper."""
    out = []
    for (path, window), (s, c) in points.items():
        beaten = any(w == window and p != path and s2 <= s and c2 <= c and (s2, c2) != (s, c) for (p, w), (s2, c2) in points.items())
        out.append({"path": path, "window": window, "seconds": s, "usd": c, "best": not beaten})
    return out


def relative_error(found: DataFrame, oracle: DataFrame, group: Sequence[str], column: str) -> float:
    """Largest relative difference of a ratio over groups; a group on one side alone is infinite."""
    from pyspark.sql import functions as F

    a, b = found.select(*group, F.col(column).alias("_a")), oracle.select(*group, F.col(column).alias("_b"))
    both = a.join(b, [a[g].eqNullSafe(b[g]) for g in group] if group else F.lit(True), "full")
    wrong = F.when(F.col("_a").isNull() != F.col("_b").isNull(), F.lit(float("inf"))).otherwise(F.abs(F.col("_a") - F.col("_b")) / F.greatest(F.abs("_b"), F.lit(1e-300)))
    return both.agg(F.max(wrong)).first()[0] or 0.0
