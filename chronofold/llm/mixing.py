"""Mixing to target weights with soft domain membership.

A classifier learnt from the labelled table gives each document a posterior over domains.  Document rates r >= 0 (at most
``most``, if given) minimise, by accelerated projected gradient steps,

    1/2 sum_k (S_k - T_k)^2 / (B^2 s_k)  +  ridge/2 sum_d w_d (r_d - 1)^2

where S_k = sum_d r_d t_d p_dk is the expected token total of domain k, T_k its target, B all tokens, s_k the domain's share
before and w_d = t_d / B.  Each step is one aggregation over all documents, and rates are replayed from the steps' residuals, so
there is no state per document to keep.  Steps go on until the projected gradient is below ``TOLERANCE``.

They need few rounds over the documents as they start near the end: the same steps first run on the documents' sums by cells
of a grid over posteriors, whose number the grid bounds whatever the table's size (``CELLS``).  Where that ends, a rate is
r(p) = 1 - p.g / ridge within its bounds, with g the scaled residuals, and from there the steps over all documents begin.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import spool, tidy

#: Most labelled documents that the classifier is fitted on (about; chosen by a hash of the id).
LABELLED_ROWS = 8_000
LEAST_DOCS = 3
#: Words enter the classifier if their chi-square exceeds this (one in a million by chance).
CHI_SQUARE = 24.0
#: Most cells of the grid over posteriors; steps on them and over all documents, at most.
CELLS = 150_000
CELL_STEPS, STEPS = 5_000, 200
TOLERANCE = 1e-6
RIDGE = 1e-3
DOMAINS = ("good", "plain", "toxic")

_CAPITALS = b"ABCDEFGHIJKLMNOPQRSTUVWXYZ"
_WORD = re.compile(r"[^\W\d_]+")
#: Shape features, each in ten levels, beside the words.
_SHAPES = 5
_LEVELS = 10


def domain_of(quality: Column, toxic: Column) -> Column:
    """Domain of a labelled row; null if unlabelled."""
    return F.when(toxic == 1, "toxic").when(quality == 1, "good").when(quality == 0, "plain")


def shape_levels(text: str) -> list[int]:
    """Which level each shape feature has: shares of upper case, digits, symbols, pipes, and of distinct words."""
    raw, words = text.encode(), text.split()
    n = max(1, len(raw))

    def share(of: bytes) -> float:
        return (len(raw) - len(raw.translate(None, of))) / n

    capital, small = share(_CAPITALS), share(_CAPITALS.lower())
    shares = (capital / max(capital + small, 1 / n), share(b"0123456789"), share(b"#$%&*!@^~<>{}") * 2, share(b"|") * 5, len(set(words)) / max(1, len(words)))
    return [i * _LEVELS + min(_LEVELS - 1, int(s * _LEVELS + (s > 0) * 0.999)) for i, s in enumerate(shares)]


def traits(text: str) -> set[str]:
    """Words of a text, and the first five letters of longer ones, marked."""
    words = set(_WORD.findall(text.lower()))
    return words | {f"{w[:5]}-" for w in words if len(w) > 5}


class Classifier(NamedTuple):
    index: dict[str, int]  # word to row
    weights: np.ndarray  # words, then shape levels, then one row for all
    domains: tuple[str, ...]

    def rows(self, text: str) -> list[int]:
        get, base = self.index.get, len(self.index)
        found = {i for w in traits(text) if (i := get(w)) is not None}
        return [*found, *(base + x for x in shape_levels(text)), len(self.weights) - 1]

    def posterior(self, text: str | None) -> np.ndarray:
        z = self.weights[self.rows(text or "")].sum(axis=0)
        z = np.exp(z - z.max())
        return z / z.sum()


def fit(flat: np.ndarray, owner: np.ndarray, labels: np.ndarray, features: int, classes: int, epochs: int = 40, rate: float = 0.4, sparsity: float = 2e-4) -> np.ndarray:
    """Softmax weights by AdaGrad on all rows at once, with soft thresholds so that words without evidence weigh nothing.  Feature
    ``flat[i]`` is one of row ``owner[i]``'s; owners ascend and each has some."""
    starts = np.concatenate([[0], np.flatnonzero(np.diff(owner)) + 1])
    wanted = np.eye(classes)[labels]
    share = wanted.mean(axis=0)
    weight = (1 / np.maximum(share, 1e-9))[labels]
    weight /= weight.sum()
    w, squares = np.zeros((features, classes)), np.full((features, classes), 1e-8)
    for _ in range(epochs):
        z = np.add.reduceat(w[flat], starts, axis=0)
        p = np.exp(z - z.max(axis=1, keepdims=True))
        p /= p.sum(axis=1, keepdims=True)
        off = (p - wanted) * weight[:, None]
        g = np.stack([np.bincount(flat, weights=off[owner, c], minlength=features) for c in range(classes)], axis=1)
        squares += g**2
        step = rate / np.sqrt(squares)
        w -= step * g
        w[:-1] = np.sign(w[:-1]) * np.maximum(np.abs(w[:-1]) - step[:-1] * sparsity, 0)
    w[-1] += np.log(np.maximum(share, 1e-9)) / 2  # classes weighed alike so far; half way to their shares
    return w


def train(docs: DataFrame, labels: DataFrame, most: int = LABELLED_ROWS) -> Classifier:
    """Classifier from the rows of ``docs`` (doc_id, text) that ``labels`` (doc_id, quality, toxic) covers.  Repeated labels of one
    document are one; if they differ, toxic goes before good and good before plain.  Rows of ``docs`` with one id count each."""
    known = labels.select("doc_id", domain_of(F.col("quality"), F.col("toxic")).alias("domain")).where("doc_id IS NOT NULL AND domain IS NOT NULL")
    known = known.groupBy("doc_id").agg(F.min_by("domain", F.array_position(F.array(*map(F.lit, ("toxic", "good", "plain"))), F.col("domain"))).alias("domain"))
    sizes = {r["domain"]: r["count"] for r in known.groupBy("domain").count().collect()}  # three at most
    chosen = F.lit(False)
    for d, n in sorted(sizes.items()):
        share = min(1_000_000, -(-most * 1_000_000 // (len(sizes) * n)))
        chosen = chosen | ((F.col("domain") == d) & (F.pmod(F.xxhash64("doc_id"), F.lit(1_000_000)) < share))
    sample = known.where(chosen)
    # the sample is bounded by `most`, so it may be broadcast
    joined = docs.select("doc_id", "text").where("text IS NOT NULL").join(F.broadcast(sample), "doc_id").select("domain", "text")

    def words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch["text"].to_pylist()
            own = [sorted(traits(t)) for t in texts]
            yield pa.record_batch([batch["domain"], pa.array(own, pa.list_(pa.string())), pa.array([shape_levels(t) for t in texts], pa.list_(pa.int32()))], names=["domain", "words", "shapes"])

    seen = spool(joined.mapInArrow(tidy(words), "domain string, words array<string>, shapes array<int>"))
    own = {r["domain"]: r["count"] for r in seen.groupBy("domain").count().collect()}  # three at most
    n = float(sum(own.values()))
    counts = seen.select("domain", F.explode("words").alias("w")).groupBy("w").agg(F.count(F.lit(1)).cast("double").alias("n"), *(F.count(F.when(F.col("domain") == d, 1)).cast("double").alias(f"n_{d}") for d in own))

    def chi_square(d: str) -> Column:
        spread = F.col("n") * (n - F.col("n")) * float(own[d]) * (n - own[d])
        return n * F.pow(F.col(f"n_{d}") * n - F.col("n") * float(own[d]), 2) / F.greatest(spread, F.lit(1.0))

    told = counts.where(F.col("n") >= LEAST_DOCS).where(F.greatest(*map(chi_square, own), F.lit(0.0), F.lit(0.0)) > CHI_SQUARE).select("w")
    index = {w: i for i, w in enumerate(sorted(told.toArrow()["w"].to_pylist()))}  # of the sample's words, those that tell domains apart
    base = len(index)
    shared = docs.sparkSession.sparkContext.broadcast(index)

    def ids(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [[*(i for w in ws if (i := shared.value.get(w)) is not None), *(base + x for x in ss), base + _SHAPES * _LEVELS] for ws, ss in zip(batch["words"].to_pylist(), batch["shapes"].to_pylist(), strict=True)]
            yield pa.record_batch([batch["domain"], pa.array(rows, pa.list_(pa.int32()))], names=["domain", "rows"])

    table = seen.mapInArrow(tidy(ids), "domain string, rows array<int>").toArrow()
    if not table.num_rows:
        return Classifier({}, np.zeros((_SHAPES * _LEVELS + 1, len(DOMAINS))), DOMAINS)
    labels_ = np.array([DOMAINS.index(d) for d in table["domain"].to_pylist()])
    rows = table["rows"].combine_chunks()
    owner = np.repeat(np.arange(len(labels_)), np.diff(rows.offsets.to_numpy()))
    weights = fit(rows.flatten().to_numpy().astype(np.int64), owner, labels_, base + _SHAPES * _LEVELS + 1, len(DOMAINS))
    return Classifier(index, weights, DOMAINS)


def posteriors(docs: DataFrame, classifier: Classifier) -> DataFrame:
    """(doc_id, n_tokens, p): words of each row's text and its posterior over the classifier's domains.  A null text is empty
    and has no tokens."""
    shared = docs.sparkSession.sparkContext.broadcast(classifier)

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch["text"].to_pylist()
            p = [shared.value.posterior(t) for t in texts]
            yield pa.record_batch([batch["doc_id"], pa.array([len(t.split()) if t else 0 for t in texts], pa.int64()), pa.array(p, pa.list_(pa.float64()))], names=["doc_id", "n_tokens", "p"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(tidy(each), "doc_id long, n_tokens long, p array<double>")


class Mixture(NamedTuple):
    """Where the steps over all documents began, and their residuals; ``rates`` replays them for any posteriors."""

    start: np.ndarray
    residuals: list[np.ndarray]
    ridge: float
    most: float
    target: np.ndarray
    totals: np.ndarray  # expected token totals at the end; where the targets can't be met, they say by how much
    gradient: float  # norm of the projected gradient at the end

    def rates(self, p: np.ndarray) -> np.ndarray:
        return _replay(p, self.residuals, self.ridge, self.most, self.start)[0]


def _replay(p: np.ndarray, residuals: list[np.ndarray], ridge: float, most: float, start: np.ndarray | float = 0.0) -> tuple[np.ndarray, np.ndarray]:
    """Rates after the steps, and the point where the next residual is taken."""
    r = look = np.clip(1 - p @ np.broadcast_to(start, p.shape[1]) / ridge, 0, most)
    step, t = 1 / (p.shape[1] + ridge), 1.0
    for residual in residuals:
        new = np.clip(look - step * (p @ residual + ridge * (look - 1)), 0, most)
        t_new = (1 + np.sqrt(1 + 4 * t * t)) / 2
        look = new + (t - 1) / t_new * (new - r)
        r, t = new, t_new
    return r, look


def _projected(r: np.ndarray, slope: np.ndarray, most: float) -> np.ndarray:
    """The gradient without what points out of the bounds."""
    return np.where((r <= 0) & (slope > 0) | (r >= most) & (slope < 0), 0.0, slope)


def on_cells(t: np.ndarray, p: np.ndarray, residual, ridge: float, most: float, steps: int = CELL_STEPS) -> np.ndarray:
    """Scaled residuals after the steps over sums by cell (tokens ``t``, mean posterior ``p``), begun anew whenever momentum
    points uphill.  ``residual`` gives them for totals."""
    r = look = np.ones(len(p))
    step, m, share = 1 / (p.shape[1] + ridge), 1.0, t / max(t.sum(), 1.0)
    g = residual((r * t) @ p)
    for _ in range(steps):
        slope = p @ residual((look * t) @ p) + ridge * (look - 1)
        new = np.clip(look - step * slope, 0, most)
        if ((look - new) * (new - r) * share).sum() > 0:
            m = 1.0
        m_new = (1 + np.sqrt(1 + 4 * m * m)) / 2
        look, r, m = new + (m - 1) / m_new * (new - r), new, m_new
        g = residual((r * t) @ p)
        if np.sqrt((share * _projected(r, p @ g + ridge * (r - 1), most) ** 2).sum()) < TOLERANCE / 10:
            break
    return g


def fineness(k: int) -> int:
    """Cells a side of the grid over posteriors of k domains, of which there are at most ``CELLS`` then."""
    m = 512
    while math.comb(m + k - 1, k - 1) > CELLS and m > 1:
        m -= 1
    return m


def solve(found: DataFrame, weights: dict[str, float] | None, domains: tuple[str, ...] = DOMAINS, budget: float | None = None, most: float | None = None, ridge: float = RIDGE, steps: int = STEPS) -> Mixture:
    """Rates for a table (n_tokens, p) that is cheap to read again.  ``weights``: target share of each domain (a missing one: 0),
    scaled to ``budget`` tokens (all there are, if not given); None: the domains' own totals, with nothing of the domain toxic.
    Without ``most`` rates have no upper bound."""
    k, top = len(domains), math.inf if most is None else most
    rows = found.where("n_tokens > 0").select("n_tokens", "p")
    side = fineness(k)
    cell = F.transform(F.slice("p", 1, k - 1), lambda x: F.floor(x * side).cast("int"))
    sums = [F.sum(F.col("n_tokens") * F.col("p")[i]).alias(f"s{i}") for i in range(k)]
    cells = rows.groupBy(cell.alias("c")).agg(F.sum("n_tokens").cast("double").alias("t"), *sums).toArrow()  # CELLS rows at most
    t = cells["t"].to_numpy()
    p = np.stack([cells[f"s{i}"].to_numpy() for i in range(k)], axis=1) / t[:, None]
    before = t @ p
    everything = max(1.0, before.sum())
    if weights is None:
        target = before * [d != "toxic" for d in domains]
    else:
        wanted = np.array([weights.get(d, 0.0) for d in domains])
        target = wanted / wanted.sum() * (budget or everything)
    scale = np.maximum(before / everything, 1e-12)

    def residual(total: np.ndarray) -> np.ndarray:
        return (total - target) / everything / scale

    start = on_cells(t, p, residual, ridge, top)

    def totals(residuals: list[np.ndarray], final: bool, g: np.ndarray | None = None) -> np.ndarray:
        """Expected totals where the next residual is taken (``final``: of the rates themselves); with residuals ``g`` the
        squared projected gradient instead."""

        def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total = np.zeros(k)
            for batch in batches:
                p, n = batch["p"].flatten().to_numpy().reshape(-1, k), batch["n_tokens"].to_numpy()
                r = _replay(p, residuals, ridge, top, start)[0 if final else 1]
                total += (r * n) @ p if g is None else (_projected(r, p @ g + ridge * (r - 1), top) ** 2 * n).sum()
            yield pa.record_batch([pa.array([x]) for x in total], names=[f"s{i}" for i in range(k)])

        out = rows.mapInArrow(tidy(each), ", ".join(f"s{i} double" for i in range(k))).agg(*(F.sum(f"s{i}") for i in range(k))).first()
        return np.array([x or 0.0 for x in out])

    residuals: list[np.ndarray] = []
    while True:
        at_end = totals(residuals, True)
        gradient = float(np.sqrt(totals(residuals, True, residual(at_end))[0] / everything))
        if gradient < TOLERANCE or len(residuals) >= steps:
            return Mixture(start, residuals, ridge, top, target, at_end, gradient)
        for _ in range(5):
            residuals.append(residual(totals(residuals, False)))


def mixed(found: DataFrame, mixture: Mixture) -> DataFrame:
    """``found`` with the column rate."""

    @F.pandas_udf("double")
    def rate(p):
        import pandas as pd

        return pd.Series(mixture.rates(np.stack(p.to_numpy()))) if len(p) else pd.Series([], dtype="float64")

    return found.withColumn("rate", rate("p"))


def copies(rate: Column, doc_id: Column) -> Column:
    """Whole copies of a document: the rate's whole part, and one more with the chance of the rest, by a hash of the id."""
    chance = F.pmod(F.xxhash64(doc_id, F.lit(11)), F.lit(1_000_000)) / 1_000_000.0
    return (F.floor(rate) + F.when(chance < rate - F.floor(rate), 1).otherwise(0)).cast("long")


def op7_soft_membership_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rates that bring good, plain and toxic text to shares of 80, 20 and 0 per cent."""
    docs, labels = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("documents", "labels"))
    found = spool(posteriors(docs, train(docs, labels)))
    out = mixed(found, solve(found, {"good": 0.8, "plain": 0.2}))
    members = [F.col("p")[i].alias(f"p_{d}") for i, d in enumerate(DOMAINS)]
    return out.select("doc_id", "n_tokens", *members, "rate", copies(F.col("rate"), F.col("doc_id")).alias("copies"))
