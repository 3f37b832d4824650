"""Document fingerprints from improbable features.

A feature is a window of ``WINDOW`` bytes.  Its precedence follows from how rare its Shannon entropy is among windows of
prose: the commoner, the later.  Of every ``WINDOW`` windows in a row the first of lowest precedence gets a point; windows with
``LEAST_POINTS`` points are selected.  Selected features go, in order and once each, into a chain of Bloom filters of 256 bytes
and at most ``PER_FILTER`` features.  Likeness of two filters is their common bits beyond those expected of chance, relative to
the most they could share; likeness of two digests the mean, over the filters of the smaller, of the best match in the other.

All windows of a run of texts are ranked together in numpy: sums of c log c move from window to window by two look-ups, in
whole numbers, so equal windows rank equally wherever they stand.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import parts_of, range_bounds, tidy

WINDOW = 32
MOST_BITS = 5  # log2 of WINDOW
LEAST_POINTS = 8
SHORT_WINDOW, SHORT_TEXT = 8, 4 * WINDOW
#: A text with fewer selected windows takes all that have a point.
FEW = 6
PER_FILTER = 160
FILTER_BYTES = 256
HASHES = 5
RUN_BYTES = 200_000  # texts ranked together; positions must fit 18 bits with a longer text cut into overlapping runs
MAX_RANGES = 20_000
#: Entropy (bits) at which windows of prose are commonest, and the spread of that: the rule for rarity.
COMMON_ENTROPY, SPREAD = 3.5, 0.3
LEVELS = 1000

_SCALE = 1 << 16
_C_LOG_C = np.array([0, *(round(c * np.log2(c) * _SCALE) for c in range(1, WINDOW + 1))], dtype=np.int32)
_LEAVE = _C_LOG_C - np.concatenate([[0], _C_LOG_C[:-1]])  # what a count's last occurrence adds


def precedence() -> np.ndarray:
    """Rank (0 to 1000, low first) of each of ``LEVELS`` + 1 entropy levels from 0 to MOST_BITS: by rarity; windows of hardly
    any content come last."""
    bits = np.arange(LEVELS + 1) * MOST_BITS / LEVELS
    ranks = np.round(1 + 998 * np.exp(-(((bits - COMMON_ENTROPY) / SPREAD) ** 2) / 2))
    return np.where(bits < 1.5, LEVELS, ranks).astype(np.int32)


_PRECEDENCE = precedence()


class Digest(NamedTuple):
    filters: np.ndarray  # (k, FILTER_BYTES) of uint8
    sizes: tuple[int, ...]

    def __str__(self) -> str:
        return f"{len(self.sizes)}:{','.join(map(str, self.sizes))}:{base64.b64encode(self.filters.tobytes()).decode()}"


def parse_digest(text: str) -> Digest:
    _, sizes, raw = text.split(":")
    return Digest(np.frombuffer(base64.b64decode(raw), dtype=np.uint8).reshape(-1, FILTER_BYTES), tuple(map(int, filter(None, sizes.split(",")))))


def window_ranks(data: np.ndarray) -> np.ndarray:
    """Precedence of each window of the bytes."""
    n = len(data)
    ahead, behind = np.zeros(n, dtype=np.uint8), np.zeros(n, dtype=np.uint8)
    same = np.empty(n, dtype=bool)
    for d in range(1, WINDOW):
        e = np.equal(data[d:], data[:-d], out=same[: n - d]).view(np.uint8)
        np.add(ahead[: n - d], e, out=ahead[: n - d])
        np.add(behind[d:], e, out=behind[d:])
    counts = np.bincount(data[:WINDOW], minlength=256)
    change = np.empty(n - WINDOW + 1, dtype=np.int32)
    change[0] = _C_LOG_C[counts].sum()
    change[1:] = _LEAVE[1:][behind[WINDOW:]]  # the byte that enters
    change[1:] -= _LEAVE[1:][ahead[: n - WINDOW]]  # the byte that leaves
    total = np.cumsum(change, dtype=np.int32)
    return _PRECEDENCE[(LEVELS - total.astype(np.int64) * LEVELS // (MOST_BITS * WINDOW * _SCALE)).clip(0, LEVELS)]


def _selected(ranks: np.ndarray, starts: np.ndarray, windows: np.ndarray) -> np.ndarray:
    """Chosen positions among ranked windows, for texts whose windows begin at ``starts``."""
    n = len(ranks)
    key = (ranks.astype(np.int32) << 18) | np.arange(n, dtype=np.int32)
    least, width = key, 1
    while width < WINDOW and len(least) > width:
        least = np.minimum(least[:-width], least[width:])
        width *= 2
    points = np.zeros(n, dtype=np.int32)
    if width == WINDOW:
        inside = np.zeros(len(least) + 1, dtype=np.int32)
        full = windows >= WINDOW
        np.add.at(inside, starts[full], 1)
        np.add.at(inside, starts[full] + windows[full] - WINDOW + 1, -1)
        rows = np.cumsum(inside[:-1]) > 0
        points = np.bincount(least[rows] & 0x3FFFF, minlength=n)
    chosen = points >= LEAST_POINTS
    before = np.concatenate([[0], np.cumsum(chosen)])
    for s, w in zip(starts.tolist(), windows.tolist(), strict=True):
        if w > 0 and before[s + w] - before[s] < FEW:  # a text with few windows, or few that stand out
            chosen[s : s + w] |= points[s : s + w] > 0
            chosen[s + int(key[s : s + w].argmin())] = True
    return np.flatnonzero(chosen)


def _hashed(features: np.ndarray) -> np.ndarray:
    """64-bit hashes of rows of WINDOW bytes."""
    words = np.ascontiguousarray(features).view("<u8")
    h = np.full(len(words), 0x9E3779B97F4A7C15, dtype=np.uint64)
    for i in range(words.shape[1]):
        h ^= words[:, i]
        h *= np.uint64(0xFF51AFD7ED558CCD)
        h ^= h >> np.uint64(32)
        h *= np.uint64(0xC4CEB9FE1A85EC53)
        h ^= h >> np.uint64(29)
    return h


def _chained(hashes: np.ndarray) -> Digest:
    _, first = np.unique(hashes, return_index=True)
    own = hashes[np.sort(first)]
    k = -(-len(own) // PER_FILTER)
    bits = np.zeros((k, FILTER_BYTES * 8), dtype=np.uint8)
    which = np.arange(len(own)) // PER_FILTER
    for i in range(HASHES):
        bits[which, ((own >> np.uint64(11 * i)) & np.uint64(FILTER_BYTES * 8 - 1)).astype(np.int64)] = 1
    return Digest(np.packbits(bits, axis=1), tuple(np.bincount(which, minlength=k).tolist()))


def digests(texts: list[bytes]) -> list[Digest]:
    """Digests of texts.  A text of fewer than SHORT_TEXT bytes has short windows for features, an empty one none."""
    out: list[Digest | None] = [None] * len(texts)
    run: list[int] = []
    size = 0

    def rank_run() -> None:
        data = np.frombuffer(b"".join(texts[i] for i in run), dtype=np.uint8)
        lengths = np.array([len(texts[i]) for i in run])
        starts = np.cumsum(lengths) - lengths
        chosen = _selected(window_ranks(data), starts, lengths - WINDOW + 1)
        hashes = _hashed(data[chosen[:, None] + np.arange(WINDOW)])
        cuts = np.searchsorted(chosen, [*starts.tolist(), len(data)])
        for j, i in enumerate(run):
            out[i] = _chained(hashes[cuts[j] : cuts[j + 1]])

    for i, text in enumerate(texts):
        if len(text) < SHORT_TEXT:
            out[i] = _short(text)
        elif len(text) > RUN_BYTES:
            out[i] = _long(text)
        else:
            if size + len(text) > RUN_BYTES:
                rank_run()
                run, size = [], 0
            run.append(i)
            size += len(text)
    if run:
        rank_run()
    return out


def _short(text: bytes) -> Digest:
    """Every window of SHORT_WINDOW bytes of a text that has no room for the others."""
    if not text:
        return _chained(np.zeros(0, dtype=np.uint64))
    own = [text[i : i + SHORT_WINDOW] for i in range(max(1, len(text) - SHORT_WINDOW + 1))]
    return _chained(_hashed(np.frombuffer(b"".join(x.ljust(WINDOW, b"\0") for x in own), dtype=np.uint8).reshape(-1, WINDOW)))


def _long(text: bytes) -> Digest:
    """A text of any length in overlapping runs; every position's points are counted once."""
    data = np.frombuffer(text, dtype=np.uint8)
    step = RUN_BYTES - 2 * WINDOW
    points = np.zeros(len(data), dtype=np.int32)
    for at in range(0, len(data) - WINDOW + 1, step):
        ranks = window_ranks(data[at : at + step + 2 * WINDOW - 2])
        key = (ranks.astype(np.int32) << 18) | np.arange(len(ranks), dtype=np.int32)
        width = 1
        while width < WINDOW and len(key) > width:
            key = np.minimum(key[:-width], key[width:])
            width *= 2
        if width == WINDOW:
            np.add.at(points, at + (key[:step] & 0x3FFFF), 1)
    chosen = np.flatnonzero(points >= LEAST_POINTS)
    if len(chosen) < FEW:
        chosen = np.flatnonzero(points)
    return _chained(_hashed(data[chosen[:, None] + np.arange(WINDOW)]))


def likeness(a: Digest, b: Digest) -> float:
    """From 0 (no more in common than by chance) to 1; equal digests, empty ones too, are alike in full."""
    if a.sizes == b.sizes and np.array_equal(a.filters, b.filters):
        return 1.0
    if not a.sizes or not b.sizes:
        return 0.0
    if (len(a.sizes), sum(a.sizes), a.filters.tobytes()) > (len(b.sizes), sum(b.sizes), b.filters.tobytes()):
        a, b = b, a
    in_a, in_b = (np.bitwise_count(x.filters).sum(axis=1, dtype=np.int64)[:, None] for x in (a, b))
    best = np.zeros(len(a.sizes))
    for i, own in enumerate(a.filters):
        common = np.bitwise_count(own & b.filters).sum(axis=1, dtype=np.int64)
        chance = in_a[i] * in_b[:, 0] / (FILTER_BYTES * 8)
        most = np.minimum(in_a[i], in_b[:, 0])
        best[i] = ((common - chance) / np.maximum(most - chance, 1e-9)).max()
    return float(np.clip(best, 0, 1) @ np.array(a.sizes) / sum(a.sizes))


def edited(text: str, following: str) -> str:
    """The text with its last half (rounded down) replaced by the first as many code points of another, or all."""
    half = len(text) // 2
    return text[: len(text) - half] + following[:half]


def fingerprint_pairs(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """Per row: doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next; the next row is that
    of the next doc_id (a null id comes first, rows of one id are ordered by text), the first one's after the last.

    Ranges of ids go to one partition each; the first rows of a range also go, as a look-ahead, to the range before.  Null
    texts are empty.  A single row is its own next.  Other columns aren't read.
    """
    lowest = -(2**63)
    rows = docs.select(F.coalesce(F.col(doc_id).cast("long"), F.lit(lowest)).alias("o"), F.col(doc_id).cast("long").alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    parts = max(parts_of(docs), int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    ids = docs.select(F.coalesce(F.col(doc_id).cast("long"), F.lit(lowest)).alias("o"))
    first = ids.agg(F.min("o").alias("m")).first().m
    bounds = np.array([b for b in range_bounds(ids, "o", min(parts, MAX_RANGES)) if first is not None and b > first], dtype=np.int64)
    ranges = len(bounds) + 1
    heads = np.concatenate([[first if first is not None else 0], bounds]).astype(np.int64)

    @F.pandas_udf("array<int>")
    def places(o):
        import pandas as pd

        own = np.searchsorted(bounds, o.to_numpy(), side="right")
        return pd.Series([[r, (r - 1) % ranges] if v == heads[r] else [r] for r, v in zip(own.tolist(), o.tolist(), strict=True)])

    def described(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"]
        kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64()]

        def out(held: list[tuple[int, str]], known: Digest | None) -> tuple[pa.RecordBatch, Digest]:
            """Rows for all but the last, which is only their next; and the digest of that."""
            texts = [t for _, t in held]
            changed = [edited(a, b).encode() for a, b in zip(texts, texts[1:])]
            found = digests([t.encode() for t in texts[known is not None :]] + changed)
            cut = len(found) - len(changed)
            own, new = [known, *found[:cut]] if known is not None else found[:cut], found[cut:]
            values = [
                [d for d, _ in held[:-1]], [len(t) for t in texts[:-1]], [hashlib.sha256(c).hexdigest() for c in changed],
                list(map(str, own[:-1])), list(map(str, new)), list(map(likeness, own, new)), list(map(likeness, own, own[1:])),
            ]
            return pa.record_batch([pa.array(v, k) for v, k in zip(values, kinds, strict=True)], names=names), own[-1]

        held: list[tuple[int, str]] = []
        known, size, now, ahead = None, 0, None, False
        for batch in batches:
            for r, look, d, t in zip(*(batch[c] for c in ("r", "look", "doc_id", "text")), strict=True):
                r, look = r.as_py(), look.as_py()
                if r != now:
                    held, known, size, now, ahead = [], None, 0, r, False
                if ahead:
                    continue  # only the first row of the look-ahead counts
                held.append((d.as_py(), t.as_py()))
                size += len(held[-1][1])
                ahead = look
                if len(held) > 1 and (look or size > 2_000_000):
                    made, known = out(held, known)
                    yield made
                    held, size = held[-1:], len(held[-1][1])

    dealt = rows.withColumn("places", places("o")).select("o", "doc_id", "text", F.posexplode("places").alias("p", "r")).select("r", (F.col("p") == 1).alias("look"), "o", "doc_id", "text")
    sorted_rows = dealt.repartitionById(ranges, "r").sortWithinPartitions("r", "look", "o", "text").drop("o")
    return sorted_rows.mapInArrow(tidy(described), "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double")


def op3_improbable_feature_digest(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fingerprints of every document and its edited text, with their likeness."""
    return fingerprint_pairs(spark.read.parquet(f"{sf_dir}/documents.parquet"))
