"""Token ids in fixed-width bit packing.

A *segment* image: magic, bits per id, ids per block, counts; then the start (in ids) of each document, the byte offset of
each block, and the blocks.  Every id takes the fewest bits that the vocabulary needs, most significant bit first, and
each block begins on a byte, so any run of ids is unpacked with numpy from the blocks that hold it.

Images are rows of a Parquet table, as Spark has no sink for raw binary files: every store that Spark writes will do.  A
range of the document ids goes to one partition, sorted; the position of a segment among all ids follows from the ranges'
totals, of which there are at most ``MAX_RANGES``.
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import parts_of, range_bounds, tidy, work_folder
from .encoding import shared_encoder, vocabulary_size

MAGIC = b"FWID"
BLOCK_IDS = 1024
#: Ids in a segment image, at which it is closed (a longer document is in one segment whole).
SEGMENT_IDS = 1 << 20
MAX_RANGES = 20_000
_HEAD = struct.Struct("<4sHHQQQ")


def bits_for(vocabulary: int) -> int:
    """Fewest bits that tell ``vocabulary`` ids apart."""
    return max(1, (vocabulary - 1).bit_length())


def _pack(ids: np.ndarray, bits: int) -> bytes:
    if bits == 16:
        return ids.astype(">u2").tobytes()
    shifts = np.arange(bits - 1, -1, -1, dtype=np.uint32)
    return np.packbits(((ids.astype(np.uint32)[:, None] >> shifts) & 1).astype(np.uint8).ravel()).tobytes()


def _unpack(raw: memoryview | bytes, n: int, bits: int) -> np.ndarray:
    if bits == 16:
        return np.frombuffer(raw, dtype=">u2", count=n).astype("<u4")
    flags = np.unpackbits(np.frombuffer(raw, dtype=np.uint8), count=n * bits).reshape(n, bits)
    weights = (1 << np.arange(bits - 1, -1, -1, dtype=np.int64)).astype(np.float64)
    return (flags @ weights).astype("<u4")


def _image(starts: np.ndarray, blocks: list[bytes] | bytes, bits: int) -> bytes:
    n = int(starts[-1])
    whole = BLOCK_IDS * bits // 8  # bytes of a full block; only the last may be shorter
    offsets = np.minimum(np.arange(-(-n // BLOCK_IDS) + 1, dtype=np.int64) * whole, -(-n * bits // 8)).astype("<u8")
    head = _HEAD.pack(MAGIC, bits, BLOCK_IDS, len(starts) - 1, n, len(offsets) - 1)
    return b"".join([head, starts.astype("<u8").tobytes(), offsets.tobytes(), *blocks])


def pack_segment(documents: list[np.ndarray], bits: int) -> bytes:
    """Image of some documents' ids, in order."""
    starts = np.concatenate([[0], np.cumsum([len(d) for d in documents])])
    ids = np.concatenate(documents) if documents else np.zeros(0, dtype=np.uint32)
    if len(ids) and int(ids.max()) >> bits:
        raise ValueError(f"an id needs more than {bits} bits")
    return _image(starts, [_pack(ids, bits)], bits)  # a full block ends on a byte, so all are packed at once


def join_packed(held: list[bytes | memoryview], sizes: list[int], bits: int) -> bytes:
    """The image of documents that are packed one by one: whole bytes an id need no unpacking."""
    if bits % 8:
        return pack_segment([_unpack(x, n, bits) for x, n in zip(held, sizes, strict=True)], bits)
    return _image(np.concatenate([[0], np.cumsum(sizes)]), held, bits)


class Segment:
    """Reads an image; ``ids(start, stop)`` touches only the blocks it needs."""

    def __init__(self, image: bytes) -> None:
        magic, self.bits, self.block, self.documents, self.n_ids, blocks = _HEAD.unpack_from(image)
        if magic != MAGIC:
            raise ValueError("not a segment of packed ids")
        self.starts = np.frombuffer(image, dtype="<u8", count=self.documents + 1, offset=_HEAD.size)
        at = _HEAD.size + self.starts.nbytes
        self.offsets = np.frombuffer(image, dtype="<u8", count=blocks + 1, offset=at)
        self._data = memoryview(image)[at + self.offsets.nbytes :]

    def ids(self, start: int, stop: int) -> np.ndarray:
        if not 0 <= start <= stop <= self.n_ids:
            raise IndexError(f"ids {start} to {stop} of {self.n_ids}")
        first, last = start // self.block, -(-stop // self.block)
        parts = [_unpack(self._data[int(self.offsets[b]) : int(self.offsets[b + 1])], min(self.block, self.n_ids - b * self.block), self.bits) for b in range(first, last)]
        found = np.concatenate(parts) if parts else np.zeros(0, dtype="<u4")
        return found[start - first * self.block : stop - first * self.block]

    def document(self, i: int) -> np.ndarray:
        return self.ids(int(self.starts[i]), int(self.starts[i + 1]))

    def all(self) -> np.ndarray:
        if self.n_ids and (self.block * self.bits) % 8 == 0:  # no padding between blocks: one call
            return _unpack(self._data[: int(self.offsets[-1])], self.n_ids, self.bits)
        return self.ids(0, self.n_ids)


def write_packed(docs: DataFrame, path: str, end_id: int, vocabulary: str | None = None, doc_id: str = "doc_id", text: str = "text") -> None:
    """Encode every whole text, end each document with ``end_id`` and write segments in ascending order of ``doc_id``.

    Null texts are empty; null ids come first; rows of one id keep a fixed order (by their ids' bytes).  Columns other
    than the two named are not read.  An empty table gives an empty table of segments.
    """
    bits = bits_for(max(vocabulary_size(vocabulary), end_id + 1))
    docs = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text"))
    parts = max(parts_of(docs), int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    bounds = np.array(range_bounds(docs, "doc_id", min(parts, MAX_RANGES)), dtype=np.int64)

    def encoded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = shared_encoder(vocabulary)
        for batch in batches:
            for first, stop in encoder.runs(batch["text"]):
                own = batch["doc_id"].slice(first, stop - first)
                flat, at = encoder.encode_run(batch["text"].slice(first, stop - first), end_id)
                if bits % 8:
                    held = pa.array([_pack(flat[a:b], bits) for a, b in zip(at.tolist(), at[1:].tolist())], pa.large_binary())
                else:
                    held = pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(own), [None, pa.py_buffer((at * (bits // 8)).astype(np.int64)), pa.py_buffer(_pack(flat, bits))])
                part = np.searchsorted(bounds, own.fill_null(-(2**63)).to_numpy(zero_copy_only=False), side="right")
                yield pa.record_batch([pa.array(part.astype(np.int32)), own, pa.array(np.diff(at)), held.cast(pa.binary())], names=["id_range", "doc_id", "n", "held"])

    def segments(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["id_range", "number", "first_id", "n_ids", "doc_ids", "image"]
        kinds = [pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.int64()), pa.binary()]
        now, number, before, n = None, 0, 0, 0
        docs_: list[int | None] = []
        held_: list[memoryview] = []
        sizes: list[int] = []

        def image() -> pa.RecordBatch:
            values = [[now], [number], [before], [n], [docs_], [join_packed(held_, sizes, bits)]]
            return pa.record_batch([pa.array(v, k) for v, k in zip(values, kinds, strict=True)], names=names)

        for batch in batches:
            held = batch["held"].cast(pa.large_binary())
            ends = np.frombuffer(held.buffers()[1], dtype=np.int64)[held.offset : held.offset + len(held) + 1].tolist()
            raw = memoryview(held.buffers()[2] or b"")
            for i, (r, d, k) in enumerate(zip(batch["id_range"].to_pylist(), batch["doc_id"].to_pylist(), batch["n"].to_pylist(), strict=True)):
                if docs_ and (r != now or n >= SEGMENT_IDS):
                    yield image()
                    before, number, docs_, held_, sizes, n = before + n, number + 1, [], [], [], 0
                if r != now:
                    now, number, before = r, 0, 0
                docs_.append(d)
                held_.append(raw[ends[i] : ends[i + 1]])
                sizes.append(k)
                n += k
        if docs_:
            yield image()

    rows = docs.mapInArrow(tidy(encoded), "id_range int, doc_id long, n long, held binary")
    placed = rows.repartitionById(max(1, len(bounds) + 1), "id_range").sortWithinPartitions("id_range", "doc_id", "held")
    images = placed.mapInArrow(tidy(segments), "id_range int, number long, first_id long, n_ids long, doc_ids array<long>, image binary")
    images.write.option("compression", "none").parquet(path)


def _documents(spark: SparkSession, path: str, digest: bool) -> DataFrame:
    totals = {r.id_range: r.n for r in spark.read.parquet(path).groupBy("id_range").agg(F.sum("n_ids").alias("n")).collect()}  # MAX_RANGES rows at most
    base, at = {}, 0
    for r in sorted(totals):
        base[r], at = at, at + totals[r]
    last = ("ids_crc32", pa.int64()) if digest else ("ids", pa.binary())

    def documents(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):
                segment = Segment(batch["image"][i].as_buffer())
                flat, starts = memoryview(segment.all()).cast("B"), segment.starts.astype(np.int64)
                first = base[batch["id_range"][i].as_py()] + batch["first_id"][i].as_py()
                cuts = (starts * 4).tolist()
                own = [zlib.crc32(flat[a:b]) if digest else bytes(flat[a:b]) for a, b in zip(cuts, cuts[1:])]
                yield pa.record_batch([batch["doc_ids"][i].values, pa.array(first + starts[:-1]), pa.array(np.diff(starts)), pa.array(own, last[1])], names=["doc_id", "start", "n_tokens", last[0]])

    images = spark.read.parquet(path).select("id_range", "first_id", "doc_ids", "image")
    return images.mapInArrow(tidy(documents), f"doc_id long, start long, n_tokens long, {last[0]} {'long' if digest else 'binary'}")


def read_packed(spark: SparkSession, path: str) -> DataFrame:
    """Documents of packed segments: doc_id, start (ids of all documents before it), n_tokens, ids (unsigned 32-bit,
    little-endian bytes)."""
    return _documents(spark, path, digest=False)


def packed_digest(spark: SparkSession, path: str) -> DataFrame:
    """Per document of packed segments: doc_id, start, n_tokens and the crc32 of its ids, read back."""
    return _documents(spark, path, digest=True)


def op8_packed_token_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document encoded, written as packed segments and read back."""
    path = work_folder(spark)
    write_packed(spark.read.parquet(f"{sf_dir}/documents.parquet"), path, end_id=2)
    return packed_digest(spark, path)
