"""Packing of documents into sequences by the sum-of-squares rule.

N(g) is the number of open sequences with gap g.  A piece of s tokens goes where the sum of N(g)^2 over all gaps becomes
smallest: into a sequence with some gap g >= s (N(g) loses one, N(g - s) gains one unless it is filled), or into a new one
if no open sequence has room (opening one earlier, to spread the gaps, cost 0.3 to 1.2 % more sequences on trial lengths).
Sequences of one gap are alike, so the state is one count and one stack per gap, whatever the number of pieces.

Pieces are dealt evenly to shards of about ``SHARD_DOCS`` documents, each packed on its own from the longest piece to the
shortest; a shard leaves about one sequence unfilled, so the loss is a fixed share of a shard, not of the table.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import tidy
from .encoding import MEMO_CHUNKS, shared_encoder

CAPACITY = 2048
SHARD_DOCS = 16_384


def sum_of_squares(lengths: np.ndarray, capacity: int = CAPACITY) -> tuple[np.ndarray, np.ndarray, int]:
    """Sequence and offset of each piece (1 to ``capacity`` tokens), and the number of sequences."""
    lengths = np.asarray(lengths, dtype=np.int64)
    if len(lengths) and (lengths.min() < 1 or lengths.max() > capacity):
        raise ValueError("a piece must have from 1 to capacity tokens")
    bins, offsets = np.empty(len(lengths), dtype=np.int64), np.zeros(len(lengths), dtype=np.int64)
    full = lengths == capacity
    made = int(full.sum())
    bins[full] = np.arange(made)
    open_by_gap: list[list[int]] = [[] for _ in range(capacity + 1)]
    count = np.zeros(capacity + 1, dtype=np.int64)
    order = np.argsort(-lengths, kind="stable")
    for i in order[made:].tolist():
        s = int(lengths[i])
        # change of the sum for each gap g from s to capacity; a filled sequence is no longer open
        change = 2 * (count[: capacity + 1 - s] - count[s:]) + 2
        change[0] -= 2 * count[0] + 1
        change[count[s:] == 0] = np.iinfo(np.int64).max
        at = int(change.argmin())
        if open_by_gap[at + s]:
            b = open_by_gap[at + s].pop()
            count[at + s] -= 1
            offsets[i] = capacity - at - s
        else:
            b, at, made = made, capacity - s, made + 1
        bins[i] = b
        if at:
            open_by_gap[at].append(b)
            count[at] += 1
    return bins, offsets, made


def cuts(sizes: np.ndarray, capacity: int = CAPACITY) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Document, piece, start and length of all pieces of some documents: only a longer document is cut, its first piece takes
    the remainder."""
    pieces = -(-sizes // capacity)
    of = np.repeat(np.arange(len(sizes)), pieces)
    piece = np.arange(len(of)) - np.repeat(np.cumsum(pieces) - pieces, pieces)
    lead = (sizes - (pieces - 1) * capacity)[of]
    return of, piece, np.where(piece > 0, lead + (piece - 1) * capacity, 0), np.where(piece > 0, capacity, lead)


def cut(n: int, capacity: int = CAPACITY) -> list[tuple[int, int]]:
    """(start, length) of one document's pieces."""
    _, _, start, length = cuts(np.array([n]), capacity)
    return list(zip(start.tolist(), length.tolist(), strict=True))


def token_pieces(docs: DataFrame, end_id: int = 0, capacity: int = CAPACITY, vocabulary: str | None = None, keep_ids: bool = False, doc_id: str = "doc_id", text: str = "text", memo_chunks: int = MEMO_CHUNKS) -> DataFrame:
    """Pieces of every whole text, encoded and ended by ``end_id``: doc_id, piece, start, length, ids_crc32, and their ids
    as unsigned 32-bit little-endian bytes if ``keep_ids``.  Null texts are empty; other columns aren't read."""
    schema = "doc_id long, piece int, start long, length long, ids_crc32 long" + ", ids binary" * keep_ids

    names = ["doc_id", "piece", "start", "length", "ids_crc32", "ids"][: 5 + keep_ids]

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = shared_encoder(vocabulary, memo_chunks)
        for batch in batches:
            for first, stop in encoder.runs(batch["text"]):
                flat, at = encoder.encode_run(batch["text"].slice(first, stop - first), end_id)
                of, piece, start, length = cuts(np.diff(at), capacity)
                raw, begin = memoryview(flat).cast("B"), ((at[:-1][of] + start) * 4).tolist()
                own = [raw[x : x + n] for x, n in zip(begin, (length * 4).tolist(), strict=True)]
                columns = [batch["doc_id"].slice(first, stop - first).take(pa.array(of)), pa.array(piece, pa.int32()), pa.array(start), pa.array(length), pa.array([zlib.crc32(x) for x in own], pa.int64())]
                yield pa.record_batch(columns + ([pa.array([bytes(x) for x in own], pa.binary())] if keep_ids else []), names=names)

    return docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text")).mapInArrow(tidy(each), schema)


def pack(pieces: DataFrame, shards: int, capacity: int = CAPACITY) -> DataFrame:
    """``pieces`` (with a long column length) and where each goes: sequence_id and offset, gapless from 0."""
    schema = f"{', '.join(f'`{f.name}` {f.dataType.simpleString()}' for f in pieces.schema)}, sequence_id long, offset long"

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = list(batches)
        if not held:
            return
        table = pa.Table.from_batches(held).combine_chunks()
        bins, offsets, _ = sum_of_squares(table["length"].to_numpy(), capacity)
        ids = bins + (TaskContext.get().partitionId() << 40)
        yield from table.append_column("sequence_id", pa.array(ids)).append_column("offset", pa.array(offsets)).to_batches()

    return pieces.repartition(shards).mapInArrow(tidy(each), schema)


def shards_for(docs: DataFrame, shard_docs: int = SHARD_DOCS) -> int:
    return max(1, -(-docs.select(F.lit(1)).count() // shard_docs))


def packed_sequences(docs: DataFrame, end_id: int = 0, capacity: int = CAPACITY, vocabulary: str | None = None) -> DataFrame:
    """Real sequences: sequence_id, n_tokens, ids (bytes as in ``token_pieces``) and the documents of its pieces in order.
    A sequence has at most ``capacity`` ids, which bounds what a group holds."""
    placed = pack(token_pieces(docs, end_id, capacity, vocabulary, keep_ids=True), shards_for(docs), capacity)
    parts = F.sort_array(F.collect_list(F.struct("offset", "doc_id", "piece", "length", "ids")))
    whole = placed.groupBy("sequence_id").agg(parts.alias("p"))
    return whole.select("sequence_id", F.aggregate("p", F.lit(0).cast("long"), lambda a, x: a + x["length"]).alias("n_tokens"), F.aggregate("p", F.lit(b""), lambda a, x: F.concat(a, x["ids"])).alias("ids"), F.transform("p", lambda x: F.struct(x["doc_id"], x["piece"], x["offset"])).alias("pieces"))


def pack_documents(docs: DataFrame, end_id: int = 0, capacity: int = CAPACITY, vocabulary: str | None = None, memo_chunks: int = MEMO_CHUNKS) -> DataFrame:
    """Every document's pieces with their places.  An empty table gives an empty result; repeated rows are packed as often
    as they come."""
    return pack(token_pieces(docs, end_id, capacity, vocabulary, memo_chunks=memo_chunks), shards_for(docs), capacity)


def op1_sum_of_squares_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents in sequences of at most 2048 tokens."""
    return pack_documents(spark.read.parquet(f"{sf_dir}/documents.parquet"))
