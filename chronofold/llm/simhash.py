"""SimHash near-duplicates by covering locality-sensitive hashing.

A fingerprint's 64 bits get vectors of r + 1 bits, none of them zero; mask v (one per nonzero vector) keeps the bits whose
vector has an odd number of ones in common with v.  Up to r differing bits span at most r dimensions, so some v is
orthogonal to all of them: its mask drops every differing bit, and the pair meets in its table.  No pair within the radius
is lost.

Equal fingerprints are one node from the start, so a group of copies costs one row.  A bucket of at most ``BUCKET`` nodes is
compared pair by pair and leaves a spanning forest.  In a larger one every node is dealt again, to itself and to each
neighbour one bit away outside the mask: two fingerprints are within 2 of each other just if they share such a point,
and a point has at most 65 of them.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import part_of, spool, spread_join, tidy
from .components import component_roots

BITS = 64
#: Most nodes of a bucket that are compared pair by pair; larger buckets are dealt again, without loss.
BUCKET = 64


def covering_masks(radius: int) -> list[int]:
    """2^(radius+1) - 1 masks as unsigned 64-bit integers."""
    vectors = [1 + i % ((2 << radius) - 1) for i in range(BITS)]
    return [sum(1 << i for i, m in enumerate(vectors) if (m & v).bit_count() & 1) for v in range(1, 2 << radius)]


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def majority(hashes: np.ndarray) -> bytes:
    """Bits, the most significant first, that are set in over half of some unsigned 64-bit hashes."""
    total = np.zeros(BITS, dtype=np.int64)
    for at in range(0, len(hashes), 100_000):
        total += np.unpackbits(hashes[at : at + 100_000].astype(">u8").view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
    return np.packbits(total * 2 > len(hashes)).tobytes()


def shingle_hashes(words: list[bytes], shingle: int, seed: int) -> np.ndarray:
    """XXH64 of every shingle, repeats included; of the whole sequence if that is shorter."""
    import xxhash

    shingles = map(b" ".join, zip(*(words[i:] for i in range(shingle)))) if len(words) >= shingle else [b" ".join(words)]
    return np.fromiter(map(xxhash.xxh64_intdigest, shingles, repeat(seed)), dtype=np.uint64)


def simhash(text: str | None, shingle: int = 3, seed: int = 42) -> bytes:
    """Fingerprint, most significant byte first; all zero for a text without words."""
    words = (text or "").encode().lower().split()  # of bytes: A-Z only, and at ASCII white space only
    return majority(shingle_hashes(words, shingle, seed)) if words else bytes(8)


def fingerprints(docs: DataFrame, shingle: int = 3, seed: int = 42, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, fingerprint as a long) of every row; null texts count as empty.  Other columns aren't read."""

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = b"".join(simhash(x.as_py(), shingle, seed) for x in batch["text"])
            yield pa.record_batch([batch["doc_id"], pa.array(np.frombuffer(found, dtype=">u8").astype(np.uint64).view(np.int64))], names=["doc_id", "fingerprint"])

    return docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text")).mapInArrow(tidy(each), "doc_id long, fingerprint long")


def _spanning(radius: int):
    """For a group of nodes: edges that connect what pairs within the radius connect."""

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            low: list[int] = []
            high: list[int] = []
            for i in range(batch.num_rows):
                members = batch["members"][i].values
                nodes = members.field("node").to_numpy()
                bits = members.field("fingerprint").to_numpy().view(np.uint64)
                order = np.argsort(nodes)
                nodes, bits = nodes[order], bits[order]
                near = np.bitwise_count(bits[:, None] ^ bits[None, :]) <= radius
                todo = np.ones(len(nodes), dtype=bool)
                for root in range(len(nodes)):
                    if not todo[root]:
                        continue
                    todo[root] = False
                    reach = near[root] & todo
                    while reach.any():
                        todo &= ~reach
                        fresh = np.flatnonzero(reach)
                        low += [int(nodes[root])] * len(fresh)
                        high += nodes[fresh].tolist()
                        reach = near[fresh].any(axis=0) & todo
            yield pa.record_batch([pa.array(low, pa.int64()), pa.array(high, pa.int64())], names=["low", "high"])

    return each


def near_edges(nodes: DataFrame, radius: int = 2) -> DataFrame:
    """Edges (low, high) between the nodes of a table (node, fingerprint) of distinct fingerprints: they connect exactly
    what the pairs at ``radius`` or fewer differing bits connect."""
    if not 0 <= radius <= 2:
        raise ValueError("covering masks are built for radii from 0 to 2")
    masks = covering_masks(radius)
    tables = F.array(*[F.struct(F.lit(t).alias("t"), F.lit(_signed(m)).alias("mask")) for t, m in enumerate(masks)])
    dealt = nodes.select("node", "fingerprint", F.explode(tables).alias("k")).select("node", "fingerprint", F.col("k.t").alias("t"), F.col("k.mask").alias("mask"), F.col("fingerprint").bitwiseAND(F.col("k.mask")).alias("bucket"))
    # counted by part of a bucket first, and joined by part, so that no bucket is in one task
    parts = dealt.groupBy("t", "bucket", part_of("node").alias("part")).agg(F.count(F.lit(1)).alias("n"))
    sizes = parts.groupBy("t", "bucket").agg(F.sum("n").alias("size"), F.collect_list("part").alias("parts")).where("size > 1")
    sizes = sizes.select("t", "bucket", "size", F.explode("parts").alias("part"))
    met = dealt.withColumn("part", part_of("node")).join(sizes, ["t", "bucket", "part"])
    points = F.transform(
        F.filter(F.array(F.lit(0), *[F.lit(_signed(1 << i)) for i in range(BITS)]), lambda b: b.bitwiseAND(F.col("mask")) == 0),
        lambda b: F.col("fingerprint").bitwiseXOR(b),
    )
    groups = met.select("node", "fingerprint", "t", "bucket", F.explode(F.when(F.col("size") > BUCKET, points).otherwise(F.array(F.lit(0).cast("long")))).alias("point"), (F.col("size") > BUCKET).alias("large"))
    groups = groups.groupBy("t", "bucket", "large", "point").agg(F.collect_list(F.struct("node", "fingerprint")).alias("members")).where(F.size("members") > 1)
    return groups.select("members").mapInArrow(tidy(_spanning(radius)), "low long, high long")


def near_duplicate_components(prints: DataFrame, radius: int = 2) -> DataFrame:
    """(doc_id, fingerprint, component_id): component_id is the smallest doc_id reachable over links of ``radius`` or fewer
    differing bits.  ``prints`` is a table (doc_id, fingerprint) that is cheap to read again.

    A document whose id is null has the component of its fingerprint; if no id of that fingerprint is known, null.
    Documents of one id are one node.  An empty table gives an empty result.
    """
    distinct = prints.groupBy("fingerprint").agg(F.min("doc_id").alias("node"))
    distinct = spool(distinct)
    roots = component_roots(near_edges(distinct.where("node IS NOT NULL"), radius), "low", "high")
    of_print = distinct.join(roots, "node", "left").select("fingerprint", F.coalesce("root", "node").alias("component_id"))
    return spread_join(prints, of_print, ["fingerprint"], "doc_id")


def op9_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document's fingerprint and near-duplicate component."""
    prints = spool(fingerprints(spark.read.parquet(f"{sf_dir}/documents.parquet")))
    found = near_duplicate_components(prints)
    return found.select("doc_id", F.lower(F.lpad(F.hex("fingerprint"), 16, "0")).alias("fingerprint"), "component_id")
