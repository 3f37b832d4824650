"""Exact top-k by inner product: branch and bound over ball trees, one per shard.

Vectors are dealt to shards of about ``SHARD_ROWS``; each becomes one ball tree, kept as bytes.  A node's ball (centre c,
radius R) bounds every inner product below it by q.c + |q|R, so a query opens nodes by descending bound and ends where the
bound falls below its kth score.  Queries go in blocks: each block first searches one shard (blocks are spread over all
shards), and the kth scores it finds there are the start for every other shard.

Scores are exact integers: int64 arithmetic where it can't overflow, else Python's.  The bound is floating point with room
for rounding.  A node is skipped at a bound equal to the kth score only if its smallest id can't win the tie.
"""

from __future__ import annotations

import heapq
import io
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import spool, tidy

SHARD_ROWS = 8192
BLOCK_QUERIES = 256
LEAF_ROWS = 64


def quantized(ids: pa.Array, vectors: pa.Array, scale: float = 1024.0) -> dict[int, tuple[np.ndarray, np.ndarray]]:
    """By dimension: ids and floor(scale * x) as whole numbers in float64.  Rows with a null id, and vectors that are null,
    empty, or hold null or non-finite components, take no part."""
    keep = np.flatnonzero(~(ids.is_null().to_numpy(zero_copy_only=False) | vectors.is_null().to_numpy(zero_copy_only=False)))
    vectors, ids = vectors.take(pa.array(keep)), ids.take(pa.array(keep))
    sizes = np.diff(vectors.offsets.to_numpy())
    flat = np.floor(vectors.flatten().to_numpy(zero_copy_only=False).astype(np.float64) * scale)
    starts = np.concatenate([[0], np.cumsum(sizes)])[:-1].astype(np.int64)
    bad = np.bincount(np.repeat(np.arange(len(sizes)), sizes)[~np.isfinite(flat)], minlength=len(sizes)) > 0
    found, numbers = {}, ids.to_numpy(zero_copy_only=False).astype(np.int64)
    for d in np.unique(sizes[~bad & (sizes > 0)]).tolist():
        rows = np.flatnonzero((sizes == d) & ~bad)
        found[d] = numbers[rows], flat[starts[rows][:, None] + np.arange(d)]
    return found


def build_tree(ids: np.ndarray, vectors: np.ndarray) -> dict[str, np.ndarray]:
    """Arrays of a tree: rows in leaf order, and per node its rows (first, last), children (0: a leaf), ball and least id."""
    order = np.arange(len(ids))
    nodes: list[list] = []
    todo = [(0, len(ids), -1, 0)]
    while todo:
        first, last, parent, side = todo.pop()
        rows = order[first:last]
        own = vectors[rows]
        centre = own.mean(axis=0)
        radius = float(np.sqrt(((own - centre) ** 2).sum(axis=1).max()))
        if parent >= 0:
            nodes[parent][2 + side] = len(nodes)
        nodes.append([first, last, 0, 0, centre, radius * (1 + 1e-9) + 1e-9, int(ids[rows].min())])
        if last - first > LEAF_ROWS and radius > 0:
            a = own[((own - centre) ** 2).sum(axis=1).argmax()]
            b = own[((own - a) ** 2).sum(axis=1).argmax()]
            split = np.argsort(own @ (b - a), kind="stable")
            order[first:last] = rows[split]
            middle = first + (last - first) // 2
            me = len(nodes) - 1
            todo += [(first, middle, me, 0), (middle, last, me, 1)]
    columns = list(zip(*nodes, strict=True))
    names = ("first", "last", "left", "right", "centre", "radius", "least_id")
    return {"ids": ids[order], "vectors": vectors[order]} | {n: np.array(c) for n, c in zip(names, columns, strict=True)}


def exact_products(vectors: np.ndarray, query: np.ndarray) -> list[int]:
    """Integer inner products of whole numbers held as float64."""
    most = float(np.abs(vectors).max(initial=0)) * float(np.abs(query).max(initial=0)) * len(query)
    if most < 2**53:
        return (vectors @ query).astype(np.int64).tolist()
    q = [int(x) for x in query]
    return [sum(int(a) * b for a, b in zip(v, q, strict=True)) for v in vectors]


def search(tree: dict[str, np.ndarray], own_ids: np.ndarray, queries: np.ndarray, k: int, floors: list[int | None]) -> list[list[tuple[int, int]]]:
    """Per query its best (score, vec_id), at most k, without its own id; what is below its floor may be missing."""
    bounds = queries @ tree["centre"].T + np.sqrt((queries**2).sum(axis=1))[:, None] * tree["radius"]
    bounds += 1e-6 + np.abs(bounds) * 1e-9
    first, last, left, right, least = (tree[n].tolist() for n in ("first", "last", "left", "right", "least_id"))
    out = []
    for q, query in enumerate(queries):
        bound, floor, own = bounds[q].tolist(), floors[q], int(own_ids[q])
        best: list[tuple[int, int]] = []  # heap of (score, -id): its least is the kth
        open_nodes = [(-bound[0], 0)]
        while open_nodes:
            b, node = heapq.heappop(open_nodes)
            if floor is not None and -b < floor or len(best) == k and (-b, -least[node]) < best[0]:
                break  # nodes come by descending bound
            if left[node]:
                for child in (left[node], right[node]):
                    heapq.heappush(open_nodes, (-bound[child], child))
                continue
            rows = slice(first[node], last[node])
            for score, i in zip(exact_products(tree["vectors"][rows], query), tree["ids"][rows].tolist(), strict=True):
                if i != own and (floor is None or score >= floor):
                    if len(best) < k:
                        heapq.heappush(best, (score, -i))
                    elif (score, -i) > best[0]:
                        heapq.heapreplace(best, (score, -i))
        out.append([(s, -i) for s, i in sorted(best, reverse=True)])
    return out


def _frozen(**arrays: np.ndarray) -> bytes:
    held = io.BytesIO()
    np.savez(held, **arrays)
    return held.getvalue()


def _thawed(raw: bytes) -> dict[str, np.ndarray]:
    with np.load(io.BytesIO(raw)) as held:
        return {n: held[n] for n in held.files}


def _gathered(batches: Iterator[pa.RecordBatch], most: int, scale: float) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(dimension, ids, vectors) of at most ``most`` rows each."""
    held: dict[int, list] = {}
    for batch in batches:
        for d, (ids, vectors) in quantized(batch["id"], batch["vector"], scale).items():
            held.setdefault(d, []).append((ids, vectors))
            while sum(len(i) for i, _ in held[d]) >= most:
                ids, vectors = (np.concatenate(x) for x in zip(*held[d], strict=True))
                yield d, ids[:most], vectors[:most]
                held[d] = [(ids[most:], vectors[most:])]
    for d, parts in held.items():
        ids, vectors = (np.concatenate(x) for x in zip(*parts, strict=True))
        if len(ids):
            yield d, ids, vectors


def top_k(vectors: DataFrame, is_query: Column, k: int = 10, scale: float = 1024.0, vec_id: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """(query_id, rank, vec_id, score): the k highest integer inner products of each query row with all rows but those of
    its own id, ties to the smaller id; all, if fewer.  Vectors meet only those of their own dimension.  Rows of one id are
    separate; a repeated query row gives its answers each time.  An empty table gives an empty result."""
    rows = vectors.select(F.col(vec_id).cast("long").alias("id"), F.col(vector).alias("vector"), is_query.alias("q"))
    shards = max(1, -(-vectors.select(F.lit(1)).count() // SHARD_ROWS))
    groups = min(shards, 4096)

    def trees(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        group = TaskContext.get().partitionId() % groups
        for n, (d, ids, own) in enumerate(_gathered(batches, 2 * SHARD_ROWS, scale)):
            yield pa.record_batch([pa.array([group], pa.int32()), pa.array([d], pa.int32()), pa.array([n], pa.int32()), pa.array([_frozen(**build_tree(ids, own))])], names=["g", "d", "n", "tree"])

    def blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part = TaskContext.get().partitionId()
        for n, (d, ids, own) in enumerate(_gathered(batches, BLOCK_QUERIES, scale)):
            yield pa.record_batch([pa.array([(part << 32) + n]), pa.array([d], pa.int32()), pa.array([_frozen(ids=ids, vectors=own)])], names=["block", "d", "queries"])

    def hits(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):
                tree, own = _thawed(batch["tree"][i].as_py()), _thawed(batch["queries"][i].as_py())
                floors = batch["floors"][i].as_py() if "floors" in batch.schema.names else None
                found = search(tree, own["ids"], own["vectors"], k, floors or [None] * len(own["ids"]))
                at = [q for q, f in enumerate(found) for _ in f]
                n, block = len(at), batch["block"][i].as_py()
                columns = [[block] * n, at, own["ids"][at].tolist(), [x for f in found for _, x in f], [s for f in found for s, _ in f], [batch["g"][i].as_py()] * n, [batch["n"][i].as_py()] * n]
                kinds = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int32()]
                yield pa.record_batch([pa.array(c, t) for c, t in zip(columns, kinds, strict=True)], names=["block", "at", "query_id", "vec_id", "score", "g", "n"])

    found_schema = "block long, at int, query_id long, vec_id long, score long, g int, n int"
    tree_table = spool(rows.repartition(shards).mapInArrow(tidy(trees), "g int, d int, n int, tree binary"), "none")
    asked = spool(rows.where("q").mapInArrow(tidy(blocks), "block long, d int, queries binary"), "none")

    # a block's first shard: the first tree of its group
    firsts = tree_table.where("n = 0").select("g", "d", "n", "tree")
    homes = asked.withColumn("g", F.pmod(F.xxhash64("block"), F.lit(groups)).cast("int"))
    seeds = spool(homes.join(firsts, ["g", "d"]).select("block", "g", "n", "queries", "tree").mapInArrow(tidy(hits), found_schema))
    kth = seeds.groupBy("block", "at").agg(F.count(F.lit(1)).alias("c"), F.min("score").alias("s")).select("block", "at", F.when(F.col("c") >= k, F.col("s")).alias("s"))
    floors = kth.groupBy("block").agg(F.map_from_entries(F.collect_list(F.struct("at", "s"))).alias("m"))  # BLOCK_QUERIES at most
    longest = F.sequence(F.lit(0), F.lit(BLOCK_QUERIES - 1))
    floors = floors.select("block", F.transform(longest, lambda i: F.try_element_at("m", i)).alias("floors"))
    seeded = seeds.select("block", "g", "n").distinct().withColumn("done", F.lit(True))

    everywhere = asked.join(floors, "block", "left").withColumn("g", F.explode(F.sequence(F.lit(0), F.lit(groups - 1))))
    pairs = everywhere.join(tree_table, ["g", "d"]).join(seeded, ["block", "g", "n"], "left").where("done IS NULL")
    rest = pairs.select("block", "g", "n", "queries", "floors", "tree").mapInArrow(tidy(hits), found_schema)
    best = Window.partitionBy("block", "at").orderBy(F.desc("score"), "vec_id")
    ranked = seeds.unionByName(rest).withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k)
    return ranked.select("query_id", "rank", "vec_id", "score")


def op4_exact_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The ten highest scores of every hundredth vector against all vectors."""
    vectors = spark.read.parquet(f"{sf_dir}/embeddings.parquet")
    return top_k(vectors, F.col("vec_id") % 100 == 0)
