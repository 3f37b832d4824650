"""Near copies of texts by SimHash tables, checked by shingle overlap.

For copies with a few changed words a 64-bit SimHash of the whole text is too coarse (at a similarity of 0.8 on five-word
shingles it differs in about 10 bits, which no family of covering masks of workable size covers).  So besides the whole text's
fingerprint, covered up to two bits, a text shows fingerprints of its *passages*: runs of words cut where a word's hash says
so, hence alike in copies.  A text enters the tables with the ``PASSAGES`` least of them, and in every bucket it meets one
text, the bucket's first by a hash of the node: as many pairs as rows, and mostly the same few in all buckets of a group.

That first pass only joins large groups cheaply.  A second one is complete: similar sets of shingles share one of their first
few in a fixed order (prefix keys), so every pair that the first pass left apart and that can reach ``SIMILARITY`` meets there.
Pairs of both passes are checked on their whole sets of five-word shingles.

Texts with the same words are one node.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import discard, finished, part_of, spool, spread_join, temporary, tidy
from .components import component_roots
from .simhash import _signed, covering_masks, majority, shingle_hashes

SHINGLE, SIMILARITY = 5, 0.8
PASSAGES, PASSAGE_CUT = 8, 8
BLOCK = 256
#: Texts that tell the frequent shingles, in how many of them, and how many shingles; a matter of speed, not of results.
ORDER_DOCS, ORDER_LEAST, ORDER_SHINGLES = 2_000, 3, 50_000
PARITY_BITS = 10  # 2 ** 10 bits
#: Bits of ``marks`` for each id and places that an id has; at most so many bits in all (16 MB), beyond which more rows pass.
MARK_BITS, MARK_PLACES, MARKS_MOST = 16, 3, 1 << 27
#: Keys are the upper 48 bits of a shingle's hash, as they are most of what the stage writes.  Two shingles of one key make pairs
#: that the whole sets tell apart; none is lost.
KEY_MASK = ~0xFFFF
#: Pairs that a group of rows of one key may leave for each row in the first round; beyond, it leaves a forest and is taken up
#: again when that is joined.
EAGER = 4


def describe(text: str | None) -> dict:
    """Digest of the words, whole fingerprint, number of distinct shingles, least passages and shingle hashes, ascending."""
    import xxhash

    words = (text or "").encode().lower().split()
    joined = b" ".join(words)
    own = shingle_hashes(words, SHINGLE, 42)
    h = np.unique(own)
    hashes = np.fromiter(map(xxhash.xxh32_intdigest, words, repeat(3)), dtype=np.uint32, count=len(words))
    stops = [*(np.flatnonzero(hashes % PASSAGE_CUT == 0) + 1).tolist(), len(words)]
    passages = {xxhash.xxh64_intdigest(b" ".join(words[a:b]), 5) for a, b in zip([0, *stops], stops) if b > a}
    return {
        "digest": xxhash.xxh128_digest(joined), "fingerprint": int.from_bytes(majority(own), "big", signed=True) if words else 0,
        "shingles": len(h), "passages": [_signed(x) for x in sorted(passages)[:PASSAGES]], "hashes": h.astype("<u8").tobytes(),
    }


def told(docs: DataFrame) -> DataFrame:
    """(doc_id, digest, fingerprint, shingles, passages, rare, frequent, parity, sketch) of every row: what ``describe`` and
    ``keys_of`` say, and a parity of one to two places a shingle where that is longer.  The hashes themselves are not kept;
    ``_alike`` takes them anew from the few texts that it compares."""
    order = frequent(docs)
    by_hash = np.argsort(order)
    shared = docs.sparkSession.sparkContext.broadcast((order[by_hash], by_hash + 1))
    long = pa.list_(pa.int64())
    kinds = {"digest": pa.binary(), "fingerprint": pa.int64(), "shingles": pa.int32(), "passages": long, "rare": long, "frequent": long, "parity": pa.binary(), "sketch": pa.binary()}

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 1000):
                part = batch.slice(at, 1000)
                rows = []
                for text in part["text"]:
                    r = describe(text.as_py())
                    keys, n, parity = keys_of(r["hashes"], *shared.value)
                    bits = (r["shingles"] - 1).bit_length()
                    sketch = parity_of(np.frombuffer(r["hashes"], dtype="<u8"), bits).tobytes() if bits > PARITY_BITS else None
                    rows.append(r | {"rare": keys[:n], "frequent": keys[n:], "parity": parity, "sketch": sketch})
                yield pa.record_batch([part["doc_id"], *(pa.array([r[n] for r in rows], k) for n, k in kinds.items())], names=["doc_id", *kinds])

    return docs.mapInArrow(tidy(each), "doc_id long, digest binary, fingerprint long, shingles int, passages array<long>, rare array<long>, frequent array<long>, parity binary, sketch binary")


def _worth(a: str, b: str) -> Column:
    """Whether two texts' (struct columns) sizes and passages make the similarity likely."""
    small, large = F.least(f"{a}.shingles", f"{b}.shingles"), F.greatest(f"{a}.shingles", f"{b}.shingles")
    most = F.least(F.size(f"{a}.passages"), F.size(f"{b}.passages"))
    common = F.size(F.array_intersect(f"{a}.passages", f"{b}.passages"))
    return (small * 5 >= large * 4) & ((common >= F.least(F.lit(2), F.floor(most / 3))) | (F.bit_count(F.col(f"{a}.fingerprint").bitwiseXOR(F.col(f"{b}.fingerprint"))) <= 2))


def first_pairs(nodes: DataFrame) -> DataFrame:
    """Likely pairs (low, high): in every table's bucket each node with the bucket's first.  No more pairs than rows, and no
    bucket in one task: counts and firsts are aggregated by part of a bucket before they are brought together."""
    covers = [F.struct(F.lit(t).alias("t"), F.col("fingerprint").bitwiseAND(F.lit(_signed(m))).alias("k")) for t, m in enumerate(covering_masks(2))]
    keys = F.concat(F.array(*covers), F.transform("passages", lambda p: F.struct(F.lit(-1).alias("t"), p.alias("k"))))
    dealt = nodes.select("node", F.explode(keys).alias("b")).select("b.t", "b.k", part_of("node").alias("part"), "node")
    rank = F.struct(F.xxhash64("node", F.lit(17)).alias("order"), "node")
    parts = dealt.groupBy("t", "k", "part").agg(F.count(F.lit(1)).alias("n"), F.min(rank).alias("first"))
    firsts = parts.groupBy("t", "k").agg(F.sum("n").alias("n"), F.min("first").alias("first"), F.collect_list("part").alias("parts")).where("n > 1")
    firsts = firsts.select("t", "k", F.col("first.node").alias("first"), F.explode("parts").alias("part"))
    pairs = dealt.join(firsts, ["t", "k", "part"]).where("node <> first").select(F.least("node", "first").alias("low"), F.greatest("node", "first").alias("high"))
    pairs = spool(pairs.distinct())
    x = nodes.select("node", F.struct("fingerprint", "shingles", "passages").alias("x"))
    both = spread_join(pairs, x.toDF("low", "a"), ["low"], "high")
    return spool(spread_join(both, x.toDF("high", "b"), ["high"], "low").where(_worth("a", "b")).select("low", "high"))


def similar(a: bytes, b: bytes) -> bool:
    """Whether two sets of shingle hashes (8 bytes each, ascending) have a Jaccard similarity of ``SIMILARITY`` or more."""
    small, large = sorted((len(a) // 8, len(b) // 8))
    if 5 * small < 4 * large:
        return False
    common = small + large - len(np.union1d(np.frombuffer(a, dtype="<u8"), np.frombuffer(b, dtype="<u8")))
    return 5 * common >= 4 * (small + large - common)


def parity_of(hashes: np.ndarray, bits: int) -> np.ndarray:
    """Whether an odd number of hashes fall on each of 2^``bits`` places: sets that differ in d hashes differ in d places at most."""
    return np.packbits((np.bincount(hashes >> np.uint64(64 - bits), minlength=1 << bits) & 1).astype(np.uint8))


def _odd_places(a: bytes, b: bytes) -> int:
    """Places in which two parities differ, the longer folded to the length of the shorter."""
    x, y = (np.unpackbits(np.frombuffer(v, dtype=np.uint8)) for v in sorted((a, b), key=len))
    return int((x ^ (y.reshape(len(x), -1).sum(axis=1) & 1)).sum())


def _places(of: str, bits: int) -> list[Column]:
    return [F.pmod(F.xxhash64(F.lit(i), of), F.lit(bits)) for i in range(MARK_PLACES)]


def marks(ids: DataFrame, of: str, rows: int) -> np.ndarray:
    """Bytes of a Bloom filter in which the ``_places`` of all ids are set, of two bytes or less for each of ``rows`` ids."""
    bits = min(MARKS_MOST, -(-max(1, rows) * MARK_BITS // 32_768) * 32_768)
    at = ids.select(F.explode(F.array(*_places(of, bits))).alias("at"))
    parts = at.groupBy(F.shiftright("at", 15).alias("part")).agg(F.bitmap_construct_agg(F.col("at") % 32_768).alias("bits")).toArrow()
    out = np.zeros((bits // 32_768, 4096), dtype=np.uint8)
    for part, own in zip(parts["part"].to_pylist(), parts["bits"].to_pylist(), strict=True):
        out[part] = np.frombuffer(own, dtype=np.uint8)
    return out.ravel()


def _hash_sets(docs: DataFrame, pairs: DataFrame) -> DataFrame:
    """(node, hashes): the shingle sets of all texts of the pairs (low, high), and of few others.  Texts are picked where they are
    read, by ``marks``: dealing them out for a join would write the whole corpus to disk."""
    sc = docs.sparkSession.sparkContext
    own = marks(pairs.select(F.explode(F.array("low", "high")).alias("node")), "node", 2 * pairs.count())
    bits, shared = 8 * len(own), sc.broadcast(own)

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = shared.value
        for batch in batches:
            hit = np.ones(batch.num_rows, dtype=bool)
            for i in range(MARK_PLACES):
                at = batch[f"at{i}"].to_numpy()
                hit &= (own[at >> 3] >> (at & 7).astype(np.uint8)) & 1 == 1
            found = batch.select(["doc_id", "text"]).filter(pa.array(hit))
            for at in range(0, found.num_rows, 200):
                part = found.slice(at, 200)
                yield pa.record_batch([part["doc_id"], pa.array([describe(t.as_py())["hashes"] for t in part["text"]], pa.binary())], names=["node", "hashes"])

    return docs.select("doc_id", "text", *(c.alias(f"at{i}") for i, c in enumerate(_places("doc_id", bits)))).mapInArrow(tidy(each), "node long, hashes binary")


def _alike(pairs: DataFrame, docs: DataFrame, sketches: DataFrame, repeated: bool) -> DataFrame:
    """The pairs (low, high) whose texts' shingle sets are similar.  ``sketches`` (node, n, parity), of one to two places a
    shingle, tell most that can't be, before the sets themselves meet.  ``repeated``: some ids have several rows."""

    def possible(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            columns = zip(*(batch[c].to_pylist() for c in ("n_low", "n_high")), batch["parity_low"], batch["parity_high"], strict=True)
            keep = [5 * min(n, m) >= 4 * max(n, m) and _odd_places(a.as_py(), b.as_py()) <= n + m - 2 * ((4 * (n + m) + 8) // 9) for n, m, a, b in columns]
            yield batch.select(["low", "high"]).filter(pa.array(keep, pa.bool_()))

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = pa.array([similar(a.as_py(), b.as_py()) for a, b in zip(batch["hashes_low"], batch["hashes_high"], strict=True)], pa.bool_())
            yield batch.select(["low", "high"]).filter(keep)

    def once(rows: DataFrame) -> DataFrame:
        return spool(rows.distinct() if repeated else rows, "lz4")

    def both(pairs: DataFrame, rows: DataFrame) -> DataFrame:
        for side, other in (("low", "high"), ("high", "low")):
            pairs = spread_join(pairs, rows.select(F.col("node").alias(side), *(F.col(c).alias(f"{c}_{side}") for c in rows.columns[1:])), [side], other)
        return pairs

    with temporary(docs.sparkSession):
        wanted = pairs.select(F.explode(F.array("low", "high")).alias("node")).distinct()
        likely = both(pairs, once(sketches.join(wanted, "node", "left_semi")))
        likely = spool(likely.mapInArrow(tidy(possible), "low long, high long").distinct())
        found = both(likely, once(_hash_sets(docs, likely)))
        return finished(found.mapInArrow(tidy(each), "low long, high long").distinct())


def frequent(docs: DataFrame) -> np.ndarray:
    """Hashes of shingles that many texts of a sample have, the most frequent last.  They are the last in the order of shingles
    (before them come all others by hash), as keys that few texts share cost the least."""

    def flat(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 200):
                own = b"".join(describe(t.as_py())["hashes"] for t in batch["text"].slice(at, 200))
                yield pa.record_batch([pa.array(np.frombuffer(own, dtype="<i8"))], names=["k"])

    share = min(1_000_000, -(-ORDER_DOCS * 1_000_000 // max(1, docs.count())))
    sample = docs.where(F.pmod(F.xxhash64("doc_id"), F.lit(1_000_000)) < share).select("text")
    counts = sample.mapInArrow(tidy(flat), "k long").groupBy("k").count().where(F.col("count") >= ORDER_LEAST)
    return counts.orderBy(F.desc("count"), "k").limit(ORDER_SHINGLES).select("k").toArrow()["k"].to_numpy()[::-1].astype(np.int64)


def keys_of(hashes: bytes, last: np.ndarray, rank: np.ndarray) -> tuple[np.ndarray, int, bytes]:
    """The first shingles in the order, of which similar sets share one, how many of them aren't frequent (those come first),
    and the parities of how many hashes fall on each bit.  ``last``: the frequent shingles' hashes, ascending, with their
    ranks from 1."""
    h = np.frombuffer(hashes, dtype="<i8")
    first = len(h) - (4 * len(h) + 4) // 5 + 1
    ranks = np.zeros(len(h), dtype=np.int64)
    if len(last):
        at = np.minimum(np.searchsorted(last, h), len(last) - 1)
        ranks = np.where(last[at] == h, rank[at], 0)
    order = np.lexsort((h, ranks))[:first]
    return h[order] & KEY_MASK, int((ranks[order] == 0).sum()), parity_of(h.view(np.uint64), PARITY_BITS).tobytes()


def forest(low: np.ndarray, high: np.ndarray) -> np.ndarray:
    """Which of some edges to keep so that they still connect what all do: fewer than there are nodes, times a logarithm."""
    nodes, flat = np.unique(np.concatenate([low, high]), return_inverse=True)
    a, b = flat[: len(low)], flat[len(low) :]
    label, keep = np.arange(len(nodes)), np.zeros(len(low), dtype=bool)
    while True:
        x, y = label[a], label[b]
        apart = np.flatnonzero(x != y)
        if not len(apart):
            return keep
        less, more = np.minimum(x, y)[apart], np.maximum(x, y)[apart]
        order = np.lexsort((less, more))
        first = order[np.concatenate([[True], np.diff(more[order]) != 0])]  # of each larger label, the edge to its least one
        keep[apart[first]] = True
        up = np.arange(len(nodes))
        up[more[first]] = less[first]
        while (up[up] != up).any():
            up = up[up]
        label = up[label]


def _near(eager: int | None):
    """From rows sorted by (k, b1, b2): pairs (low, high) of rows of one group that no bound rejects.  With ``eager`` a group that
    has more such pairs than that for each row leaves only as many as connect the same roots, and a row (k) that says so."""
    names = ("k", "b1", "b2", "block", "node", "root", "size", "place")

    def pairs(x: dict[str, np.ndarray]) -> pa.RecordBatch:
        n = len(x["k"])
        fresh = np.ones(n, dtype=bool)
        fresh[1:] = (np.diff(x["k"]) != 0) | (np.diff(x["b1"]) != 0) | (np.diff(x["b2"]) != 0)
        group = np.cumsum(fresh)
        found = [np.zeros((0, 2), dtype=np.int64)]
        for d in range(1, n):
            i = np.flatnonzero(group[d:] == group[:-d])
            if not len(i):
                break
            j = i + d
            ok = (x["root"][i] != x["root"][j]) & ((x["b1"][i] == x["b2"][i]) | (x["block"][i] != x["block"][j]))
            i, j = i[ok], j[ok]
            both = x["size"][i] + x["size"][j]
            need = (4 * both + 8) // 9
            left = np.minimum(x["size"][i] - x["place"][i], x["size"][j] - x["place"][j])
            ok = (5 * np.minimum(x["size"][i], x["size"][j]) >= 4 * np.maximum(x["size"][i], x["size"][j])) & (left >= need)
            i, j, most = i[ok], j[ok], (both - 2 * need)[ok]
            ok = np.bitwise_count(x["parity"][i] ^ x["parity"][j]).sum(axis=1, dtype=np.int64) <= most
            found.append(np.stack([i[ok], j[ok]], axis=1))
        i, j = np.concatenate(found).T
        again = x["k"][:0]
        if eager is not None and len(i):
            rows, made = np.bincount(group), np.bincount(group[i], minlength=group[-1] + 1)
            many = made > eager * rows
            if many.any():
                _, label = np.unique(np.stack([group, x["root"]]), axis=1, return_inverse=True)
                label, hard = label.ravel(), np.flatnonzero(many[group[i]])
                kept = np.ones(len(i), dtype=bool)
                kept[hard] = forest(label[i[hard]], label[j[hard]])
                again = np.unique(x["k"][i[hard]])
                i, j = i[kept], j[kept]
        out = np.unique(np.stack([np.minimum(x["node"][i], x["node"][j]), np.maximum(x["node"][i], x["node"][j])], axis=1), axis=0)
        none = [pa.nulls(len(again), pa.int64()), pa.nulls(len(out), pa.int64())]
        return pa.record_batch([pa.concat_arrays([pa.array(out[:, c]), none[0]]) for c in (0, 1)] + [pa.concat_arrays([none[1], pa.array(again)])], names=["low", "high", "k"])

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[str, np.ndarray] = {}
        for batch in batches:
            if not batch.num_rows:
                continue
            x = {c: batch[c].to_numpy(zero_copy_only=False).astype(np.int64) for c in names}
            x["parity"] = np.frombuffer(b"".join(batch["parity"].to_pylist()), dtype=np.uint64).reshape(batch.num_rows, -1)
            held = {c: np.concatenate([held[c], x[c]]) for c in x} if held else x
            same = np.ones(len(held["k"]), dtype=bool)
            for c in ("k", "b1", "b2"):
                same &= held[c] == held[c][-1]
            open_at = len(same) - int(same.sum())  # the last group may go on in the next batch
            if open_at:
                yield pairs({c: v[:open_at] for c, v in held.items()})
                held = {c: v[open_at:] for c, v in held.items()}
        if held:
            yield pairs(held)

    return each


def packed(rows: DataFrame) -> DataFrame:
    """Rows (node, root, place, k) dealt by k, which is most of the stage's bytes: the place goes in the key's free bits and the
    root as what differs from the node, mostly nothing.  A place too large for these bits gets the largest, which bounds less."""
    key = F.col("kp").bitwiseAND(F.lit(KEY_MASK))
    rows = rows.select(F.col("k").bitwiseOR(F.least("place", F.lit(~KEY_MASK)).cast("long")).alias("kp"), "node", F.col("node").bitwiseXOR(F.col("root")).alias("off"))
    return rows.repartition(key).select("node", F.col("node").bitwiseXOR(F.col("off")).alias("root"), F.col("kp").bitwiseAND(F.lit(~KEY_MASK)).cast("int").alias("place"), key.alias("k"))


def meetings(all_rows: DataFrame, rooted: DataFrame, repeated: bool) -> DataFrame:
    """(k, blocks, node, root, place): keys that texts of different roots share, a row for each text that has them.  ``rooted``:
    (digest, node, root).  ``all_rows``, a spooled table, is deleted once its keys are copied.

    A rare key's rows are in one partition, where counting needs no further shuffle; a frequent one's are counted by part.
    """
    keyed = all_rows.select("digest", F.col("doc_id").alias("node"), "rare", "frequent").join(rooted, ["digest", "node"])
    keyed = spool((keyed.dropDuplicates(["digest", "node"]) if repeated else keyed).drop("digest"))
    discard(all_rows)
    rare = packed(keyed.select("node", "root", F.posexplode("rare").alias("place", "k")))
    of_key = Window.partitionBy("k")
    rare = rare.withColumns({"n": F.count(F.lit(1)).over(of_key), "a": F.min("root").over(of_key), "b": F.max("root").over(of_key)}).where("a < b").drop("a", "b")
    often = keyed.select("node", "root", part_of("node").alias("part"), F.size("rare").alias("before"), F.posexplode("frequent").alias("place", "k")).withColumn("place", F.col("place") + F.col("before")).drop("before")
    parts = often.groupBy("k", "part").agg(F.count(F.lit(1)).alias("n"), F.min("root").alias("a"), F.max("root").alias("b"))
    sizes = parts.groupBy("k").agg(F.sum("n").alias("n"), F.min("a").alias("a"), F.max("b").alias("b"), F.collect_list("part").alias("parts")).where("a < b").select("k", "n", F.explode("parts").alias("part"))
    often = often.join(sizes, ["k", "part"]).drop("part").select(*rare.columns)
    return spool(rare.unionByName(often).withColumn("blocks", F.ceil(F.col("n") / BLOCK).cast("int")).drop("n"))


def pairs_apart(met: DataFrame, parities: DataFrame, eager: int | None) -> DataFrame:
    """(low, high, k): pairs of nodes with different roots that share a key of ``meetings``, among them all whose similarity is
    ``SIMILARITY`` or more, but for the keys k that are named apart (see ``_near``).  A large key's rows are dealt block against
    block."""
    met = met.join(parities, "node").withColumn("block", F.pmod(F.xxhash64("node", F.lit(13)), F.col("blocks")).cast("int"))
    met = met.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    met = met.select("k", F.least("block", "other").alias("b1"), F.greatest("block", "other").alias("b2"), "block", "node", "root", "size", "place", "parity")
    return spool(met.repartition("k", "b1", "b2").sortWithinPartitions("k", "b1", "b2").mapInArrow(tidy(_near(eager)), "low long, high long, k long").distinct())


def near_copy_roots(docs: DataFrame) -> DataFrame:
    """(doc_id, root) of every row whose group's smallest doc_id is another; null ids and their rows have no group."""
    with temporary(docs.sparkSession):
        docs = docs.where("doc_id IS NOT NULL").select(F.col("doc_id").cast("long").alias("doc_id"), "text")
        rows = spool(told(docs))
        light = spool(rows.select("doc_id", "digest", "fingerprint", "shingles", "passages", "parity", "sketch"))
        nodes = spool(light.groupBy("digest").agg(F.min(F.struct(F.col("doc_id").alias("node"), "fingerprint", "shingles", "passages")).alias("x")).select("digest", "x.*"))

        repeated = not docs.groupBy("doc_id").count().where("count > 1").isEmpty()  # if not, shuffles to drop duplicates aren't needed
        sketches = light.select(F.col("doc_id").alias("node"), F.col("shingles").alias("n"), F.coalesce("sketch", "parity").alias("parity"))
        roots = component_roots(_alike(first_pairs(nodes), docs, sketches, repeated), "low", "high")
        rooted = spool(nodes.join(roots, "node", "left").select("digest", "node", F.coalesce("root", "node").alias("root")))
        met = meetings(rows, rooted, repeated)
        parities = light.select(F.col("doc_id").alias("node"), F.col("shingles").alias("size"), "parity")
        parities = parities.distinct() if repeated else parities
        found = pairs_apart(met, parities, EAGER)

        def joined(pairs: DataFrame) -> DataFrame:
            return component_roots(_alike(pairs, docs, sketches, repeated).unionByName(roots.select(F.col("root").alias("low"), F.col("node").alias("high"))), "low", "high")

        roots = joined(found.where("k IS NULL").select("low", "high"))
        again = found.where("k IS NOT NULL").select("k").distinct()
        if not again.isEmpty():
            left = spread_join(met, again, ["k"], "node").join(roots.toDF("node", "_to"), "node", "left").withColumn("root", F.coalesce("_to", "root")).drop("_to")
            roots = joined(pairs_apart(left, parities, None).select("low", "high"))
        of_digest = nodes.join(roots, "node", "left").select("digest", F.coalesce("root", "node").alias("root"))
        return finished(spread_join(light.select("doc_id", "digest"), of_digest, ["digest"], "doc_id").where("root <> doc_id").select("doc_id", "root"))


def keep_one_each(docs: DataFrame) -> DataFrame:
    """``docs`` with one row of each group of copies and near copies: that of the smallest doc_id.  Rows of one doc_id are one
    document, of which one row stays; rows without an id stay as they are."""
    gone = near_copy_roots(docs).select("doc_id").distinct()
    again = docs.where("doc_id IS NOT NULL").groupBy("doc_id").count().where("count > 1").select("doc_id")
    odd = spool(gone.withColumn("gone", F.lit(True)).join(again.withColumn("again", F.lit(True)), "doc_id", "full"))
    single = docs.join(odd.select("doc_id"), "doc_id", "left_anti")
    several = docs.join(odd.where("again AND gone IS NULL").select("doc_id"), "doc_id", "left_semi").dropDuplicates(["doc_id"])
    return single.unionByName(several).select(*docs.columns)
