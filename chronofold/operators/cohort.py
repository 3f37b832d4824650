"""Comparison of a fixed set of keys on common cuts."""

from __future__ import annotations

from collections.abc import Iterable, Iterator, Mapping, Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.instants import FROM, TO, micros, on_axis
from ..functions.predicates import predicate
from .canonical import coalesce_pieces
from .same_base import chunked, prefix_steps

#: Comparators by name.
COMPARE = {"lt": lambda a, b: a < b, "le": lambda a, b: a <= b, "gt": lambda a, b: a > b, "ge": lambda a, b: a >= b, "eq": lambda a, b: a == b, "ne": lambda a, b: a != b}


#: A block has two to the power of this many segments.
BLOCK_LEVELS = 6
#: Parts that candidates are dealt to where they meet the reference, whose rows are copied to each.
REFERENCE_PARTS = 8
#: Stretches of equal length into which a chunk is divided to tell which rows can have a rank at all.
STRETCHES = 16
#: Beyond so many chunks from the first to the last, or ranks, rows are not told apart beforehand.
MOST_CHUNKS, MOST_RANKS = 1024, 64
#: So many rows that can have a rank, and no more, are ranked where the query is planned.
FEW_ROWS = 1 << 15
#: Microseconds of the first and last instants that Python has.
FIRST_INSTANT, LAST_INSTANT = -62_135_596_800_000_000, 253_402_300_799_999_999


def assert_cohort_closed(piece: DataFrame, history: DataFrame, key: str) -> None:
    """The piece must hold every row of the cohort that overlaps its chunk: raises if one is missing."""
    lost = history.join(piece, [key, FROM, TO], "left_anti")
    if not lost.isEmpty():
        raise ValueError("the piece lacks rows of its cohort")


def shard_of(key: str | Column, shards: int) -> Column:
    return F.pmod(F.xxhash64(key), F.lit(shards)).cast("int")


def numbered_cuts(rows: DataFrame, ids: Sequence[str]) -> DataFrame:
    """(ids, seg_from, seg_to, _n): the cuts of each id in order from 0; segment n lies between the cuts n and n + 1.

    Join them by merging: the planner guesses their size by that of compressed files, and would broadcast millions of them.
    """
    by = Window.partitionBy(*ids).orderBy("seg_from")
    cuts = rows.select(*ids, F.explode(F.array(FROM, TO)).alias("seg_from")).distinct()
    return cuts.withColumns({"seg_to": F.lead("seg_from").over(by), "_n": F.row_number().over(by) - 1})


def best_of_segments(rows: DataFrame, cuts: DataFrame, ids: Sequence[str], k: int, descending: bool) -> DataFrame:
    """(ids, _block, _n, rank, key, x): the best k of every segment, without a row for each member that holds in it.

    A row's segments are a run of numbers, which is the union of a few nodes: 2^level segments from a multiple of 2^level on, two
    nodes of a level at most.  A node needs its best k alone.  Nodes wider than a block go to their blocks, which keep the best k
    of these; then nodes go to their segments, where a block's rows are in one task.  So a row costs the logarithm of the number
    of cuts and a segment k rows a level, however many members hold at once.
    """
    order = [F.desc("x") if descending else F.asc("x"), F.asc("key")]

    def best(entries: DataFrame, *of: str, name: str = "_rank") -> DataFrame:
        at = Window.partitionBy(*ids, *of).orderBy(*order)
        return entries.withColumn(name, F.row_number().over(at)).where(F.col(name) <= k)

    number = cuts.select(*ids, "seg_from", "_n")
    for end, name in ((FROM, "_low"), (TO, "_high")):
        rows = rows.join(number.toDF(*ids, end, name).hint("merge"), [*ids, end])
    carried = [*ids, "key", "x"]
    levels = F.sequence(F.lit(0), F.floor(F.log2(F.col("_high") - F.col("_low"))).cast("int"))
    ends = rows.select(*carried, "_low", "_high", F.explode(levels).alias("_level"))
    ends = ends.selectExpr(*carried, "_level", "shiftright(_low + shiftleft(1, _level) - 1, _level) AS _low", "shiftright(_high, _level) AS _high").where("_low < _high")
    sides = F.array(F.when(F.col("_low") % 2 == 1, F.col("_low")), F.when(F.col("_high") % 2 == 1, F.col("_high") - 1))
    nodes = best(ends.select(*carried, "_level", F.explode(sides).alias("_node")).where("_node IS NOT NULL"), "_level", "_node")

    up, down = f"greatest(_level - {BLOCK_LEVELS}, 0)", f"greatest({BLOCK_LEVELS} - _level, 0)"
    blocks = F.expr(f"explode(sequence(shiftright(shiftleft(_node, {up}), {down}), shiftright(shiftleft(_node + 1, {up}) - 1, {down})))")
    dealt = nodes.select(*carried, "_level", "_node", blocks.alias("_block"))
    wide = F.col("_level") >= BLOCK_LEVELS
    dealt = dealt.withColumns({"_node": F.when(wide, F.col("_block")).otherwise(F.col("_node")), "_level": F.least("_level", F.lit(BLOCK_LEVELS))})
    kept = best(dealt.repartition(*ids, "_block"), "_block", "_level", "_node")
    segments = F.expr("explode(sequence(shiftleft(_node, _level), shiftleft(_node + 1, _level) - 1))")
    return best(kept.select(*carried, "_block", segments.alias("_n")), "_block", "_n", name="rank")


def spans_of(rows: DataFrame, low: Column, high: Column) -> dict[int, tuple[int, int]]:
    """The least ``low`` and greatest ``high`` of each chunk that has a row of some length; one chunk over the limit at most."""
    found = rows.groupBy("chunk").agg(F.min(low).alias("low"), F.max(high).alias("high")).where("low < high").limit(MOST_CHUNKS + 1)
    return {r.chunk: (r.low, r.high) for r in found.collect()}


def within_reach(rows: DataFrame, k: int, descending: bool, spans: Mapping[int, tuple[int, int]] | None = None) -> DataFrame:
    """The rows (chunk, key, x, valid_from, valid_to) without those that have none of the best k ranks at any time.

    A chunk is divided into stretches.  Members are dealt to k classes by their key; if each class has one that lasts through a
    stretch, the worst of the classes' best x is a bound: k members are there all the time that are as good.  A row that is worse
    than the bound of every stretch it touches is never shown.  A stretch in which a class has no such member has no bound, and
    all of its rows stay; so what is left is ranked as before.  The bounds, some numbers a chunk, are found when the query is planned.
    ``spans``: the first and last instant of each chunk's rows as numbers (see on_axis), looked up if not given.
    """
    kind = rows.schema["x"].dataType
    if k > MOST_RANKS or not isinstance(kind, T.NumericType):
        return rows
    low, high = on_axis(rows, FROM), on_axis(rows, TO)
    if spans is None:
        spans = spans_of(rows, low, high)
    if not spans or max(spans) - min(spans) >= MOST_CHUNKS:
        return rows
    first = min(spans)
    every = range(first, max(spans) + 1)
    of = {c: (low, high, -((low - high) // STRETCHES)) for c, (low, high) in spans.items()}

    def listed(values: dict, kind: str) -> Column:
        """The value of a row's chunk; null where there is none."""
        texts = ", ".join(str(values.get(c, "NULL")) for c in every)
        return F.get(F.expr(f"CAST(array({texts}) AS array<{kind}>)"), (F.col("chunk") - first).cast("int"))

    names = ("_low", "_high", "_width")
    placed = rows.withColumns({"_f": low, "_t": high} | {n: listed({c: v[i] for c, v in of.items()}, "bigint") for i, n in enumerate(names)})
    inner, outer = (F.max, F.min) if descending else (F.min, F.max)
    # a row is a member of the stretches that it lasts through, mostly a few
    ends = placed.select("chunk", shard_of("key", k).alias("_class"), "x", F.expr("int((_f - _low + _width - 1) div _width)").alias("_from"), F.expr(f"int(if(_t >= _high, {STRETCHES}, (_t - _low) div _width))").alias("_upto"))
    through = ends.where("_from < _upto").select("chunk", "_class", "x", F.explode(F.expr("sequence(_from, _upto - 1)")).alias("_stretch"))
    classes = through.groupBy("chunk", "_class", "_stretch").agg(inner("x").alias("x"))
    worst = classes.groupBy("chunk", "_stretch").agg(F.count("x").alias("_n"), outer("x").cast("string").alias("x")).where(F.col("_n") == k)
    bounds: dict[int, list[str]] = {}
    for r in worst.collect():
        bounds.setdefault(r.chunk, ["NULL"] * STRETCHES)[r["_stretch"]] = f"'{r.x}'"
    arrays = f"array<{kind.simpleString()}>"
    of_chunk = {c: f"CAST(array({', '.join(v)}) AS {arrays})" for c, v in bounds.items()}
    loosest = {c: f"array_{'min' if descending else 'max'}({of_chunk[c]})" for c, v in bounds.items() if "NULL" not in v}
    told = placed.withColumns({"_any": listed(loosest, kind.simpleString()), "_bounds": listed(of_chunk, arrays)})
    start, sign = "(_f - _low) div _width", ">=" if descending else "<="
    touched = f"slice(_bounds, int({start}) + 1, greatest(int((_t - 1 - _low) div _width - {start}) + 1, 0))"
    # the loosest bound of the chunk first, which is cheap and rejects most rows
    return told.where(f"(_any IS NULL OR x {sign} _any) AND coalesce(exists({touched}, b -> b IS NULL OR x {sign} b), true)").select(*rows.columns)


def few_rows(rows: DataFrame) -> list | None:
    """The rows (chunk, key, x, valid_from, valid_to) of some length, if there are ``FEW_ROWS`` at most and Python orders their
    values as Spark does; None otherwise.  Each task gives ``FEW_ROWS`` + 1 rows at most."""
    kinds = [rows.schema[c].dataType for c in ("key", "x", FROM)]
    exact = (T.IntegralType, T.DecimalType)
    if not isinstance(kinds[0], T.IntegralType) or not isinstance(kinds[1], exact) or not isinstance(kinds[2], (T.IntegralType, T.TimestampNTZType)):
        return None
    some = rows.where(F.col(FROM) < F.col(TO)).select("chunk", "key", "x", FROM, TO)
    if isinstance(kinds[2], T.TimestampNTZType):
        ends = (F.when(micros(F.col(c)).between(FIRST_INSTANT, LAST_INSTANT), F.col(c)).alias(c) for c in (FROM, TO))
        some = some.select("chunk", "key", "x", *ends)
    found = some.limit(FEW_ROWS + 1).agg(F.collect_list(F.struct(*some.columns)).alias("rows")).first().rows
    return None if len(found) > FEW_ROWS or any(v is None for r in found for v in r) else found


def ranked_here(few: list, rows: DataFrame, k: int, descending: bool, on: Sequence[str]) -> DataFrame:
    """(valid_from, valid_to, rank, on): the ranked timeline of what few_rows found in ``rows``."""
    import pyarrow as pa
    from pyspark.sql.pandas.types import to_arrow_schema

    by_chunk: dict = {}
    for chunk, *row in few:
        by_chunk.setdefault(chunk, []).append(row)
    swept = sweeper(k, descending)
    pieces = sorted((rank, f, t, key, x) for chunk in by_chunk.values() for rank, key, x, f, t in swept(chunk))
    out: list[list] = []
    for rank, f, t, key, x in pieces:
        kept = [key, x] if "key" in on else [x]
        if out and out[-1][1:] == [f, rank, *kept]:
            out[-1][1] = t
        else:
            out.append([f, t, rank, *kept])
    schema = T.StructType([rows.schema[FROM], rows.schema[TO], T.StructField("rank", T.IntegerType()), *(rows.schema[c] for c in on)])
    # as Arrow, which needs no Python worker
    columns = zip(*out, strict=True) if out else ([] for _ in schema)
    table = pa.table([pa.array(list(c), f.type) for c, f in zip(columns, to_arrow_schema(schema), strict=True)], schema=to_arrow_schema(schema))
    return rows.sparkSession.createDataFrame(table, schema)


def pairwise_compare(seg: DataFrame, key: str, left, right, x: str, cmp: str = "lt", emit: str = "true") -> DataFrame:
    """(left_key, right_key, valid_from, valid_to): where the left key's x stands in ``cmp`` to the right's.

    Only where both hold a value; ``emit="both"`` also gives the false stretches, in a column holds.  Sides are carried forward
    over the cuts of their chunk, without a join.
    """
    rows = chunked(seg).where(F.col(key).isin(left, right))
    side = F.when(F.col(key) == left, "l").otherwise("r")
    ends = F.array(F.struct(F.col(FROM).alias("at"), F.lit(1).alias("on"), F.col(x).alias("x")), F.struct(F.col(TO).alias("at"), F.lit(0).alias("on"), F.lit(None).cast(seg.schema[x].dataType).alias("x")))
    events = rows.select("chunk", side.alias("side"), F.explode(ends).alias("e")).select("chunk", "side", "e.at", F.struct("e.on", "e.x").alias("s"))
    # a start at the instant of an end replaces it
    events = events.groupBy("chunk", "at").agg(F.max(F.when(F.col("side") == "l", F.col("s"))).alias("l"), F.max(F.when(F.col("side") == "r", F.col("s"))).alias("r"))
    by = Window.partitionBy("chunk").orderBy("at")
    far = by.rowsBetween(Window.unboundedPreceding, 0)
    states = events.select("chunk", F.col("at").alias(FROM), F.lead("at").over(by).alias(TO), F.last("l", ignorenulls=True).over(far).alias("l"), F.last("r", ignorenulls=True).over(far).alias("r"))
    holds = predicate(COMPARE[cmp](F.col("l.x"), F.col("r.x")))
    both = states.where(F.col(TO).isNotNull() & (F.col("l.on") == 1) & (F.col("r.on") == 1) & F.col("l.x").isNotNull() & F.col("r.x").isNotNull())
    kind = seg.schema[key].dataType
    out = both.select(F.lit(left).cast(kind).alias("left_key"), F.lit(right).cast(kind).alias("right_key"), "chunk", FROM, TO, holds.alias("holds"))
    ids = ["left_key", "right_key"]
    if emit == "both":
        return coalesce_pieces(out, ids, ["holds"])
    return coalesce_pieces(out.where("holds"), ids)


def better_deltas(seg: DataFrame, key: str, reference, x: str, cmp: str = "lt", by: Sequence[str] = ()) -> DataFrame:
    """(by, chunk, at, delta, cover): changes of the number of candidates that beat the reference, and of the reference's own
    presence.  The reference's rows join each candidate's by chunk and overlap; a null x neither beats nor covers.  Candidates are
    dealt to ``REFERENCE_PARTS`` parts of a chunk, and the reference's few rows are copied to each."""
    rows = chunked(seg).where(F.col(x).isNotNull())
    ref = rows.where(F.col(key) == reference).select("chunk", F.col(FROM).alias("rf"), F.col(TO).alias("rt"), F.col(x).alias("rx")).distinct()
    parts = F.explode(F.sequence(F.lit(0), F.lit(REFERENCE_PARTS - 1)))
    met = rows.where(F.col(key) != reference).withColumn("_part", shard_of(key, REFERENCE_PARTS)).join(ref.withColumn("_part", parts), ["chunk", "_part"]).where((F.col(FROM) < F.col("rt")) & (F.col("rf") < F.col(TO)) & predicate(COMPARE[cmp](F.col(x), F.col("rx"))))
    met = met.select(*by, "chunk", F.greatest(FROM, "rf").alias("f"), F.least(TO, "rt").alias("t"))

    def ends(rows: DataFrame, better: int, cover: int) -> DataFrame:
        pair = F.array(*(F.struct(F.col(c).alias("at"), F.lit(s * better).cast("long").alias("delta"), F.lit(s * cover).cast("long").alias("cover")) for c, s in (("f", 1), ("t", -1))))
        return rows.select(*by, "chunk", F.explode(pair).alias("e")).select(*by, "chunk", "e.*")

    cover = ref.select("chunk", F.col("rf").alias("f"), F.col("rt").alias("t"))
    for c in by:
        cover = cover.withColumn(c, F.lit(0))
    return ends(met, 1, 0).unionByName(ends(cover.select(*by, "chunk", "f", "t"), 0, 1)).groupBy(*by, "chunk", "at").agg(F.sum("delta").alias("delta"), F.sum("cover").alias("cover"))


def merge_better(deltas: DataFrame, reference, kind) -> DataFrame:
    """(reference_key, valid_from, valid_to, better) from the deltas of disjoint candidate shards.  Where the reference is absent
    there is no answer; where it is present and unbeaten, the answer is zero."""
    summed = deltas.groupBy("chunk", "at").agg(F.sum("delta").alias("delta"), F.max("cover").alias("up"), F.min("cover").alias("down"))
    summed = summed.withColumn("cover", F.when(F.col("up") > 0, F.col("up")).otherwise(F.col("down")))
    by = Window.partitionBy("chunk").orderBy("at")
    far = by.rowsBetween(Window.unboundedPreceding, 0)
    steps = summed.select("chunk", F.col("at").alias(FROM), F.lead("at").over(by).alias(TO), F.sum("delta").over(far).alias("better"), F.sum("cover").over(far).alias("present"))
    out = steps.where((F.col("present") > 0) & F.col(TO).isNotNull()).select(F.lit(reference).cast(kind).alias("reference_key"), "chunk", FROM, TO, "better")
    return coalesce_pieces(out, ["reference_key"], ["better"])


def count_better_than(seg: DataFrame, key: str, reference, x: str, cmp: str = "lt", shards: int = 1) -> DataFrame:
    """How many others of the cohort beat the reference, where the reference holds a value.

    With ``shards`` each candidate shard has its own deltas beside the reference's replicated rows; sums don't change.
    """
    kind = seg.schema[key].dataType
    if shards == 1:
        return merge_better(better_deltas(seg, key, reference, x, cmp), reference, kind)
    dealt = chunked(seg).withColumn("shard", shard_of(key, shards))
    return merge_better(better_deltas(dealt, key, reference, x, cmp, by=["shard"]).select("chunk", "at", "delta", "cover"), reference, kind)


def ranked_timeline(seg: DataFrame, key: str, x: str, k: int, descending: bool = False, family: Sequence[str] = (), shards: int = 1, strategy: str = "native", identity: str = "entity", spans: Mapping[int, tuple[int, int]] | None = None) -> DataFrame:
    """(family, valid_from, valid_to, rank, key, x): ranks 1 to k of the members that hold a value, ties to the smaller key.

    ``shards``: each shard of candidates keeps its own best k, which are aligned and ranked again; a member among the best of
    all is among the best of its shard.  ``strategy``: native ranks by nodes of segments (see best_of_segments), or here, if few
    rows of a single cohort can have a rank at all; sweep walks a chunk's events in order with a sorted set, for chunks that fit
    one worker.  ``identity="value"`` joins rows by rank and x alone.  ``spans``: see within_reach.
    """
    family = list(family)
    rows = chunked(seg).where(F.col(x).isNotNull()).select(*family, "chunk", F.col(key).alias("key"), F.col(x).alias("x"), FROM, TO)
    on = ["key", "x"] if identity == "entity" else ["x"]
    if not family:
        near = within_reach(rows, k, descending, spans)
        if near is not rows and shards == 1 and strategy == "native" and (few := few_rows(near)) is not None:
            return ranked_here(few, near, k, descending, on)
        rows = near
    if shards > 1:
        dealt = rows.withColumn("shard", shard_of("key", shards))
        best = _best(dealt, [*family, "shard"], k, descending, strategy)
        rows = best.select(*family, "chunk", "key", "x", FROM, TO)
    best = _best(rows, family, k, descending, strategy)
    out = coalesce_pieces(best, [*family, "rank"], on)
    return out.select(*family, FROM, TO, "rank", *on)


def ranked_lists(seg: DataFrame, key: str, x: str, k: int, descending: bool = False, family: Sequence[str] = ()) -> DataFrame:
    """(family, valid_from, valid_to, members): the best k of every segment between neighbouring cuts as one ordered list of
    (rank, key, x); a list has k members at most."""
    family = list(family)
    rows = chunked(seg).where(F.col(x).isNotNull()).select(*family, "chunk", F.col(key).alias("key"), F.col(x).alias("x"), FROM, TO)
    ids = [*family, "chunk"]
    cuts = numbered_cuts(rows, ids)
    best = best_of_segments(rows, cuts, ids, k, descending).join(cuts.hint("merge"), [*ids, "_n"]).withColumnsRenamed({"seg_from": FROM, "seg_to": TO})
    return best.groupBy(*family, "chunk", FROM, TO).agg(F.sort_array(F.collect_list(F.struct("rank", "key", "x"))).alias("members")).drop("chunk")


def winner_timeline(seg: DataFrame, key: str, x: str, **options) -> DataFrame:
    return ranked_timeline(seg, key, x, 1, **options)


def _best(rows: DataFrame, family: Sequence[str], k: int, descending: bool, strategy: str) -> DataFrame:
    """(family, chunk, rank, key, x, valid_from, valid_to), pieces not yet joined."""
    ids = [*family, "chunk"]
    if strategy == "native":
        cuts = numbered_cuts(rows, ids)
        shown = [*ids, "_block", "rank", "key", "x"]
        # segments of a block that follow each other with the same member at a rank are one row before they leave the task
        nth = F.row_number().over(Window.partitionBy(*shown).orderBy("_n"))
        runs = best_of_segments(rows, cuts, ids, k, descending).withColumn("_run", F.col("_n") - nth)
        runs = runs.groupBy(*shown, "_run").agg(F.min("_n").alias("_first"), F.max("_n").alias("_last"))
        for end, name, at in ((FROM, "_first", "seg_from"), (TO, "_last", "seg_to")):
            runs = runs.join(cuts.select(*ids, at, "_n").toDF(*ids, end, name).hint("merge"), [*ids, name])
        return runs.select(*ids, "rank", "key", "x", FROM, TO)
    if strategy != "sweep":
        raise ValueError(f"strategy is native or sweep, not {strategy}")
    kinds = {f.name: f.dataType.simpleString() for f in rows.schema}
    schema = ", ".join([*(f"`{c}` {kinds[c]}" for c in ids), "rank int", f"key {kinds['key']}", f"x {kinds['x']}", f"{FROM} {kinds[FROM]}", f"{TO} {kinds[TO]}"])
    return rows.groupBy(*ids).applyInPandas(_sweep(ids, k, descending), schema)


def sweeper(k: int, descending: bool):
    """A function of one (family, chunk)'s rows (key, x, valid_from, valid_to) that gives (rank, key, x, valid_from, valid_to): one pass
    over their starts and ends, with a sorted list of who holds.  It goes to workers whole, which need not have this package."""

    def swept(rows: Iterable) -> list[tuple]:
        import bisect

        rows = list(rows)
        values = sorted({x for _, x, _, _ in rows}, reverse=descending)
        place = {x: i for i, x in enumerate(values)}
        events: dict = {}
        for key, x, f, t in rows:
            events.setdefault(t, ([], []))[0].append((place[x], key))
            events.setdefault(f, ([], []))[1].append((place[x], key))
        active: list = []
        shown: list = []
        since: list = []
        out: list[tuple] = []
        for at in sorted(events):
            ended, began = events[at]
            for e in ended:
                active.pop(bisect.bisect_left(active, e))
            for e in began:
                bisect.insort(active, e)
            now = active[:k]
            for r in range(max(len(now), len(shown))):
                old, new = (shown[r] if r < len(shown) else None), (now[r] if r < len(now) else None)
                if old != new:
                    if old is not None:
                        out.append((r + 1, old[1], values[old[0]], since[r], at))
                    if r < len(since):
                        since[r] = at
                    else:
                        since.append(at)
            shown = now
        return out

    return swept


def _sweep(ids: Sequence[str], k: int, descending: bool):
    """Sweeps one (family, chunk), which is in one worker whole, with a dict of its events: for groups that fit one, as shards of
    candidates make them."""

    swept = sweeper(k, descending)

    def walk(group):
        import pandas as pd

        found = swept(zip(group["key"], group["x"], group[FROM], group[TO], strict=True))
        frame = pd.DataFrame(found, columns=["rank", "key", "x", FROM, TO])
        for i, c in enumerate(ids):
            frame.insert(i, c, group[c].iloc[0])
        return frame

    return walk


def active_per_cut(seg: DataFrame, family: Sequence[str] = ()) -> Iterator[int] | int:
    """Estimate of cuts times members in the fullest chunk, to choose between the strategies."""
    ids = [*family, "chunk"]
    sizes = chunked(seg).groupBy(*ids).agg((F.approx_count_distinct(FROM) * 2).alias("cuts"), F.count(F.lit(1)).alias("n"))
    row = sizes.agg(F.max(F.col("cuts") * F.col("n")).alias("m")).first()
    return int(row.m or 0)


def choose_strategy(seg: DataFrame, family: Sequence[str] = (), limit: int = 50_000_000) -> str:
    return "native" if active_per_cut(seg, family) <= limit else "sweep"
