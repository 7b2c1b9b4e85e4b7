"""Nearness on a line inside groups: what the pairs give, without the pairs.

Rows (k, n, b): a key, a group and a place.  Two rows of a group are near where their
places differ by less than a width.  In the order of places the rows near to one are a
run, so sums over them are differences of running sums.  Differences are taken in double
precision, as a join would; they rise with the place, so runs have exact ends.
"""

from __future__ import annotations

from collections.abc import Iterator
from heapq import heappop, heappush

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Places in a task of a strip, in widths; those that its rows look at on either side come besides.
STRIP = 10
#: Rows that a task hands on at once; pairs of places in a run that are kept to be read again are those of so many places.
ROWS, KEPT = 200_000, 512
#: Tasks, at least, that make pairs of near rows.
TASKS = 64
#: Pairs that a task of near_counts works on at once, and cells of its table of sums.
BLOCK, CELLS = 500_000, 24_000_000
#: Rows that a task of near_distances starts from, and ends that follow each other in its pairs and in those of near_reach.
STARTS, CHUNK = 1024, 256


def placed(rows: DataFrame) -> DataFrame:
    """Rows that can be near to another: nothing is null and the place is finite."""
    return rows.where("k is not null and n is not null and b is not null and not isnan(b) and abs(b) < double('infinity')")


def unique_keys(rows: DataFrame) -> bool:
    return rows.groupBy("k").count().where("count > 1").limit(1).count() == 0


def runs(u: np.ndarray, width: float) -> tuple[np.ndarray, np.ndarray]:
    """For each of the rising places u the first place near to it, and the one behind the last."""
    low, high = np.searchsorted(u, u - width, "left"), np.searchsorted(u, u + width, "left")
    last, inside = len(u) - 1, lambda i: np.clip(i, 0, len(u) - 1)
    while True:  # rounding moves an end by a place or two
        down, up = (low > 0) & (u - u[inside(low - 1)] < width), u - u[inside(low)] >= width
        more, less = (high <= last) & (u[inside(high)] - u < width), u[inside(high - 1)] - u >= width
        if not (down.any() or up.any() or more.any() or less.any()):
            return low, high
        low, high = low - down + up, high + more - less


def trail_counts(places: np.ndarray, width: float, low: int, up: int) -> np.ndarray:
    """Trails of low to up (at most three) edges from each row, over near rows.

    In a simple graph trails of up to three edges are the walks that never turn back at once.
    """
    u, at = np.unique(places, return_inverse=True)
    a, b = runs(u, width)

    def around(x: np.ndarray) -> np.ndarray:
        """Sum of x over the rows near to each, itself not counted."""
        total = np.concatenate([[0], np.cumsum(_summed(at, x, len(u)))])
        return (total[b] - total[a])[at] - x

    degree = around(np.ones(len(places), np.int64))
    on = around(degree - 1)  # trails of two edges
    by = [degree, on, around(on) - degree * (degree - 1)]
    return np.sum(by[low - 1:up], axis=0)


def _summed(at: np.ndarray, x: np.ndarray, n: int) -> np.ndarray:
    out = np.zeros(n, np.int64)
    np.add.at(out, at, x)
    return out


def near_trails(rows: DataFrame, width: float, low: int, up: int | None) -> DataFrame | None:
    """(k, n): numbers of trails over near rows, where there are some; None where this way does not count them."""
    rows = placed(rows)
    if low < 1 or up is None or up > 3 or not unique_keys(rows):
        return None

    def count(group: pa.Table) -> pa.Table:
        return pa.table([group.column("k"), pa.array(trail_counts(group.column("b").to_numpy(), width, low, up), pa.int64())], ["k", "trails"])

    return rows.groupBy("n").applyInArrow(count, "k long, trails long").where("trails > 0")


def near_distances(rows: DataFrame, width: float) -> DataFrame:
    """(start, end, hops): fewest steps over near rows between all rows (k, n, b) that reach each other.

    Rows of one more hop lie on both sides of those of fewer, up to the ends of their runs.
    A task has a group's places and the starts of a block; it gives stretches of rows that are
    equally far from a start, cut where a chunk of ends begins, and a pair is made where it is written.
    Starts of a block stand behind each other at each chunk, so that columns of pairs repeat.
    """
    rows = rows.where("k is not null")
    can = placed(rows)
    blocks = can.groupBy("n").agg(F.ceil(F.count(F.lit(1)) / STARTS).cast("int").alias("blocks"))
    dealt = can.join(blocks, "n").withColumn("block", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    dealt = dealt.repartition(max(int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")), TASKS), "n", "block")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        group = _ordered(batches)
        k = group.column("k").to_numpy()
        blocks, block = group.column("blocks")[0].as_py(), group.column("block")[0].as_py()
        starts = np.arange(block, len(k), blocks)
        ends, hops = rings(group.column("b").to_numpy(), width, starts)
        of, ring = np.nonzero(np.diff(ends, axis=1))
        low, high = ends[of, ring], ends[of, ring + 1]
        pieces = (high - 1) // CHUNK - low // CHUNK + 1
        i = np.repeat(np.arange(len(of)), pieces)
        chunk = low[i] // CHUNK + np.arange(len(i)) - np.repeat(np.cumsum(pieces) - pieces, pieces)
        i, chunk = (x[np.argsort(chunk, kind="stable")] for x in (i, chunk))
        low, high = np.maximum(low[i], chunk * CHUNK), np.minimum(high[i], (chunk + 1) * CHUNK)
        cuts = np.searchsorted(chunk, np.arange(-(-len(k) // CHUNK) + 1))
        for c, (lo, hi) in enumerate(zip(cuts, cuts[1:])):
            at, j = c * CHUNK, i[lo:hi]
            columns = [(k[starts[of[j]]], pa.int64()), (low[lo:hi] - at + 1, pa.int32()), (high[lo:hi] - low[lo:hi], pa.int32()), (hops[ring[j]], pa.int32())]
            found = pa.StructArray.from_arrays([pa.array(x, t) for x, t in columns], ["start", "low", "size", "hops"])
            lists = [pa.ListArray.from_arrays(pa.array([0, len(x)], pa.int32()), x) for x in (pa.array(k[at:at + CHUNK], pa.int64()), found)]
            yield pa.RecordBatch.from_arrays(lists, ["ends", "found"])

    found = dealt.groupBy("n", "block").applyInArrow(run, "ends array<long>, found array<struct<start: long, low: int, size: int, hops: int>>")
    found = found.select("ends", F.explode("found").alias("x")).select(F.col("x.start").alias("start"), F.explode(F.slice("ends", F.col("x.low"), F.col("x.size"))).alias("end"), F.col("x.hops").alias("hops"))
    known = "n is not null and b is not null and not isnan(b) and abs(b) < double('infinity')"
    alone = rows.where(f"not coalesce({known}, false)")
    return found.unionByName(alone.select(F.col("k").alias("start"), F.col("k").alias("end"), F.lit(0).alias("hops")))


def rings(places: np.ndarray, width: float, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Borders between rows that are equally far from each start, a line a start, and how far those behind each border are; places rise."""
    u, at = np.unique(places, return_inverse=True)
    first, behind = runs(u, width)
    edge = np.searchsorted(at, np.arange(len(u) + 1))  # where a place's rows begin
    low, high = at[starts], at[starts] + 1
    left, right = [edge[low]], [edge[high]]
    while True:
        a, c = first[low], behind[high - 1]
        if np.array_equal(a, low) and np.array_equal(c, high):
            break
        low, high = a, c
        left.append(edge[low])
        right.append(edge[high])
    n = len(left) - 1
    return np.stack([*reversed(left), starts, starts + 1, *right], axis=1), np.concatenate([np.arange(n, 0, -1), [1, 0, 1], np.arange(1, n + 1)])


def near_components(rows: DataFrame, width: float) -> DataFrame:
    """(k, n, part, at): placed rows, the number in its group of the stretch of places that reach each other, and the row's own number in the group."""
    order = Window.partitionBy("n").orderBy("b", "k")
    far = F.coalesce(F.col("b") - F.lag("b").over(order) >= width, F.lit(False))
    return placed(rows).withColumns({"_far": far.cast("long"), "at": F.row_number().over(order)}).select("k", "n", F.sum("_far").over(order.rowsBetween(Window.unboundedPreceding, 0)).alias("part"), "at")


def near_reach(rows: DataFrame, width: float, low: int, chunk: int = CHUNK) -> DataFrame:
    """(a, b): rows and those that walks of at least low (0 or 1) steps over near rows lead to, once each; keys are unique.

    Rows that reach each other are a stretch of places.  Starts of a chunk meet the ends of a chunk as two
    lists, and a pair is made where it is written; nothing but the rows is shuffled.
    """
    found = near_components(rows, width)
    chunks = [found.groupBy("n", "part", F.floor(F.col("at") / size).alias("block")).agg(F.collect_list("k").alias(name)) for size, name in ((STARTS, "starts"), (chunk, "keys"))]
    whole = chunks[0].groupBy("n", "part").agg(F.collect_list("block").alias("blocks"), F.sum(F.size("starts")).alias("size"))
    if low:
        whole = whole.where("size > 1")
    tasks = max(int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")), TASKS)
    starts = chunks[0].repartition(tasks, "n", "part", "block")
    ends = chunks[1].drop("block").join(whole, ["n", "part"]).select("n", "part", "keys", F.explode("blocks").alias("block")).repartition(tasks, "n", "part", "block")
    pairs = starts.join(ends.hint("shuffle_merge"), ["n", "part", "block"])
    out = pairs.select("keys", F.explode("starts").alias("a")).select("a", F.explode("keys").alias("b"))
    if low:
        return out
    known = "n is not null and b is not null and not isnan(b) and abs(b) < double('infinity')"
    alone = rows.where(f"k is not null and not coalesce({known}, false)")
    return out.unionByName(alone.select(F.col("k").alias("a"), F.col("k").alias("b")))


def strips(rows: DataFrame, width: float, reach: int) -> DataFrame:
    """Rows dealt to strips of places: each to its own strip and to those that look so many widths far."""
    size, far = width * STRIP, width * (reach + 0.001)  # a little further, for what rounding makes near
    rows = placed(rows)
    near = F.array_distinct(F.array(F.floor((F.col("b") - far) / size), F.floor(F.col("b") / size), F.floor((F.col("b") + far) / size)))
    return rows.withColumn("own", F.floor(F.col("b") / size)).withColumn("strip", F.explode(near))


def _ordered(batches: Iterator[pa.RecordBatch]) -> pa.Table:
    return pa.Table.from_batches(batches).sort_by([("b", "ascending"), ("k", "ascending")])


def _strip(batches: Iterator[pa.RecordBatch], width: float) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Keys of a strip in the order of places, its own rows, and where the run of each begins and ends."""
    return _runs_of(_ordered(batches), width)


def _runs_of(group: pa.Table, width: float) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    u, at = np.unique(group.column("b").to_numpy(), return_inverse=True)
    first, behind = runs(u, width)
    edge = np.searchsorted(at, np.arange(len(u) + 1))
    mine = np.flatnonzero(group.column("own").to_numpy() == group.column("strip").to_numpy())
    return group.column("k").to_numpy(), mine, edge[first[at]], edge[behind[at]]


def _handed_on(found: Iterator[tuple[np.ndarray, ...]], names: list[str]) -> Iterator[pa.RecordBatch]:
    """Columns in batches of some ROWS rows."""
    waiting, rows = [], 0
    for columns in found:
        waiting.append(columns)
        rows += len(columns[0])
        if rows >= ROWS:
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*waiting)], names)
            waiting, rows = [], 0
    if rows:
        yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*waiting)], names)


def near_triangles(rows: DataFrame, width: float, kept: int = KEPT) -> DataFrame:
    """(a, b, c): rows near to each other in threes, a < b < c, of unique keys.

    The lowest place of three has the other two in the upper half of its run, where any two
    are near to each other: no pair is looked up, and nothing but the rows is shuffled.
    """
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def found():
            k, mine, _, behind = _strip(batches, width)
            q = np.repeat(np.arange(kept), np.arange(kept))
            p = np.arange(len(q)) - q * (q - 1) // 2  # pairs p < q; those of fewer places come first
            for i in mine:
                x, others = k[i], np.sort(k[i + 1 : behind[i]])
                m = min(len(others), kept)
                few = m * (m - 1) // 2
                yield ordered(x, others[p[:few]], others[q[:few]])
                for j in range(kept, len(others)):
                    yield ordered(x, others[:j], np.full(j, others[j]))

        def ordered(x, low, high):
            return np.minimum(x, low), np.maximum(np.minimum(x, high), low), np.maximum(x, high)

        yield from _handed_on(found(), ["a", "b", "c"])

    return strips(rows, width, 1).select("k", "n", "b", "own", "strip").groupBy("n", "strip").applyInArrow(run, "a long, b long, c long")


def near_pairs(rows: DataFrame, width: float, direction: str, firsts: list[str] = (), seconds: list[str] = (), handed: int = ROWS) -> DataFrame:
    """(k, k2, turned, v0..., w0...): pairs k < k2 of near rows with columns of the end that a pair is read from and of the other one.

    Read out, in or both ways (then twice); turned: from k2.  Where rows have a column start, only from
    those that hold it.  With columns was and now, which say how often a row stood and stands, the pairs
    that come or go, and __w of them.  Nothing but the rows is shuffled.
    """
    kinds = dict(rows.dtypes)
    weighted, some = "now" in kinds, "start" in kinds
    fields = ["k long", "k2 long", "turned boolean", *(f"v{i} {kinds[c]}" for i, c in enumerate(firsts)), *(f"w{i} {kinds[c]}" for i, c in enumerate(seconds))]
    names = [f.split()[0] for f in fields] + (["__w"] if weighted else [])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        group = _ordered(batches)
        k, mine, first, behind = _runs_of(group, width)
        column = {c: group.column(c).combine_chunks() for c in {*firsts, *seconds}}
        if some:
            mine = mine[group.column("start").to_numpy()[mine]]
        if weighted:
            was, now = (group.column(c).to_numpy() for c in ("was", "now"))
        size = (behind - first)[mine]
        ends = np.cumsum(size)
        lo = 0
        while lo < len(mine):
            hi = max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + handed, "right")))
            n = size[lo:hi]
            i = np.repeat(mine[lo:hi], n)
            j = np.arange(n.sum()) + np.repeat(first[mine[lo:hi]] - np.cumsum(n) + n, n)
            keep = k[i] < k[j] if direction == "out" else k[i] > k[j] if direction == "in" else k[i] != k[j]
            if weighted:
                keep &= now[i] * now[j] != was[i] * was[j]
            i, j = i[keep], j[keep]
            x, y = k[i], k[j]
            out = [np.minimum(x, y), np.maximum(x, y), x > y]
            out = [pa.array(c) for c in out] + [column[c].take(pa.array(i)) for c in firsts] + [column[c].take(pa.array(j)) for c in seconds]
            if weighted:
                out.append(pa.array(now[i] * now[j] - was[i] * was[j]))
            yield pa.RecordBatch.from_arrays(out, names)
            lo = hi

    # beside one more row the optimizer takes pairs for more than they are in its own estimate, and broadcasts only those of few rows
    wide = rows.crossJoin(rows.sparkSession.range(1).select(F.col("id").alias("_one")))
    dealt = strips(wide, width, 1).select("k", "n", "b", "own", "strip", *sorted({*firsts, *seconds} - {"k", "n", "b"}), *(["start"] if some else []), *(["was", "now"] if weighted else []))
    # few rows make many pairs: as many tasks as there are shuffle partitions, not as the rows' bytes would have it
    dealt = dealt.repartition(max(int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")), TASKS), "n", "strip")
    return dealt.groupBy("n", "strip").applyInArrow(run, ", ".join(fields + (["__w long"] if weighted else [])))


def near_counts(rows: DataFrame, width: float, reach: int, third: str, firsts: list[str], seconds: list[str], same: list[str] = (), kinds_of: int = 1, block: int = BLOCK, cells: int = CELLS) -> DataFrame:
    """(k, k2, v0..., w0..., sums): pairs k < k2 with columns of both ends, and how many rows of each kind z are near to both.

    reach: 1 where the ends are near to each other, 2 where it is enough that one row is near to both.
    third: which rows count by their key: below, between or above those of the ends; same: columns in
    which the ends are equal and not null.  Columns was and now say whether a row stood and stands; sums
    are those of now less those of was.  The rows near to both ends are a run of places and a range of
    keys, so each number is a difference of sums over corners, and no third row is looked up.
    """
    types = dict(rows.dtypes)
    fields = ["k long", "k2 long", *(f"v{i} {types[c]}" for i, c in enumerate(firsts)), *(f"w{i} {types[c]}" for i, c in enumerate(seconds)), "sums array<long>"]
    names = [f.split()[0] for f in fields]
    block = max(1, block // -(-kinds_of // 8))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        group = _ordered(batches)
        k, mine, first, behind = _runs_of(group, width)
        z, was, now = (group.column(c).to_numpy() for c in ("z", "was", "now"))
        column = {c: group.column(c).combine_chunks() for c in {*firsts, *seconds}}
        codes = [_codes(group.column(c)) for c in same]
        if np.array_equal(was, now):
            return
        low, high = (first, behind) if reach == 1 else (first[first], behind[behind - 1])
        size = (high - low)[mine]
        ends = np.cumsum(size)
        lo = 0
        while lo < len(mine):
            hi = max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + block, "right")))
            n, from_ = size[lo:hi], mine[lo:hi]
            i = np.repeat(from_, n)
            j = np.arange(n.sum()) + np.repeat(low[from_] - np.cumsum(n) + n, n)
            keep = (k[i] < k[j]) & ((now[i] * now[j] != 0) | (was[i] * was[j] != 0))
            for c in codes:
                keep &= (c[i] == c[j]) & (c[i] >= 0)
            i, j = i[keep], j[keep]
            base, top = low[from_].min(), high[from_].max()
            rank = np.unique(k[base:top], return_inverse=True)[1]
            start, stop = np.maximum(first[i], first[j]) - base, np.minimum(behind[i], behind[j]) - base
            a, b = rank[i - base], rank[j - base]
            above, below = {"below": (np.zeros_like(a), a), "between": (a + 1, b), "above": (b + 1, np.full_like(b, top - base))}[third]
            sums = np.zeros((len(i), kinds_of), np.int64)
            for w, sign in ((now, 1), (was, -1)):
                pair = sign * w[i] * w[j]
                for c in range(kinds_of):
                    some = np.flatnonzero((z[base:top] == c) & (w[base:top] != 0))
                    if len(some) and pair.any():
                        sums[:, c] += pair * _in_boxes(some, rank[some], w[base:top][some], top - base, start, stop, above, below, cells)
            kept = np.flatnonzero(sums.any(axis=1))
            i, j, sums = i[kept], j[kept], sums[kept]
            out = [pa.array(k[i]), pa.array(k[j])] + [column[c].take(pa.array(i)) for c in firsts] + [column[c].take(pa.array(j)) for c in seconds]
            out.append(pa.ListArray.from_arrays(pa.array(np.arange(len(i) + 1, dtype=np.int32) * kinds_of), pa.array(sums.ravel())))
            made = pa.RecordBatch.from_arrays(out, names)
            for at in range(0, len(i), ROWS):
                yield made.slice(at, ROWS)
            lo = hi

    dealt = strips(rows, width, reach).select("k", "n", "b", "z", "was", "now", "own", "strip", *sorted({*firsts, *seconds, *same} - {"k", "n", "b", "z"}))
    dealt = dealt.repartition(max(int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")), TASKS), "n", "strip")
    return dealt.groupBy("n", "strip").applyInArrow(run, ", ".join(fields))


def _codes(values: pa.ChunkedArray) -> np.ndarray:
    """Numbers of values, equal where those are; -1 for null."""
    coded = values.combine_chunks().dictionary_encode()
    return coded.indices.fill_null(-1).to_numpy(zero_copy_only=False)


def _in_boxes(place: np.ndarray, rank: np.ndarray, weight: np.ndarray, n: int, start, stop, above, below, cells: int) -> np.ndarray:
    """Weight of the points (place, rank), both under n, in each box of places from start and ranks from above, up to stop and below.

    A table of sums holds so many ranks that it has some cells; further ranks come in further tables.
    """
    total = np.zeros(len(start), np.int64)
    step = max(1, min(n, cells // (n + 1)))
    for r in range(0, n, step):
        inside = (rank >= r) & (rank < r + step)
        if not inside.any():
            continue
        table = np.zeros((n + 1, step + 1), np.int32)
        np.add.at(table, (place[inside] + 1, rank[inside] - r + 1), weight[inside])
        np.cumsum(table, 0, np.int32, table)
        np.cumsum(table, 1, np.int32, table)
        table = table.ravel()
        a, b = np.clip(above - r, 0, step), np.clip(below - r, 0, step)
        b = np.maximum(a, b)
        x, y = start * (step + 1), np.maximum(start, stop) * (step + 1)
        total += table.take(y + b) - table.take(y + a) - table.take(x + b) + table.take(x + a)
    return total


def near_walks(rows: DataFrame, width: float, kept: int = KEPT, back: bool = True) -> DataFrame:
    """(a, b): ends of all walks of two edges over near rows, once a walk; keys are unique.  Walks turn back where back says so."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def found():
            k, mine, first, behind = _strip(batches, width)
            for i in mine:
                for lo in range(first[i], behind[i], kept):
                    over = np.arange(lo, min(lo + kept, behind[i]))
                    over = over[over != i]
                    size = behind[over] - first[over]
                    at = np.arange(size.sum()) + np.repeat(first[over] - np.cumsum(size) + size, size)
                    on = at != np.repeat(over, size)
                    ends = k[at[on if back else on & (at != i)]]
                    yield np.full(len(ends), k[i]), ends

        yield from _handed_on(found(), ["a", "b"])

    return strips(rows, width, 2).select("k", "n", "b", "own", "strip").groupBy("n", "strip").applyInArrow(run, "a long, b long")


def best_of_near(rows: DataFrame, width: float, best: int) -> DataFrame:
    """(c, p, n): for each row (k, n, b, items) the items of most near rows that are not its own; ties to the smaller.

    A task holds a strip of a group's places and slides over it: items enter and leave the
    counts with their rows, and each count has a heap of its items, cleaned when it is read.
    """
    dealt = strips(rows, width, 1)

    def run(group: pa.Table) -> pa.Table:
        group = group.sort_by("b")
        b, keys = group.column("b").to_pylist(), group.column("k").to_pylist()
        mine = [x == y for x, y in zip(group.column("own").to_pylist(), group.column("strip").to_pylist())]
        items = [x or [] for x in group.column("items").to_pylist()]
        found = list(slide(b, items, mine, width, best))
        columns = list(zip(*((keys[i], p, n) for i, p, n in found))) or [(), (), ()]
        return pa.table([pa.array(c, pa.int64()) for c in columns], ["c", "p", "n"])

    return dealt.select("k", "n", "b", "items", "own", "strip").groupBy("n", "strip").applyInArrow(run, "c long, p long, n long")


def all_of_near(rows: DataFrame, width: float, handed: int = ROWS) -> DataFrame:
    """(c, p, n): for each row (k, n, b, items) every item of near rows that is not its own, and of how many; items are sets.

    A task slides over a strip as in best_of_near; the items of a row leave it as one list, and nothing
    but the rows is shuffled.
    """
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        group = _ordered(batches)
        k, mine, first, behind = _runs_of(group, width)
        lists = group.column("items").combine_chunks()
        size = lists.value_lengths().fill_null(0).to_numpy(zero_copy_only=False)
        edge = np.concatenate([[0], np.cumsum(size)])
        values, at = np.unique(lists.flatten().to_numpy(), return_inverse=True)
        count = np.zeros(len(values), np.int32)
        lo = hi = waiting = 0
        keys, found, numbers = [], [], []

        def batch() -> pa.RecordBatch:
            ends = pa.array(np.concatenate([[0], np.cumsum([len(x) for x in found])]).astype(np.int32))
            made = [pa.ListArray.from_arrays(ends, pa.array(np.concatenate(x))) for x in (found, numbers)]
            return pa.RecordBatch.from_arrays([pa.array(keys, pa.int64()), *made], ["c", "items", "counts"])

        for i in mine:
            for j in range(hi, behind[i]):
                count[at[edge[j]:edge[j + 1]]] += 1
            for j in range(lo, first[i]):
                count[at[edge[j]:edge[j + 1]]] -= 1
            lo, hi = first[i], behind[i]
            own = at[edge[i]:edge[i + 1]]
            held, count[own] = count[own], 0
            some = np.flatnonzero(count)
            if len(some):
                keys.append(k[i])
                found.append(values[some])
                numbers.append(count[some])
                waiting += len(some)
            count[own] = held
            if waiting >= handed:
                yield batch()
                keys, found, numbers, waiting = [], [], [], 0
        if keys:
            yield batch()

    dealt = strips(rows, width, 1).select("k", "n", "b", "items", "own", "strip")
    dealt = dealt.repartition(max(int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")), TASKS), "n", "strip")
    listed = dealt.groupBy("n", "strip").applyInArrow(run, "c long, items array<long>, counts array<int>")
    return listed.select("c", "counts", F.posexplode("items").alias("_at", "p")).select("c", "p", F.get("counts", F.col("_at")).cast("long").alias("n"))


def slide(b: list[float], items: list[list[int]], mine: list[bool], width: float, best: int):
    """(place in the list, item, number): the best items of the rows near to each of mine."""
    count: dict[int, int] = {}
    heaps: list[list[int]] = [[]]
    first = behind = 0
    for i, at in enumerate(b):
        if not mine[i]:
            continue
        while behind < len(b) and b[behind] - at < width:
            for p in items[behind]:
                count[p] = c = count.get(p, 0) + 1
                if c == len(heaps):
                    heaps.append([])
                heappush(heaps[c], p)
            behind += 1
        while at - b[first] >= width:
            for p in items[first]:
                c = count[p] - 1
                if c:
                    count[p] = c
                    heappush(heaps[c], p)
                else:
                    del count[p]
            first += 1
        own, taken = set(items[i]), 0
        for c in range(len(heaps) - 1, 0, -1):
            heap, kept, last = heaps[c], [], None
            while heap and taken < best:
                p = heappop(heap)
                if p == last or count.get(p) != c:
                    continue
                kept.append(p)
                last = p
                if p not in own:
                    taken += 1
                    yield i, p, c
            for p in kept:
                heappush(heap, p)
            if taken == best:
                break
