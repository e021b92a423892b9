"""Best-fit packing of tokenised documents by bin completion.

Bin packing sees lengths only, and there are at most `capacity` of them, so the search works on a
histogram whose size does not depend on the data. A node of the search takes the largest piece
left and enumerates the undominated fillings of the room beside it; a filling is used as often as
its counts allow; a branch whose waste exceeds what the incumbent permits is cut. The incumbent is
best-fit decreasing. The result is a list of patterns (a filling and how often), which documents
then meet by their rank among the pieces of their length - ranks are counted in salted groups.

Defined results: a null text is packed as empty (one end token); repeated rows are packed each; an
empty table packs nothing. `pack` needs doc_id and text; further columns are dropped.
"""

from __future__ import annotations

import itertools
import zlib
from array import array
from bisect import bisect_right
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from celldiv.llm import tokens
from celldiv.llm.common import persisted

CAPACITY = 2048
#: Nodes of the search and fillings of one node; the incumbent stands when they are used up.
MAX_NODES, MAX_FILLINGS, FEW_PIECES = 6_000, 24, 16

Pattern = tuple[tuple[int, ...], int]


# ---- the search over a histogram -------------------------------------------------------------

def best_fit(counts: dict[int, int], capacity: int) -> list[Pattern]:
    """Best-fit decreasing on a histogram: equal bins that get equal pieces stay one group."""
    groups: dict[tuple[int, ...], int] = {}
    by_room: dict[int, list[tuple[int, ...]]] = {}
    rooms: list[int] = []

    def put(bin_: tuple[int, ...], n: int, room: int) -> None:
        if bin_ not in groups:
            if room not in by_room:
                by_room[room] = []
                rooms.insert(bisect_right(rooms, room), room)
            by_room[room].append(bin_)
        groups[bin_] = groups.get(bin_, 0) + n

    for size in sorted(counts, reverse=True):
        left = counts[size]
        while left:
            at = bisect_right(rooms, size - 1)
            if at == len(rooms):
                each = min(capacity // size, left)
                n = left // each
                put((size,) * each, n, capacity - size * each)
                left -= n * each
                continue
            room = rooms[at]
            bin_ = by_room[room][-1]
            have, fits = groups[bin_], room // size
            each = min(fits, left)
            n = min(have, left // each)
            groups[bin_] -= n
            if not groups[bin_]:
                del groups[bin_]
                by_room[room].pop()
                if not by_room[room]:
                    del by_room[room]
                    rooms.pop(at)
            put(bin_ + (size,) * each, n, room - size * each)
            left -= n * each
    return list(groups.items())


def lower_bound(counts: dict[int, int], capacity: int) -> int:
    """The larger of the volume bound and, for each k, pieces over capacity - k plus what cannot join them."""
    total = sum(s * n for s, n in counts.items())
    best = -(-total // capacity)
    sizes = sorted(counts)
    for k in [0, *[s for s in sizes if 2 * s <= capacity]]:
        over = sum(n for s, n in counts.items() if s > capacity - k)
        half = [(s, n) for s, n in counts.items() if 2 * s > capacity and s <= capacity - k]
        rest = sum(s * n for s, n in counts.items() if k <= s and 2 * s <= capacity)
        free = sum((capacity - s) * n for s, n in half)
        best = max(best, over + sum(n for _, n in half) + max(0, -(-(rest - free) // capacity)))
    return best


def fullest(counts: dict[int, int], room: int, largest: int | None = None) -> tuple[int, ...]:
    """The set of pieces (none above `largest`) with the greatest sum within the room; of those, the one of largest pieces.

    Sums that the pieces up to a size can make are the bits of one number; a piece used up to c times
    shifts them by its powers of two.
    """
    mask = (1 << (room + 1)) - 1
    sizes = sorted(s for s in counts if counts[s] and s <= min(room, largest or room))
    reach, steps = 1, []
    for s in sizes:
        steps.append(reach)
        times = min(counts[s], room // s)
        part = 1
        while times:
            part = min(part, times)
            reach |= (reach << s * part) & mask
            times -= part
            part *= 2
    target, found = reach.bit_length() - 1, []
    for s, below in zip(reversed(sizes), reversed(steps)):
        # as many of the largest as leave a sum that the smaller ones make
        for n in range(min(counts[s], target // s), -1, -1):
            if below >> (target - n * s) & 1:
                found += [s] * n
                target -= n * s
                break
    return tuple(found)


def fillings(counts: dict[int, int], room: int, limit: int) -> Iterator[tuple[int, ...]]:
    """Undominated sets of pieces for the room, the fullest first.

    A set is dominated if its pieces can be dealt to the pieces of another without overfilling one:
    putting the other's pieces there instead never hurts the rest. Few pieces are enumerated in full;
    of many, the fullest set for each choice of its largest piece, at most `limit`.
    """
    best, few, held = fullest(counts, room), sum(counts.values()) <= FEW_PIECES, _packed(counts)
    del counts  # a search has as many waiting nodes as it is deep
    yield best
    counts = _unpacked(held)
    if few:
        every = sorted(_maximal(counts, room), key=lambda f: (-sum(f), len(f), tuple(-x for x in f)))
        kept: list[tuple[int, ...]] = [best]
        for f in every:
            if not any(_dominates(g, f) for g in kept):
                kept.append(f)
                yield f
        return
    tops = sorted((s for s in counts if s <= room and s != (best or (0,))[0]), reverse=True)[:limit]
    del counts
    for s in tops:
        after = _unpacked(held)
        after[s] -= 1
        got = (s, *fullest(after, room - s, s))
        del after
        if not _dominates(best, got):
            yield got


def _packed(counts: dict[int, int]) -> array:
    return array("q", itertools.chain.from_iterable(counts.items()))


def _unpacked(held: array) -> dict[int, int]:
    return dict(zip(held[::2], held[1::2]))


def _less(held: array, whole: tuple[int, ...], times: int) -> dict[int, int]:
    left = _unpacked(held)
    for s in set(whole):
        left[s] -= times * whole.count(s)
        if not left[s]:
            del left[s]
    return left


def _maximal(counts: dict[int, int], room: int) -> Iterator[tuple[int, ...]]:
    """All sets to which no further piece can be added."""
    sizes = sorted((s for s in counts if counts[s]), reverse=True)

    def go(i: int, r: int, got: tuple[int, ...]) -> Iterator[tuple[int, ...]]:
        if i == len(sizes):
            if not any(s <= r and got.count(s) < counts[s] for s in sizes):
                yield got
            return
        for n in range(min(counts[sizes[i]], r // sizes[i]), -1, -1):
            yield from go(i + 1, r - n * sizes[i], got + (sizes[i],) * n)

    return go(0, room, ())


def _dominates(g: tuple[int, ...], f: tuple[int, ...]) -> bool:
    """Whether f's pieces can be dealt to g's pieces so that none is overfull."""
    if f == g:
        return True
    if sum(f) > sum(g) or len(f) > 8 or (f and (not g or f[0] > g[0])):
        return False

    def deal(i: int, rooms: tuple[int, ...]) -> bool:
        return i == len(f) or any(rooms[j] >= f[i] and deal(i + 1, (*rooms[:j], rooms[j] - f[i], *rooms[j + 1:])) for j in range(len(rooms)))

    return deal(0, g)


def complete(counts: dict[int, int], capacity: int, max_nodes: int = MAX_NODES, max_fillings: int = MAX_FILLINGS) -> list[Pattern]:
    """Patterns for the histogram in as few bins as the search finds; the least if it ends by itself."""
    counts = {s: n for s, n in counts.items() if n > 0}
    bins = lambda ps: sum(n for _, n in ps)
    incumbent, least, total = best_fit(counts, capacity), lower_bound(counts, capacity), sum(s * n for s, n in counts.items())
    best, nodes = bins(incumbent), 0

    def branches(left: dict[int, int], done: tuple, used: int, waste: int) -> Iterator[tuple]:
        """The node's children: its largest piece with each filling, as often as the counts and the bound allow."""
        top, held = max(left), _packed(left)
        ways = fillings(_less(held, (top,), 1), capacity - top, max_fillings)
        del left
        for f in ways:
            whole = (top, *f)
            lost = capacity - sum(whole)
            most = (lambda left: min(left[s] // whole.count(s) for s in set(whole)))(_unpacked(held))
            spare = (best - 1) * capacity - total - waste
            if lost and spare < lost * most:
                most = spare // lost
            for times in dict.fromkeys((most, 1) if most > 0 else ()):
                yield _less(held, whole, times), (done, (whole, times)), used + times, waste + times * lost

    stack = [branches(counts, (), 0, 0)] if best > least else []
    while stack and nodes < max_nodes and best > least:
        child = next(stack[-1], None)
        if child is None:
            stack.pop()
            continue
        nodes += 1
        left, done, used, waste = child
        if waste > (best - 1) * capacity - total:
            continue
        rest = best_fit(left, capacity) if left and (len(left) < 300 or nodes % 50 == 0) else []
        if (not left or rest) and used + bins(rest) < best:
            best, incumbent = used + bins(rest), _listed(done) + rest
        if left:
            stack.append(branches(left, done, used, waste))
    return incumbent


def _listed(done: tuple) -> list[Pattern]:
    out = []
    while done:
        done, one = done
        out.append(one)
    return out


# ---- pieces ----------------------------------------------------------------------------------

PIECE = "doc_id long, piece int, start long, length long, ids_crc32 long"


def pieces(docs: DataFrame, vocabulary: str, capacity: int = CAPACITY, end: int = 0) -> DataFrame:
    """One row per piece of every document; a longer document's remainder comes first."""
    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = tokens.encoder(vocabulary)
        for batch in batches:
            rows: list[tuple] = []
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1)):
                ids = np.array([*encode([text.as_py() or ""])[0], end], dtype="<u4")
                first = len(ids) % capacity or min(capacity, len(ids))
                for piece, start in enumerate([0, *range(first, len(ids), capacity)]):
                    part = ids[start:first if piece == 0 else start + capacity]
                    rows.append((doc, piece, start, len(part), zlib.crc32(part.tobytes())))
            kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], ["doc_id", "piece", "start", "length", "ids_crc32"])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(cut, PIECE)


# ---- from patterns to places -----------------------------------------------------------------

def _slots(spark: SparkSession, patterns: list[Pattern], capacity: int) -> DataFrame:
    """(length, slots): which ranks of a length go to which sequences; at most a few thousand numbers."""
    given: dict[int, int] = {}
    slots: dict[int, list[tuple]] = {}
    first = 0
    for whole, times in sorted(patterns, reverse=True):
        offset = 0
        for size in sorted(set(whole), reverse=True):
            each = whole.count(size)
            low = given.get(size, 0)
            given[size] = low + each * times
            slots.setdefault(size, []).append((low, low + each * times, each, first, offset))
            offset += size * each
        first += times
    kind = "length long, slots array<struct<low:long,high:long,each:long,first:long,offset:long>>"
    return spark.createDataFrame([(s, x) for s, x in sorted(slots.items())], kind)


def _ranked(cut: DataFrame, counts: dict[int, int], per_group: int) -> DataFrame:
    """cut with rank: the place, from 0, among the pieces of the same length, counted in salted groups."""
    spark = cut.sparkSession
    groups = F.broadcast(spark.createDataFrame([(s, -(-n // per_group)) for s, n in counts.items()], "length long, groups long"))
    salted = cut.join(groups, "length").withColumn("salt", F.pmod(F.xxhash64("doc_id", "piece", "start", "ids_crc32", "copy"), F.col("groups")))
    sizes = salted.groupBy("length", "salt").agg(F.count(F.lit(1)).alias("size"))
    before = Window.partitionBy("length").orderBy("salt").rowsBetween(Window.unboundedPreceding, -1)
    sizes = sizes.select("length", "salt", F.coalesce(F.sum("size").over(before), F.lit(0)).alias("skipped"))
    inside = Window.partitionBy("length", "salt").orderBy("doc_id", "piece", "start", "ids_crc32", "copy")
    return salted.withColumn("inside", F.row_number().over(inside) - 1).join(sizes, ["length", "salt"]).withColumn("rank", F.col("inside") + F.col("skipped")).drop("salt", "groups", "inside", "skipped")


def pack(docs: DataFrame, vocabulary: str | None = None, capacity: int = CAPACITY, end: int = 0, per_group: int = 2_000) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset for every piece of every document."""
    spark = docs.sparkSession
    cut = persisted(pieces(docs, vocabulary or tokens.path(), capacity, end).withColumn("copy", F.monotonically_increasing_id()))
    counts = {r["length"]: r["n"] for r in cut.groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect()}  # at most `capacity` rows
    if not counts:
        return cut.select("doc_id", "piece", "start", "length", "ids_crc32", F.lit(0).cast("long").alias("sequence_id"), F.lit(0).cast("long").alias("offset"))
    slots = F.broadcast(_slots(spark, complete(counts, capacity), capacity))
    placed = _ranked(cut, counts, per_group).join(slots, "length")
    slot = F.element_at(F.filter("slots", lambda s: (F.col("rank") >= s["low"]) & (F.col("rank") < s["high"])), 1)
    placed = placed.withColumn("slot", slot).withColumn("k", F.col("rank") - F.col("slot.low"))
    return placed.select(
        "doc_id", "piece", "start", "length", "ids_crc32",
        (F.col("slot.first") + F.expr("k div slot.each")).alias("sequence_id"),
        (F.col("slot.offset") + F.pmod("k", F.col("slot.each")) * F.col("length")).alias("offset"))
