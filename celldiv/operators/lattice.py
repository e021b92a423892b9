"""Phase one of many projections of a large table, and the phases in which their releases end, from its histogram as arrays.

QI values and the sensitive value are coded in one number a row. A stage deals the histogram out by one QI, so cells of every
projection that has this QI lie in one bucket, and tasks sum up all of them from what they hold. The next stage has the
histogram without that QI. So the table is shuffled once for each QI, not once for each projection, and ever smaller. A bucket
of over BUCKET_PAIRS pairs is dealt out by one more QI, without and with it, until it fits.

Nulls are ordinary values, first in the order; an empty table gives no rows.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Callable, Iterable, Iterator, Sequence
from math import comb

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from celldiv.model import MicrodataSpec
from celldiv.operators import bounds, curve, vectors
from celldiv.storage import persisted

#: Projections, and rows times projections, from which on a lattice is summed up here.
PROJECTIONS = 7
EXPANDED = 1_000_000
#: Types whose values are equal just where Python says so.
KINDS = ("byte", "short", "integer", "long", "string", "boolean", "date")
#: Sensitive values of such a table: every projection and bucket has an entry for each.
VALUES = 1_000
#: Buckets of a stage, at most, and the (cell, value) pairs that one may have.
BUCKETS = 256
BUCKET_PAIRS = 4_000_000
#: Pairs of a task, on average.
TASK_PAIRS = 100_000
#: Pairs of a table that are not dealt out any more.
ALONE = 100_000
#: Rows coded before they are summed up.
BATCH = 1_000_000
#: Cells of a bucket that phase two may take rows from, the first and the second time.
CANDIDATES = (16, 1_024)
BLOCKS = "bucket int, pairs long, key binary, h binary"
Arrays = Callable[[Iterator[pd.DataFrame]], Iterator[tuple[np.ndarray, np.ndarray]]]
Fields = tuple[tuple[int, int], ...]  # (QI, its bits), the highest bits first, above those of the sensitive value


def starts(key: np.ndarray) -> np.ndarray:
    return np.flatnonzero(np.r_[True, key[1:] != key[:-1]]) if len(key) else np.zeros(0, np.int64)


def merged(key: np.ndarray, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct keys in order, and the sums of their h."""
    if not len(key):
        return key, h
    low = key.min()
    key = key - low
    span, bits = int(key.max()) + 1, int(h.max()).bit_length()
    if span <= 4 * len(key):
        sums = np.bincount(key, h)
        key = np.flatnonzero(sums)
        return key + low, sums[key].astype(np.int64)
    if span.bit_length() + bits <= 63:
        both = np.sort(key << bits | h)
        key, h = both >> bits, both & (1 << bits) - 1
    else:
        order = np.argsort(key, kind="stable")
        key, h = key[order], h[order]
    begin = starts(key)
    return key[begin] + low, np.add.reduceat(h, begin)


def without(key: np.ndarray, fields: Fields, at: int, low: int) -> tuple[np.ndarray, Fields]:
    """Keys without one field. low: bits of the sensitive value."""
    below = low + sum(w for _, w in fields[at + 1:])
    return key >> below + fields[at][1] << below | key & (1 << below) - 1, fields[:at] + fields[at + 1:]


def projected(key: np.ndarray, h: np.ndarray, fields: Fields, low: int, least: int, free: int) -> Iterator[tuple[tuple[int, ...], np.ndarray, np.ndarray]]:
    """(QIs, keys, h) of all projections that leave out some of the last `free` fields and have `least` QIs or more; each is summed from one a QI wider."""
    yield tuple(sorted(q for q, _ in fields)), key, h
    if len(fields) > least:
        for at in range(len(fields) - free, len(fields)):
            less, left = without(key, fields, at, low)
            yield from projected(*merged(less, h), left, low, least, len(fields) - at - 1)


class Heights:
    """Cells of one projection that have enough values for some l, with what their caps follow from."""

    def __init__(self, key: np.ndarray, h: np.ndarray, low: int, ls: Sequence[int]):
        cell = key >> low
        first = starts(cell)
        many = np.diff(first, append=len(key))
        big = many >= min(ls)
        some = np.repeat(big, many)
        self.key, self.h, self.cell, self.many = key[some], h[some], cell[first[big]], many[big]
        self.first = np.cumsum(self.many) - self.many
        if not len(self.cell):
            return
        top, bits = int(self.h.max()), int(self.h.max()).bit_length()
        place = np.repeat(np.arange(len(self.many)), self.many)
        if len(self.many).bit_length() + bits <= 63:
            self.falling = top - (np.sort(place << bits | top - self.h) & (1 << bits) - 1)
        else:
            self.falling = self.h[np.lexsort((-self.h, place))]
        self.total = np.add.reduceat(self.h, self.first)

    def kept(self, ls: Sequence[int]) -> Iterator[tuple[int, np.ndarray]]:
        """(l, rows that phase one leaves of each pair)."""
        if not len(self.cell):
            yield from ((l, self.h) for l in ls)
            return
        caps = {l: np.full(len(self.cell), np.iinfo(np.int64).max) for l in ls}
        left, last = self.total.copy(), len(self.h) - 1
        for j in range(max(ls)):
            for l, cap in caps.items():
                if j < l:
                    np.minimum(cap, left // (l - j), out=cap)
            left -= np.where(self.many > j, self.falling[np.minimum(self.first + j, last)], 0)
        for l, cap in caps.items():
            yield l, np.minimum(self.h, np.repeat(np.where(self.many < l, 0, cap), self.many))


def removed(key: np.ndarray, h: np.ndarray, low: int, m: int, ls: Sequence[int]) -> np.ndarray:
    """Rows of each sensitive value: all of them, and for every l those that phase one moves."""
    sums = lambda k, x: np.bincount(k & (1 << low) - 1, x, m).astype(np.int64)
    out, cells = [sums(key, h)], Heights(key, h, low, ls)
    out += [out[0] - sums(cells.key, kept) for _, kept in cells.kept(ls)]
    return np.stack(out)


def candidates(cells: Heights, kept: np.ndarray, l: int, low: int, m: int, most: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Keys and heights after phase one of the cells with most rows to spare, and in how many other cells each value is left."""
    if not len(cells.cell):
        return cells.key, kept, np.zeros(m, np.int64)
    size = np.add.reduceat(kept, cells.first)
    alive = np.flatnonzero(size)
    chosen = np.zeros(len(size), bool)
    if len(alive) > most:
        surplus = (size - l * np.maximum.reduceat(kept, cells.first))[alive]
        alive = alive[np.argpartition(-surplus, most)[:most]]
    chosen[alive] = True
    own = np.repeat(chosen, cells.many)
    at = own & (kept > 0)
    return cells.key[at], kept[at], np.bincount(cells.key[~own & (kept > 0)] & (1 << low) - 1, minlength=m)


def phase_from(key: np.ndarray, kept: np.ndarray, others: np.ndarray, residue: dict[int, int], l: int, low: int) -> int:
    """The phase that ends a release whose phase one left these cells and others; 0 if these do not tell.

    Phase two on these cells is phase two on all, in one order of cells, if no value that others hold ran out here: a cell that
    cannot give a value never can again, so it is enough that one here can give it at the end. Phase three is taken only on all cells."""
    names, place = np.unique(key >> low, return_inverse=True)
    cells: list[dict] = [{} for _ in names]
    for c, v, k in zip(place.tolist(), (key & (1 << low) - 1).tolist(), kept.tolist()):
        cells[c][v] = k
    start, residue = Counter(residue), Counter(residue)
    vectors.drain(cells, residue, l)
    if others.any():
        height = max(residue.values())
        top = {v for v, r in residue.items() if r == height}
        able = {v for cell in cells if cell and (sum(cell.values()) > l * max(cell.values()) or not vectors.peaks(cell) & top) for v in cell}
        if not set(np.flatnonzero(others).tolist()) - {v for v, r in start.items() if r == height} <= able:
            return 0
    bounds.check_drained(start, residue, l)
    if vectors.eligible(residue, l):
        return 2
    if others.any():
        return 0
    vectors.overhaul(cells, residue, l)
    return 3


def _bytes(key: np.ndarray, h: np.ndarray) -> dict:
    return {"pairs": len(key), "key": key.astype(np.int64).tobytes(), "h": h.astype(np.uint32 if not len(h) or h.max() < 1 << 32 else np.int64).tobytes()}


def _arrays(row) -> tuple[np.ndarray, np.ndarray]:
    return np.frombuffer(row.key, np.int64), np.frombuffer(row.h, np.uint32 if len(row.h) == 4 * row.pairs else np.int64).astype(np.int64)


def _whole(batches: Iterator[pd.DataFrame]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    for b in batches:
        yield from map(_arrays, b.itertuples(index=False))


def _coded(batches: Iterator[pd.DataFrame]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    held, n = [], 0
    for b in batches:
        held.append(b["key"].to_numpy())
        n += len(b)
        if n >= BATCH:
            yield np.concatenate(held), np.ones(n, np.int64)
            held, n = [], 0
    if n:
        yield np.concatenate(held), np.ones(n, np.int64)


def grouping(qi: Sequence[int], d: int) -> int:
    """A bit per QI left out, as grouping_id has it."""
    return sum(1 << d - 1 - i for i in range(d) if i not in qi)


class Lattice:
    """The coded histogram of a table, dealt out in stages; see `of`."""

    def __init__(self, keys: DataFrame, spec: MicrodataSpec, sizes: Iterable[int], ls: Sequence[int], fields: Fields, low: int, m: int, rows: int):
        self.spark, self.d, self.sizes, self.ls = keys.sparkSession, len(spec.qi), sorted(set(sizes)), list(ls)
        self.low, self.m = low, m
        self.sums: DataFrame | None = None
        self.stages: list[tuple[DataFrame, Fields, int]] = []  # blocks, fields, how many of them may be left out
        self._with(keys, _coded, fields, 0, rows)

    @staticmethod
    def of(df: DataFrame, spec: MicrodataSpec, sizes: Iterable[int], ls: Sequence[int]) -> Lattice | None:
        """None where a lattice is small, or its codes do not fit."""
        sizes = set(sizes)
        some = sum(comb(len(spec.qi), k) for k in sizes)
        columns = [*spec.qi, spec.sa]
        if not ls or some < PROJECTIONS or any(df.schema[c].dataType.typeName() not in KINDS for c in columns):
            return None
        rows, *many = df.agg(F.count(F.lit(1)).alias("n"), *[F.approx_count_distinct(c).alias(f"c{i}") for i, c in enumerate(columns)]).first()
        if rows * some <= EXPANDED or max(many) > curve.DOMAIN or many[-1] > VALUES:
            return None
        told = [F.struct(F.collect_set(c).alias("vs"), F.bool_or(F.col(c).isNull()).alias("none")).alias(f"c{i}") for i, c in enumerate(columns)]
        domains = [[*([None] if x["none"] else []), *sorted(x["vs"])] for x in df.agg(*told).first()]
        widths = [(len(values) - 1).bit_length() for values in domains]
        if sum(widths) > 62:
            return None
        # the QI with most values has the highest bits and the first stage
        fields = tuple((i, widths[i]) for i in sorted(range(len(spec.qi)), key=lambda i: -len(domains[i])))
        key, below = F.lit(0).cast("long"), 0
        for i in [len(spec.qi), *[i for i, _ in reversed(fields)]]:
            codes = df.sparkSession.createDataFrame([(v, k) for k, v in enumerate(domains[i])], f"`__v` {df.schema[columns[i]].dataType.simpleString()}, `__c{i}` long")
            df = df.join(F.broadcast(codes), F.col(columns[i]).eqNullSafe(F.col("__v"))).drop("__v")  # curve.DOMAIN rows at most
            key = key + F.shiftleft(F.col(f"__c{i}"), below)
            below += widths[i]
        return Lattice(df.select(key.alias("key")), spec, sizes, ls, fields, widths[-1], len(domains[-1]), rows)

    def _dealt(self, source: DataFrame, arrays: Arrays, fields: Fields, fixed: int, rows: int) -> tuple[DataFrame, int, int]:
        """The source's histogram in blocks by its first `fixed` fields, the pairs of the largest bucket and of all."""
        shift = self.low + sum(w for _, w in fields[fixed:])
        buckets = min(1 << min(30, sum(w for _, w in fields[:fixed])), max(BUCKETS, 4 * rows // BUCKET_PAIRS))

        def deal(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for key, h in arrays(batches):
                key, h = merged(key, h)
                bucket = (key >> shift) % buckets
                order = np.argsort(bucket, kind="stable")
                key, h, bucket = key[order], h[order], bucket[order]
                begin = starts(bucket)
                for a, b in zip(begin, np.r_[begin[1:], len(key)]):
                    yield pd.DataFrame([{"bucket": int(bucket[a])} | _bytes(key[a:b], h[a:b])])

        def meet(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            at, held = None, []
            told = lambda: pd.DataFrame([{"bucket": at} | _bytes(*merged(*map(np.concatenate, zip(*held))))])
            for b in batches:
                for row in b.itertuples(index=False):
                    if held and row.bucket != at:
                        yield told()
                        held = []
                    at = row.bucket
                    held.append(_arrays(row))
            if held:
                yield told()

        parts = max(2 * int(self.spark.conf.get("spark.sql.shuffle.partitions", "200")), rows // TASK_PAIRS)
        dealt = source.mapInPandas(deal, BLOCKS).repartition(min(buckets, parts), "bucket").sortWithinPartitions("bucket")
        blocks = persisted(dealt.mapInPandas(meet, BLOCKS))
        sizes = blocks.agg(F.max("pairs").alias("most"), F.sum("pairs").alias("all")).first()
        return blocks, sizes["most"] or 0, sizes["all"] or 0

    def _with(self, source: DataFrame, arrays: Arrays, fields: Fields, fixed: int, rows: int) -> None:
        """Stages for all projections that have the first `fixed` fields."""
        low = self.low
        while len(fields) > fixed:
            blocks, most, rows = self._dealt(source, arrays, fields, fixed + 1, rows)
            if not rows:
                return
            if most > BUCKET_PAIRS and len(fields) > fixed + 1:
                self._with(blocks, _whole, fields, fixed + 1, rows)
            else:
                self.stages.append((blocks, fields, len(fields) - fixed - 1))
            source, arrays = blocks, lambda batches, f=fields: ((without(key, f, fixed, low)[0], h) for key, h in _whole(batches))
            fields = fields[:fixed] + fields[fixed + 1:]
            if len(fields) < self.sizes[0]:
                return
            if not fixed and rows <= ALONE:
                break
        if len(fields) >= self.sizes[0]:
            self.stages.append((self._dealt(source, arrays, fields, fixed, rows)[0], fields, len(fields) - fixed))

    def trimmed(self) -> DataFrame:
        """(grouping, l, residue_rows, height, done, feasible, residue) of phase one; residue has the rows of each value's code where it is not done."""
        if self.sums is None:
            self.sums = persisted(self._trimmed())
        return self.sums

    def _trimmed(self) -> DataFrame:
        low, m, d, ls, sizes = self.low, self.m, self.d, self.ls, self.sizes

        def run(batches: Iterator[pd.DataFrame], fields: Fields, free: int) -> Iterator[pd.DataFrame]:
            for b in batches:
                for row in b.itertuples(index=False):
                    got = [(grouping(qi, d), removed(key, h, low, m, ls).tobytes()) for qi, key, h in projected(*_arrays(row), fields, low, sizes[0], free) if len(qi) in sizes]
                    yield pd.DataFrame(got, columns=["grouping", "sums"])

        def told(pdf: pd.DataFrame) -> pd.DataFrame:
            sums = sum(np.frombuffer(x, np.int64) for x in pdf["sums"]).reshape(-1, m)
            n, top = int(sums[0].sum()), int(sums[0].max())
            return pd.DataFrame([(int(pdf["grouping"].iloc[0]), l, int(r.sum()), int(r.max()), bool(r.sum() >= l * r.max()), n >= l * top, r.tobytes() if r.sum() < l * r.max() else None) for l, r in zip(ls, sums[1:])],
                                columns=["grouping", "l", "residue_rows", "height", "done", "feasible", "residue"])

        parts = [blocks.mapInPandas(lambda batches, f=fields, k=free: run(batches, f, k), "grouping int, sums binary") for blocks, fields, free in self.stages]
        every = parts[0] if parts else self.spark.createDataFrame([], "grouping int, sums binary")
        for part in parts[1:]:
            every = every.unionByName(part)
        return every.groupBy("grouping").applyInPandas(told, "grouping int, l int, residue_rows long, height long, done boolean, feasible boolean, residue binary")

    def ends(self) -> dict[tuple[int, int], int]:
        """The phase that ends the release of each (grouping, l) that phase one does not, 0 where it is not feasible; those that
        some cells of a bucket do not tell are left out."""
        rows = self.trimmed().where("not done").collect()  # at most one per projection and l
        undone = {(r["grouping"], r["l"]): np.frombuffer(r["residue"], np.int64) for r in rows if r["feasible"]}
        found = {(r["grouping"], r["l"]): 0 for r in rows if not r["feasible"]}
        for most in CANDIDATES:
            left = {case: r for case, r in undone.items() if case not in found}
            if left:
                found |= {(r["grouping"], r["l"]): r["phase"] for r in self._ends(left, most).collect() if r["phase"]}  # one row per projection and l
        return found

    def _ends(self, undone: dict[tuple[int, int], np.ndarray], most: int) -> DataFrame:
        low, m, d, asked = self.low, self.m, self.d, {}
        for g, l in undone:
            asked.setdefault(g, []).append(l)
        least = min(self.d - g.bit_count() for g in asked)
        residues = {case: {v: int(r) for v, r in enumerate(x) if r} for case, x in undone.items()}
        kind = "grouping int, l int, pairs long, key binary, h binary, others binary"

        def run(batches: Iterator[pd.DataFrame], fields: Fields, free: int) -> Iterator[pd.DataFrame]:
            for b in batches:
                for row in b.itertuples(index=False):
                    got = []
                    for qi, key, h in projected(*_arrays(row), fields, low, least, free):
                        if ls := asked.get(g := grouping(qi, d)):
                            cells = Heights(key, h, low, ls)
                            for l, kept in cells.kept(ls):
                                some, heights, others = candidates(cells, kept, l, low, m, most)
                                got.append({"grouping": g, "l": l} | _bytes(some, heights) | {"others": others.astype(np.int64).tobytes()})
                    if got:
                        yield pd.DataFrame(got)

        def told(pdf: pd.DataFrame) -> pd.DataFrame:
            g, l = int(pdf["grouping"].iloc[0]), int(pdf["l"].iloc[0])
            key, kept = map(np.concatenate, zip(*map(_arrays, pdf.itertuples(index=False))))
            others = sum(np.frombuffer(x, np.int64) for x in pdf["others"])
            return pd.DataFrame([(g, l, phase_from(key, kept, others, residues[g, l], l, low))], columns=["grouping", "l", "phase"])

        parts = [blocks.mapInPandas(lambda batches, f=fields, k=free: run(batches, f, k), kind) for blocks, fields, free in self.stages]
        every = parts[0]
        for part in parts[1:]:
            every = every.unionByName(part)
        return every.groupBy("grouping", "l").applyInPandas(told, "grouping int, l int, phase int")
