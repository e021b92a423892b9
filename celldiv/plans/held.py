"""Whole families of releases of tables that a task can hold as arrays: some projections a task, every l and method in it.

The table is coded once: a row is its QI codes in one word, its sensitive value's code and the leading bits of the two
hashes that order rows. Rows lie in the order of their ids, packed in blocks that go to every task, so each holds the
whole table (about 14 bytes a row) and makes the releases of its projections by the rules of the operators: same clipping,
same order of picks, same chunks of the curve, whose cells are formed in all chunks side by side.

Two choices between ties differ from the operators: phase two takes cells in the order of their values, by the exact
rule, and hashes order rows by 32 bits. Nulls are ordinary values, first in the order; row ids must be unique.
"""

from __future__ import annotations

import time
from collections import Counter
from collections.abc import Iterator, Sequence

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from celldiv.functions.curve import POSITION_BITS, hilbert_numbers
from celldiv.model import MicrodataSpec, shown
from celldiv.operators import bounds, curve, publish, vectors
from celldiv.plans import family
from celldiv.plans.family import RELEASES
from celldiv.storage import persisted

#: Rows of a table that every task may hold.
HELD_ROWS = 4_000_000
#: Sensitive values of such a table: every chunk of the curve has an entry for each.
HELD_VALUES = 10_000
#: Tasks of one family.
TASKS = 12
#: Cells that phase two may take rows from before all are looked at.
DRAINED_CELLS = 4_096
#: Steps for which chunks must be able to go on side by side; below, a chunk is finished by itself.
LEAST_STEPS = 16
#: Steps after which stars are counted.
STEPS = 2_048
#: Rows whose positions are computed at once.
SLICE = 1 << 14


class Table:
    """Arrays in the order of row ids: words (QI codes) and sa; rows by (sa, hash on the curve) and by (sa, hash of picks)."""

    def __init__(self, words: np.ndarray, sa: np.ndarray, near: np.ndarray, pick: np.ndarray, shifts: Sequence[int], widths: Sequence[int]):
        self.m = int(sa.max()) + 1 if len(sa) else 0
        self.words, self.sa, self.shifts, self.widths = words, sa.astype(np.uint8 if self.m <= 256 else np.uint32), list(shifts), list(widths)
        self.ends = np.cumsum(np.bincount(sa, minlength=self.m))
        self.by_near, self.by_pick = (sorted_by((self.sa, self.m.bit_length()), (h, 32)) for h in (near, pick))

    def field(self, i: int, words: np.ndarray) -> np.ndarray:
        return words >> words.dtype.type(self.shifts[i]) & words.dtype.type((1 << self.widths[i]) - 1)

    def mask(self, qi: Sequence[int]) -> np.generic:
        return self.words.dtype.type(sum((1 << self.widths[i]) - 1 << self.shifts[i] for i in qi))


def sorted_by(*keys: tuple[np.ndarray, int]) -> np.ndarray:
    """Stable order by (key, its bits), the first key first: a radix sort by 16 bits at a time."""
    order = np.arange(len(keys[0][0]), dtype=np.int32)
    for key, bits in reversed(keys):
        for low in range(0, bits, 16):
            digit = (key >> key.dtype.type(low) if low else key).astype(np.uint16)
            order = order[np.argsort(digit[order], kind="stable")]
    return order


def _starts(key: np.ndarray) -> np.ndarray:
    return np.flatnonzero(np.r_[True, key[1:] != key[:-1]]) if len(key) else np.zeros(0, np.int64)


def positions(t: Table, qi: Sequence[int], words: np.ndarray) -> tuple[np.ndarray, int]:
    """Places on the curve over the codes that occur in these words, and their bits. Where the codes' grid is smaller than the
    table, just the cells that occur are placed."""
    dense, grid = [], 1
    for i in qi:
        there = np.zeros(1 << t.widths[i], bool)
        for a in range(0, len(words), SLICE):
            there[t.field(i, words[a:a + SLICE])] = True
        dense.append(np.cumsum(there, dtype=np.int64) - 1)
        grid *= int(dense[-1][-1]) + 1
    bits = max(1, int(max(d[-1] for d in dense)).bit_length())
    keep = max(1, min(bits, POSITION_BITS // len(qi)))
    kind = np.uint32 if keep * len(qi) <= 32 else np.int64
    if grid < len(words) // 2:
        spot = np.zeros(len(words), np.int32)
        for i, d in zip(qi, dense):
            spot *= int(d[-1]) + 1
            for a in range(0, len(words), SLICE):
                spot[a:a + SLICE] += d.astype(np.int32)[t.field(i, words[a:a + SLICE])]
        there = np.zeros(grid, bool)
        there[spot] = True
        cells, codes = np.flatnonzero(there), []
        left = cells
        for d in reversed(dense):
            codes.append(left % (int(d[-1]) + 1))
            left = left // (int(d[-1]) + 1)
        place = np.zeros(grid, kind)
        place[cells] = hilbert_numbers(np.column_stack(codes[::-1]) >> (bits - keep), keep)
        return place[spot], keep * len(qi)
    at = np.empty(len(words), kind)
    for a in range(0, len(words), SLICE):
        some = words[a:a + SLICE]
        at[a:a + SLICE] = hilbert_numbers(np.column_stack([d[t.field(i, some)] for i, d in zip(qi, dense)]) >> (bits - keep), keep)
    return at, keep * len(qi)


def joined(counts: np.ndarray, l: int) -> np.ndarray:
    """curve.joined_chunks on an array: counts by chunk and value; the chunk that each becomes part of."""
    into, stretch = np.arange(len(counts)), 1 << 16
    while True:
        now, at = np.unique(into, return_inverse=True)
        h = np.zeros((len(now), counts.shape[1]), np.int64)
        np.add.at(h, at, counts)
        fits = h.sum(1) >= l * h.max(1)
        if fits.all() or len(now) == 1:
            return into
        near = now // stretch
        total = np.cumsum(fits)
        first = np.searchsorted(near, near)
        before = total - fits - (total - fits)[first]
        last = np.searchsorted(near, near, side="right") - 1
        of = np.minimum(before, np.maximum(total[last] - (total - fits)[first] - 1, 0))
        _, begin, group = np.unique(near * (len(now) + 1) + of, return_index=True, return_inverse=True)
        into = now[begin][group][at]
        stretch *= 2


def _told(t: Table, qi: Sequence[int], differs: np.ndarray, size: np.ndarray | int) -> tuple[int, int]:
    """Stars and starred rows of cells of these sizes, whose rows differ in these bits."""
    many = lambda there: int((there * size).sum())
    return sum(many((differs & t.mask([i])) != 0) for i in qi), many((differs & t.mask(qi)) != 0)


def star_counts(t: Table, qi: Sequence[int], words: np.ndarray, cell: np.ndarray) -> tuple[int, int]:
    if not len(words):
        return 0, 0
    order = np.argsort(cell, kind="stable")
    begin = _starts(cell[order])
    size = np.diff(np.r_[begin, len(cell)])
    got = words[order]
    return _told(t, qi, np.bitwise_or.reduceat(got ^ np.repeat(got[begin], size), begin), size)


def chunk_stars(t: Table, qi: Sequence[int], words: np.ndarray, sa: np.ndarray, ends: np.ndarray, l: int) -> tuple[int, int]:
    """Stars and starred rows of curve.group_sorted in every chunk. Rows lie in the order of the curve, chunk after chunk, which end there.

    While no value must give a row, a cell has the earliest rows of l values: that step is taken in all chunks at once.
    What is left of a chunk when it could be otherwise is grouped by itself: the rule depends on the rows left only."""
    lanes, m, n = len(ends), t.m, len(words)
    rows = np.full(n + lanes * m, np.iinfo(np.int32).max, np.int32)  # every value's rows, and an end after them
    counts, edges = np.zeros((lanes, m), np.int64), np.r_[0, ends]
    for k in range(lanes):
        own = sa[edges[k]:edges[k + 1]]
        order = np.argsort(own, kind="stable")
        counts[k] = np.bincount(own, minlength=m)
        rows[edges[k] + k * m + np.arange(len(own)) + own[order]] = order + edges[k]
    counts = counts.ravel()
    end = np.cumsum(counts) + np.arange(lanes * m)
    at, end = (end - counts).reshape(lanes, m), end.reshape(lanes, m)
    done, stars, starred = np.zeros(n, bool), 0, 0
    while len(at) and m >= l:
        left = end - at
        spare = (left.sum(1) - l) // l - left.max(1)
        go = spare >= LEAST_STEPS
        at, end, spare = at[go], end[go], spare[go]
        if not len(at):
            break
        heads, offset, flat_at = rows[at].ravel(), (np.arange(len(at)) * m)[:, None], at.ravel()
        steps = int(spare.min()) + 1
        for a in range(0, steps, STEPS):
            taken = np.empty((min(STEPS, steps - a), len(at), l), np.int32)
            for out in taken:
                of = np.argpartition(heads.reshape(-1, m), l - 1, axis=1)[:, :l] + offset if l < m else np.arange(m)[None, :] + offset
                out[:] = heads[of]
                flat_at[of] += 1
                heads[of] = rows[flat_at[of]]
            flat = taken.reshape(-1, l)
            done[flat] = True
            got = words[flat]
            s, r = _told(t, qi, np.bitwise_or.reduce(got ^ got[:, :1], axis=1), l)
            stars, starred = stars + s, starred + r
        at = flat_at.reshape(-1, m)
    for a, b in zip(edges, ends):
        some = a + np.flatnonzero(~done[a:b])
        s, r = star_counts(t, qi, words[some], curve.group_sorted(np.unique(sa[some], return_inverse=True)[1].astype(np.int64), l))
        stars, starred = stars + s, starred + r
    return stars, starred


class Curve:
    """Some rows (places in the table, rising) along the curve in stratified chunks, for every l."""

    def __init__(self, t: Table, qi: Sequence[int], chunk_rows: int, rows: np.ndarray | None = None):
        words, sa = (t.words, t.sa) if rows is None else (t.words[rows], t.sa[rows])
        at, bits = positions(t, qi, words)
        self.t, self.qi, n = t, qi, len(words)
        chunks = max(1, n // chunk_rows)
        chunk = np.zeros(n, np.uint16)
        self.counts = np.zeros((chunks, t.m), np.int64)
        if rows is not None:
            place = np.full(len(t.words), -1, np.int32)
            place[rows] = np.arange(n, dtype=np.int32)
        for v in range(t.m):
            own = t.by_near[t.ends[v - 1] if v else 0:t.ends[v]]
            if rows is not None:
                own = place[own]
                own = own[own >= 0]
            share = np.arange(len(own)) * chunks // max(1, len(own))
            self.counts[:, v] = np.bincount(share, minlength=chunks)
            if chunks > 1:
                chunk[own[sorted_by((at[own], bits))]] = share
        self.at, self.bits, self.chunk, self.words, self.sa = at, bits, chunk, words, sa
        self.into: np.ndarray | None = None

    def stars(self, l: int) -> tuple[int, int]:
        into = joined(self.counts, l)
        if self.into is None or not np.array_equal(into, self.into):  # most l have the same chunks
            self.into, a, ends = into, 0, []
            words, sa = np.empty_like(self.words), np.empty_like(self.sa)
            for k in np.unique(into):
                own = np.flatnonzero((into == k)[self.chunk])
                own = own[sorted_by((self.at[own], self.bits))]
                words[a:a + len(own)], sa[a:a + len(own)] = self.words[own], self.sa[own]
                a += len(own)
                ends.append(a)
            self.ordered = words, sa, np.array(ends)
        return chunk_stars(self.t, self.qi, *self.ordered, l)


def _drained(cell: np.ndarray, value: np.ndarray, kept: np.ndarray, residue: Counter, l: int) -> tuple[np.ndarray, int]:
    """kept after phases two and three, and the phase that ended. Cells are numbered in their order; residue is changed."""
    start = Counter(residue)
    alive = np.unique(cell[kept > 0])
    for many in (DRAINED_CELLS, len(alive)):
        some = alive[-many:]
        at = np.flatnonzero((kept > 0) & (cell >= some[0])) if len(some) else np.zeros(0, np.int64)
        place = np.searchsorted(some, cell[at]).tolist()
        cells: list[dict] = [{} for _ in some]
        for c, v, k in zip(place, value[at].tolist(), kept[at].tolist()):
            cells[c][v] = k
        residue.clear()
        residue.update(start)
        vectors.drain(cells, residue, l)
        if vectors.eligible(residue, l) or many >= len(alive):
            break
    bounds.check_drained(start, residue, l)
    phase = 2
    if not vectors.eligible(residue, l):
        phase = 3
        vectors.overhaul(cells, residue, l)
    kept = kept.copy()
    kept[at] = [cells[c].get(v, 0) for c, v in zip(place, value[at].tolist())]
    return kept, phase


class Trimmed:
    """Rows of one projection by (value, cell), in the order in which they are picked, and pairs by cell in falling height."""

    def __init__(self, t: Table, qi: Sequence[int]):
        bits, spot = 0, np.zeros_like(t.words)
        for i in qi:  # the fields side by side
            for a in range(0, len(spot), SLICE):
                spot[a:a + SLICE] |= t.field(i, t.words[a:a + SLICE]) << spot.dtype.type(bits)
            bits += t.widths[i]
        self.t, self.qi, self.rows, spots, begins, values = t, qi, np.empty_like(t.by_pick), [], [], []
        for v in range(t.m):
            a, b = t.ends[v - 1] if v else 0, t.ends[v]
            own = t.by_pick[a:b]
            order = sorted_by((spot[own], bits))
            self.rows[a:b] = own = own[order]
            begin = _starts(spot[own])
            spots.append(spot[own[begin]])
            begins.append((begin + a).astype(np.int32))
            values.append(np.full(len(begin), v, t.sa.dtype))
        spot, begin, value = np.concatenate(spots), np.concatenate(begins), np.concatenate(values)
        h = np.diff(begin, append=np.int32(len(t.words)))
        top = int(h.max())
        order = sorted_by((spot, bits), (top - h, top.bit_length()))
        spot, self.begin, self.value, self.h = spot[order], begin[order], value[order], h[order]
        del spots, begins, values, begin, value, h, order
        starts = spot[1:] != spot[:-1]
        self.cell = np.cumsum(np.r_[False, starts], dtype=np.int32)
        self.first = _starts(spot).astype(np.int32)
        self.many = np.diff(self.first, append=np.int32(len(spot)))
        before = np.cumsum(self.h, dtype=np.int32) - self.h
        self.rest = np.repeat(np.add.reduceat(self.h, self.first, dtype=np.int32) + before[self.first], self.many) - before
        self.j = np.minimum(np.arange(len(spot), dtype=np.int32) - np.repeat(self.first, self.many), 1 << 15).astype(np.int16 if len(spot) and t.m < 1 << 15 else np.int32)

    def gone(self, l: int) -> tuple[np.ndarray, int]:
        """Rows of the residue (places in the table, rising), and the phase that ended."""
        bound = np.where(self.j < l, self.rest // np.maximum(np.int32(1), np.int32(l) - self.j), np.int32(np.iinfo(np.int32).max))
        cap = np.where(self.many < l, np.int32(0), np.minimum.reduceat(bound, self.first))
        kept, phase = np.minimum(self.h, np.repeat(cap, self.many)), 1
        sums = np.bincount(self.value, self.h - kept, self.t.m).astype(np.int64)
        residue = Counter({v: int(r) for v, r in enumerate(sums) if r})
        if not vectors.eligible(residue, l):
            kept, phase = _drained(self.cell, self.value, kept, residue, l)
            kept = kept.astype(np.int32)
        moved = self.h - kept
        some = np.flatnonzero(moved)
        many = moved[some]
        at = np.repeat(self.begin[some] - (np.cumsum(many, dtype=np.int32) - many), many) + np.arange(int(many.sum()), dtype=np.int32)
        return np.sort(self.rows[at]), phase


def released(t: Table, qi: Sequence[int], ls: Sequence[int], methods: Sequence[str], chunk_rows: int = curve.CHUNK_ROWS) -> Iterator[tuple]:
    """(method, l, n, stars, starred rows, phase, seconds) of one projection; what all l share counts for the first."""
    n, top = len(t.sa), int(np.diff(t.ends, prepend=0).max())
    ls, since = [l for l in ls if n >= l * top], time.time()
    if ls and {"tiered", "hybrid"} & set(methods):
        trimmed = Trimmed(t, qi)
        for l in ls:
            rows, phase = trimmed.gone(l)
            spent, since = time.time() - since, time.time()
            if "tiered" in methods:
                yield ("tiered", l, n, *star_counts(t, qi, t.words[rows], np.zeros(len(rows), np.int8)), phase, round(spent + time.time() - since, 3))
                since = time.time()
            if "hybrid" in methods:
                yield ("hybrid", l, n, *(Curve(t, qi, chunk_rows, rows).stars(l) if len(rows) else (0, 0)), phase, round(spent + time.time() - since, 3))
            since = time.time()
        del trimmed
    if ls and "curve" in methods:
        line = Curve(t, qi, chunk_rows)
        for l in ls:
            yield ("curve", l, n, *line.stars(l), 0, round(time.time() - since, 3))
            since = time.time()


def _coded(rows: DataFrame, spec: MicrodataSpec) -> tuple[DataFrame, list[int], list[int], int]:
    """(row_id, word, sa, near, pick), where the word has which QI's code, in how many bits, and the number of sensitive values."""
    domains = curve.domains(rows, MicrodataSpec((*spec.qi, spec.sa), spec.sa, spec.row_id))
    for i, (q, values) in enumerate(domains.items()):
        codes = rows.sparkSession.createDataFrame([(v, k) for k, v in enumerate(values)], f"__v {rows.schema[q].dataType.simpleString()}, `__c{i}` long")
        rows = rows.join(F.broadcast(codes), F.col(q).eqNullSafe(F.col("__v"))).drop("__v")  # curve.DOMAIN rows at most
    widths = [max(1, (len(domains[q]) - 1).bit_length()) for q in spec.qi]
    shifts = [sum(widths[:i]) for i in range(len(widths))]
    word = sum((F.shiftleft(F.col(f"__c{i}"), s) for i, s in enumerate(shifts)), F.lit(0).cast("long"))
    leading = lambda h, bits: F.shiftrightunsigned(h.bitwiseXOR(F.lit(-(1 << 63))), 64 - bits)
    near = F.xxhash64(spec.row_id)
    pick = F.shiftleft(F.pmod(near, F.lit(publish.SALTS)), 26) + leading(F.xxhash64(spec.row_id, F.lit(1)), 26)
    return rows.select(F.col(spec.row_id).alias("row_id"), word.alias("word"), F.col(f"__c{len(spec.qi)}").alias("sa"), leading(near, 32).alias("near"), pick.alias("pick")), shifts, widths, len(domains[spec.sa])


def takes(df: DataFrame) -> bool:
    """Whether the table is beyond family.FAMILY_ROWS, and a task can hold it."""
    return family.FAMILY_ROWS < df.limit(HELD_ROWS + 1).count() <= HELD_ROWS


def releases(df: DataFrame, spec: MicrodataSpec, projections: Sequence[tuple[str, ...]], ls: Sequence[int], methods: Sequence[str]) -> DataFrame:
    """(place, method, l, n, stars, starred_rows, phase, seconds): place counts the projections; infeasible l are left out."""
    if df.limit(HELD_ROWS + 1).count() > HELD_ROWS:
        raise ValueError(f"over {HELD_ROWS} rows: release the projections one by one")
    coded, shifts, widths, many = _coded(shown(df, spec), spec)
    if sum(widths) > 63:
        raise ValueError("a row's codes take over 63 bits: release the projections one by one")
    if many > HELD_VALUES:
        raise ValueError(f"over {HELD_VALUES} sensitive values: release the projections one by one")
    kinds = {"word": np.uint32 if sum(widths) <= 32 else np.uint64, "sa": np.uint16, "near": np.uint32, "pick": np.uint32}

    def pack(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            if len(b):
                yield pd.DataFrame({"start": b["row_id"].iloc[:1].to_numpy()} | {k: [b[k].to_numpy().astype(kind).tobytes()] for k, kind in kinds.items()})

    parts = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions", "200"))
    kind = coded.schema["row_id"].dataType.simpleString()
    blocks = persisted(coded.repartitionByRange(parts, "row_id").sortWithinPartitions("row_id").mapInPandas(pack, f"start {kind}, " + ", ".join(f"{k} binary" for k in kinds)))
    of, ls, methods = [tuple(spec.qi.index(q) for q in qi) for qi in projections], list(ls), list(methods)
    tasks = min(TASKS, len(of))
    # the heavier projections, those of many QIs, are dealt out first
    heavy = sorted(range(len(of)), key=lambda p: -len(of[p]))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        found, own = {}, set()  # tasks of one partition share the table
        for b in batches:
            own |= set(b["task"])
            found |= {row.start: row for row in b.itertuples(index=False)}
            del b
        if not own:
            return
        row = [found.pop(start) for start in sorted(found)]
        arrays = {}
        for k, kind in kinds.items():
            arrays[k] = np.concatenate([np.frombuffer(getattr(r, k), kind) for r in row])
        del row
        t = Table(*arrays.values(), shifts, widths)
        arrays.clear()
        for task in sorted(own):
            # half of the tasks end with the heavier ones, so that not all hold most at once
            for p in heavy[task::tasks][::1 if task % 2 else -1]:
                yield pd.DataFrame([(p, *r) for r in released(t, of[p], ls, methods)], columns=[f.split()[0] for f in RELEASES.split(", ")])

    dealt = blocks.withColumn("task", F.explode(F.array(*[F.lit(i) for i in range(tasks)]))).repartitionByRange(tasks, "task")
    return dealt.mapInPandas(run, RELEASES)
