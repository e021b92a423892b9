"""Many small releases at once: one projection of the table a task, every l and method in it.

A family has hundreds of releases of one table; run one after the other they are hundreds of small jobs. Here the rows are
dealt out once per projection and each task makes the releases of its projection from arrays, by the rules that the
operators use (same clipping, same order of picks and of the curve), so that the figures are theirs. A task holds one
projection's rows, so tables of more than FAMILY_ROWS rows are refused: those are released one by one over the cluster.

Nulls are ordinary values, first in the order; an empty table gives no figures; row ids must be unique.
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
from celldiv.operators import bounds, curve, drain, publish, vectors
from celldiv.storage import small

#: Below this a table is one chunk of the curve, and phases two and three follow the exact rule.
FAMILY_ROWS = min(2 * curve.CHUNK_ROWS, drain.DRIVER_ROWS) - 1
RELEASES = "place int, method string, l int, n long, stars long, starred_rows long, phase int, seconds double"


def fits(df: DataFrame) -> bool:
    return df.limit(FAMILY_ROWS + 1).count() <= FAMILY_ROWS


def _coded(df: DataFrame, spec: MicrodataSpec) -> DataFrame:
    """df with every QI and the sensitive value as ranks in their domains, nulls first, by joins with the domains."""
    for i, c in enumerate([*spec.qi, spec.sa]):
        domain = df.groupBy(F.col(c).alias("__v")).agg(F.count(F.lit(1)).alias("__n"))
        codes = domain.select(F.array_sort(F.collect_list(F.struct(F.col("__v").isNotNull().alias("has"), F.col("__v").alias("v")))).alias("vs"))
        codes = codes.select(F.posexplode("vs").alias("__k", "__s")).select(F.col("__k").alias(f"__c{i}"), F.col("__s.v").alias("__v"))
        df = df.join(small(codes), F.col(c).eqNullSafe(F.col("__v"))).drop("__v")
    return df


def _trimmed(cells: np.ndarray, sa: np.ndarray, l: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(cell, value, height, kept) of phase one, ordered by cell and falling height."""
    m = int(sa.max()) + 1
    pairs, h = np.unique(cells * m + sa, return_counts=True)
    cell, value = pairs // m, pairs % m
    order = np.lexsort((value, -h, cell))
    cell, value, h = cell[order], value[order], h[order]
    first = np.r_[True, cell[1:] != cell[:-1]]
    begin = np.flatnonzero(first)
    which = np.cumsum(first) - 1
    before = np.cumsum(h) - h
    before -= before[begin][which]
    total, many = np.add.reduceat(h, begin), np.diff(np.r_[begin, len(h)])
    j = np.arange(len(h)) - begin[which]
    bound = np.where(j < l, (total[which] - before) // np.maximum(1, l - j), np.iinfo(np.int64).max)
    cap = np.where(many < l, 0, np.minimum.reduceat(bound, begin))
    return cell, value, h, np.minimum(h, cap[which])


def _later(cell: np.ndarray, value: np.ndarray, h: np.ndarray, kept: np.ndarray, l: int) -> tuple[np.ndarray, int]:
    """kept after phases two and three, and the phase that ended. Cells must be numbered in the order of their hashes."""
    residue = Counter({int(v): int(n) for v, n in zip(*_sums(value, h - kept)) if n})
    if vectors.eligible(residue, l):
        return kept, 1
    alive = np.unique(cell[kept > 0])
    cells: list[dict] = [{} for _ in alive]
    for c, v, k in zip(np.searchsorted(alive, cell).tolist(), value.tolist(), kept.tolist()):
        if k:
            cells[c][v] = k
    start, phase = Counter(residue), 2
    vectors.drain(cells, residue, l)
    bounds.check_drained(start, residue, l)
    if not vectors.eligible(residue, l):
        phase = 3
        vectors.overhaul(cells, residue, l)
    return np.array([cells[c].get(v, 0) if k else 0 for c, v, k in zip(np.searchsorted(alive, cell).tolist(), value.tolist(), kept.tolist())], np.int64), phase


def _sums(keys: np.ndarray, numbers: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    got, at = np.unique(keys, return_inverse=True)
    return got, np.bincount(at, numbers, len(got)).astype(np.int64)


def _on_curve(codes: np.ndarray, row_id: np.ndarray, sa: np.ndarray, l: int) -> np.ndarray:
    """Cell numbers of the curve baseline for rows of one chunk."""
    dense = np.column_stack([np.unique(c, return_inverse=True)[1] for c in codes.T])
    bits = max(1, int(dense.max()).bit_length())
    keep = max(1, min(bits, POSITION_BITS // dense.shape[1]))
    order = np.lexsort((row_id, hilbert_numbers(dense >> (bits - keep), keep)))
    out = np.empty(len(sa), np.int64)
    out[order] = curve.group_sorted(np.unique(sa[order], return_inverse=True)[1].astype(np.int64), l)
    return out


def _stars(codes: np.ndarray, cell: np.ndarray) -> tuple[int, int]:
    """Stars and starred rows when rows of a cell keep what they share."""
    if not len(cell):
        return 0, 0
    order = np.argsort(cell, kind="stable")
    begin = np.flatnonzero(np.r_[True, np.diff(cell[order]) != 0])
    size = np.diff(np.r_[begin, len(cell)])
    differs = np.minimum.reduceat(codes[order], begin) != np.maximum.reduceat(codes[order], begin)
    return int((differs.sum(1) * size).sum()), int(size[differs.any(1)].sum())


def released(rows: pd.DataFrame, qi: Sequence[int], ls: Sequence[int], methods: Sequence[str]) -> Iterator[tuple]:
    """(method, l, n, stars, starred rows, phase, seconds) of one projection. rows: codes, sa, row_id, spot, pick, salt."""
    codes = np.column_stack([rows[f"c{i}"].to_numpy(np.int64) for i in qi])
    sa, row_id = rows["sa"].to_numpy(np.int64), rows["row_id"].to_numpy()
    _, cells = np.unique(rows["spot"].to_numpy(np.int64), return_inverse=True)
    n, top, m = len(rows), int(np.bincount(sa).max()), int(sa.max()) + 1
    order = np.lexsort((row_id, rows["pick"].to_numpy(np.int64), rows["salt"].to_numpy(np.int64), sa, cells))
    pair = (cells * m + sa)[order]
    begin = np.flatnonzero(np.r_[True, np.diff(pair) != 0])
    rank = np.empty(n, np.int64)
    rank[order] = np.arange(n) - np.repeat(begin, np.diff(np.r_[begin, n]))
    for l in ls:
        if n < l * top:
            continue
        since = time.time()
        if {"tiered", "hybrid"} & set(methods):
            cell, value, h, kept = _trimmed(cells, sa, l)
            kept, phase = _later(cell, value, h, kept, l)
            moved = dict(zip((cell * m + value).tolist(), (h - kept).tolist()))
            gone = rank < np.array([moved[p] for p in (cells * m + sa).tolist()])
            spent = time.time() - since
            for method in ("tiered", "hybrid"):
                if method in methods:
                    since = time.time()
                    left = codes[gone]
                    of = _on_curve(left, row_id[gone], sa[gone], l) if method == "hybrid" and len(left) else np.zeros(len(left), np.int64)
                    yield (method, l, n, *_stars(left, of), phase, round(spent + time.time() - since, 3))
        if "curve" in methods:
            since = time.time()
            yield ("curve", l, n, *_stars(codes, _on_curve(codes, row_id, sa, l)), 0, round(time.time() - since, 3))


def releases(df: DataFrame, spec: MicrodataSpec, projections: Sequence[tuple[str, ...]], ls: Sequence[int], methods: Sequence[str]) -> DataFrame:
    """(place, method, l, n, stars, starred_rows, phase, seconds): place counts the projections; infeasible l are left out."""
    rows = shown(df, spec)
    if not fits(rows):
        raise ValueError(f"over {FAMILY_ROWS} rows: release the projections one by one")
    spots = F.array(*[F.xxhash64(F.struct(*qi)) for qi in projections])
    named = {f"c{i}": F.col(f"__c{i}") for i in range(len(spec.qi))} | {"sa": F.col(f"__c{len(spec.qi)}"), "row_id": F.col(spec.row_id)}
    picks = {"pick": F.xxhash64(spec.row_id, F.lit(1)), "salt": F.pmod(F.xxhash64(spec.row_id), F.lit(publish.SALTS))}
    dealt = _coded(rows, spec).select(*[c.alias(k) for k, c in (named | picks).items()], F.posexplode(spots).alias("place", "spot"))
    of = [tuple(spec.qi.index(q) for q in qi) for qi in projections]
    ls, methods = list(ls), list(methods)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        place = int(pdf["place"].iloc[0])
        return pd.DataFrame([(place, *r) for r in released(pdf, of[place], ls, methods)], columns=[f.split()[0] for f in RELEASES.split(", ")])

    return dealt.groupBy("place").applyInPandas(run, RELEASES)
