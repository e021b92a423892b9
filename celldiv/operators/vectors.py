"""Phases two and three on count vectors that fit the driver, and brute force for tiny cases.

cells: list of {value: height}; residue: {value: count}. All functions change them in place.
"""

from __future__ import annotations

import itertools
from collections import Counter

from celldiv.operators import bounds


def trim(cells: list[dict], l: int) -> Counter:
    """Phase one, step by step: the reference that the closed form is tested against."""
    residue: Counter = Counter()
    for cell in cells:
        while cell and sum(cell.values()) < l * max(cell.values()):
            v = max(cell, key=lambda x: cell[x])
            take(cell, v, residue)
    return residue


def take(cell: dict, v, residue: Counter) -> None:
    cell[v] -= 1
    residue[v] += 1
    if not cell[v]:
        del cell[v]


def eligible(counts: dict, l: int) -> bool:
    return not counts or sum(counts.values()) >= l * max(counts.values())


def peaks(counts: dict) -> set:
    top = max(counts.values(), default=0)
    return {v for v, h in counts.items() if h == top}


def _key(v) -> tuple:
    return (v is not None, v if v is not None else 0)


def drain(cells: list[dict], residue: Counter, l: int, only: set | None = None) -> int:
    """Phase two: give rows without raising the residue's height, until it is eligible or all cells are frozen.

    A cell once frozen stays so, since the residue's peaks only get more; each value therefore keeps a
    list of cells from which frozen ones are dropped for good. Returns the rows moved.
    """
    holders: dict = {}
    for i, cell in enumerate(cells):
        if only is None or i in only:
            for v in cell:
                holders.setdefault(v, []).append(i)
    moved, height = 0, max(residue.values(), default=0)
    while not eligible(residue, l):
        top = {v for v, r in residue.items() if r == height}
        for v in sorted(holders, key=lambda x: (residue[x], _key(x))):
            if v in top:
                continue
            while holders[v]:
                cell = cells[holders[v][-1]]
                size, peak = sum(cell.values()), max(cell.values(), default=0)
                if v in cell and (size > l * peak or not peaks(cell) & top):
                    break
                holders[v].pop()
            if holders[v]:
                break
        else:
            return moved
        given = [v] if size > l * peak else sorted(peaks(cell), key=_key)
        for x in given:
            take(cell, x, residue)
            moved += 1
    return moved


def cover(signatures: dict[int, object], n_peaks: int) -> list:
    """Cells whose clash sets have nothing in common, chosen greedily: each pick leaves the fewest peaks in common."""
    common, picks, left = (1 << n_peaks) - 1, [], dict(signatures)
    while common:
        mask = min(left, key=lambda s: ((common & s).bit_count(), s), default=None)
        if mask is None or common & mask == common:
            raise AssertionError("some residue peak clashes with every cell")
        picks.append(left.pop(mask))
        common &= mask
    return picks


def overhaul(cells: list[dict], residue: Counter, l: int, trace: list | None = None) -> int:
    """Phase three: rounds of widening the residue from a cover of cells and refreezing them. Returns the rounds; trace gets a row for each."""
    heights = [max(residue.values(), default=0)]
    while not eligible(residue, l):
        top = sorted(peaks(residue), key=_key)
        signatures: dict[int, object] = {}
        frozen = True
        for i, cell in enumerate(cells):
            if cell:
                own = peaks(cell)
                mask = sum(1 << k for k, v in enumerate(top) if v in own)
                signatures.setdefault(mask, i)
                frozen = frozen and mask > 0 and sum(cell.values()) == l * max(cell.values())
        bounds.check_stuck(residue, signatures, frozen, l)
        for i in cover(signatures, len(top)):
            for v in sorted(peaks(cells[i]), key=_key):
                take(cells[i], v, residue)
        if not eligible(residue, l):
            before = Counter(residue)
            drain(cells, residue, l)
            bounds.check_drained(before, residue, l)
        heights.append(max(residue.values()))
        if trace is not None:
            trace.append((f"round {len(heights) - 1}", sum(residue.values()), heights[-1]))
    bounds.check_overhauled(heights, l)
    return len(heights) - 1


def solve(cells: list[dict], l: int) -> tuple[Counter, int, int]:
    """All phases: the residue, the phase that ended, the rounds of phase three."""
    residue = trim(cells, l)
    if eligible(residue, l):
        return residue, 1, 0
    before = Counter(residue)
    drain(cells, residue, l)
    bounds.check_drained(before, residue, l)
    if eligible(residue, l):
        return residue, 2, 0
    return residue, 3, overhaul(cells, residue, l)


def least_rows(cells: list[dict], l: int) -> int:
    """Optimal residue size, by trying every sub-vector of every cell."""
    choices = []
    for cell in cells:
        ways = set()
        for kept in itertools.product(*[range(h + 1) for h in cell.values()]):
            if eligible({i: k for i, k in enumerate(kept) if k}, l):
                ways.add(tuple(h - k for h, k in zip(cell.values(), kept)))
        choices.append([(dict(zip(cell, w))) for w in ways])

    found: set[tuple] = {()}
    for ways in choices:
        found = {tuple(sorted((Counter(dict(s)) + Counter(w)).items(), key=str)) for s in found for w in ways}

    return min(sum(c for _, c in s) for s in found if eligible(dict(s), l))


def least_stars(rows: list[tuple], l: int) -> int:
    """Optimal stars over all partitions; rows are (qi tuple, sa). Up to about ten rows."""
    best = [len(rows) * len(rows[0][0])]

    def cost(group: list) -> int:
        return len(group) * sum(len({r[0][i] for r in group}) > 1 for i in range(len(group[0][0])))

    def go(i: int, groups: list[list]) -> None:
        if sum(map(cost, groups)) >= best[0] and groups:
            return
        if i == len(rows):
            if all(eligible(Counter(r[1] for r in g), l) for g in groups):
                best[0] = sum(map(cost, groups))
            return
        for g in groups:
            g.append(rows[i])
            go(i + 1, groups)
            g.pop()
        groups.append([rows[i]])
        go(i + 1, groups)
        groups.pop()

    if eligible(Counter(r[1] for r in rows), l) and all(cost([r]) == 0 for r in rows):
        go(0, [])
    return best[0]
