"""What the phases are proven to keep, asserted while they run, and the report of a run against its lower bound.

All functions work on the residue's counts (one per sensitive value) and on clash masks (at most 2^(l-1)).
"""

from __future__ import annotations

from collections.abc import Iterable


class BrokenBound(AssertionError):
    """A phase left what is proven about it: an error of the program, never of the data."""


def _top(residue: dict) -> int:
    return max(residue.values(), default=0)


def check_drained(before: dict, after: dict, l: int) -> None:
    """Phase two never raises the residue's height, and ends at most l - 1 rows above l times the height if it succeeds."""
    if _top(after) != _top(before):
        raise BrokenBound(f"phase two moved the height from {_top(before)} to {_top(after)}")
    rows, least = sum(after.values()), l * _top(after)
    if rows >= least and sum(before.values()) < least and rows > least + l - 1:
        raise BrokenBound(f"phase two took {rows} rows, {rows - least} above its bound's {least}")


def check_stuck(residue: dict, masks: Iterable[int], frozen: bool, l: int) -> None:
    """Where phase two fails all cells are frozen, no peak of the residue is one of every cell, and there are two peaks at least (so l > 2)."""
    n_peaks = sum(r == _top(residue) for r in residue.values())
    common = (1 << n_peaks) - 1
    for mask in masks:
        common &= mask
    if not frozen or common or not 2 <= n_peaks < l:
        raise BrokenBound(f"phase two stopped early: frozen={frozen}, {n_peaks} peaks, shared by all cells: {common:b}, l={l}")


def check_overhauled(heights: list[int], l: int) -> None:
    """heights: before phase three and after each of its rounds. A round adds l - 2 at most, and there are no more rounds than the first height."""
    if any(b - a > l - 2 for a, b in zip(heights, heights[1:])) or len(heights) - 1 > heights[0]:
        raise BrokenBound(f"phase three's heights {heights} at l={l}")


def run_report(trace: list[tuple[str, int, int]], l: int) -> dict:
    """From (step, rows, height) after phase one, phase two and each round: the lower bound that no solution is below, rows over it,
    and as each starred row has one star at least, bounds of the true ratios (of stars, d times that of rows)."""
    (_, _, height), (_, rows, _) = trace[0], trace[-1]
    bound = l * height
    return {"lower_bound": bound, "rows_to_bound": rows / bound if bound else 1.0, "gap": rows - bound, "trace": trace}
