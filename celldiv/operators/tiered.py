"""The whole methods: tiered suppression, its hybrid with a refined residue, coarsening, projections at once."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from itertools import combinations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from celldiv.functions.measures import star_counts
from celldiv.model import MicrodataSpec, shown
from celldiv.operators import bounds, curve, drain, vectors
from celldiv.operators.cells import cell_histogram, require_solution, violations
from celldiv.operators.lattice import Lattice
from celldiv.operators.publish import kept_rows, pick_rows, publish, suppress_all
from celldiv.operators.trim import trim_cells
from celldiv.storage import persisted


@dataclass
class Result:
    published: DataFrame  # QI columns, SA, row id, cell_id, star_mask
    split: DataFrame  # the rows with in_residue
    report: dict


def histogram_plan(hist: DataFrame, l: int, how: str = "auto") -> tuple[DataFrame, dict]:
    """(cell, sa, h, moved) after all phases, and the report, of a feasible histogram (cell, sa, h)."""
    state = persisted(trim_cells(hist, l).select("cell", "sa", F.col("kept").alias("h"), "moved"))
    trace: list[tuple[str, int, int]] = []
    state, residue, phase, rounds = drain.finish(state, l, how, trace)
    if not vectors.eligible(residue, l):
        raise bounds.BrokenBound("the residue is not eligible")
    return state, {"l": l, "phase": phase, "rounds": rounds, "trim_rows": trace[0][1], "residue_rows": sum(residue.values()),
                   "certificate": {1: "optimal in rows", 2: "optimal in rows plus l - 1", 3: "l times the optimum in rows"}[phase]} | bounds.run_report(trace, l)


def tiered_plan(df: DataFrame, spec: MicrodataSpec, l: int, how: str = "auto") -> tuple[DataFrame, dict]:
    """(cell, sa, h, moved) after all phases, and the report."""
    n, m = require_solution(df, spec, l)
    state, report = histogram_plan(cell_histogram(df, spec), l, how)
    return state, report | {"d": len(spec.qi), "n": n, "m": m}


def tiered_split(df: DataFrame, spec: MicrodataSpec, l: int, how: str = "auto") -> tuple[DataFrame, DataFrame, dict]:
    """The rows with in_residue; the residue alone, cut out and kept; the report. Rows that stay are read from the table."""
    rows = shown(df, spec)
    state, report = tiered_plan(rows, spec, l, how)
    split = pick_rows(rows, state, spec)
    return split, persisted(split.where("in_residue").drop("in_residue")), report


def tiered_suppress(df: DataFrame, spec: MicrodataSpec, l: int, how: str = "auto") -> Result:
    split, residue, report = tiered_split(df, spec, l, how)
    pub = kept_rows(split, spec)
    if report["residue_rows"]:
        pub = pub.unionByName(suppress_all(residue, spec).select(*pub.columns))
    return Result(pub, split, report | {"method": "tiered"})


def hybrid_suppress(df: DataFrame, spec: MicrodataSpec, l: int, refiner: Callable[[DataFrame, MicrodataSpec, int], DataFrame] | None = None, how: str = "auto") -> Result:
    """Tiered suppression, then the residue alone is split by the refiner (residue -> the same with cell_id, diverse)."""
    split, residue, report = tiered_split(df, spec, l, how)
    pub = kept_rows(split, spec)
    if report["residue_rows"]:
        cells = persisted((refiner or curve.curve_cells)(residue, spec, l))
        if not violations(cells, spec, l).isEmpty():
            raise ValueError("the refiner made a cell that is not diverse")
        pub = pub.unionByName(publish(cells, spec).select(*pub.columns))
    return Result(pub, split, report | {"method": "hybrid"})


def curve_suppress(df: DataFrame, spec: MicrodataSpec, l: int, chunking: str = "stratified", chunk_rows: int = curve.CHUNK_ROWS) -> Result:
    rows = shown(df, spec)
    n, m = require_solution(rows, spec, l)
    cells = persisted(curve.curve_cells(rows, spec, l, chunking, chunk_rows))
    pub = publish(cells, spec).select(*spec.qi, spec.sa, spec.row_id, "cell_id", "star_mask")
    return Result(pub, cells, {"method": "curve", "l": l, "d": len(spec.qi), "n": n, "m": m, "phase": 0, "rounds": 0})


def preprocess_then(df: DataFrame, spec: MicrodataSpec, coarsening: dict, method: Callable, l: int) -> Result:
    """Any method after replacing QI columns by coarser ones (column expressions); the coarsening need not be diverse."""
    return method(df.withColumns(coarsening), spec, l)


def sweep_coarsening(df: DataFrame, spec: MicrodataSpec, levels: dict[str, dict], l: int) -> list[dict]:
    """Stars and lower bound per named coarsening; the caller weighs them against what each level loses."""
    out = []
    for name, coarsening in levels.items():
        got = preprocess_then(df, spec, coarsening, tiered_suppress, l)
        out.append(got.report | {"level": name} | star_counts(got.published).first().asDict())
    return out


def lattice_trim(df: DataFrame, spec: MicrodataSpec, sizes: tuple[int, ...], ls: list[int], coded: Lattice | None = None) -> DataFrame:
    """(grouping, l, residue_rows, height, done) of phase one for all projections of the sizes and all l; grouping has a bit per QI left out.

    They are summed up from the coded histogram of the same table, sizes and l if there is one, else in one job by
    grouping sets over the full-QI histogram.
    """
    if coded:
        return coded.trimmed().select("grouping", "l", "residue_rows", "height", "done")
    d = len(spec.qi)
    base = df.groupBy(*spec.qi, F.col(spec.sa).alias("sa")).agg(F.count(F.lit(1)).alias("h"))
    # just the projections wanted, each with the sensitive value
    sets = [[*some, "sa"] for k in sizes for some in combinations(spec.qi, k)]
    one = base.groupingSets(sets, *spec.qi, "sa").agg(F.sum("h").alias("h"), F.grouping_id().alias("g"))
    cells = one.select(F.struct(F.expr("cast(g div 2 as int)").alias("grouping"), *spec.qi).alias("key"), "sa", "h")
    # all l share one sort of a cell's values: a cap and a count of rows moved for each
    order, whole = Window.partitionBy("key").orderBy(F.desc("h"), "sa"), Window.partitionBy("key")
    ranked = cells.withColumns({"j": F.row_number().over(order) - 1, "total": F.sum("h").over(whole), "k": F.count(F.lit(1)).over(whole), "before": F.coalesce(F.sum("h").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))})
    caps = {f"cap_{l}": F.when(F.col("k") < l, 0).otherwise(F.min(F.when(F.col("j") < l, F.expr(f"(total - before) div ({l} - j)"))).over(whole)) for l in ls}
    gone = [F.sum(F.col("h") - F.least("h", f"cap_{l}")).alias(f"r_{l}") for l in ls]
    per = ranked.withColumns(caps).groupBy("key.grouping", "sa").agg(*gone)
    facts = [F.struct(F.lit(l).alias("l"), F.sum(f"r_{l}").alias("residue_rows"), F.max(f"r_{l}").alias("height")) for l in ls]
    per = per.groupBy("grouping").agg(F.array(*facts).alias("of")).select("grouping", F.inline("of"))
    return per.withColumn("done", F.col("residue_rows") >= F.col("l") * F.col("height"))
