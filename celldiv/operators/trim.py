"""Phase one: every cell is clipped to the greatest height at which it is eligible.

Taking rows from the highest values one at a time ends in one state whatever the order: heights cut at
the largest cap c with sum(min(h, c)) >= l * c. With heights in falling order the clipped sum is the
least over j of j * c plus what the lower ones hold, so the cap is a minimum over the first l ranks.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def trim_cells(hist: DataFrame, l: int) -> DataFrame:
    """(cell, sa, h, kept, moved). One shuffle by cell; rank, running sum and totals share its sort."""
    order = Window.partitionBy("cell").orderBy(F.desc("h"), F.asc_nulls_first("sa"))
    whole = Window.partitionBy("cell")
    ranked = hist.withColumns({
        "j": F.row_number().over(order) - 1, "total": F.sum("h").over(whole), "n_values": F.count(F.lit(1)).over(whole),
        "before": F.coalesce(F.sum("h").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))})
    bound = F.when(F.col("j") < l, F.expr(f"(total - before) div ({l} - j)"))
    capped = ranked.withColumn("bound", bound).withColumn("cap", F.when(F.col("n_values") < l, 0).otherwise(F.min("bound").over(whole)))
    kept = F.least("h", "cap").cast("long")
    return capped.select("cell", "sa", "h", kept.alias("kept"), (F.col("h") - kept).alias("moved"))


def cap_of(heights: Column, l: int) -> Column:
    """The same cap from an array of one cell's heights."""
    falling = F.reverse(F.array_sort(heights))
    total = F.aggregate(heights, F.lit(0).cast("long"), lambda s, x: s + x)

    def step(s: Column, x: Column) -> Column:
        bound = F.when(s["j"] < l, F.call_function("div", total - s["before"], F.lit(l) - s["j"]))
        return F.struct((s["j"] + 1).alias("j"), (s["before"] + x).alias("before"), F.least(s["cap"], bound).alias("cap"))

    start = F.struct(F.lit(0).alias("j"), F.lit(0).cast("long").alias("before"), F.lit(None).cast("long").alias("cap"))
    return F.when(F.size(heights) < l, F.lit(0).cast("long")).otherwise(F.aggregate(falling, start, step, lambda s: s["cap"]))


def residue_vector(trimmed: DataFrame) -> DataFrame:
    """(sa, r) of the rows moved so far."""
    return trimmed.groupBy("sa").agg(F.sum("moved").alias("r")).where("r > 0")


def residue_facts(vector: DataFrame, l: int) -> DataFrame:
    """One row: rows, height, lower_bound (no solution moves fewer rows), deficit, done."""
    facts = vector.agg(F.coalesce(F.sum("r"), F.lit(0)).alias("rows"), F.coalesce(F.max("r"), F.lit(0)).alias("height"))
    return facts.select("rows", "height", (F.col("height") * l).alias("lower_bound"), F.greatest(F.lit(0), F.col("height") * l - F.col("rows")).alias("deficit"), (F.col("rows") >= l * F.col("height")).alias("done"))


def vanishing_cells(hist: DataFrame, l: int) -> DataFrame:
    """Cells with fewer than l sensitive values: none of their rows can stay."""
    return hist.groupBy("cell").agg(F.count(F.lit(1)).alias("n_values"), F.sum("h").alias("size")).where(F.col("n_values") < l)
