"""Histograms of cells, eligibility, and checks of released tables.

Defined results throughout: a null is an ordinary QI or sensitive value; an empty table has no cells, breaks no rule and is
feasible for every l of 2 or more; repeated rows count each; columns that the spec does not name are not read.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from celldiv.model import Infeasible, MicrodataSpec, check_l
from celldiv.storage import small


def cell_histogram(df: DataFrame, spec: MicrodataSpec) -> DataFrame:
    """(cell, sa, h). Rows with equal QI and SA values are interchangeable, so counts carry all that matters."""
    return df.groupBy(spec.cell().alias("cell"), F.col(spec.sa).alias("sa")).agg(F.count(F.lit(1)).alias("h"))


def cell_summary(hist: DataFrame, l: int) -> DataFrame:
    """Per cell: size, peak, number of peak and of all values, surplus, tight, eligible."""
    top = hist.groupBy("cell").agg(F.sum("h").alias("size"), F.max("h").alias("peak"), F.count(F.lit(1)).alias("n_values"))
    peaks = hist.groupBy("cell", "h").agg(F.count(F.lit(1)).alias("n_peaks")).withColumnRenamed("h", "peak")
    return top.join(peaks, ["cell", "peak"]).select(
        "cell", "size", "peak", "n_peaks", "n_values", (F.col("size") - l * F.col("peak")).alias("surplus"),
        (F.col("size") == l * F.col("peak")).alias("tight"), (F.col("size") >= l * F.col("peak")).alias("eligible"))


def max_feasible_l(df: DataFrame, sa: str) -> DataFrame:
    """One row: n, top (count of the most frequent value), m, max_l."""
    counts = df.groupBy(sa).agg(F.count(F.lit(1)).alias("c"))
    return counts.agg(F.sum("c").alias("n"), F.max("c").alias("top"), F.count(F.lit(1)).alias("m")).withColumn("max_l", F.expr("n div top"))


def is_eligible(df: DataFrame, sa: str, l: int) -> bool:
    r = max_feasible_l(df, sa).first()
    return r["n"] is None or r["n"] >= l * r["top"]


def require_solution(df: DataFrame, spec: MicrodataSpec, l: int) -> tuple[int, int]:
    """(n, m), or Infeasible if the table itself is not eligible."""
    check_l(l)
    r = max_feasible_l(df, spec.sa).first()
    if r["n"] and r["n"] < l * r["top"]:
        raise Infeasible(f"a value of {spec.sa} has {r['top']} of {r['n']} rows; l may be {r['max_l']} at most")
    return r["n"] or 0, r["m"]


def monotone_union(a: DataFrame, b: DataFrame) -> DataFrame:
    """The histogram (sa, h) of two disjoint sets of rows together. If both are eligible it is too: heights add up at most."""
    return a.unionByName(b).groupBy("sa").agg(F.sum("h").alias("h"))


def _released(pub: DataFrame, spec: MicrodataSpec, level: str) -> list:
    return ["cell_id"] if level == "strict" else ["star_mask", *spec.qi]


def violations(pub: DataFrame, spec: MicrodataSpec, l: int, level: str = "strict", mode: str = "frequency") -> DataFrame:
    """Cells of a release that break diversity: by frequency, by distinct values, or by entropy."""
    key = _released(pub, spec, level)
    cells = pub.groupBy(*key, spec.sa).agg(F.count(F.lit(1)).alias("h")).groupBy(*key).agg(
        F.sum("h").alias("size"), F.max("h").alias("peak"), F.count(F.lit(1)).alias("n_values"),
        (F.log(F.sum("h")) - F.sum(F.col("h") * F.log("h")) / F.sum("h")).alias("entropy"))
    broken = {"frequency": F.col("peak") * l > F.col("size"), "distinct": F.col("n_values") < l, "entropy": F.exp("entropy") < l - 1e-9}[mode]
    return cells.where(broken)


def k_anonymity_violations(df: DataFrame, qi: tuple[str, ...], k: int) -> DataFrame:
    return df.groupBy(*qi).agg(F.count(F.lit(1)).alias("size")).where(F.col("size") < k)


def homogeneous_cells(df: DataFrame, spec: MicrodataSpec) -> DataFrame:
    """Cells in which every row has the same sensitive value."""
    per = df.groupBy(*spec.qi, spec.sa).agg(F.count(F.lit(1)).alias("h")).groupBy(*spec.qi)
    return per.agg(F.count(F.lit(1)).alias("n_values"), F.sum("h").alias("size")).where("n_values = 1").drop("n_values")


def alpha_k_violations(df: DataFrame, spec: MicrodataSpec, alpha: float, k: int) -> DataFrame:
    cells = df.groupBy(*spec.qi, spec.sa).agg(F.count(F.lit(1)).alias("h")).groupBy(*spec.qi).agg(F.sum("h").alias("size"), F.max("h").alias("peak"))
    return cells.where((F.col("size") < k) | (F.col("peak") > alpha * F.col("size")))


def adversary_confidence(pub: DataFrame, spec: MicrodataSpec, level: str = "strict") -> DataFrame:
    """Per cell the highest share of one sensitive value: what an intruder may conclude."""
    key = _released(pub, spec, level)
    cells = pub.groupBy(*key, spec.sa).agg(F.count(F.lit(1)).alias("h")).groupBy(*key).agg(F.sum("h").alias("size"), F.max("h").alias("peak"))
    return cells.withColumn("confidence", F.col("peak") / F.col("size"))


def linking_attack(pub: DataFrame, known: DataFrame, spec: MicrodataSpec) -> DataFrame:
    """known has a person and the QI columns: per person the sensitive values of the rows that may be theirs.

    One equality join per pattern of stars, at most 2^d. A null is met by a null, a star by anything.
    """
    kept = pub.groupBy("star_mask", *spec.qi, spec.sa).agg(F.count(F.lit(1)).alias("h"))
    masks = [r[0] for r in kept.select("star_mask").distinct().collect()] or [0]  # at most 2^d numbers
    out = None
    for mask in masks:
        plain = [q for i, q in enumerate(spec.qi) if not mask >> i & 1]
        right = kept.where(F.col("star_mask") == mask).groupBy(*[F.col(q).alias(f"__{q}") for q in plain], F.col(spec.sa).alias("sa")).agg(F.sum("h").alias("h"))
        if plain:
            on = F.lit(True)
            for q in plain:
                on = on & F.col(q).eqNullSafe(F.col(f"__{q}"))
            found = known.join(right, on)
        else:  # a row of stars may be anyone's: one row per sensitive value meets each person
            found = known.crossJoin(F.broadcast(right))
        found = found.select("person", "sa", "h")
        out = found if out is None else out.union(found)
    return out.groupBy("person", "sa").agg(F.sum("h").alias("rows"))


def closeness_report(pub: DataFrame, spec: MicrodataSpec) -> DataFrame:
    """Per cell the variational distance of its sensitive values from the table's."""
    whole = pub.groupBy(F.col(spec.sa).alias("sa")).agg(F.count(F.lit(1)).alias("g"))
    total = whole.agg(F.sum("g").alias("n"))
    per = pub.groupBy("cell_id", F.col(spec.sa).alias("sa")).agg(F.count(F.lit(1)).alias("h"))
    sizes = per.groupBy(F.col("cell_id").alias("__id")).agg(F.sum("h").alias("size"))
    both = per.join(sizes, F.col("cell_id").eqNullSafe(F.col("__id"))).join(small(whole.withColumnRenamed("sa", "__s")), F.col("sa").eqNullSafe(F.col("__s"))).crossJoin(F.broadcast(total))
    p, q = F.col("h") / F.col("size"), F.col("g") / F.col("n")
    # values absent from a cell contribute their global share, which is one minus that of those present
    return both.groupBy("cell_id").agg(((F.sum(F.abs(p - q)) + 1 - F.sum(q)) / 2).alias("distance"))
