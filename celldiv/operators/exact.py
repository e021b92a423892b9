"""The two-valued case solved exactly, and hard instances."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from celldiv.model import Infeasible, MicrodataSpec
from celldiv.operators.cells import max_feasible_l

#: Cells of either value that the solver takes; their rows are not bounded.
PAIR_CELLS = 5_000


def transport(cost: np.ndarray, supply: np.ndarray, demand: np.ndarray) -> np.ndarray:
    """Amounts from each row to each column at least total cost; supply and demand have one sum (shortest augmenting paths with potentials)."""
    n, m = cost.shape
    u, v, flow, free = np.zeros(n), np.zeros(m), np.zeros((n, m), np.int64), demand.astype(np.int64)
    for row in range(n):
        left = int(supply[row])
        while left:
            reach, way, done = np.full(m, np.inf), np.full(m, -1), np.zeros(m, bool)
            entry, back = np.full(n, np.inf), np.full(n, -1)
            entry[row], fresh, at = 0, [row], 0.0
            while True:
                for r in fresh:
                    now = at + cost[r] - u[r] - v
                    better = ~done & (now < reach)
                    reach[better], way[better] = now[better], r
                col = int(np.where(done, np.inf, reach).argmin())
                at, done[col] = reach[col], True
                if free[col]:
                    break
                fresh = np.flatnonzero((flow[:, col] > 0) & np.isinf(entry))
                entry[fresh], back[fresh] = at, col
            seen = np.isfinite(entry)
            u[seen] += at - entry[seen]
            v[done] -= at - reach[done]
            path, amount, c = [], min(left, int(free[col])), col
            while (r := way[c]) != row:
                path.append((r, c, back[r]))
                amount = min(amount, int(flow[r, back[r]]))
                c = back[r]
            for r, to, of in path:
                flow[r, to] += amount
                flow[r, of] -= amount
            flow[row, c] += amount
            free[col] -= amount
            left -= amount
    return flow


def pair_cancellation(df: DataFrame, spec: MicrodataSpec) -> DataFrame:
    """Per cell, how many rows of opposite values pair at no cost, and what is left of either."""
    lo, hi = F.min("h"), F.max("h")
    per = df.groupBy(*spec.qi, spec.sa).agg(F.count(F.lit(1)).alias("h")).groupBy(*spec.qi)
    got = per.agg(lo.alias("lo"), hi.alias("hi"), F.count(F.lit(1)).alias("k"))
    return got.select(*spec.qi, F.when(F.col("k") == 2, F.col("lo")).otherwise(0).alias("pairs"), F.when(F.col("k") == 2, F.col("hi") - F.col("lo")).otherwise(F.col("hi")).alias("left"))


def pair_exact(df: DataFrame, spec: MicrodataSpec) -> DataFrame:
    """df with cell_id, m = l = 2 and equal counts: cells are pairs; the stars are least.

    The cost of a pair is a metric (twice the differing QIs), so rows with equal QIs pair first. The rest differ
    only by cell and value: their counts are a transportation problem on the driver, and each amount of its
    solution pairs a range of one cell's rows with a range of another's.
    """
    whole = max_feasible_l(df, spec.sa).first()
    if whole["n"] and (whole["m"] != 2 or whole["n"] != 2 * whole["top"]):
        raise Infeasible("pairs want two sensitive values with equal counts")
    order = Window.partitionBy(*spec.qi, spec.sa).orderBy(spec.row_id)
    ranked = df.withColumn("__k", F.row_number().over(order))
    both = ranked.groupBy(*spec.qi, "__k").agg(F.count(F.lit(1)).alias("__b"), F.min(spec.row_id).alias("__first"))
    on = F.col("__k") == F.col("__k2")
    for q in spec.qi:
        both = both.withColumnRenamed(q, f"__{q}")
        on = on & F.col(q).eqNullSafe(F.col(f"__{q}"))
    tagged = ranked.join(both.withColumnRenamed("__k", "__k2"), on).drop("__k2", *[f"__{q}" for q in spec.qi])
    free = tagged.where("__b = 2").select(*df.columns, F.xxhash64("__first").alias("cell_id"))
    rest = tagged.where("__b = 1").select(*df.columns, "__k")
    cells = rest.groupBy(*spec.qi, spec.sa).agg(F.count(F.lit(1)).alias("__n"), F.min("__k").alias("__from")).limit(2 * PAIR_CELLS + 1).collect()
    if len(cells) > 2 * PAIR_CELLS:
        raise ValueError("too many cells with unpaired rows for the exact solver")
    if not cells:
        return free
    names = sorted({r[spec.sa] for r in cells}, key=lambda v: (v is not None, v))
    sides = [[r for r in cells if r[spec.sa] == v] for v in names]
    amounts = [np.array([r["__n"] for r in side], np.int64) for side in sides]
    known: list[dict] = [{} for _ in spec.qi]
    codes = [np.array([[known[i].setdefault(r[q], len(known[i])) for i, q in enumerate(spec.qi)] for r in side]) for side in sides]
    cost = sum(2.0 * (codes[0][:, None, i] != codes[1][None, :, i]) for i in range(len(spec.qi)))
    flow, at, made, base = transport(cost, *amounts), [[r["__from"] for r in side] for side in sides], [], 0
    for a, b in zip(*np.nonzero(flow)):
        n = int(flow[a, b])
        for s, x in ((0, a), (1, b)):
            r = sides[s][x]
            made.append((*[r[q] for q in spec.qi], r[spec.sa], at[s][x], at[s][x] + n, base))
            at[s][x] += n
        base += n
    types = {f.name: f.dataType.simpleString() for f in df.schema}
    ranges = df.sparkSession.createDataFrame(made, ", ".join([*(f"`__{c}` {types[c]}" for c in (*spec.qi, spec.sa)), "__start long, __stop long, __base long"]))
    on = (F.col("__k") >= F.col("__start")) & (F.col("__k") < F.col("__stop"))
    for c in (*spec.qi, spec.sa):
        on = on & F.col(c).eqNullSafe(F.col(f"__{c}"))
    return free.unionByName(rest.join(F.broadcast(ranges), on).select(*df.columns, (F.col("__base") + F.col("__k") - F.col("__start")).alias("cell_id")))


def _codes(sizes: list[int], m: int) -> list[int]:
    """Sensitive codes of all dimensions' values in turn: each dimension has codes of its own, as many as it may."""
    out, used = [], 0
    for k, n in enumerate(sizes):
        own = min(n, m - used - (len(sizes) - 1 - k))
        out += [used + min(i, own - 1) + 1 for i in range(n)]
        used += own
    return out


def matching_to_microdata(spark: SparkSession, points: list[tuple], m: int, domains: list[list] | None = None) -> tuple[DataFrame, MicrodataSpec]:
    """The hard instance of a matching problem: a row per coordinate value, a QI per point: 0 where the value belongs to the point, else the row's code.

    points of any number of dimensions (three is the hard case for l = 3). domains lists each dimension's values, of which some
    may be on no point; by default those that points use."""
    arity = len(points[0])
    values = [sorted(d) for d in domains] if domains else [sorted({p[k] for p in points}) for k in range(arity)]
    if not arity <= m <= sum(map(len, values)):
        raise ValueError("m must lie between the number of dimensions and of rows")
    rows, codes, i = [], _codes([len(v) for v in values], m), 0
    for k in range(arity):
        for v in values[k]:
            rows.append((*[0 if p[k] == v else codes[i] for p in points], codes[i], i))
            i += 1
    qi = tuple(f"a{j}" for j in range(len(points)))
    return spark.createDataFrame(rows, ", ".join(f"{q} int" for q in qi) + ", b int, row_id long"), MicrodataSpec(qi, "b")


def reduction_facts(df: DataFrame, spec: MicrodataSpec) -> DataFrame:
    """Per QI the zeros (one per dimension) and the size of the alphabet with them."""
    long = df.unpivot([spec.row_id], list(spec.qi), "qi", "v")
    return long.groupBy("qi").agg(F.count_if(F.col("v") == 0).alias("zeros"), F.countDistinct("v").alias("alphabet"))


def distinct_sensitive(df: DataFrame, spec: MicrodataSpec) -> tuple[DataFrame, MicrodataSpec]:
    """All sensitive values distinct: diversity then means cells of l rows."""
    return df.withColumn(spec.sa, F.col(spec.row_id)), spec
