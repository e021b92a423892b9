"""Top-down single-dimensional specialization under a test of every cell: diversity or size."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from celldiv.model import Infeasible, MicrodataSpec
from celldiv.operators.cells import require_solution
from celldiv.operators.curve import domains
from celldiv.storage import persisted

ROOT = "*"


def taxonomy(values: list, groups: list = ()) -> dict:
    """leaf -> path from the root: each group is a function of the value, coarse to fine, before the value itself."""
    return {v: [ROOT, *[f"{i}:{g(v)}" for i, g in enumerate(groups)], f"={v}"] for v in values}


def balanced(values: list) -> dict:
    """leaf -> path of a balanced binary tree over ordered values."""
    paths: dict = {v: [ROOT] for v in values}

    def cut(some: list, name: str) -> None:
        if len(some) > 1:
            half = len(some) // 2
            for part, side in ((some[:half], "0"), (some[half:], "1")):
                for v in part:
                    paths[v].append(name + side)
                cut(part, name + side)

    cut(sorted(values, key=lambda v: (v is not None, v)), "b")
    return paths


#: Histogram rows up to which the cut is searched on the driver; above, each step is one aggregate. Both give one result.
DRIVER_ROWS = 2_000_000


def top_down(df: DataFrame, spec: MicrodataSpec, taxonomies: dict[str, dict], l: int | None = None, k: int | None = None, score: str = "gain", driver_rows: int = DRIVER_ROWS) -> dict[str, dict]:
    """The final cut: per QI leaf -> (node, number of leaves below it).

    All QIs begin at their roots; the best refinement whose cells all pass is made, until none passes. score: "gain" is the
    information gain on the sensitive value, "gain_per_loss" that gain per row times leaf that the node covers.
    Raises Infeasible if the table itself fails; an empty table stays at the roots.
    """
    if l:
        require_solution(df, spec, l)
    hist = persisted(df.groupBy(*spec.qi, F.col(spec.sa).alias("sa")).agg(F.count(F.lit(1)).alias("h")))
    if k and 0 < (hist.agg(F.sum("h")).first()[0] or 0) < k:
        raise Infeasible(f"the table has fewer than {k} rows")
    depth = {q: dict.fromkeys(taxonomies[q], 0) for q in spec.qi}
    closed: set[tuple[str, str]] = set()
    near = hist.count() <= driver_rows
    scores = _local_scores(hist, spec, taxonomies) if near else _spread_scores(hist, spec, taxonomies)
    while found := scores(depth, closed, l, k):  # each step refines a node or is the last
        closed |= {(q, node) for q, node, fits, _, _ in found if not fits}  # finer cuts elsewhere only make cells smaller
        worth = lambda r: round(r[3] if score == "gain" else (r[3] + 1e-9) / max(r[4], 1), 6)
        best = max((r for r in found if r[2]), key=lambda r: (worth(r), r[0], r[1]), default=None)
        if best is None:
            break
        for v, path in taxonomies[best[0]].items():
            if path[depth[best[0]][v]] == best[1] and depth[best[0]][v] + 1 < len(path):
                depth[best[0]][v] += 1
    out: dict[str, dict] = {}
    for q in spec.qi:
        nodes = {v: path[depth[q][v]] for v, path in taxonomies[q].items()}
        below: dict[str, int] = {}
        for node in nodes.values():
            below[node] = below.get(node, 0) + 1
        out[q] = {v: (node, below[node]) for v, node in nodes.items()}
    return out


def _entropies(sizes: np.ndarray, of: np.ndarray, n: int) -> np.ndarray:
    """Per group the sum of x log x over its members."""
    return np.bincount(of, weights=sizes * np.log2(np.maximum(sizes, 1)), minlength=n)


def _local_scores(hist: DataFrame, spec: MicrodataSpec, taxonomies: dict[str, dict]):
    """The scores of all open nodes from a histogram held in arrays."""
    rows = hist.toPandas()  # at most DRIVER_ROWS
    leaf = {q: {v: i for i, v in enumerate(taxonomies[q])} for q in spec.qi}
    plain = lambda v: None if v is None or v != v else v
    codes = {q: np.array([leaf[q][plain(v)] for v in rows[q].tolist()], np.int64) for q in spec.qi}
    sa, h = pd.factorize(rows["sa"], use_na_sentinel=False)[0].astype(np.int64), rows["h"].to_numpy(np.int64)

    def numbered(parts: list[np.ndarray]) -> np.ndarray:
        """Dense numbers of the tuples."""
        out = np.zeros(len(h), np.int64)
        for p in parts:
            out = np.unique(out * (int(p.max(initial=0)) + 1) + p, return_inverse=True)[1].ravel()
        return out

    def scores(depth: dict, closed: set, l: int | None, k: int | None) -> list[tuple]:
        at, child, spread, found = {}, {}, {}, []
        for q in spec.qi:
            names: dict[str, int] = {}
            number = lambda x: names.setdefault(x, len(names))  # noqa: E731, B023
            now = np.array([number(p[depth[q][v]]) for v, p in taxonomies[q].items()], np.int64)
            then = np.array([number(p[depth[q][v] + 1]) if depth[q][v] + 1 < len(p) and (q, p[depth[q][v]]) not in closed else -1 for v, p in taxonomies[q].items()], np.int64)
            at[q], child[q], spread[q] = now, then, {i: x for x, i in names.items()}
        if not len(h):
            return []
        cells = {q: at[q][codes[q]] for q in spec.qi}
        parent = numbered([cells[q] for q in spec.qi])
        both, where = np.unique(parent * (int(sa.max()) + 1) + sa, return_inverse=True)
        sums = np.bincount(where.ravel(), weights=h)
        of = both // (int(sa.max()) + 1)
        n = int(parent.max()) + 1
        before = _entropies(np.bincount(of, weights=sums, minlength=n), np.arange(n), n) - _entropies(sums, of, n)
        for q in spec.qi:
            new = child[q][codes[q]]
            open_ = np.flatnonzero(new >= 0)
            if not len(open_):
                continue
            sub = np.unique(parent[open_] * (int(new.max()) + 1) + new[open_], return_inverse=True)[1].ravel()
            pair, place = np.unique(sub * (int(sa.max()) + 1) + sa[open_], return_inverse=True)
            part = np.bincount(place.ravel(), weights=h[open_])
            of_sub = pair // (int(sa.max()) + 1)
            m = int(sub.max()) + 1
            size, peak = np.bincount(of_sub, weights=part, minlength=m), np.zeros(m)
            np.maximum.at(peak, of_sub, part)
            after = _entropies(size, np.arange(m), m) - _entropies(part, of_sub, m)
            fit = np.ones(m, bool)
            if l:
                fit &= size >= l * peak
            if k:
                fit &= size >= k
            node, old = np.empty(m, np.int64), np.empty(m, np.int64)
            node[sub], old[sub] = cells[q][open_], parent[open_]
            for x in np.unique(node):
                mine = node == x
                leaves = int((at[q] == x).sum())
                found.append((q, spread[q][int(x)], bool(fit[mine].all()), float(before[np.unique(old[mine])].sum() - after[mine].sum()), float(size[mine].sum()) * leaves))
        return found

    return scores


def _spread_scores(hist: DataFrame, spec: MicrodataSpec, taxonomies: dict[str, dict]):
    """The same by one aggregate over the cluster; what is collected is one row per node of the cut."""
    spark = hist.sparkSession

    def scores(depth: dict, closed: set, l: int | None, k: int | None) -> list[tuple]:
        got, any_open, leaves = hist, False, {}
        for q in spec.qi:
            kind = hist.schema[q].dataType.simpleString()
            rows = []
            for v, path in taxonomies[q].items():
                at = path[depth[q][v]]
                child = path[depth[q][v] + 1] if depth[q][v] + 1 < len(path) and (q, at) not in closed else None
                any_open |= child is not None
                leaves[q, at] = leaves.get((q, at), 0) + 1
                rows.append((v, at, child))
            m = spark.createDataFrame(rows, f"__v {kind}, g_{q} string, c_{q} string")
            got = got.join(F.broadcast(m), F.col(q).eqNullSafe(F.col("__v"))).drop("__v")
        if not any_open:
            return []
        small = got.groupBy(*[f"g_{q}" for q in spec.qi], *[f"c_{q}" for q in spec.qi], "sa").agg(F.sum("h").alias("h"))
        options = [F.when(F.col(f"c_{q}").isNotNull(), F.struct(F.lit(q).alias("q"), F.col(f"g_{q}").alias("node"), F.struct(*[F.col(f"c_{x}" if x == q else f"g_{x}").alias(x) for x in spec.qi]).alias("cell"), F.struct(*[F.col(f"g_{x}").alias(x) for x in spec.qi]).alias("parent"))) for q in spec.qi]
        each = small.select(F.explode(F.filter(F.array(*options), lambda x: x.isNotNull())).alias("o"), "sa", "h").groupBy("o.q", "o.node", "o.cell", "o.parent", "sa").agg(F.sum("h").alias("h"))
        cells = each.groupBy("q", "node", "cell", "parent").agg(F.sum("h").alias("size"), F.max("h").alias("peak"), F.sum(F.col("h") * F.log2("h")).alias("s"))
        fit = F.lit(True)
        if l:
            fit = fit & (F.col("size") >= l * F.col("peak"))
        if k:
            fit = fit & (F.col("size") >= k)
        own = each.groupBy("q", "node", "parent", "sa").agg(F.sum("h").alias("h")).groupBy("q", "node", "parent").agg((F.sum("h") * F.log2(F.sum("h")) - F.sum(F.col("h") * F.log2("h"))).alias("e")).groupBy("q", "node").agg(F.sum("e").alias("before"))
        scored = cells.groupBy("q", "node").agg(F.bool_and(fit).alias("fits"), F.sum(F.col("size") * F.log2("size") - F.col("s")).alias("after"), F.sum("size").alias("size")).join(own, ["q", "node"])
        return [(r["q"], r["node"], r["fits"], r["before"] - r["after"], float(r["size"]) * leaves[r["q"], r["node"]]) for r in scored.collect()]  # one row per node of the cut

    return scores


def recode(df: DataFrame, spec: MicrodataSpec, cuts: dict[str, dict]) -> DataFrame:
    """df with each QI replaced by its node."""
    for q in spec.qi:
        kind = df.schema[q].dataType.simpleString()
        m = df.sparkSession.createDataFrame([(v, c[0]) for v, c in cuts[q].items()], f"__v {kind}, __n string")
        df = df.join(F.broadcast(m), F.col(q).eqNullSafe(F.col("__v"))).withColumn(q, F.col("__n")).drop("__v", "__n")
    return df


def default_taxonomies(df: DataFrame, spec: MicrodataSpec) -> dict[str, dict]:
    """Balanced trees over ordered numbers, first word then value for strings. Domains are collected, a million values each at most."""
    out = {}
    for q, values in domains(df, spec).items():
        text = isinstance(next((v for v in values if v is not None), None), str)
        out[q] = taxonomy(values, [lambda v: str(v).split(" ")[0]]) if text and any(" " in (v or "") for v in values) else taxonomy(values) if text else balanced(values)
    return out
