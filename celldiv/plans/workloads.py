"""The experiments on the given tables: each runner returns a long DataFrame of figures."""

from __future__ import annotations

import itertools
import json
import os
import time
from collections.abc import Iterable
from concurrent.futures import ThreadPoolExecutor
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from celldiv.functions import measures
from celldiv.model import Infeasible, MicrodataSpec
from celldiv.operators import lattice, specialize, tiered
from celldiv.plans import family, held
from celldiv.sources import views
from celldiv.storage import persisted

METHODS = {"tiered": tiered.tiered_suppress, "hybrid": tiered.hybrid_suppress, "curve": tiered.curve_suppress}
FIGURES = "workload string, view string, projection string, method string, l int, d int, n long, stars long, starred_rows long, phase int, kl double, seconds double"
#: Projections whose later phases run side by side.
ENDS_AT_ONCE = 4
VIEWS = {"quantity": views.quantity_microdata, "size": views.size_microdata}


def projections(qi: tuple[str, ...], d: int, most: int | None = None) -> list[tuple[str, ...]]:
    """All choices of d QIs in order; `most` takes evenly spread ones of them for short runs."""
    every = list(itertools.combinations(qi, d))
    return every if not most or most >= len(every) else [every[i * len(every) // most] for i in range(most)]


def figure(spark: SparkSession, sf_dir: str, workload: str, case: tuple, with_kl: bool = False) -> tuple | None:
    """One row of figures; None where no release is feasible. case: (view, projection, method, l, share of six)."""
    view, qi, method, l, share = case
    df, spec = VIEWS[view](spark, sf_dir, qi)
    df = persisted(views.sample(df, spec, share) if share < 6 else df)
    kl, stars, starred, phase = None, None, None, None
    start = time.time()
    try:
        if method == "top_down":
            cuts = specialize.top_down(df, spec, specialize.default_taxonomies(df, spec), l=l)
            seconds, n = time.time() - start, df.count()
            kl = float(measures.kl_recoded(df, spec, cuts).first()[0]) if with_kl else None
        else:
            got = METHODS[method](df, spec, l)
            pub = persisted(got.published)
            seconds, (n, stars, starred), phase = time.time() - start, measures.star_counts(pub).first(), got.report["phase"]
            kl = float(measures.kl_divergence(df, pub, spec).first()[0]) if with_kl else None
    except Infeasible:
        return None
    return workload, view, "+".join(qi), method, l, len(qi), n, stars, starred, phase, kl, round(seconds, 3)


def figures(spark: SparkSession, sf_dir: str, workload: str, cases: Iterable[tuple], with_kl: bool = False) -> DataFrame:
    made = (figure(spark, sf_dir, workload, case, with_kl) for case in cases)
    return spark.createDataFrame([r for r in made if r], FIGURES)


def resumed(spark: SparkSession, sf_dir: str, workload: str, cases: Iterable[tuple], path: str, with_kl: bool = False, workers: int = 1, until: float = float("inf")) -> int:
    """The same, row by row into a file of JSON lines; cases that the file has are not run again. Returns the cases left when `until` came.

    Seconds mean something with one worker only."""
    done = set()
    if os.path.exists(path):
        with open(path, encoding="utf-8") as f:
            done = {tuple(json.loads(line)["case"]) for line in f}
    name = lambda c: (workload, c[0], "+".join(c[1]), c[2], c[3], c[4])
    todo = [c for c in cases if name(c) not in done]

    def run(case: tuple) -> bool:
        if time.time() > until:
            return False
        row = figure(spark, sf_dir, workload, case, with_kl)
        with open(path, "a", encoding="utf-8") as f:
            f.write(json.dumps({"case": name(case), "row": row}) + "\n")
        return True

    with ThreadPoolExecutor(workers) as pool:
        return sum(not x for x in pool.map(run, todo))


def read_figures(spark: SparkSession, path: str) -> DataFrame:
    with open(path, encoding="utf-8") as f:
        return spark.createDataFrame([tuple(r) for r in (json.loads(line)["row"] for line in f) if r], FIGURES)


def stars(spark: SparkSession, sf_dir: str, workload: str, qis: list[tuple[str, ...]], ls: Iterable[int], methods: Iterable[str] = tuple(METHODS)) -> DataFrame:
    """Figures of all releases of these projections: of a small table a projection a task, of one that a task can hold as arrays
    some projections a task, else one release after the other."""
    out, cases = [], []
    for name, view in VIEWS.items():
        df, spec = view(spark, sf_dir)
        made = family if family.fits(df) else held
        if made is held and not held.takes(df):
            cases += [(name, q, m, l, 6) for q in qis for m in methods for l in ls]
            continue
        named = spark.createDataFrame([(i, "+".join(q), len(q)) for i, q in enumerate(qis)], "place int, projection string, d int")
        got = made.releases(df, spec, qis, ls, methods).join(F.broadcast(named), "place")  # a few projections
        out.append(got.select(F.lit(workload).alias("workload"), F.lit(name).alias("view"), "projection", "method", "l", "d", "n", "stars", "starred_rows", "phase", F.lit(None).cast("double").alias("kl"), "seconds"))
    if cases:
        out.append(figures(spark, sf_dir, workload, cases))
    return reduce(DataFrame.unionByName, out)


def run_stars_by_l(spark, sf_dir, ls=range(2, 11), d=4, most=None):
    return stars(spark, sf_dir, "stars_by_l", projections(views.WIDE, d, most), ls)


def run_stars_by_d(spark, sf_dir, l=6, ds=range(1, 8), most=None):
    return stars(spark, sf_dir, "stars_by_d", [q for d in ds for q in projections(views.WIDE, d, most)], (l,))


def run_phases(spark, sf_dir, ls=range(2, 11), ds=range(1, 8)):
    """(view, grouping, l, residue_rows, height, done, phase): phase one of all projections at once; those not done are taken through the others.

    phase is the one that a release ended in; null where none is feasible."""
    out = []
    for name, view in VIEWS.items():
        df, spec = view(spark, sf_dir)
        coded = lattice.Lattice.of(df, spec, ds, list(ls))
        df = df if coded else persisted(df)
        got = persisted(tiered.lattice_trim(df, spec, tuple(ds), list(ls), coded).withColumn("view", F.lit(name)))
        undone: dict[tuple[str, ...], list[tuple[int, int]]] = {}
        for r in got.where("not done").collect():  # at most one row per projection and l
            qi = tuple(q for i, q in enumerate(spec.qi) if not r["grouping"] >> len(spec.qi) - 1 - i & 1)
            undone.setdefault(qi, []).append((r["grouping"], r["l"]))
        ends = _ends(spark, df, spec, undone, coded)
        out.append(got.join(F.broadcast(ends), ["grouping", "l"], "left"))
    return reduce(DataFrame.unionByName, out).withColumn("phase", F.when(F.col("done"), 1).otherwise(F.col("later"))).drop("later")


def _ends(spark: SparkSession, df: DataFrame, spec: MicrodataSpec, undone: dict[tuple[str, ...], list[tuple[int, int]]], coded: lattice.Lattice | None = None) -> DataFrame:
    """(grouping, l, later): the phase in which the releases of these projections end; infeasible ones are left out."""
    ends = []
    if undone and coded:
        known = coded.ends()
        ends = [(g, l, phase) for (g, l), phase in known.items() if phase]
        undone = {q: left for q, some in undone.items() if (left := [c for c in some if c not in known])}
    if undone and not coded and family.fits(df):
        qis = list(undone)
        got = family.releases(df, spec, qis, sorted({l for some in undone.values() for _, l in some}), ["tiered"])
        phases = {(r["place"], r["l"]): r["phase"] for r in got.collect()}  # one row per projection and l
        ends = [(g, l, phases[i, l]) for i, q in enumerate(qis) for g, l in undone[q] if (i, l) in phases]
    elif undone:
        # the phase follows from counts: projections are summed from the whole table's histogram, and no rows are picked
        base = persisted(df.groupBy(*spec.qi, F.col(spec.sa).alias("sa")).agg(F.count(F.lit(1)).alias("h")))
        heights = base.groupBy("sa").agg(F.sum("h").alias("c")).agg(F.sum("c").alias("n"), F.max("c").alias("top")).first()

        def ended(case: tuple[tuple[str, ...], list[tuple[int, int]]]) -> list[tuple[int, int, int]]:
            qi, some = case
            some = [(g, l) for g, l in some if heights["n"] >= l * heights["top"]]
            if not some:
                return []
            hist = persisted(base.groupBy(F.struct(*qi).alias("cell"), "sa").agg(F.sum("h").alias("h")))
            return [(g, l, tiered.histogram_plan(hist, l)[1]["phase"]) for g, l in some]

        with ThreadPoolExecutor(ENDS_AT_ONCE) as pool:
            ends += [e for found in pool.map(ended, undone.items()) for e in found]
    return spark.createDataFrame(ends, "grouping int, l int, later int")


def run_time_by_n(spark, sf_dir, l=6, d=4, most=1):
    return figures(spark, sf_dir, "time_by_n", [(v, q, m, l, s) for v in VIEWS for q in projections(views.WIDE, d, most) for m in METHODS for s in range(1, 7)])


def run_kl_by_l(spark, sf_dir, ls=range(2, 11), d=4, most=None):
    return figures(spark, sf_dir, "kl_by_l", [(v, q, m, l, 6) for v in VIEWS for q in projections(views.WIDE, d, most) for m in ("hybrid", "top_down") for l in ls], True)


def run_kl_by_d(spark, sf_dir, l=6, ds=range(1, 8), most=None):
    return figures(spark, sf_dir, "kl_by_d", [(v, q, m, l, 6) for v in VIEWS for d in ds for q in projections(views.WIDE, d, most) for m in ("hybrid", "top_down")], True)


def run_coarsening(spark, sf_dir, l=6):
    """Tiered suppression after coarser and coarser ship dates and names."""
    df, spec = views.quantity_microdata(spark, sf_dir, ("ship_month", "p_name", "tax", "discount"))
    year, word, band = F.expr("(ship_month - 1) div 12"), F.split("p_name", " ")[0], F.expr("discount div 6")
    levels = {"0 none": {}, "1 years": {"ship_month": year}, "2 years, words": {"ship_month": year, "p_name": word}, "3 years, words, bands": {"ship_month": year, "p_name": word, "discount": band}}
    rows = tiered.sweep_coarsening(df, spec, levels, l)
    return spark.createDataFrame([(r["level"], r["l"], r["n"], r["stars"], r["starred_rows"], r["lower_bound"], r["phase"]) for r in rows], "level string, l int, n long, stars long, starred_rows long, lower_bound long, phase int")
