"""The paper's experiments, resumable: python experiments.py FILE SF_DIR MINUTES [FAMILY...].

FILE collects one JSON line per run; a second call goes on where the first stopped. MOST (environment) takes that
many projections of a family, evenly spread; unset, all of them.
"""

import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))
os.environ["PYTHONPATH"] = os.path.dirname(os.path.abspath(__file__)) + os.pathsep + os.environ.get("PYTHONPATH", "")


def families(most: int | None) -> dict[str, tuple[list[tuple], bool, int]]:
    """name: cases, whether KL is wanted, how many may run at once (one where seconds count)."""
    from celldiv.plans.workloads import METHODS, VIEWS, projections
    from celldiv.sources.views import WIDE

    some = lambda d: projections(WIDE, d, most)
    return {
        "kl_by_l": ([(v, q, m, l, 6) for l in (6, 2, 10, 4, 8, 3, 5, 7, 9) for v in VIEWS for q in some(4) for m in ("hybrid", "top_down")], True, 4),
        "kl_by_d": ([(v, q, m, 6, 6) for d in range(1, 8) for v in VIEWS for q in some(d) for m in ("hybrid", "top_down")], True, 4),
        "stars_by_l": ([(v, q, m, l, 6) for l in (6, 2, 10, 4, 8, 3, 5, 7, 9) for v in VIEWS for q in some(4) for m in METHODS], False, 4),
        "stars_by_d": ([(v, q, m, 6, 6) for d in range(1, 8) for v in VIEWS for q in some(d) for m in METHODS], False, 4),
        "time_by_n": ([(v, q, m, 6, s) for s in (1, 6, 3, 2, 4, 5) for v in VIEWS for q in projections(WIDE, 4, 1) for m in METHODS], False, 1),
    }


def main() -> None:
    from pyspark.sql import SparkSession

    from celldiv.functions import measures
    from celldiv.plans import workloads

    path, sf_dir, until = sys.argv[1], sys.argv[2], time.time() + 60 * float(sys.argv[3])
    most = int(os.environ["MOST"]) if os.environ.get("MOST") else None
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "8g").config("spark.ui.enabled", "false")
             .config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate())
    spark.sparkContext.setLogLevel("ERROR")
    wanted = families(most)
    for name in sys.argv[4:] or list(wanted):
        cases, kl, workers = wanted[name]
        left = workloads.resumed(spark, sf_dir, name, cases, path, kl, workers, until)
        print(f"{name}: {len(cases) - left} of {len(cases)} runs done", flush=True)
    rows = workloads.read_figures(spark, path)
    for r in measures.family_average(rows).orderBy("workload", "view", "d", "l", "method").collect():
        print(*[f"{x:.4g}" if isinstance(x, float) else x for x in r], sep=" | ")


if __name__ == "__main__":
    main()
