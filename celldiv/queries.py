"""Queries over the given tables, one per method, check, measure or workload, and SQL written from other derivations."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from celldiv.functions import measures, sql
from celldiv.functions.curve import hilbert_index
from celldiv.operators import cells, curve, drain, exact, publish, specialize, tiered, trim, vectors
from celldiv.plans import workloads
from celldiv.sources import views
from celldiv.storage import persisted

Q4 = ("ship_month", "l_linestatus", "tax", "discount")
Q3 = ("l_linestatus", "tax", "p_type")
E3 = ("event_type", "day_part", "dow")
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}

_V1 = """SELECT hash(l_orderkey, l_linenumber, l_partkey, l_suppkey) AS row_id, l_linestatus, p_type, p_name, CAST(l_linenumber AS BIGINT) AS l_linenumber,
  CAST(year(l_shipdate) * 12 + month(l_shipdate) AS BIGINT) AS ship_month, CAST(round(l_tax * 100) AS BIGINT) AS tax, CAST(round(l_discount * 100) AS BIGINT) AS discount,
  CAST(l_quantity AS BIGINT) AS l_quantity, CAST(p_size AS BIGINT) AS p_size FROM lineitem JOIN part ON l_partkey = p_partkey"""
_V3 = """SELECT event_id AS row_id, event_type, CAST(hour(ts) // 6 AS BIGINT) AS day_part, CAST(dayofweek(ts) + 1 AS BIGINT) AS dow, CAST(day(ts) AS BIGINT) AS dom,
  CAST(CAST(json_extract(props, '$.k') AS BIGINT) // 10 AS BIGINT) AS k_band, CAST(least(floor(value / 20), 9) AS BIGINT) AS value_band FROM events"""
_V4 = """SELECT o_orderkey AS row_id, o_orderstatus, CAST(year(o_orderdate) AS BIGINT) AS order_year, c_mktsegment, r_name, o_orderpriority
  FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"""


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return add


def _longs(df: DataFrame, *names: str) -> DataFrame:
    return df.withColumns({n: F.col(n).cast("long") for n in names})


def _hist_sql(view: str, qi: tuple[str, ...], sa: str) -> str:
    return f"v AS ({view}), hist AS (SELECT {', '.join(qi)}, {sa} AS sa, count(*) AS h FROM v GROUP BY ALL)"


def _trim_sql(view: str, qi: tuple[str, ...], sa: str, l: int) -> str:
    """The cap as the largest c of all with sum(least(h, c)) >= l * c."""
    k = ", ".join(qi)
    return f"""{_hist_sql(view, qi, sa)}, tops AS (SELECT {k}, max(h) AS top FROM hist GROUP BY ALL),
  tries AS (SELECT {k}, c FROM tops, unnest(range(0, top + 1)) AS t(c)),
  caps AS (SELECT {k}, max(c) AS cap FROM (SELECT {k}, c FROM tries JOIN hist USING ({k}) GROUP BY {k}, c HAVING sum(least(h, c)) >= {l} * c) GROUP BY {k}),
  trimmed AS (SELECT {k}, sa, h, least(h, cap) AS kept, h - least(h, cap) AS moved FROM hist JOIN caps USING ({k}))"""


def _flat(df: DataFrame, qi: tuple[str, ...]) -> DataFrame:
    return df.select(*[F.col(f"cell.{q}").alias(q) for q in qi], *[c for c in df.columns if c != "cell"])


# ---- definitions and checks ------------------------------------------------------------------

@query(f"WITH {_hist_sql(_V3, E3, 'value_band')} SELECT * FROM hist")
def cell_histogram(spark, sf):
    df, spec = views.event_microdata(spark, sf, E3)
    return _longs(_flat(cells.cell_histogram(df, spec), E3), "day_part", "dow", "sa")


@query(f"""WITH {_hist_sql(_V3, E3, 'value_band')}, t AS (SELECT event_type, day_part, dow, CAST(sum(h) AS BIGINT) AS size, max(h) AS peak, count(*) AS n_values FROM hist GROUP BY ALL)
SELECT t.event_type, t.day_part, t.dow, size, peak, n_values, (SELECT count(*) FROM hist x WHERE x.event_type = t.event_type AND x.day_part = t.day_part AND x.dow = t.dow AND x.h = t.peak) AS n_peaks,
  size - 3 * peak AS surplus, size = 3 * peak AS tight, size >= 3 * peak AS eligible FROM t""")
def cell_summary(spark, sf):
    df, spec = views.event_microdata(spark, sf, E3)
    return _longs(_flat(cells.cell_summary(cells.cell_histogram(df, spec), 3), E3), "day_part", "dow")


@query(f"WITH v AS ({_V3}), c AS (SELECT value_band, count(*) AS c FROM v GROUP BY ALL) SELECT CAST(sum(c) AS BIGINT) AS n, max(c) AS top, count(*) AS m, CAST(sum(c) // max(c) AS BIGINT) AS max_l FROM c")
def max_feasible_l(spark, sf):
    df, spec = views.event_microdata(spark, sf)
    return cells.max_feasible_l(df, spec.sa)


@query("WITH c AS (SELECT quality, count(*) AS c FROM labels JOIN documents USING (doc_id) GROUP BY ALL) SELECT sum(c) >= 2 * max(c) AS feasible FROM c")
def infeasible_labels(spark, sf):
    df, spec = views.labelled_documents(spark, sf)
    return cells.max_feasible_l(df, spec.sa).select((F.col("max_l") >= 2).alias("feasible"))


@query(f"WITH v AS ({_V4}) SELECT o_orderstatus, order_year, c_mktsegment, r_name, count(*) AS size FROM v GROUP BY ALL HAVING count(*) < 20")
def k_anonymity_violations(spark, sf):
    df, spec = views.order_microdata(spark, sf)
    return _longs(cells.k_anonymity_violations(df, spec.qi, 20), "order_year")


@query(f"WITH v AS ({_V4}) SELECT o_orderstatus, order_year, c_mktsegment, r_name, count(*) AS size FROM v GROUP BY ALL HAVING count(DISTINCT o_orderpriority) = 1")
def homogeneous_cells(spark, sf):
    df, spec = views.order_microdata(spark, sf)
    return _longs(cells.homogeneous_cells(df, spec), "order_year")


@query(f"""WITH v AS ({_V4}), h AS (SELECT o_orderstatus, order_year, c_mktsegment, r_name, o_orderpriority, count(*) AS h FROM v GROUP BY ALL)
SELECT o_orderstatus, order_year, c_mktsegment, r_name, CAST(sum(h) AS BIGINT) AS size, max(h) AS peak FROM h GROUP BY ALL HAVING sum(h) < 10 OR max(h) > 0.4 * sum(h)""")
def alpha_k_violations(spark, sf):
    df, spec = views.order_microdata(spark, sf)
    return _longs(cells.alpha_k_violations(df, spec, 0.4, 10), "order_year")


@query(f"""WITH v AS ({_V4}), h AS (SELECT o_orderstatus, order_year, c_mktsegment, r_name, o_orderpriority, count(*) AS h FROM v GROUP BY ALL),
c AS (SELECT max(h) / sum(h) AS confidence FROM h GROUP BY o_orderstatus, order_year, c_mktsegment, r_name) SELECT round(max(confidence), 6) AS worst, round(avg(confidence), 6) AS mean FROM c""")
def adversary_confidence(spark, sf):
    df, spec = views.order_microdata(spark, sf)
    raw = df.withColumn("star_mask", F.lit(0))
    return cells.adversary_confidence(raw, spec, "visible").agg(F.round(F.max("confidence"), 6).alias("worst"), F.round(F.avg("confidence"), 6).alias("mean"))


@query(f"""WITH v AS ({_V4}), h AS (SELECT o_orderstatus, order_year, c_mktsegment, r_name, o_orderpriority AS sa, count(*) AS rows FROM v GROUP BY ALL)
SELECT 'p' || row_id AS person, sa, rows FROM v JOIN h USING (o_orderstatus, order_year, c_mktsegment, r_name)""")
def linking_candidates(spark, sf):
    """Every order is attacked."""
    df, spec = views.order_microdata(spark, sf)
    known = df.select(F.concat(F.lit("p"), F.col("row_id").cast("string")).alias("person"), *spec.qi)
    return cells.linking_attack(df.withColumn("star_mask", F.lit(0)), known, spec)


# ---- phase one -------------------------------------------------------------------------------

def _trim_query(name: str, view_sql: str, view, qi: tuple[str, ...], sa: str, l: int) -> None:
    def run(spark, sf):
        df, spec = view(spark, sf, qi)
        got = _flat(trim.trim_cells(cells.cell_histogram(df, spec), l), qi)
        return _longs(got, "kept", "moved", *[c for c, t in got.dtypes if t == "int"])

    QUERIES[name] = run
    SQL[name] = f"WITH {_trim_sql(view_sql, qi, sa, l)} SELECT {', '.join(qi)}, sa, h, CAST(kept AS BIGINT) AS kept, CAST(moved AS BIGINT) AS moved FROM trimmed"


_trim_query("trim_plan_quantity", _V1, views.quantity_microdata, Q4, "l_quantity", 6)
_trim_query("trim_plan_size", _V1, views.size_microdata, Q3, "p_size", 6)
_trim_query("trim_plan_events", _V3, views.event_microdata, E3, "value_band", 3)


@query(f"WITH {_trim_sql(_V3, E3, 'value_band', 3)} SELECT sa, CAST(sum(moved) AS BIGINT) AS r FROM trimmed GROUP BY sa HAVING sum(moved) > 0")
def residue_vector(spark, sf):
    df, spec = views.event_microdata(spark, sf, E3)
    return _longs(trim.residue_vector(trim.trim_cells(cells.cell_histogram(df, spec), 3)), "sa", "r")


@query(f"""WITH {_trim_sql(_V1, Q4, 'l_quantity', 6)}, r AS (SELECT sa, sum(moved) AS r FROM trimmed GROUP BY sa)
SELECT CAST(coalesce(sum(r), 0) AS BIGINT) AS rows, CAST(coalesce(max(r), 0) AS BIGINT) AS height, CAST(6 * coalesce(max(r), 0) AS BIGINT) AS lower_bound, CAST(greatest(0, 6 * coalesce(max(r), 0) - coalesce(sum(r), 0)) AS BIGINT) AS deficit, coalesce(sum(r), 0) >= 6 * coalesce(max(r), 0) AS done FROM r""")
def trim_certificate(spark, sf):
    df, spec = views.quantity_microdata(spark, sf, Q4)
    return _longs(trim.residue_facts(trim.residue_vector(trim.trim_cells(cells.cell_histogram(df, spec), 6)), 6), "rows", "height", "lower_bound", "deficit")


@query(f"""WITH {_trim_sql(_V1, Q4, 'l_quantity', 6)} SELECT ship_month, l_linestatus, tax, discount, CAST(max(kept) AS BIGINT) AS cap FROM trimmed GROUP BY ALL""")
def array_trim(spark, sf):
    """Caps from arrays instead of windows."""
    df, spec = views.quantity_microdata(spark, sf, Q4)
    per = cells.cell_histogram(df, spec).groupBy("cell").agg(F.collect_list("h").alias("hs"))
    cap = F.least(trim.cap_of(F.col("hs"), 6), F.array_max("hs"))
    return _longs(_flat(per.select("cell", cap.alias("cap")), Q4), "ship_month", "tax", "discount", "cap")


@query(f"""WITH {_trim_sql(_V1, Q4, 'l_quantity', 6)} SELECT ship_month, l_linestatus, tax, discount, CAST(max(kept) AS BIGINT) AS cap, sum(h) >= 6 * max(h) AS eligible FROM trimmed GROUP BY ALL""")
def sql_trim(spark, sf):
    """The registered SQL functions over a view."""
    df, _ = views.quantity_microdata(spark, sf, Q4)
    sql.register(spark)
    return spark.sql("""SELECT CAST(ship_month AS BIGINT) AS ship_month, l_linestatus, CAST(tax AS BIGINT) AS tax, CAST(discount AS BIGINT) AS discount, cell_cap(hs, 6) AS cap, cell_eligible(hs, 6) AS eligible
      FROM (SELECT ship_month, l_linestatus, tax, discount, collect_list(h) AS hs FROM
        (SELECT ship_month, l_linestatus, tax, discount, l_quantity, count(*) AS h FROM {rows} GROUP BY ALL) GROUP BY ALL)""", rows=df)


@query(f"WITH {_hist_sql(_V1, Q4, 'l_quantity')} SELECT ship_month, l_linestatus, tax, discount, count(*) AS n_values, CAST(sum(h) AS BIGINT) AS size FROM hist GROUP BY ship_month, l_linestatus, tax, discount HAVING count(*) < 6")
def vanishing_cells(spark, sf):
    df, spec = views.quantity_microdata(spark, sf, Q4)
    return _longs(_flat(trim.vanishing_cells(cells.cell_histogram(df, spec), 6), Q4), "ship_month", "tax", "discount")


def _lattice_sql() -> str:
    parts = []
    for i, q in enumerate(Q3):
        for l in (2, 6):
            mask = 7 - (1 << (2 - i))
            parts.append(f"(WITH {_trim_sql(_V1, (q,), 'l_quantity', l)}, r AS (SELECT sa, sum(moved) AS r FROM trimmed GROUP BY sa) SELECT CAST({mask} AS BIGINT) AS grouping, CAST({l} AS BIGINT) AS l, CAST(sum(r) AS BIGINT) AS residue_rows, CAST(max(r) AS BIGINT) AS height, sum(r) >= {l} * max(r) AS done FROM r)")
    return " UNION ALL ".join(parts)


@query(_lattice_sql())
def trim_lattice(spark, sf):
    df, spec = views.quantity_microdata(spark, sf, Q3)
    return _longs(tiered.lattice_trim(df, spec, (1,), [2, 6]), "grouping", "l", "residue_rows", "height")


def _residue_sql(qi: tuple[str, ...]) -> str:
    """One row: the residue's rows and, per QI, whether it is starred there. The rows that go are interchangeable, so both are unique where phase one ends."""
    return "gone AS (SELECT * FROM trimmed WHERE moved > 0), k AS (SELECT coalesce(sum(moved), 0) AS n_gone, " + ", ".join(f"count(DISTINCT {q}) > 1 AS s_{q}" for q in qi) + " FROM gone)"


@query(f"""WITH {_trim_sql(_V1, Q4, 'l_quantity', 6)}, {_residue_sql(Q4)}, u AS (SELECT DISTINCT {', '.join(Q4)} FROM v),
m AS (SELECT u.ship_month, u.l_linestatus, u.tax, u.discount, g.sa, sum(g.moved) AS rows FROM u, k JOIN gone g ON true WHERE {' AND '.join(f'(s_{q} OR u.{q} = g.{q})' for q in Q4)} GROUP BY ALL
  UNION ALL SELECT ship_month, l_linestatus, tax, discount, sa, kept FROM trimmed WHERE kept > 0)
SELECT concat_ws('-', ship_month, l_linestatus, tax, discount) AS person, sa, CAST(sum(rows) AS BIGINT) AS rows FROM m GROUP BY ALL""")
def linking_starred(spark, sf):
    """What an intruder who knows a QI tuple finds in the tiered release: its own rows and the starred ones that may be meant."""
    df, spec = views.quantity_microdata(spark, sf, Q4)
    pub = persisted(tiered.tiered_suppress(df, spec, 6).published)
    known = df.select(*Q4).distinct().withColumn("person", F.concat_ws("-", *Q4))
    return _longs(cells.linking_attack(pub, known, spec), "sa", "rows")


# ---- phases two and three --------------------------------------------------------------------

def _drain_facts(spark, sf, how):
    df, spec = views.event_microdata(spark, sf, E3)
    plan, report = tiered.tiered_plan(df, spec, 3, how)
    facts = plan.groupBy("cell").agg(F.sum("h").alias("s"), F.max("h").alias("p")).agg(F.bool_and(F.col("s") >= 3 * F.col("p")).alias("cells_eligible"))
    top = trim.residue_vector(plan).agg(F.sum("r").alias("rows"), F.max("r").alias("height"))
    return facts.crossJoin(top).select("cells_eligible", (F.col("rows") >= 3 * F.col("height")).alias("residue_eligible"),
                                       F.lit(report["trim_rows"]).cast("long").alias("trim_rows"), (F.col("rows") <= (F.lit(report["lower_bound"]) + 2) * (1 if report["phase"] < 3 else 3)).alias("within_bound"))


_DRAIN_SQL = f"WITH {_trim_sql(_V3, E3, 'value_band', 3)} SELECT true AS cells_eligible, true AS residue_eligible, CAST(sum(moved) AS BIGINT) AS trim_rows, true AS within_bound FROM trimmed"


@query(_DRAIN_SQL)
def drain_exact_invariants(spark, sf):
    return _drain_facts(spark, sf, "exact")


@query(_DRAIN_SQL)
def drain_bulk_invariants(spark, sf):
    return _drain_facts(spark, sf, "bulk")


@query("SELECT t.*, (SELECT count(*) FROM customer) AS cells FROM (VALUES ('f1', 1::BIGINT, 4::BIGINT), ('f4', 3::BIGINT, 20::BIGINT), ('f5', 3::BIGINT, 10::BIGINT)) AS t(fixture, phase, rows)")
def overhaul_fixtures(spark, sf):
    """Vectors whose end is known, laid over the customers and taken through the distributed phases: a customer is a cell.

    The customers of the least keys hold the vectors that go; all others are frozen (or, where phase one ends, eligible) whatever their number."""
    made = {"f1": (2, [(2, 0, 0, 0, 0), (0, 1, 0, 0, 0), (0, 0, 1, 0, 0)], [(0, 2, 0, 1, 1), (0, 0, 0, 1, 1)]), "f4": (4, [(4, 4, 4, 0, 0)], [(3, 1, 2, 3, 3), (1, 3, 2, 3, 3)]),
            "f5": (3, [(0, 1, 3, 0, 1), (0, 1, 0, 3, 1)], [(0, 1, 1, 0, 1), (0, 1, 0, 1, 1)])}
    keys = views.table(spark, sf, "customer").select("c_custkey")
    least = [r[0] for r in keys.orderBy("c_custkey").limit(3).collect()]
    out = []
    for name, (l, first, rest) in made.items():
        kind = F.when(F.col("c_custkey") % 2 == 0, len(first)).otherwise(len(first) + 1)
        for i, key in enumerate(least[:len(first)]):
            kind = F.when(F.col("c_custkey") == key, i).otherwise(kind)
        vector = spark.createDataFrame([(i, v, h) for i, r in enumerate(first + rest) for v, h in enumerate(r) if h], "kind int, sa int, h long")
        hist = keys.withColumn("kind", kind).join(F.broadcast(vector), "kind").select(F.struct("c_custkey").alias("cell"), "sa", "h")
        state = persisted(trim.trim_cells(hist, l).select("cell", "sa", F.col("kept").alias("h"), "moved"))
        many = state.select("cell").distinct().count()
        _, residue, phase, _ = drain.finish(state, l, "bulk")
        out.append((name, phase, sum(residue.values()), many))
    return spark.createDataFrame(out, "fixture string, phase long, rows long, cells long")


# ---- releases --------------------------------------------------------------------------------

def _broken(pub: DataFrame, spec, l: int) -> int:
    return cells.violations(pub, spec, l).count() + cells.violations(pub, spec, l, "visible").count()


#: Views and l at which phase one ends the method, so that rows, stars and starred rows of the release are unique.
UNIQUE = [("quantity", Q4, "l_quantity", 6), ("quantity", Q4, "l_quantity", 10), ("size", Q4, "p_size", 6), ("quantity", Q3, "l_quantity", 2)]


def _unique_sql() -> str:
    out = []
    for name, qi, sa, l in UNIQUE:
        starred = " + ".join(f"s_{q}::INT" for q in qi)
        out.append(f"""(WITH {_trim_sql(_V1, qi, sa, l)}, {_residue_sql(qi)} SELECT '{name}' AS view, CAST({len(qi)} AS BIGINT) AS d, CAST({l} AS BIGINT) AS l, (SELECT count(*) FROM v) AS n,
  CAST(n_gone * ({starred}) AS BIGINT) AS stars, CAST(CASE WHEN {starred} > 0 THEN n_gone ELSE 0 END AS BIGINT) AS starred_rows, 0::BIGINT AS broken FROM k)""")
    return " UNION ALL ".join(out)


@query(_unique_sql())
def tiered_release(spark, sf):
    out = []
    for name, qi, _, l in UNIQUE:
        df, spec = workloads.VIEWS[name](spark, sf, qi)
        pub = persisted(tiered.tiered_suppress(df, spec, l).published)
        out.append((name, len(qi), l, *measures.star_counts(pub).first(), _broken(pub, spec, l)))
    return spark.createDataFrame(out, "view string, d long, l long, n long, stars long, starred_rows long, broken long")


def _reports_sql() -> str:
    out = []
    for name, qi, sa, l in UNIQUE:
        out.append(f"""(WITH {_trim_sql(_V1, qi, sa, l)}, r AS (SELECT sa, sum(moved) AS r FROM trimmed GROUP BY sa), f AS (SELECT sum(r) AS rows, max(r) AS height FROM r)
SELECT '{name}' AS view, CAST({len(qi)} AS BIGINT) AS d, CAST({l} AS BIGINT) AS l, 1::BIGINT AS phase, CAST(rows AS BIGINT) AS rows, CAST(height AS BIGINT) AS height,
  CASE WHEN height = 0 THEN 1.0 ELSE round(rows / ({l} * height), 6) END::DOUBLE AS ratio, CAST(rows - {l} * height AS BIGINT) AS gap FROM f)""")
    return " UNION ALL ".join(out)


@query(_reports_sql())
def run_reports(spark, sf):
    """Rows over the lower bound (no release moves fewer), and the gap, from the traces of whole runs."""
    out = []
    for name, qi, _, l in UNIQUE:
        df, spec = workloads.VIEWS[name](spark, sf, qi)
        _, got = tiered.tiered_plan(df, spec, l)
        _, rows, height = got["trace"][-1]
        out.append((name, len(qi), l, got["phase"], rows, height, round(got["rows_to_bound"], 6), got["gap"]))
    return spark.createDataFrame(out, "view string, d long, l long, phase long, rows long, height long, ratio double, gap long")


@query(f"""WITH {_trim_sql(_V1, Q4, 'l_quantity', 6)}, {_residue_sql(Q4)}
SELECT sa, CAST(sum(kept) AS BIGINT) AS kept, CAST(sum(moved) AS BIGINT) AS refined, (SELECT CAST(n_gone * ({' + '.join(f's_{q}::INT' for q in Q4)}) AS BIGINT) FROM k) AS stars_before, true AS not_more, 0::BIGINT AS broken FROM trimmed GROUP BY sa""")
def hybrid_release(spark, sf):
    """Rows that stay in their cells and rows of refined cells by sensitive value; stars against those of the tiered release."""
    df, spec = views.quantity_microdata(spark, sf, Q4)
    got = tiered.hybrid_suppress(df, spec, 6)
    pub = persisted(got.published)
    own = F.col("cell_id") == F.xxhash64(spec.cell())
    before = measures.star_counts(tiered.tiered_suppress(df, spec, 6).published).first()["stars"]
    after = measures.star_counts(pub).first()["stars"]
    per = pub.groupBy(F.col(spec.sa).cast("long").alias("sa")).agg(F.count_if(own).alias("kept"), F.count_if(~own).alias("refined"))
    return per.withColumns({"stars_before": F.lit(before), "not_more": F.lit(after <= before), "broken": F.lit(_broken(pub, spec, 6)).cast("long")})


_RATES = """WITH r AS (SELECT 'tax' AS kind, CAST(round(l_tax * 100) AS BIGINT) AS rate FROM lineitem UNION ALL SELECT 'discount', CAST(round(l_discount * 100) AS BIGINT) FROM lineitem)"""
_CURVE_SQL = f"""{_RATES}, o AS (SELECT kind, rate, row_number() OVER (PARTITION BY kind ORDER BY rate) AS spot FROM r),
p AS (SELECT a.rate <> b.rate AS starred FROM o a JOIN o b USING (spot) WHERE a.kind = 'tax' AND b.kind = 'discount')
SELECT CAST(2 * count(*) AS BIGINT) AS n, CAST(2 * count_if(starred) AS BIGINT) AS stars, CAST(2 * count_if(starred) AS BIGINT) AS starred_rows, 0::BIGINT AS broken FROM p"""


@query(_CURVE_SQL)
def curve_release(spark, sf):
    """On one QI the curve is its order, and with l = m = 2 equally frequent values cells pair equal ranks, whatever the chunks."""
    df, spec = views.rate_microdata(spark, sf)
    pub = persisted(tiered.curve_suppress(df, spec, 2, chunk_rows=2_500).published)
    return measures.star_counts(pub).withColumn("broken", F.lit(_broken(pub, spec, 2)).cast("long"))


@query(_CURVE_SQL)
def curve_release_range(spark, sf):
    """One range chunk holds all rows here, and over TASK_ROWS the ranks that it would come to; tests hold several chunks against their rules."""
    df, spec = views.rate_microdata(spark, sf)
    pub = persisted(tiered.curve_suppress(df, spec, 2, "range", chunk_rows=10_000_000).published)
    return measures.star_counts(pub).withColumn("broken", F.lit(_broken(pub, spec, 2)).cast("long"))


def curve_release_wide(spark, sf):
    df, spec = views.quantity_microdata(spark, sf, Q4)
    return measures.star_counts(tiered.curve_suppress(df, spec, 6).published)


QUERIES["curve_release_wide"] = curve_release_wide


@query(f"WITH v AS ({_V3}) SELECT value_band, count(*) AS n FROM v GROUP BY ALL")
def sensitive_multiset(spark, sf):
    df, spec = views.event_microdata(spark, sf, E3)
    return _longs(tiered.hybrid_suppress(df, spec, 3).published.groupBy("value_band").agg(F.count(F.lit(1)).alias("n")), "value_band")


@query(f"WITH v AS ({_V4}) SELECT count(*) AS n, 4 * count(*) AS stars, count(*) AS starred_rows FROM v")
def full_suppression(spark, sf):
    df, spec = views.order_microdata(spark, sf)
    return measures.star_counts(publish.suppress_all(df, spec))


@query("SELECT count(*) AS n, count(*) AS covered FROM events")
def boxes_cover(spark, sf):
    df, spec = views.event_microdata(spark, sf, E3)
    pub = persisted(tiered.hybrid_suppress(df, spec, 3).published)
    box = publish.to_boxes(df, pub, spec).select("row_id", *[f"box_{q}" for q in E3]).join(df, "row_id")
    ok = F.lit(True)
    for q in E3:
        ok = ok & F.array_contains(f"box_{q}", F.col(q))
    return box.agg(F.count(F.lit(1)).alias("n"), F.count_if(ok).alias("covered"))


# ---- baselines, exact cases, measures ---------------------------------------------------------

@query("""WITH RECURSIVE c AS (SELECT 0 AS k, 0::BIGINT AS x, 0::BIGINT AS y, 0::BIGINT AS p UNION ALL
  SELECT k + 1, CASE q WHEN 0 THEN y WHEN 1 THEN x WHEN 2 THEN x + s ELSE 2 * s - 1 - y END, CASE q WHEN 0 THEN x WHEN 1 THEN y + s WHEN 2 THEN y + s ELSE s - 1 - x END, p + q * s * s
  FROM (SELECT k, x, y, p, CAST(1 << k AS BIGINT) AS s, unnest([0, 1, 2, 3]) AS q FROM c WHERE k < 4))
SELECT x, y, CAST(p AS BIGINT) AS position, n FROM c JOIN (SELECT l_orderkey % 16 AS x, l_partkey % 16 AS y, count(*) AS n FROM lineitem GROUP BY ALL) USING (x, y) WHERE k = 4""")
def hilbert_square(spark, sf):
    """Lines by the remainders of their keys on a 16 by 16 grid, in the order of the plane's curve; the SQL builds it from four turned copies of the half as wide one."""
    line = views.table(spark, sf, "lineitem").select((F.col("l_orderkey") % 16).alias("x"), (F.col("l_partkey") % 16).alias("y"))
    grid = line.groupBy("x", "y").agg(F.count(F.lit(1)).alias("n"))
    return grid.withColumn("position", hilbert_index([F.col("x"), F.col("y")], 4))


def hilbert_positions(spark, sf):
    df, spec = views.quantity_microdata(spark, sf, Q4)
    return curve.by_rank(df, spec).select("row_id", "position", "rank")


QUERIES["hilbert_positions"] = hilbert_positions


def _cut_sql(fits: str) -> str:
    """The cut of one ordered QI: a range of its values is halved if both halves fit; with one QI the order of refinements does not matter."""
    return f"""WITH RECURSIVE v AS ({_V3}), vals AS (SELECT dom, row_number() OVER (ORDER BY dom) - 1 AS r FROM (SELECT DISTINCT dom FROM v)),
h AS (SELECT r, dom, value_band AS sa, count(*) AS c FROM v JOIN vals USING (dom) GROUP BY ALL),
tree AS (SELECT 0::BIGINT AS lo, (SELECT count(*) FROM vals) AS hi UNION ALL SELECT CASE s WHEN 0 THEN lo ELSE lo + (hi - lo) // 2 END, CASE s WHEN 0 THEN lo + (hi - lo) // 2 ELSE hi END FROM (SELECT lo, hi, unnest([0, 1]) AS s FROM tree WHERE hi - lo > 1)),
heights AS (SELECT lo, hi, sa, sum(c) AS h FROM tree JOIN h ON r >= lo AND r < hi GROUP BY ALL),
good AS (SELECT lo, hi FROM heights GROUP BY lo, hi HAVING {fits}),
split AS (SELECT lo, hi FROM tree t WHERE hi - lo > 1 AND (lo, lo + (hi - lo) // 2) IN (SELECT (lo, hi) FROM good) AND (lo + (hi - lo) // 2, hi) IN (SELECT (lo, hi) FROM good)),
reached AS (SELECT lo, hi FROM tree WHERE lo = 0 AND hi = (SELECT count(*) FROM vals) UNION ALL SELECT CASE s WHEN 0 THEN lo ELSE lo + (hi - lo) // 2 END, CASE s WHEN 0 THEN lo + (hi - lo) // 2 ELSE hi END FROM (SELECT lo, hi, unnest([0, 1]) AS s FROM reached JOIN split USING (lo, hi)))
SELECT min(dom) AS first, max(dom) AS last, CAST(sum(c) AS BIGINT) AS rows FROM reached JOIN h ON r >= lo AND r < hi WHERE (lo, hi) NOT IN (SELECT (lo, hi) FROM split) GROUP BY lo, hi"""


def _cut(spark, sf, **test) -> DataFrame:
    df, spec = views.event_microdata(spark, sf, ("dom",))
    node = specialize.recode(df.withColumn("day", F.col("dom").cast("long")), spec, specialize.top_down(df, spec, specialize.default_taxonomies(df, spec), **test))
    return node.groupBy("dom").agg(F.min("day").alias("first"), F.max("day").alias("last"), F.count(F.lit(1)).alias("rows")).drop("dom")


@query(_cut_sql("sum(h) >= 3 * max(h)"))
def top_down_release(spark, sf):
    return _cut(spark, sf, l=3)


@query(_cut_sql("sum(h) >= 500"))
def top_down_k_anonymity(spark, sf):
    return _cut(spark, sf, k=500)


def top_down_wide(spark, sf):
    """The cut of three QIs: how many values each keeps, by either score."""
    df, spec = views.quantity_microdata(spark, sf, ("ship_month", "l_linestatus", "tax"))
    trees, out = specialize.default_taxonomies(df, spec), []
    for score in ("gain", "gain_per_loss"):
        cuts = specialize.top_down(df, spec, trees, l=6, score=score)
        pub = specialize.recode(df, spec, cuts).withColumn("star_mask", F.lit(0))
        out += [(score, q, len({n for n, _ in c.values()}), cells.violations(pub, spec, 6, "visible").count()) for q, c in cuts.items()]
    return spark.createDataFrame(out, "score string, qi string, nodes long, violations long")


QUERIES["top_down_wide"] = top_down_wide


@query(f"""WITH v AS ({_V3}), s AS (SELECT event_type, day_part, dow, value_band AS sa, count(*) AS h FROM v GROUP BY ALL), k AS (SELECT count(DISTINCT event_type) * count(DISTINCT day_part) * count(DISTINCT dow) AS c, count(*) AS n FROM v),
p AS (SELECT value_band AS sa, count(*) AS c FROM v GROUP BY ALL) SELECT round(sum(h / n * ln(h * k.c / p.c)), 6) AS kl FROM s JOIN p USING (sa), k""")
def kl_full_suppression(spark, sf):
    df, spec = views.event_microdata(spark, sf, E3)
    return measures.kl_divergence(df, publish.suppress_all(df, spec), spec).select(F.round("kl", 6).alias("kl"))


@query(f"""WITH {_trim_sql(_V1, Q4, 'l_quantity', 6)}, {_residue_sql(Q4)}, n AS (SELECT count(*) AS n, {', '.join(f'count(DISTINCT {q}) AS a_{q}' for q in Q4)} FROM v),
w AS (SELECT {' * '.join(f'(CASE WHEN s_{q} THEN 1.0 / a_{q} ELSE 1.0 END)' for q in Q4)} AS w FROM k, n),
s AS (SELECT t.ship_month, t.l_linestatus, t.tax, t.discount, t.sa, t.h, t.kept, coalesce(sum(g.moved), 0) AS met FROM trimmed t CROSS JOIN k LEFT JOIN gone g ON g.sa = t.sa AND {' AND '.join(f'(s_{q} OR t.{q} = g.{q})' for q in Q4)} GROUP BY ALL)
SELECT round(sum(h / n * ln(h / (kept + met * w))), 6) AS kl_tiered, true AS hybrid_not_above, true AS boxes_not_above FROM s, w, n""")
def kl_releases(spark, sf):
    """KL of the tiered release by its exact value, and the orders hybrid <= tiered and boxes <= stars."""
    df, spec = views.quantity_microdata(spark, sf, Q4)
    df = persisted(df)
    tier = measures.kl_divergence(df, persisted(tiered.tiered_suppress(df, spec, 6).published), spec).first()["kl"]
    pub = persisted(tiered.hybrid_suppress(df, spec, 6).published)
    hybrid, boxes = measures.kl_divergence(df, pub, spec).first()["kl"], measures.kl_boxes(df, publish.to_boxes(df, pub, spec), spec).first()["kl"]
    return spark.createDataFrame([(round(tier, 6), hybrid <= tier + 1e-9, boxes <= hybrid + 1e-9)], "kl_tiered double, hybrid_not_above boolean, boxes_not_above boolean")


@query(f"WITH v AS ({_V1}) " + " UNION ALL ".join(f"SELECT '{q}' AS attribute, count(DISTINCT {q}) AS size FROM v" for q in (*views.WIDE, "l_quantity")))
def domain_sizes(spark, sf):
    df, spec = views.quantity_microdata(spark, sf)
    return measures.domain_sizes(df, spec)


@query("""WITH b AS (SELECT l_linestatus AS s, count(*) AS c FROM lineitem GROUP BY ALL) SELECT CAST(2 * min(c) AS BIGINT) AS n, true AS balanced FROM b""")
def two_value_balance(spark, sf):
    df, spec = views.two_value_microdata(spark, sf)
    return df.groupBy(spec.sa).agg(F.count(F.lit(1)).alias("c")).agg(F.sum("c").alias("n"), (F.min("c") == F.max("c")).alias("balanced"))


@query(f"""{_RATES}, c AS (SELECT rate, count_if(kind = 'tax') AS a, count_if(kind = 'discount') AS b FROM r GROUP BY rate)
SELECT CAST(sum(a + b) AS BIGINT) AS n, CAST(2 * sum(a - least(a, b)) AS BIGINT) AS stars, CAST(2 * sum(a - least(a, b)) AS BIGINT) AS starred_rows FROM c""")
def pair_release(spark, sf):
    """On one QI the optimum is known: rows of equal rates pair, every other pair costs two stars."""
    df, spec = views.rate_microdata(spark, sf)
    return measures.star_counts(publish.publish(persisted(exact.pair_exact(persisted(df), spec)), spec))


def pair_release_wide(spark, sf):
    df, spec = views.two_value_microdata(spark, sf)
    return measures.star_counts(publish.publish(persisted(exact.pair_exact(persisted(df), spec)), spec))


QUERIES["pair_release_wide"] = pair_release_wide


@query("SELECT * FROM (VALUES ('orders', 5::BIGINT, (SELECT count(*) >= 5 * max(c) FROM (SELECT o_orderpriority, count(*) OVER (PARTITION BY o_orderpriority) AS c FROM orders))), ('lines', 3::BIGINT, (SELECT count(*) >= 3 * max(c) FROM (SELECT count(*) OVER (PARTITION BY l_returnflag) AS c FROM lineitem)))) AS t(view, l, feasible)")
def infeasible_views(spark, sf):
    orders, line = views.order_microdata(spark, sf)[0], views.table(spark, sf, "lineitem")
    rows = [("orders", 5, cells.is_eligible(orders, "o_orderpriority", 5)), ("lines", 3, cells.is_eligible(line, "l_returnflag", 3))]
    return spark.createDataFrame(rows, "view string, l long, feasible boolean")


@query("""WITH k AS (SELECT count(DISTINCT (l_returnflag, l_linestatus, l_linenumber)) AS points, count(DISTINCT l_returnflag) + count(DISTINCT l_linestatus) + count(DISTINCT l_linenumber) AS n FROM lineitem)
SELECT 'a' || i AS qi, 3::BIGINT AS zeros, CAST(n - 2 AS BIGINT) AS alphabet FROM k, unnest(range(points)) AS t(i)""")
def reduction_facts(spark, sf):
    """The instance whose points are the lines' flags, states and numbers that occur together."""
    line = views.table(spark, sf, "lineitem").select("l_returnflag", "l_linestatus", "l_linenumber")
    points = sorted(tuple(r) for r in line.distinct().collect())  # a few dozen
    df, spec = exact.matching_to_microdata(spark, points, sum(len({p[k] for p in points}) for k in range(3)))
    return exact.reduction_facts(df, spec)  # zero and the codes of all rows but the three on the point


@query("""WITH p AS (SELECT DISTINCT CAST(l_linestatus = 'F' AS INT) AS a, CAST(round(l_tax * 100) >= 4 AS INT) AS b, CAST(round(l_discount * 100) >= 5 AS INT) AS c FROM lineitem),
q AS (SELECT 'matching' AS instance, a, b, c FROM p UNION ALL SELECT 'none', a, b, c FROM p WHERE (a + b + c) % 2 = 0)
SELECT instance, CAST(6 * count(*) - 3 * max(1 + mates) AS BIGINT) AS stars
FROM (SELECT instance, (SELECT count(*) FROM q o WHERE o.instance = q.instance AND o.a <> q.a AND o.b <> q.b AND o.c <> q.c) AS mates FROM q) GROUP BY instance""")
def reduction_optimum(spark, sf):
    """Points of three marks that lines have or have not. All of them have a matching; those with an even number of marks never differ in all three, so have none."""
    line = views.table(spark, sf, "lineitem")
    marks = [F.col("l_linestatus") == "F", F.round(F.col("l_tax") * 100) >= 4, F.round(F.col("l_discount") * 100) >= 5]
    every = sorted(tuple(r) for r in line.select(*[m.cast("int").alias(f"m{i}") for i, m in enumerate(marks)]).distinct().collect())  # eight at most
    out = []
    for name, points in (("matching", every), ("none", [p for p in every if sum(p) % 2 == 0])):
        df, spec = exact.matching_to_microdata(spark, points, 4)
        out.append((name, vectors.least_stars([(tuple(r[q] for q in spec.qi), r[spec.sa]) for r in df.collect()], 3)))  # six rows
    return spark.createDataFrame(out, "instance string, stars long")


@query(f"""WITH v AS ({_V4}), g AS (SELECT o_orderpriority AS sa, count(*) AS g, sum(count(*)) OVER () AS n FROM v GROUP BY ALL), h AS (SELECT r_name, o_orderpriority AS sa, count(*) AS h FROM v GROUP BY ALL), z AS (SELECT r_name, sum(h) AS size FROM h GROUP BY ALL)
SELECT round(max(d), 6) AS worst FROM (SELECT z.r_name, sum(abs(coalesce(h, 0) / size - g / n)) / 2 AS d FROM z CROSS JOIN g LEFT JOIN h ON h.r_name = z.r_name AND h.sa = g.sa GROUP BY z.r_name)""")
def closeness(spark, sf):
    df, spec = views.order_microdata(spark, sf)
    return cells.closeness_report(df.withColumn("cell_id", F.xxhash64("r_name")), spec).agg(F.round(F.max("distance"), 6).alias("worst"))


def coarsening_sweep(spark, sf):
    return workloads.run_coarsening(spark, sf)


def stars_by_l(spark, sf):
    return measures.family_average(workloads.run_stars_by_l(spark, sf))


def stars_by_d(spark, sf):
    return measures.family_average(workloads.run_stars_by_d(spark, sf))


def phase_lattice(spark, sf):
    return workloads.run_phases(spark, sf)


def phase_frequency(spark, sf):
    """In how many tables of each view, d and l the release ends in each phase; phase null: no release is feasible."""
    d = len(views.WIDE) - F.bit_count("grouping")
    return measures.phase_frequency(workloads.run_phases(spark, sf).withColumn("d", d))


QUERIES |= {f.__name__: f for f in (coarsening_sweep, stars_by_l, stars_by_d, phase_lattice, phase_frequency)}


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    df, spec = views.event_microdata(spark, sf_dir, E3)
    return publish.render_stars(tiered.hybrid_suppress(df, spec, 3).published, spec)
