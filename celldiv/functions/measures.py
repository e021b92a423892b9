"""Costs and accuracy of releases."""

from __future__ import annotations

from functools import reduce
import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from celldiv.model import MicrodataSpec


def star_counts(pub: DataFrame) -> DataFrame:
    """One row: n, stars, starred_rows."""
    return pub.agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.sum(F.bit_count("star_mask")), F.lit(0)).cast("long").alias("stars"), F.count_if(F.col("star_mask") != 0).alias("starred_rows"))


def domain_sizes(df: DataFrame, spec: MicrodataSpec, approximate: bool = False) -> DataFrame:
    """(attribute, size): distinct values, nulls as one."""
    count = F.approx_count_distinct if approximate else F.countDistinct
    row = df.agg(*[(count(c) + F.coalesce(F.max(F.col(c).isNull().cast("int")), F.lit(0))).alias(c) for c in (*spec.qi, spec.sa)])
    return row.select(F.explode(F.array(*[F.struct(F.lit(c).alias("attribute"), F.col(c).cast("long").alias("size")) for c in (*spec.qi, spec.sa)])).alias("x")).select("x.*")


def kl_divergence(df: DataFrame, pub: DataFrame, spec: MicrodataSpec) -> DataFrame:
    """One row, kl: sum over the table's support of f ln(f / f*), a star standing for its whole domain evenly.

    Each support point meets each pattern of stars that occurs (2^d at most) by equality on the kept values.
    """
    sizes = {r["attribute"]: r["size"] for r in domain_sizes(df, spec).collect()} | spec.domains
    support = df.groupBy(*spec.qi, F.col(spec.sa).alias("sa")).agg(F.count(F.lit(1)).alias("h"))
    n = support.agg(F.sum("h").alias("n"))
    forms = pub.groupBy("star_mask", *spec.qi, F.col(spec.sa).alias("sa")).agg(F.count(F.lit(1)).alias("c"))
    masks = sorted(r[0] for r in forms.select("star_mask").distinct().collect()) or [0]  # at most 2^d numbers
    points = support.withColumn("mask", F.explode(F.array(*[F.lit(m) for m in masks])))
    starred = lambda i: F.col("mask").bitwiseAND(F.lit(1 << i)) != 0
    weight = reduce(lambda a, b: a * b, [F.when(starred(i), 1.0 / max(sizes[q], 1)).otherwise(1.0) for i, q in enumerate(spec.qi)], F.lit(1.0))
    points = points.select(*spec.qi, "sa", "h", "mask", weight.alias("w"), F.struct(*[F.when(~starred(i), F.col(q)).alias(q) for i, q in enumerate(spec.qi)]).alias("form"))
    forms = forms.select(F.col("star_mask").alias("__m"), F.struct(*spec.qi).alias("__f"), F.col("sa").alias("__s"), "c")
    met = points.join(forms, (F.col("mask") == F.col("__m")) & (F.col("form") == F.col("__f")) & F.col("sa").eqNullSafe(F.col("__s")))
    star = met.groupBy(F.struct(*spec.qi).alias("p"), "sa").agg(F.max("h").alias("h"), F.sum(F.col("c") * F.col("w")).alias("g"))
    return star.crossJoin(F.broadcast(n)).agg(F.coalesce(F.sum(F.col("h") / F.col("n") * F.log(F.col("h") / F.col("g"))), F.lit(0.0)).alias("kl"))


def kl_recoded(df: DataFrame, spec: MicrodataSpec, cuts: dict[str, dict]) -> DataFrame:
    """The same for a single-dimensional recoding: cuts map each QI's leaf value to (node, number of leaves below)."""
    spark = df.sparkSession
    support = df.groupBy(*spec.qi, F.col(spec.sa).alias("sa")).agg(F.count(F.lit(1)).alias("h"))
    for q in spec.qi:
        kind = df.schema[q].dataType.simpleString()
        m = spark.createDataFrame([(k, str(v[0]), v[1]) for k, v in cuts[q].items()], f"__k {kind}, g_{q} string, w_{q} long")
        support = support.join(F.broadcast(m), F.col(q).eqNullSafe(F.col("__k"))).drop("__k")
    forms = support.groupBy(*[f"g_{q}" for q in spec.qi], "sa").agg(F.sum("h").alias("c"))
    weight = reduce(lambda a, b: a * b, [F.col(f"w_{q}") for q in spec.qi])
    n = support.agg(F.sum("h").alias("n"))
    got = support.withColumn("w", weight).join(forms.withColumnRenamed("sa", "__s"), [f"g_{q}" for q in spec.qi]).where(F.col("sa").eqNullSafe(F.col("__s"))).crossJoin(F.broadcast(n))
    return got.agg(F.sum(F.col("h") / F.col("n") * F.log(F.col("h") * F.col("w") / F.col("c"))).alias("kl"))


def kl_boxes(df: DataFrame, boxes: DataFrame, spec: MicrodataSpec) -> DataFrame:
    """The same for sub-domain releases (`to_boxes` of kind "set"): a starred value stands evenly for the values of its cell.

    A cell's first starred QI is unrolled to its values, so a support point meets the cells that share its sensitive value, its
    plain values and that one by equality; the other stars are tested. Boxes hold no null: a null QI value is a plain one.
    """
    support = df.groupBy(*spec.qi, F.col(spec.sa).alias("sa")).agg(F.count(F.lit(1)).alias("h"))
    n = support.agg(F.sum("h").alias("n"))
    starred = lambda i: F.col("star_mask").bitwiseAND(F.lit(1 << i)) != 0
    box = [f"box_{q}" for q in spec.qi]
    forms = boxes.groupBy("cell_id", "star_mask", *spec.qi, *box, F.col(spec.sa).alias("sa")).agg(F.count(F.lit(1)).alias("c"))
    forms = forms.withColumn("w", reduce(lambda a, b: a / b, [F.when(starred(i), F.greatest(F.size(b), F.lit(1))).otherwise(1) for i, b in enumerate(box)], F.lit(1.0)))
    masks = sorted(r[0] for r in forms.select("star_mask").distinct().collect())  # at most 2^d numbers
    found = None
    for mask in masks:
        some = [i for i in range(len(spec.qi)) if mask >> i & 1]
        right = forms.where(F.col("star_mask") == mask)
        keys = {q: F.col(q) for i, q in enumerate(spec.qi) if i not in some}
        if some:
            right = right.withColumn("__first", F.explode_outer(box[some[0]]))
            keys[spec.qi[some[0]]] = F.col("__first")
        right = right.select(*[k.alias(f"__{q}") for q, k in keys.items()], *[F.col(box[i]).alias(f"__b{i}") for i in some[1:]], F.col("sa").alias("__s"), "c", "w")
        on = F.col("sa").eqNullSafe(F.col("__s"))
        for q in keys:
            on = on & F.col(q).eqNullSafe(F.col(f"__{q}"))
        for i in some[1:]:
            on = on & (F.array_contains(f"__b{i}", F.col(spec.qi[i])) | (F.col(spec.qi[i]).isNull() & (F.size(f"__b{i}") == 0)))
        part = support.join(right, on).select(*spec.qi, "sa", "h", (F.col("c") * F.col("w")).alias("g"))
        found = part if found is None else found.unionByName(part)
    if found is None:
        found = support.limit(0).withColumn("g", F.lit(0.0))
    star = found.groupBy(F.struct(*spec.qi).alias("p"), "sa").agg(F.max("h").alias("h"), F.sum("g").alias("g"))
    return star.crossJoin(F.broadcast(n)).agg(F.coalesce(F.sum(F.col("h") / F.col("n") * F.log(F.col("h") / F.col("g"))), F.lit(0.0)).alias("kl"))


def family_average(rows: DataFrame) -> DataFrame:
    """Figures of runs averaged over their projections, by workload, view, method, l and d."""
    return rows.groupBy("workload", "view", "method", "l", "d").agg(F.count(F.lit(1)).alias("projections"), *[F.avg(c).alias(c) for c in ("stars", "starred_rows", "kl", "seconds")])


def phase_frequency(rows: DataFrame) -> DataFrame:
    """(view, d, l, phase, tables): in which phase runs ended."""
    return rows.groupBy("view", "d", "l", "phase").agg(F.count(F.lit(1)).alias("tables"))


def cell_sizes(pub: DataFrame) -> DataFrame:
    return pub.groupBy("cell_id").agg(F.count(F.lit(1)).alias("size")).groupBy("size").agg(F.count(F.lit(1)).alias("cells"))


def futile_cells(pub: DataFrame, spec: MicrodataSpec) -> DataFrame:
    """Cells with every QI starred."""
    return pub.where(F.col("star_mask") == (1 << len(spec.qi)) - 1).groupBy("cell_id").agg(F.count(F.lit(1)).alias("size"))


def count_query_error(df: DataFrame, pub: DataFrame, spec: MicrodataSpec, predicates: list[dict]) -> DataFrame:
    """Relative error of COUNT with QI equalities, stars read as even over the domain. (query, exact, estimate, error)."""
    sizes = {r["attribute"]: r["size"] for r in domain_sizes(df, spec).collect()} | spec.domains
    exact = df.agg(*[F.count_if(reduce(lambda a, b: a & b, [F.col(q) == v for q, v in p.items()])).alias(f"q{i}") for i, p in enumerate(predicates)])
    share = lambda q, v: F.when(F.col("star_mask").bitwiseAND(F.lit(1 << spec.qi.index(q))) != 0, 1.0 / sizes[q]).when(F.col(q) == v, 1.0).otherwise(0.0)
    guess = pub.agg(*[F.sum(reduce(lambda a, b: a * b, [share(q, v) for q, v in p.items()])).alias(f"q{i}") for i, p in enumerate(predicates)])
    both = exact.select(F.posexplode(F.array("*")).alias("query", "exact")).join(guess.select(F.posexplode(F.array("*")).alias("query", "estimate")), "query")
    return both.withColumn("error", F.abs(F.col("estimate") - F.col("exact")) / F.greatest(F.lit(1), "exact"))


def timed(make) -> float:
    """Seconds to run what make() plans, without writing it anywhere."""
    start = time.time()
    make().write.format("noop").mode("overwrite").save()
    return time.time() - start
