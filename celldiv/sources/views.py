"""Microdata views of the given tables: (DataFrame, MicrodataSpec)."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from celldiv.model import MicrodataSpec

WIDE = ("ship_month", "l_linestatus", "tax", "p_type", "p_name", "discount", "l_linenumber")
COARSE = ("ship_year", "l_linestatus", "tax_band", "p_type", "p_word", "discount_band", "line_parity")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    line, part = table(spark, sf_dir, "lineitem"), table(spark, sf_dir, "part")
    got = line.join(part, F.col("l_partkey") == F.col("p_partkey"))
    return got.select(
        F.xxhash64("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey").alias("row_id"), "l_linestatus", "p_type", "p_name", "l_linenumber",
        (F.year("l_shipdate") * 12 + F.month("l_shipdate")).alias("ship_month"), F.round(F.col("l_tax") * 100).cast("int").alias("tax"), F.round(F.col("l_discount") * 100).cast("int").alias("discount"),
        F.col("l_quantity").cast("int").alias("l_quantity"), "p_size")


def quantity_microdata(spark: SparkSession, sf_dir: str, qi: tuple[str, ...] = WIDE, sa: str = "l_quantity") -> tuple[DataFrame, MicrodataSpec]:
    return _lines(spark, sf_dir).select(*qi, sa, "row_id"), MicrodataSpec(tuple(qi), sa)


def size_microdata(spark: SparkSession, sf_dir: str, qi: tuple[str, ...] = WIDE) -> tuple[DataFrame, MicrodataSpec]:
    return quantity_microdata(spark, sf_dir, qi, "p_size")


def coarse_microdata(spark: SparkSession, sf_dir: str, qi: tuple[str, ...] = COARSE, sa: str = "l_quantity") -> tuple[DataFrame, MicrodataSpec]:
    got = _lines(spark, sf_dir).withColumns({
        "ship_year": F.expr("(ship_month - 1) div 12").cast("int"), "tax_band": F.expr("tax div 3").cast("int"), "p_word": F.split("p_name", " ")[0],
        "discount_band": F.expr("discount div 6").cast("int"), "line_parity": F.col("l_linenumber") % 2})
    return got.select(*qi, sa, "row_id"), MicrodataSpec(tuple(qi), sa)


def event_microdata(spark: SparkSession, sf_dir: str, qi: tuple[str, ...] = ("event_type", "day_part", "dow", "dom", "k_band")) -> tuple[DataFrame, MicrodataSpec]:
    e = table(spark, sf_dir, "events").withColumns({
        "day_part": F.expr("hour(ts) div 6").cast("int"), "dow": F.dayofweek("ts"), "dom": F.dayofmonth("ts"),
        "k_band": F.expr("cast(get_json_object(props, '$.k') as int) div 10").cast("int"), "value_band": F.least(F.floor(F.col("value") / 20), F.lit(9)).cast("int")})
    return e.select(*qi, "value_band", F.col("event_id").alias("row_id")), MicrodataSpec(tuple(qi), "value_band")


def order_microdata(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, MicrodataSpec]:
    o, c = table(spark, sf_dir, "orders"), table(spark, sf_dir, "customer")
    n, r = table(spark, sf_dir, "nation"), table(spark, sf_dir, "region")
    got = o.join(c, F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey"))
    qi = ("o_orderstatus", "order_year", "c_mktsegment", "r_name")
    return got.select("o_orderstatus", F.year("o_orderdate").alias("order_year"), "c_mktsegment", "r_name", "o_orderpriority", F.col("o_orderkey").alias("row_id")), MicrodataSpec(qi, "o_orderpriority")


def two_value_microdata(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, MicrodataSpec]:
    """Equal numbers of rows of the two line states: all of the rarer one, as many of the other, of least hash.

    How many of the other's hashes lie below a border is counted by its leading bits, so only the rows at the border are ranked.
    """
    line = table(spark, sf_dir, "lineitem").select(
        "l_returnflag", F.round(F.col("l_tax") * 100).cast("int").alias("tax"), F.round(F.col("l_discount") * 100).cast("int").alias("discount"), "l_linestatus",
        F.xxhash64("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey").alias("row_id"))
    line = line.withColumn("lead", F.shiftright("row_id", 48))  # 65,536 shares
    least = line.groupBy("l_linestatus").count().agg(F.min("count")).first()[0] or 0
    sizes = line.groupBy(F.col("l_linestatus").alias("s"), F.col("lead").alias("b")).agg(F.count(F.lit(1)).alias("c"))
    before = Window.partitionBy("s").orderBy("b").rowsBetween(Window.unboundedPreceding, -1)
    sizes = sizes.withColumn("quota", least - F.coalesce(F.sum("c").over(before), F.lit(0))).where("quota > 0")
    rank = F.row_number().over(Window.partitionBy("l_linestatus", "lead").orderBy("row_id"))
    met = line.join(F.broadcast(sizes), (F.col("l_linestatus") == F.col("s")) & (F.col("lead") == F.col("b"))).withColumn("k", rank).where("k <= quota")
    return met.select("l_returnflag", "tax", "discount", "l_linestatus", "row_id"), MicrodataSpec(("l_returnflag", "tax", "discount"), "l_linestatus")


def rate_microdata(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, MicrodataSpec]:
    """Two rows a line, its tax and its discount as one rate: two sensitive values with equal counts by construction."""
    line = table(spark, sf_dir, "lineitem")
    key = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
    sides = [line.select(F.round(F.col(c) * 100).cast("int").alias("rate"), F.lit(c[2:]).alias("kind"), F.xxhash64(F.lit(c), *key).alias("row_id")) for c in ("l_tax", "l_discount")]
    return sides[0].unionByName(sides[1]), MicrodataSpec(("rate",), "kind")


def labelled_documents(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, MicrodataSpec]:
    """No l is feasible here: one label has most rows."""
    d, x = table(spark, sf_dir, "documents").select("doc_id", "lang", "source", "n_chars"), table(spark, sf_dir, "labels")
    got = d.join(x, "doc_id").select("lang", "source", F.length(F.col("n_chars").cast("string")).alias("length_band"), "quality", F.col("doc_id").alias("row_id"))
    return got, MicrodataSpec(("lang", "source", "length_band"), "quality")


def sample(df: DataFrame, spec: MicrodataSpec, share: int, of: int = 6) -> DataFrame:
    """Nested samples for growth experiments: rows whose hashed id falls below share of `of` parts."""
    return df.where(F.pmod(F.xxhash64(F.lit(7), spec.row_id), F.lit(of)) < share)
