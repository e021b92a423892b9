"""From counts to rows, and from cells to stars.

Column names of the input are free, but for those that the results add (in_residue, cell_id, star_mask, box_<qi>): a QI
of such a name is refused by `shown`.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from celldiv.model import MicrodataSpec
from celldiv.storage import persisted, small

#: Parts into which the rows of a pair are dealt before any of them is ranked.
SALTS = 64


def pick_rows(df: DataFrame, plan: DataFrame, spec: MicrodataSpec) -> DataFrame:
    """df with in_residue. plan: (cell, sa, h, moved) of pairs that lose rows; other pairs stay whole.

    Rows of pairs that lose some rows but not all are dealt to SALTS parts by a hash of the row id, and ranked in them
    against what the parts before leave of the pair's quota. So no task ranks all rows of a pair that holds a third of the table.
    """
    p = plan.where("moved > 0").select(F.col("cell").alias("__c"), F.col("sa").alias("__s"), F.col("moved").alias("__moved"), F.col("h").alias("__left"))
    joined = df.withColumn("__cell", spec.cell()).join(small(p), (F.col("__cell") == F.col("__c")) & F.col(spec.sa).eqNullSafe(F.col("__s")), "left")
    some = F.col("__moved").isNotNull() & (F.col("__left") > 0)
    whole = joined.where(~some).withColumn("in_residue", F.col("__moved").isNotNull())
    part = joined.where(some).withColumn("__salt", F.pmod(F.xxhash64(spec.row_id), F.lit(SALTS)))
    sizes = part.groupBy("__c", "__s", "__salt").agg(F.count(F.lit(1)).alias("__size"))
    earlier = Window.partitionBy("__c", "__s").orderBy("__salt").rowsBetween(Window.unboundedPreceding, -1)
    sizes = sizes.withColumn("__before", F.coalesce(F.sum("__size").over(earlier), F.lit(0))).withColumnsRenamed({"__c": "__c2", "__s": "__s2", "__salt": "__salt2"})
    dealt = part.join(sizes, (F.col("__c") == F.col("__c2")) & F.col("__s").eqNullSafe(F.col("__s2")) & (F.col("__salt") == F.col("__salt2"))).withColumn("__quota", F.col("__moved") - F.col("__before"))
    order = Window.partitionBy("__c", "__s", "__salt").orderBy(F.xxhash64(spec.row_id, F.lit(1)), spec.row_id)
    part = dealt.withColumn("in_residue", F.row_number().over(order) <= F.col("__quota"))
    own = [*df.columns, "in_residue"]
    return whole.select(own).unionByName(part.select(own))


def publish(df: DataFrame, spec: MicrodataSpec, cell_id: str = "cell_id") -> DataFrame:
    """QI values stay where all rows of the cell share them; star_mask has a bit per starred QI (a null value is no star)."""
    told = []
    for q in spec.qi:
        told += [F.min(q).alias(f"lo_{q}"), F.max(q).alias(f"hi_{q}"), F.count(q).alias(f"n_{q}")]
    per = df.groupBy(F.col(cell_id).alias("__id")).agg(F.count(F.lit(1)).alias("__n"), *told)
    differs = {q: ~((F.col(f"n_{q}") == 0) | ((F.col(f"n_{q}") == F.col("__n")) & (F.col(f"lo_{q}") == F.col(f"hi_{q}")))) for q in spec.qi}
    mask = sum((F.when(differs[q], 1 << i).otherwise(0) for i, q in enumerate(spec.qi)), F.lit(0))
    per = persisted(per.select("__id", mask.alias("star_mask")))
    got = df.join(small(per), F.col(cell_id).eqNullSafe(F.col("__id"))).drop("__id")
    return got.withColumns({q: F.when(F.col("star_mask").bitwiseAND(F.lit(1 << i)) == 0, F.col(q)) for i, q in enumerate(spec.qi)})


def kept_rows(split: DataFrame, spec: MicrodataSpec) -> DataFrame:
    """The rows outside the residue as they are published: no star, the cell's own number."""
    return split.where(~F.col("in_residue")).select(*spec.qi, spec.sa, spec.row_id, F.xxhash64(spec.cell()).alias("cell_id"), F.lit(0).alias("star_mask"))


def suppress_all(df: DataFrame, spec: MicrodataSpec) -> DataFrame:
    """One cell: the trivial release."""
    return publish(df.withColumn("cell_id", F.lit(0).cast("long")), spec)


def render_stars(pub: DataFrame, spec: MicrodataSpec) -> DataFrame:
    return pub.withColumns({q: F.when(F.col("star_mask").bitwiseAND(F.lit(1 << i)) != 0, F.lit("*")).otherwise(F.col(q).cast("string")) for i, q in enumerate(spec.qi)})


def to_boxes(df: DataFrame, pub: DataFrame, spec: MicrodataSpec, kind: str = "set") -> DataFrame:
    """Multi-dimensional recoding: each star becomes the sub-domain of the values in its cell (a set, or an interval); a null is no member.

    Row ids must be unique. A box never holds more than the star's whole domain.
    """
    made = (lambda q: F.array_sort(F.collect_set(q))) if kind == "set" else (lambda q: F.array(F.min(q), F.max(q)))
    raw = df.select(F.col(spec.row_id).alias("__r"), *[F.col(q).alias(f"__{q}") for q in spec.qi])
    cells = pub.select("cell_id", spec.row_id).join(raw, F.col(spec.row_id) == F.col("__r")).groupBy("cell_id").agg(*[made(f"__{q}").alias(f"box_{q}") for q in spec.qi])
    return pub.join(cells, "cell_id")
