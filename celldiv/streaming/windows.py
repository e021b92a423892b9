"""Releases of parts of a stream. Parts hold disjoint rows, and unions of diverse releases of disjoint rows are diverse.

Two forms: micro-batches as they come, row by row (`publish_stream`), and windows closed by the watermark, as counts of
interchangeable rows (`publish_windows`). What has no diverse release waits and joins the next part; `waiting_batch` and `waiting`
show what waits. The guarantee is about rows: the same person in several windows is beyond it.

Defined results: a null QI or sensitive value is an ordinary one; a row without a time belongs to no window and is dropped by the
watermark, as are late rows, which `late_rows` counts; an empty batch releases nothing and passes on what waits.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import DataStreamWriter, StreamingQuery

from celldiv.model import Infeasible, MicrodataSpec, check_l
from celldiv.operators.tiered import histogram_plan, hybrid_suppress
from celldiv.storage import persisted


def publish_stream(events: DataFrame, spec: MicrodataSpec, l: int, sink: str, checkpoint: str, method: Callable = hybrid_suppress) -> DataStreamWriter:
    """Micro-batches are released to `sink`/released by batch number; `sink`/pending has what waits after each.

    Batches are rewritten under their number, so a restart repeats none.
    """
    def release(batch: DataFrame, number: int) -> None:
        rows = batch.select(*spec.qi, spec.sa, spec.row_id)
        if number:
            rows = rows.unionByName(batch.sparkSession.read.schema(rows.schema).parquet(f"{sink}/pending/{number - 1}"))
        waits = rows.limit(0)
        try:
            if not rows.isEmpty():
                method(rows, spec, l).published.withColumn("batch", F.lit(number)).write.mode("overwrite").parquet(f"{sink}/released/batch={number}")
        except Infeasible:
            waits = rows
        waits.write.mode("overwrite").parquet(f"{sink}/pending/{number}")

    return events.writeStream.foreachBatch(release).option("checkpointLocation", checkpoint)


def waiting_batch(spark: SparkSession, sink: str, number: int) -> DataFrame:
    """The rows of `publish_stream` that wait after batch `number`: they have no diverse release by themselves."""
    return spark.read.parquet(f"{sink}/pending/{number}")


def window_histogram(events: DataFrame, spec: MicrodataSpec, ts: str, size: str, late: str, slide: str | None = None) -> DataFrame:
    """Streaming (window, cell, sa, h): one row per group once its window is closed.

    With a slide, an event goes to the slide it falls in alone (as a tumbling window of that length), so that windows stay disjoint.
    """
    at = F.window(ts, slide or size)
    return events.withWatermark(ts, late).groupBy(at.alias("window"), spec.cell().alias("cell"), F.col(spec.sa).alias("sa")).agg(F.count(F.lit(1)).alias("h"))


def publish_counts(plan: DataFrame, spec: MicrodataSpec) -> DataFrame:
    """QI columns, SA, star_mask, rows of a plan (cell, sa, h, moved): rows that stay in their cells, and the residue as one cell."""
    own = [F.col(f"cell.{q}").alias(q) for q in spec.qi]
    kept = plan.where("h > 0").select(*own, F.col("sa").alias(spec.sa), F.lit(0).alias("star_mask"), F.col("h").cast("long").alias("rows"))
    gone = persisted(plan.where("moved > 0").select(*own, F.col("sa").alias(spec.sa), "moved"))
    # a struct around the value makes a null one value among others
    stars = gone.agg(*[(F.count_distinct(F.struct(q)) > 1).alias(f"star_{q}") for q in spec.qi])
    mask = sum((F.when(F.col(f"star_{q}"), 1 << i).otherwise(0) for i, q in enumerate(spec.qi)), F.lit(0))
    starred = gone.crossJoin(F.broadcast(stars)).select(*[F.when(~F.col(f"star_{q}"), F.col(q)).alias(q) for q in spec.qi], spec.sa, mask.alias("star_mask"), "moved")  # one row beside it
    return kept.unionByName(starred.groupBy(*spec.qi, spec.sa, "star_mask").agg(F.sum("moved").cast("long").alias("rows")))


def publish_windows(events: DataFrame, spec: MicrodataSpec, l: int, ts: str, size: str, late: str, sink: str, checkpoint: str, slide: str | None = None) -> DataStreamWriter:
    """Each window is released as counts when the watermark has passed it, to `sink`/released by the window's end.

    Windows of one micro-batch are taken in the order of their ends. One that has no diverse release joins the next;
    `waiting` has what still waits. Everything is written under the batch's number or the window's end: a restart repeats nothing.
    """
    check_l(l)

    def release(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        hist = persisted(batch.select(F.unix_micros(F.col("window.end")).alias("end"), "cell", "sa", "h"))
        waits = hist.select("cell", "sa", "h").limit(0)
        if number:
            waits = spark.read.schema(waits.schema).parquet(f"{sink}/pending/{number - 1}")
        for r in hist.select("end").distinct().orderBy("end").collect():  # the windows that one trigger closes
            both = waits.unionByName(hist.where(F.col("end") == r["end"]).drop("end"))
            whole = persisted(both.groupBy("cell", "sa").agg(F.sum("h").alias("h")))
            top = whole.groupBy("sa").agg(F.sum("h").alias("c")).agg(F.sum("c").alias("n"), F.max("c").alias("top")).first()
            if top["n"] < l * top["top"]:
                waits = whole
                continue
            plan, _ = histogram_plan(whole, l)
            publish_counts(plan, spec).write.mode("overwrite").parquet(f"{sink}/released/window_end={r['end']}")
            waits = whole.limit(0)
        waits.write.mode("overwrite").parquet(f"{sink}/pending/{number}")

    hist = window_histogram(events, spec, ts, size, late, slide)
    return hist.writeStream.outputMode("append").foreachBatch(release).option("checkpointLocation", checkpoint)


def waiting(spark: SparkSession, sink: str, spec: MicrodataSpec, number: int) -> DataFrame:
    """QI columns, SA, rows of what `publish_windows` still holds back after batch `number`."""
    got = spark.read.parquet(f"{sink}/pending/{number}")
    return got.select(*[F.col(f"cell.{q}").alias(q) for q in spec.qi], F.col("sa").alias(spec.sa), F.col("h").alias("rows"))


def late_rows(query: StreamingQuery) -> int:
    """Rows that came after their window was closed, over the progress reports that the query still has."""
    return sum(s.get("numRowsDroppedByWatermark", 0) for p in query.recentProgress for s in p["stateOperators"])
