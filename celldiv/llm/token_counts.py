"""Token counts from an exact length histogram.

Documents are counted by encoded length; suffix sums over the lengths then answer, for any context
limit, how many documents and tokens lie beyond it and what truncation at the limit keeps.

Defined results: a null text counts as empty, length 0; an empty table gives no rows; repeated rows
count each. Extra columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from celldiv.llm import tokens

#: Lengths are summed in blocks of so many neighbours, then over the blocks.
BLOCK = 1024


def lengths(docs: DataFrame, vocabulary: str, end_tokens: int = 1) -> DataFrame:
    """(length, n_docs): each batch is counted before it leaves Python."""
    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = tokens.encoder(vocabulary)
        for batch in batches:
            found: dict[int, int] = {}
            for text in batch.column(0):
                n = len(encode([text.as_py() or ""])[0]) + end_tokens
                found[n] = found.get(n, 0) + 1
            yield pa.RecordBatch.from_arrays([pa.array(list(found), pa.int64()), pa.array(list(found.values()), pa.int64())], ["length", "n_docs"])

    return docs.select("text").mapInArrow(count, "length long, n_docs long").groupBy("length").agg(F.sum("n_docs").alias("n_docs"))


def histogram(docs: DataFrame, vocabulary: str | None = None, end_tokens: int = 1) -> DataFrame:
    """length, n_docs, and for a context limit of that length:

    n_docs_from, n_tokens_from: documents and tokens of this length or more; n_tokens_truncated: all
    tokens after truncation to the limit; n_docs_upto, n_tokens_upto; quantile: share of documents of
    this length or less. Limits between two lengths follow: with the next length's row and L below it,
    truncated total = n_tokens_truncated there - (length - L) * n_docs_from.
    """
    from celldiv.llm.common import persisted

    counts = persisted(lengths(docs, vocabulary or tokens.path(), end_tokens)).withColumn("block", F.floor(F.col("length") / BLOCK))
    sizes = counts.groupBy("block").agg(F.sum("n_docs").alias("d"), F.sum(F.col("n_docs") * F.col("length")).alias("t"))
    # one row per block of lengths: a text of a billion tokens makes a million of them at most
    earlier = Window.orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    everything = Window.partitionBy(F.lit(1))
    sizes = sizes.select("block", *[F.coalesce(F.sum(c).over(earlier), F.lit(0)).alias(f"{c}0") for c in "dt"], *[F.sum(c).over(everything).alias(f"{c}_all") for c in "dt"])
    inside = Window.partitionBy("block").orderBy("length").rowsBetween(Window.unboundedPreceding, 0)
    upto = counts.join(sizes, "block").select(
        "length", "n_docs", "d_all", "t_all",
        (F.col("d0") + F.sum("n_docs").over(inside)).alias("n_docs_upto"),
        (F.col("t0") + F.sum(F.col("n_docs") * F.col("length")).over(inside)).alias("n_tokens_upto"))
    return upto.select(
        "length", "n_docs", "n_docs_upto", "n_tokens_upto",
        (F.col("d_all") - F.col("n_docs_upto") + F.col("n_docs")).alias("n_docs_from"),
        (F.col("t_all") - F.col("n_tokens_upto") + F.col("n_docs") * F.col("length")).alias("n_tokens_from"),
        (F.col("n_tokens_upto") + F.col("length") * (F.col("d_all") - F.col("n_docs_upto"))).alias("n_tokens_truncated"),
        (F.col("n_docs_upto") / F.col("d_all")).alias("quantile"))


def at_limits(counts: DataFrame, limits: list[int]) -> DataFrame:
    """limit, n_docs_over, n_tokens_over, n_tokens_truncated for any limits, from the histogram."""
    spark = counts.sparkSession
    wanted = spark.createDataFrame([(int(x),) for x in limits], "limit long")
    over = counts.join(F.broadcast(wanted), F.col("length") > F.col("limit"), "right").groupBy("limit").agg(
        F.coalesce(F.sum("n_docs"), F.lit(0)).alias("n_docs_over"),
        F.coalesce(F.sum(F.col("n_docs") * F.col("length")), F.lit(0)).alias("n_tokens_over"))
    whole = counts.agg(F.coalesce(F.sum(F.col("n_docs") * F.col("length")), F.lit(0)).alias("whole"))
    return over.join(F.broadcast(whole)).select("limit", "n_docs_over", "n_tokens_over", (F.col("whole") - F.col("n_tokens_over") + F.col("limit") * F.col("n_docs_over")).alias("n_tokens_truncated"))


def quantile(counts: DataFrame, q: float) -> DataFrame:
    """The least length that at least a share q of the documents does not exceed."""
    return counts.where(F.col("quantile") >= q).agg(F.min("length").alias("length"))
