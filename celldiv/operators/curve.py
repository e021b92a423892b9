"""The curve baseline: rows in Hilbert order, cells of rows with l different sensitive values.

Rows are sorted once over the cluster (a range exchange, kept as a checkpoint); their ranks follow from the place in
the partition and the partition's offset, so no further sort and no sketch is needed. A chunk is a range of ranks,
exact to the row even where many rows share one position. Chunks that are not eligible join their neighbours in
distributed rounds. Cells are formed inside chunks, one task each.

Nulls are ordinary values, first in the order; an empty table gives an empty one; repeated rows are rows. Row ids only break ties.
"""

from __future__ import annotations

import heapq

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from celldiv.functions.curve import hilbert_index
from celldiv.model import MicrodataSpec
from celldiv.storage import persisted, small

#: Rows of one chunk. Stratified chunks have at most twice as many and one per sensitive value, unless they must join for eligibility.
CHUNK_ROWS = 100_000
#: Rows of a chunk beyond which tight tables get their cells from ranks, not in tasks that hold a chunk.
TASK_ROWS = 1_000_000
#: Values of one QI that are collected as a dictionary.
DOMAIN = 1_000_000


def domains(df: DataFrame, spec: MicrodataSpec) -> dict[str, list]:
    """Each QI's values in order, nulls first: two jobs for all QIs."""
    many = df.agg(*[F.approx_count_distinct(q).alias(q) for q in spec.qi]).first()
    for q in spec.qi:
        if (many[q] or 0) > DOMAIN:
            raise ValueError(f"{q} has over a million values; coarsen it first")
    row = df.agg(*[F.collect_set(q).alias(q) for q in spec.qi], *[F.bool_or(F.col(q).isNull()).alias(f"none_{q}") for q in spec.qi]).first()
    return {q: [*([None] if row[f"none_{q}"] else []), *sorted(row[q] or [])] for q in spec.qi}


def encode(df: DataFrame, spec: MicrodataSpec) -> tuple[DataFrame, int]:
    """df with code_<qi> (rank in the domain, nulls first) and the bits that the largest code needs."""
    most = 1
    for q, values in domains(df, spec).items():
        most = max(most, len(values))
        kind = df.schema[q].dataType.simpleString()
        codes = df.sparkSession.createDataFrame([(v, i) for i, v in enumerate(values)], f"__v {kind}, `code_{q}` long")
        df = df.join(F.broadcast(codes), F.col(q).eqNullSafe(F.col("__v"))).drop("__v")  # DOMAIN rows at most
    return df, max(1, (most - 1).bit_length())


def placed_rows(df: DataFrame, spec: MicrodataSpec) -> DataFrame:
    """df with __at, its position on the curve."""
    coded, bits = encode(df, spec)
    return coded.withColumn("__at", hilbert_index([F.col(f"code_{q}") for q in spec.qi], bits)).drop(*[f"code_{q}" for q in spec.qi])


def ranked(placed: DataFrame, spec: MicrodataSpec, by_value: bool) -> DataFrame:
    """placed with __rank along the curve, from 0 (within each sensitive value if by_value), and __of, the number of rows ranked together.

    The number of partitions follows from the data; the checkpoint fixes their rows and their order."""
    spark = placed.sparkSession
    keys = ([F.col(spec.sa)] if by_value else []) + [F.col("__at"), F.xxhash64(spec.row_id), F.col(spec.row_id)]
    parts = int(spark.conf.get("spark.sql.shuffle.partitions", "200"))
    fixed = persisted(placed.repartitionByRange(parts, *keys).sortWithinPartitions(*keys)).withColumn("__id", F.monotonically_increasing_id())
    fixed = fixed.withColumns({"__part": F.shiftright("__id", 33), "__row": F.col("__id").bitwiseAND(F.lit((1 << 33) - 1))})
    group = F.col(spec.sa) if by_value else F.lit(0)
    runs = fixed.groupBy(F.col("__part").alias("__p"), group.alias("__g")).agg(F.count(F.lit(1)).alias("__n"), F.min("__row").alias("__first"))
    # a run per partition, and one more per value: a few numbers each
    earlier = Window.partitionBy("__g").orderBy("__p").rowsBetween(Window.unboundedPreceding, -1)
    runs = runs.select("__p", "__g", (F.coalesce(F.sum("__n").over(earlier), F.lit(0)) - F.col("__first")).alias("__shift"), F.sum("__n").over(Window.partitionBy("__g")).alias("__of"))
    met = fixed.withColumn("__h", group).join(small(persisted(runs)), (F.col("__part") == F.col("__p")) & F.col("__h").eqNullSafe(F.col("__g")))
    return met.withColumn("__rank", F.col("__row") + F.col("__shift")).drop("__id", "__part", "__row", "__p", "__g", "__h", "__shift")


def joined_chunks(counts: DataFrame, l: int) -> DataFrame:
    """(chunk, into): which chunk each becomes part of, so that all are eligible. counts: (chunk, sa, h).

    In each round the chunks that are not eligible join the next that is (the last ones of a stretch the one before); stretches
    double, so it ends, with one chunk if need be. Unions of eligible chunks are eligible.
    """
    now, stretch = persisted(counts.withColumn("into", F.col("chunk"))), 1 << 16
    while True:
        per = now.groupBy("into", "sa").agg(F.sum("h").alias("h")).groupBy("into").agg((F.sum("h") >= l * F.max("h")).cast("int").alias("fits"))
        if per.where("fits = 0").isEmpty() or per.limit(2).count() == 1:
            return now.select("chunk", "into").distinct()
        per = per.withColumn("near", F.expr(f"into div {stretch}"))
        order, all_ = Window.partitionBy("near").orderBy("into"), Window.partitionBy("near")
        before = F.coalesce(F.sum("fits").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
        per = per.withColumn("of", F.least(before, F.greatest(F.sum("fits").over(all_) - 1, F.lit(0))))
        moves = per.select("into", F.min("into").over(Window.partitionBy("near", "of")).alias("__to"))
        now = persisted(now.join(moves, "into").select("chunk", "sa", "h", F.col("__to").alias("into")))
        stretch *= 2


def group_sorted(sa: np.ndarray, l: int) -> np.ndarray:
    """Cell numbers for rows in curve order whose sensitive values are codes sa; the rows must be eligible.

    A cell takes the earliest row of each of l values: those that the rest could not spare, then those
    whose earliest rows come first. When the rest could not stay eligible it becomes one cell.
    """
    n, cell = len(sa), np.zeros(len(sa), np.int64)
    if not n:
        return cell
    order = np.argsort(sa, kind="stable")
    begins = np.searchsorted(sa[order], np.arange(sa.max() + 2)).tolist()
    order = order.tolist()
    head, ends, m = begins[:-1], begins[1:], len(begins) - 1
    left = [e - h for h, e in zip(head, ends)]
    of_height: dict[int, int] = {}
    for x in left:
        of_height[x] = of_height.get(x, 0) + 1
    peak = max(left)
    first = [(order[head[v]], v) for v in range(m) if left[v]]
    heapq.heapify(first)
    out, number = [0] * n, 0
    total = n
    while total >= 2 * l:
        # values above this height must give a row now, or the rest could not stay eligible
        limit = (total - l) // l
        if peak <= limit:
            if len(first) < l:
                break
            chosen = [heapq.heappop(first) for _ in range(l)]
        else:
            must = {v for v in range(m) if left[v] > limit}
            chosen, aside = [], []
            while first and len(chosen) < max(l, len(must)):
                x = heapq.heappop(first)
                if x[1] in must or len(chosen) + len(must - {c[1] for c in chosen}) < l:
                    chosen.append(x)
                else:
                    aside.append(x)
            for x in aside:
                heapq.heappush(first, x)
            after = max((left[v] - (v in {c[1] for c in chosen}) for v in range(m)), default=0)
            if len(chosen) < l or after * l > total - len(chosen):
                for x in chosen:
                    heapq.heappush(first, x)
                break
        for at, v in chosen:
            out[at] = number
            of_height[left[v]] -= 1
            left[v] -= 1
            of_height[left[v]] = of_height.get(left[v], 0) + 1
            head[v] += 1
            if left[v]:
                heapq.heappush(first, (order[head[v]], v))
        while peak and not of_height.get(peak):
            peak -= 1
        total -= len(chosen)
        number += 1
    for v in range(m):
        for i in range(head[v], ends[v]):
            out[order[i]] = number
    return np.array(out, np.int64)


def is_tight(df: DataFrame, spec: MicrodataSpec, l: int) -> bool:
    """Whether the table has just l sensitive values, equally often: every cell then takes the next row of each."""
    row = df.groupBy(spec.sa).agg(F.count(F.lit(1)).alias("h")).agg(F.count(F.lit(1)).alias("m"), F.min("h").alias("low"), F.max("h").alias("top")).first()
    return row["m"] == l and row["low"] == row["top"]


def curve_cells(df: DataFrame, spec: MicrodataSpec, l: int, chunking: str = "stratified", chunk_rows: int = CHUNK_ROWS) -> DataFrame:
    """df with cell_id. Chunks are equal shares of each sensitive value's ranks ("stratified"), or of all ranks ("range").

    Range chunks follow the curve alone; where the sensitive value does too they must join, and if one of them
    outgrows four chunks so, stratified chunks are taken instead.

    Chunks of a tight table (see is_tight) are eligible only if they are tight too, so whatever the chunks a cell has the
    rows of one rank among their values. Where a task would hold over TASK_ROWS of its rows, cells are those ranks.
    """
    by_value = chunking == "stratified"
    n = df.count()
    chunks = max(1, n // chunk_rows)
    # range chunks of a tight table join, mostly into one
    if (n // chunks if by_value else n) > TASK_ROWS and is_tight(df, spec, l):
        return ranked(placed_rows(df, spec), spec, True).withColumn("cell_id", F.col("__rank") + (1 << 40)).drop("__at", "__rank", "__of")
    rows = ranked(placed_rows(df, spec), spec, by_value)
    rows = rows.withColumn("__chunk", F.expr(f"(__rank * {chunks}) div __of") if chunks > 1 else F.lit(0).cast("long")).drop("__rank", "__of")
    if chunks > 1:
        counts = persisted(rows.groupBy(F.col("__chunk").alias("chunk"), F.col(spec.sa).alias("sa")).agg(F.count(F.lit(1)).alias("h")))
        into = persisted(joined_chunks(counts, l))
        if not by_value and not counts.join(into, "chunk").groupBy("into").agg(F.sum("h").alias("h")).where(F.col("h") > 4 * chunk_rows).isEmpty():
            return curve_cells(df, spec, l, "stratified", chunk_rows)
        rows = rows.join(small(into), F.col("__chunk") == F.col("chunk")).drop("__chunk", "chunk").withColumnRenamed("into", "__chunk")
    kinds = [f for f in rows.schema.fields if f.name not in ("__at", "__chunk")]
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in kinds) + ", cell_id long"

    def group(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["__at", spec.row_id], kind="stable").reset_index(drop=True)
        codes, _ = pd.factorize(pdf[spec.sa], use_na_sentinel=False)
        chunk = int(pdf["__chunk"].iloc[0])
        pdf["cell_id"] = (group_sorted(codes.astype(np.int64), l) + (chunk + 1) * (1 << 40)).astype(np.int64)
        return pdf[[f.name for f in kinds] + ["cell_id"]]

    return rows.groupBy("__chunk").applyInPandas(group, schema)


def by_rank(df: DataFrame, spec: MicrodataSpec) -> DataFrame:
    """Position and rank (from 1) along the curve within each sensitive value."""
    return ranked(placed_rows(df, spec), spec, True).withColumnRenamed("__at", "position").withColumn("rank", F.col("__rank") + 1).drop("__rank", "__of")
