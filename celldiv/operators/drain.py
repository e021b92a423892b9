"""Phases two and three over distributed state (cell, sa, h, moved).

Only vectors of at most m values and at most 2^(l-1) clash signatures reach the driver. A round lets all
cells offer rows at once; offers are clipped to what the residue may take: a value to its slack below
the residue's height, all together to the deficit. Running sums are taken in hashed buckets whose
totals are added up on the driver, so no task sees all offers. The state is cut after each round.
"""

from __future__ import annotations

from collections import Counter

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from celldiv.operators import bounds, vectors
from celldiv.storage import persisted

#: Offers of one bucket, on average: the number of buckets follows from the offers.
BUCKET_OFFERS = 100_000
#: State rows up to which phases two and three run on the driver.
DRIVER_ROWS = 200_000


def residue_of(state: DataFrame) -> Counter:
    return Counter({r["sa"]: r["r"] for r in state.groupBy("sa").agg(F.sum("moved").alias("r")).where("r > 0").collect()})  # m rows


def _vector(spark: SparkSession, state: DataFrame, residue: Counter) -> DataFrame:
    kind = state.schema["sa"].dataType.simpleString()
    return F.broadcast(spark.createDataFrame([(v, r) for v, r in residue.items()] or [], f"v {kind}, r long"))


def classify(state: DataFrame, residue: Counter, l: int) -> DataFrame:
    """State rows with r, and per cell size, peak, surplus, clash (a peak value of it is one of the residue's), frozen."""
    height = max(residue.values(), default=0)
    joined = state.where("h > 0").join(_vector(state.sparkSession, state, residue), F.col("sa").eqNullSafe(F.col("v")), "left").withColumn("r", F.coalesce("r", F.lit(0))).drop("v")
    whole = Window.partitionBy("cell")
    got = joined.withColumns({"size": F.sum("h").over(whole), "peak": F.max("h").over(whole)}).withColumn("surplus", F.col("size") - l * F.col("peak"))
    got = got.withColumn("clash", F.max(((F.col("h") == F.col("peak")) & (F.col("r") == height)).cast("int")).over(whole) == 1)
    return got.withColumn("frozen", (F.col("surplus") == 0) & F.col("clash"))


def _running(df: DataFrame, value: str, by: list[str]) -> DataFrame:
    """df with `before`: the sum of value over the rows before, in the order of (bucket, cell hash), per `by`."""
    inside = Window.partitionBy(*by, "bucket").orderBy("spot", "cell", "sa").rowsBetween(Window.unboundedPreceding, -1)
    sums = df.groupBy(*by, "bucket").agg(F.sum(value).alias("__s"))
    earlier = Window.partitionBy(*(by or [F.lit(1)])).orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    starts = sums.select(*by, F.col("bucket").alias("__b"), F.coalesce(F.sum("__s").over(earlier), F.lit(0)).alias("__o"))
    on: Column = F.col("bucket") == F.col("__b")
    for c in by:
        starts = starts.withColumnRenamed(c, f"__{c}")
        on = on & F.col(c).eqNullSafe(F.col(f"__{c}"))
    return df.withColumn("__i", F.coalesce(F.sum(value).over(inside), F.lit(0))).join(F.broadcast(starts), on).withColumn("before", F.col("__i") + F.col("__o")).drop("__i", "__o", "__b", *[f"__{c}" for c in by])


def _offers(state: DataFrame, residue: Counter, l: int) -> DataFrame:
    """(cell, sa, x, r, package, spot): loose cells offer values rarest in the residue first, up to their surplus; tight ones that
    do not clash offer one row of each peak value, all or nothing."""
    height = max(residue.values(), default=0)
    got = classify(state, residue, l).where(~F.col("frozen"))
    rare = Window.partitionBy("cell").orderBy((F.col("r") >= height).cast("int"), "r", "sa").rowsBetween(Window.unboundedPreceding, -1)
    free = F.when(F.col("r") < height, F.least("h", height - F.col("r"))).otherwise(0)
    loose = F.greatest(F.lit(0), F.least("free", F.col("surplus") - F.coalesce(F.sum("free").over(rare), F.lit(0))))
    got = got.withColumn("free", free).withColumn("x", F.when(F.col("surplus") > 0, loose).otherwise((F.col("h") == F.col("peak")).cast("long")))
    spot = F.xxhash64("cell")
    return got.where("x > 0").select("cell", "sa", F.col("x").cast("long").alias("x"), "r", (F.col("surplus") == 0).alias("package"), spot.alias("spot"))


def drain_bulk(state: DataFrame, residue: Counter, l: int) -> tuple[DataFrame, Counter, int]:
    """State, residue and rounds when the residue is eligible or nothing more can be offered."""
    rounds, at_start = 0, max(residue.values(), default=0)
    while not vectors.eligible(residue, l):
        deficit = l * at_start - sum(residue.values())
        offers = persisted(_offers(state, residue, l))
        if not (many := offers.count()):
            break
        offers = offers.withColumn("bucket", F.pmod("spot", F.lit(max(16, many // BUCKET_OFFERS))))
        rounds += 1
        slack = at_start - F.col("r")
        clipped = _running(offers, "x", ["sa"]).withColumn("fit", F.greatest(F.lit(0), F.least("x", slack - F.col("before")))).drop("before")
        whole = Window.partitionBy("cell")
        clipped = clipped.withColumn("fit", F.when(F.col("package") & (F.min(F.col("fit") - F.col("x")).over(whole) < 0), 0).otherwise(F.col("fit"))).where("fit > 0")
        # one place per package, so that the deficit cuts before or after it
        taken = _running(clipped, "fit", []).withColumn("start", F.when(F.col("package"), F.min("before").over(whole)).otherwise(F.col("before")))
        left = F.lit(deficit) - F.col("start")
        taken = taken.withColumn("fit", F.when(F.col("package"), F.when(left > 0, F.col("fit")).otherwise(0)).otherwise(F.greatest(F.lit(0), F.least("fit", left)))).where("fit > 0")
        taken = persisted(taken.select("cell", "sa", F.col("fit").cast("long").alias("x")))
        if taken.isEmpty():  # clipping refused all: the first offer alone always fits
            first = offers.orderBy("r", "spot", "cell").limit(1).select(F.col("cell").alias("__c"), F.col("package").alias("__p"), F.col("sa").alias("__s"))
            taken = persisted(offers.join(F.broadcast(first), (F.col("cell") == F.col("__c")) & (F.col("__p") | F.col("sa").eqNullSafe(F.col("__s")))).select("cell", "sa", F.when(F.col("__p"), F.col("x")).otherwise(1).cast("long").alias("x")))
        state = give(state, taken)
        residue = residue_of(state)
        if max(residue.values()) != at_start:
            raise AssertionError("a drain round raised the residue's height")
    return state, residue, rounds


def give(state: DataFrame, taken: DataFrame) -> DataFrame:
    """The state after moving x rows of (cell, sa) each."""
    t = taken.select(F.col("cell").alias("__c"), F.col("sa").alias("__s"), "x")
    got = state.join(t, (F.col("cell") == F.col("__c")) & F.col("sa").eqNullSafe(F.col("__s")), "left")
    return persisted(got.select("cell", "sa", (F.col("h") - F.coalesce("x", F.lit(0))).alias("h"), (F.col("moved") + F.coalesce("x", F.lit(0))).alias("moved")))


def overhaul_bulk(state: DataFrame, residue: Counter, l: int, trace: list | None = None) -> tuple[DataFrame, Counter, int]:
    """Phase three by clash signatures: one row per signature reaches the driver, at most l - 1 cells are picked."""
    heights = [max(residue.values(), default=0)]
    while not vectors.eligible(residue, l):
        tops = sorted(vectors.peaks(residue), key=vectors._key)
        bit = F.lit(0)
        for k, v in enumerate(tops):
            bit = F.when((F.col("h") == F.col("peak")) & F.col("sa").eqNullSafe(F.lit(v)), 1 << k).otherwise(bit)
        alive = classify(state, residue, l)
        masks = alive.groupBy("cell", "frozen").agg(F.bit_or(bit).alias("mask")).groupBy("mask").agg(F.min(F.struct(F.xxhash64("cell").alias("spot"), F.col("cell"))).alias("pick"), F.bool_and("frozen").alias("frozen"))
        found = masks.collect()  # at most 2^(l-1) rows
        signatures = {r["mask"]: r["pick"]["spot"] for r in found}
        bounds.check_stuck(residue, signatures, all(r["frozen"] for r in found), l)
        picks = vectors.cover(signatures, len(tops))
        chosen = alive.where(F.xxhash64("cell").isin(picks) & (F.col("h") == F.col("peak"))).select("cell", "sa", F.lit(1).cast("long").alias("x"))
        state = give(state, chosen)
        residue = residue_of(state)
        state, residue, _ = drain_bulk(state, residue, l)
        heights.append(max(residue.values()))
        if trace is not None:
            trace.append((f"round {len(heights) - 1}", sum(residue.values()), heights[-1]))
    bounds.check_overhauled(heights, l)
    return state, residue, len(heights) - 1


def finish(state: DataFrame, l: int, how: str = "auto", trace: list | None = None) -> tuple[DataFrame, Counter, int, int]:
    """Phases two and three from a trimmed state: state, residue, phase, rounds. how: auto, exact or bulk. trace gets (step, rows, height)."""
    residue = residue_of(state)
    trace = [] if trace is None else trace
    note = lambda step: trace.append((step, sum(residue.values()), max(residue.values(), default=0)))
    note("trim")
    first = Counter(residue)
    if vectors.eligible(residue, l):
        return state, residue, 1, 0
    if how == "exact" or how == "auto" and state.where("h > 0").limit(DRIVER_ROWS + 1).count() <= DRIVER_ROWS:
        rows = state.where("h > 0").select(F.xxhash64("cell").alias("spot"), "sa", "h").orderBy("spot").collect()  # bounded above
        names = sorted({r["spot"] for r in rows})
        place = {s: i for i, s in enumerate(names)}
        cells: list[dict] = [{} for _ in names]
        for r in rows:
            cells[place[r["spot"]]][r["sa"]] = r["h"]
        old = [dict(c) for c in cells]
        vectors.drain(cells, residue, l)
        bounds.check_drained(first, residue, l)
        note("drain")
        phase, rounds = 2, 0
        if not vectors.eligible(residue, l):
            phase, rounds = 3, vectors.overhaul(cells, residue, l, trace)
        gone = [(names[i], v, h - cells[i].get(v, 0)) for i, c in enumerate(old) for v, h in c.items() if h != cells[i].get(v, 0)]
        kind = state.schema["sa"].dataType.simpleString()
        moves = state.sparkSession.createDataFrame(gone, f"spot long, s {kind}, x long")
        got = state.join(F.broadcast(moves), (F.xxhash64("cell") == F.col("spot")) & F.col("sa").eqNullSafe(F.col("s")), "left")
        return got.select("cell", "sa", (F.col("h") - F.coalesce("x", F.lit(0))).alias("h"), (F.col("moved") + F.coalesce("x", F.lit(0))).alias("moved")), residue, phase, rounds
    state, residue, rounds = drain_bulk(state, residue, l)
    bounds.check_drained(first, residue, l)
    note("drain")
    if vectors.eligible(residue, l):
        return state, residue, 2, rounds
    state, residue, rounds = overhaul_bulk(state, residue, l, trace)
    return state, residue, 3, rounds
