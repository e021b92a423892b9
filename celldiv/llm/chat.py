"""Cumulative-snapshot collapse of logged conversations, then chat rendering.

A log that saves a conversation after every turn holds each conversation many times, each a prefix
of the next. The rolling hash of a conversation's first k turns is an exclusive or of hashes of
(place, role, text), kept twice under different tags (128 bits): it grows turn by turn, and as its
parts commute it can be summed by blocks, so one endless conversation is not one task's work.
Conversations whose full hash is a proper prefix hash of another go (anti-join); of equal ones the
smallest conv_id stays.

Only hashes of the texts travel until it is known what stays. Texts then travel once, by conversation; those of a
conversation of more than `long_rows` rows travel by turn, and again by part.

Defined results: equal rows are one turn; turns are ordered by (turn, role, text), nulls first, and
a null differs from an empty text; a null conv_id is a conversation of its own; extra columns are
dropped. Of every kept conversation the parts of `part_turns` turns are rendered, one row each. Turns without a number, or with
equal ones, are ordered in one task per conversation, by their hashes and roles (texts only where role and number are equal).
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from celldiv.llm.common import persisted, small

#: Fixed marks around a rendered turn.
OPEN, MIDDLE, CLOSE = "<|im_start|>", "\n", "<|im_end|>\n"
#: Rows of a conversation from which it is dealt to several tasks.
LONG_ROWS = 4_096
#: Conversations in a list that is broadcast.
BROADCAST_ROWS = 1_000_000
CONV, BLOCK = ["c", "none"], ["c", "none", "block"]
TURN = [*BLOCK, "turn", "role", "t1", "t2"]


def _keyed(turns: DataFrame, block_turns: int) -> DataFrame:
    """Turns with non-null keys: the conversation (c, none), its block of turn numbers, and two hashes of role and text."""
    shown = [x for v in ("role", "text") for x in (F.col(v).isNull(), F.col(v))]
    block = F.coalesce(F.floor(F.col("turn").cast("long") / block_turns), F.lit(-(1 << 62)))  # turns without a number come first
    return turns.select(
        F.coalesce("conv_id", F.lit(0)).alias("c"), F.col("conv_id").isNull().alias("none"), block.cast("long").alias("block"), F.col("turn").cast("long").alias("turn"), "role", "text",
        F.xxhash64(F.lit("a"), *shown).alias("t1"), F.xxhash64(F.lit("b"), *reversed(shown)).alias("t2"))


def _order(*last: str) -> list[Column]:
    return [F.col(c).asc_nulls_first() for c in ("turn", "role", *last)]


def placed_turns(turns: DataFrame, block_turns: int = 256) -> DataFrame:
    """Distinct turns without texts: their place in the conversation, the rolling hashes up to it, the conversation's turns and rows."""
    keyed = _keyed(turns, block_turns)
    same = Window.partitionBy(*BLOCK, "turn", "role")
    one = keyed.groupBy(*TURN).agg(F.count(F.lit(1)).alias("copies")).withColumn("alike", F.count(F.lit(1)).over(same))
    one = persisted(one.withColumn("tie", F.lit(None).cast("string")))
    if not (open_ := one.where("alike > 1")).isEmpty():  # turns that only their texts put in order
        wanted = open_.select(*[F.col(c).alias(f"__{c}") for c in TURN])
        on = F.lit(True)
        for c in TURN:
            on = on & F.col(c).eqNullSafe(F.col(f"__{c}"))
        texts = keyed.join(small(wanted, BROADCAST_ROWS // 10), on).groupBy(*TURN, "__c").agg(F.any_value("text").alias("tie"))
        one = one.where("alike = 1").unionByName(_met(open_.drop("tie"), texts.select(*TURN, "tie")))
    inside = Window.partitionBy(*BLOCK)
    one = one.select(*TURN, "copies", F.row_number().over(inside.orderBy(*_order("tie"), "t1", "t2")).alias("rank"))
    earlier = Window.partitionBy(*CONV).orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    sizes = one.groupBy(*BLOCK).agg(F.count(F.lit(1)).alias("size"), F.sum("copies").alias("copies"))
    sizes = sizes.select(*BLOCK, F.coalesce(F.sum("size").over(earlier), F.lit(0)).alias("skipped"), *[F.sum(x).over(Window.partitionBy(*CONV)).alias(y) for x, y in (("size", "n_turns"), ("copies", "n_rows"))])
    placed = one.drop("copies").join(sizes, BLOCK).withColumn("place", F.col("rank") + F.col("skipped")).drop("rank", "skipped")
    placed = placed.withColumns({"a": F.xxhash64(F.lit("a"), "place", "t1"), "b": F.xxhash64("t2", "place", F.lit("b"))})
    sums = placed.groupBy(*BLOCK).agg(F.bit_xor("a").alias("a"), F.bit_xor("b").alias("b"))
    sums = sums.select(*BLOCK, *[F.coalesce(F.bit_xor(x).over(earlier), F.lit(0).cast("long")).alias(f"{x}0") for x in "ab"])
    rolling = inside.orderBy("place").rowsBetween(Window.unboundedPreceding, 0)
    rolled = placed.join(sums, BLOCK).withColumns({f"h{x}": F.bit_xor(x).over(rolling).bitwiseXOR(F.col(f"{x}0")) for x in "ab"})
    return rolled.select(*TURN, "place", "ha", "hb", "n_turns", "n_rows")


def _met(left: DataFrame, right: DataFrame) -> DataFrame:
    """Join on the keys of a turn; nulls meet."""
    r = right.select(*[F.col(c).alias(f"__{c}") for c in TURN], *[c for c in right.columns if c not in TURN])
    on = F.lit(True)
    for c in TURN:
        on = on & (F.col(c).eqNullSafe(F.col(f"__{c}")) if c in ("turn", "role") else F.col(c) == F.col(f"__{c}"))
    return left.join(r, on).drop(*[f"__{c}" for c in TURN])


def maximal(placed: DataFrame) -> DataFrame:
    """(conv_id, n_turns, n_copies, n_rows): the conversations that no other one continues."""
    own = F.when(~F.col("none"), F.col("c"))
    ends = placed.where("place = n_turns").groupBy("n_turns", "ha", "hb")
    full = ends.agg(F.min(F.struct(F.col("none").alias("last"), own.alias("conv_id"), "n_rows")).alias("x"), F.count(F.lit(1)).alias("n_copies"))
    inner = placed.where("place < n_turns").select(F.col("place").alias("n_turns"), "ha", "hb").distinct()
    return full.join(inner, ["n_turns", "ha", "hb"], "left_anti").select("x.conv_id", "n_turns", "n_copies", "x.n_rows")


def _collapsed(turns: DataFrame, block_turns: int, long_rows: int) -> list[DataFrame]:
    """(c, none, place, role, text, n_turns, n_copies) of maximal conversations: those of few rows, and the others if there are any."""
    placed = persisted(placed_turns(turns, block_turns))
    kept = persisted(maximal(placed).select(F.coalesce("conv_id", F.lit(0)).alias("c"), F.col("conv_id").isNull().alias("none"), "n_turns", "n_copies", "n_rows"))
    keyed = _keyed(turns, block_turns)
    shown = [*CONV, "place", "role", "text", "n_turns", "n_copies"]
    # a conversation of few rows: all in one place, where distinct turns are numbered once more
    few = keyed.select(*CONV, "turn", "role", "text").join(kept.where(F.col("n_rows") <= long_rows).drop("n_rows"), CONV)
    order = Window.partitionBy(*CONV).orderBy(*_order("text"))
    before = lambda x: F.lag(x).over(order)
    again = (F.row_number().over(order) > 1) & before("turn").eqNullSafe(F.col("turn")) & before("role").eqNullSafe(F.col("role")) & before("text").eqNullSafe(F.col("text"))
    few = few.withColumn("again", again).where(~F.col("again")).withColumn("place", F.row_number().over(order))
    long = kept.where(F.col("n_rows") > long_rows).drop("n_rows")
    if long.isEmpty():
        return [few.select(*shown)]
    long = small(long, BROADCAST_ROWS)
    texts = keyed.join(long.select(*CONV), CONV, "left_semi").groupBy(*TURN).agg(F.any_value("text").alias("text"))
    many = _met(texts, placed.select(*TURN, "place").join(long, CONV))
    return [few.select(*shown), many.select(*shown)]


def collapse(turns: DataFrame, block_turns: int = 256, long_rows: int = LONG_ROWS) -> DataFrame:
    """The turns of maximal conversations: conv_id, place, role, text, n_turns, n_copies."""
    whole = reduce(DataFrame.unionByName, _collapsed(turns, block_turns, long_rows))
    return whole.select(F.when(~F.col("none"), F.col("c")).alias("conv_id"), "place", "role", "text", "n_turns", "n_copies")


def _render(kept: DataFrame, keys: list[str], part_turns: int) -> DataFrame:
    shown = F.concat(F.lit(OPEN), F.coalesce("role", F.lit("")), F.lit(MIDDLE), F.coalesce("text", F.lit("")), F.lit(CLOSE))
    rows = kept.select(*keys, F.floor((F.col("place") - 1) / part_turns).cast("long").alias("part"), "n_turns", "n_copies", F.struct("place", shown.alias("shown")).alias("turn"))
    texts = rows.groupBy(*keys, "part").agg(F.max("n_turns").alias("n_turns"), F.max("n_copies").alias("n_copies"), F.array_sort(F.collect_list("turn")).alias("turns"))
    return texts.select(*keys, "part", "n_turns", "n_copies", F.array_join("turns.shown", "").alias("text"))


def render(kept: DataFrame, part_turns: int = 256) -> DataFrame:
    """conv_id, part, n_turns, n_copies, text: each part of a conversation as one marked-up text."""
    return _render(kept, ["conv_id"], part_turns)


def collapse_and_render(turns: DataFrame, block_turns: int = 256, long_rows: int = LONG_ROWS, part_turns: int = 256) -> DataFrame:
    """`render` of `collapse`. Conversations of few rows are rendered where their turns were put in order, so their texts travel once."""
    whole = reduce(DataFrame.unionByName, [_render(some, CONV, part_turns) for some in _collapsed(turns, block_turns, long_rows)])
    return whole.select(F.when(~F.col("none"), F.col("c")).alias("conv_id"), "part", "n_turns", "n_copies", "text")
