"""Cuts of long lineages in the folder that the session names for checkpoints, and sides that may be broadcast."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Rows (of a few numbers each) up to which a side is broadcast; a larger one is shuffled.
BROADCAST_ROWS = 1_000_000


def persisted(df: DataFrame) -> DataFrame:
    """df, written to the session's checkpoint folder and read from there. Only a local session may do without one."""
    context = df.sparkSession.sparkContext
    if context.getCheckpointDir() is None:
        folder = df.sparkSession.conf.get("spark.checkpoint.dir", None)
        if not folder and not context.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        context.setCheckpointDir(folder or tempfile.mkdtemp(prefix="celldiv-"))
    return df.checkpoint(eager=True)


def small(df: DataFrame, rows: int = BROADCAST_ROWS) -> DataFrame:
    """df with a broadcast hint if it has at most so many rows, else as it is."""
    return F.broadcast(df) if df.limit(rows + 1).count() <= rows else df
