"""What the training-data operators share: reading, persisted cuts, let-bindings, word rules."""

from __future__ import annotations

import tempfile
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: ASCII white space as a regular expression class body.
SPACE = r"\x20\x09-\x0D"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def persisted(df: DataFrame) -> DataFrame:
    """Cut the lineage in the folder that the cluster names in spark.checkpoint.dir.

    Reliable checkpoint: the files are shared, so a lost executor costs nothing. Only a local
    session that names no folder (tests) gets a temporary one; a cluster without one is an error.
    """
    checkpoint_folder(df.sparkSession)
    return df.checkpoint(eager=True)


def checkpoint_folder(spark: SparkSession) -> str:
    """The shared folder of the session, set on the context if it was not."""
    context = spark.sparkContext
    if context.getCheckpointDir() is None:
        folder = spark.conf.get("spark.checkpoint.dir", None)
        if not folder and not context.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        context.setCheckpointDir(folder or tempfile.mkdtemp(prefix="celldiv-"))
    return context.getCheckpointDir()


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """body(value) with value evaluated once, inside one expression.

    A lambda's outer expressions are evaluated again for each element; a lambda variable is not.
    """
    return F.element_at(F.transform(F.array(value), body), 1)


def ascii_lower(text: Column) -> Column:
    """A-Z to a-z and nothing else. Pure ASCII takes the fast built-in way."""
    return F.when(F.char_length(text) == F.octet_length(text), F.lower(text)).otherwise(F.translate(text, UPPER, LOWER))


def space_words(text: Column) -> Column:
    """Maximal runs of characters that are not ASCII white space."""
    return F.filter(F.split(text, f"[{SPACE}]+"), lambda w: w != "")


def counted(df: DataFrame, bound: int) -> bool:
    """Whether df has at most `bound` rows; stops counting just beyond."""
    return df.limit(bound + 1).count() <= bound


def small(df: DataFrame, bound: int) -> DataFrame:
    """df with a broadcast hint if it has at most `bound` rows, else as it is: then Spark shuffles it."""
    return F.broadcast(df) if counted(df, bound) else df
