"""The corpus pipeline: five stages over documents, each written as Parquet and read again by the next."""

from __future__ import annotations

import ctypes
import functools
import gc
import uuid
from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from celldiv.llm import decontam, packing, pii, simhash, toxicity
from celldiv.llm.common import table
from celldiv.llm.queries import KEY, _learning

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def tidied(stage: Callable[[SparkSession, DataFrame, str], DataFrame]) -> Callable[[SparkSession, DataFrame, str], DataFrame]:
    """The stage, with the driver's unused memory handed back before it and once it is planned: what one stage frees is else kept beside the next one's."""
    def tidy() -> None:
        gc.collect()
        pa.default_memory_pool().release_unused()
        if trim := getattr(ctypes.CDLL(None), "malloc_trim", None):  # glibc only
            trim(0)

    @functools.wraps(stage)
    def run(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        tidy()
        out = stage(spark, docs, sf_dir)
        tidy()
        return out

    return run


@tidied
def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that score below the limit; learnt from the labelled rows of the corpus."""
    corpus = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = toxicity.fit(corpus, _learning(table(spark, sf_dir, "labels").select("doc_id", "toxic")))
    return toxicity.reject(docs.select(*COLUMNS), model)


@tidied
def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The first document of each near-duplicate class."""
    return simhash.representatives(docs.select(*COLUMNS))


@tidied
def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that share no window with the benchmark."""
    return decontam.clean(docs.select(*COLUMNS), table(spark, sf_dir, "benchmark"))


@tidied
def replace_private(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, with surrogates for private data."""
    out = pii.replace(docs.select(*COLUMNS), KEY)
    return out.withColumn("n_chars", F.char_length("text").cast("long")).select(*COLUMNS)


@tidied
def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of all documents with their places in sequences."""
    return packing.pack(docs)


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("toxicity", drop_toxic), ("simhash_near_dedup", drop_near_copies), ("decontamination", drop_contaminated), ("pii_surrogates", replace_private), ("packing", pack)]

#: Tokenizer ids and XXH64 are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages in order; each result is written to the shared folder and read again."""
    from celldiv.llm.common import checkpoint_folder

    docs = table(spark, sf_dir, "documents")
    home = f"{checkpoint_folder(spark)}/pipeline-{uuid.uuid4().hex}"
    for name, stage in STAGES[:-1]:
        stage(spark, docs, sf_dir).write.parquet(f"{home}/{name}")
        docs = spark.read.parquet(f"{home}/{name}")
    name, stage = STAGES[-1]
    return stage(spark, docs, sf_dir)
