"""From raw documents to packed training sequences, in five stages.

Each stage takes all that its predecessor kept, as Parquet: documents without a language go, toxic ones go, one document
of each near-duplicate group stays, sources are mixed to target weights, and the mix is packed into sequences. All but
the last return the columns of ``documents``; a document that the mix takes twice is two rows from then on.
"""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

from salvage.llm import language_id, mixing, packing, simhash, toxicity
from salvage.llm.common import remove, table


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language was found. A null, empty or letterless text has none and goes; repeated rows share their
    fate; an empty table gives an empty one; columns that ``docs`` has beyond those of documents stay."""
    return language_id.documents_in_a_language(docs)


def clean(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that are not predicted toxic. Null and empty texts have no evidence and stay; equal texts share their
    fate; without labels of both classes all stay; an empty table gives an empty one; further columns stay."""
    return toxicity.drop_toxic(docs, table(spark, sf_dir, "labels"))


def unique(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of texts linked by a five-word Jaccard index of 0.8 or more: that with the smallest id,
    a null id being last, ties by the text's hash. Null and empty texts are one group; an empty table gives an empty one;
    further columns stay."""
    return simhash.drop_near_duplicates(docs, simhash.near_duplicates(docs))


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The mix: a row for each time that a document is taken. Null and empty texts have no words and are never taken; a
    null source is a source; null and repeated ids are documents of their own; an empty table gives an empty one; further
    columns stay."""
    return mixing.mixed_documents(docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces in sequences. A null or empty text is its end id alone; repeated rows are documents of their own; long texts
    are cut; an empty table gives an empty result; other columns are left out."""
    return packing.pack_documents(docs)


STAGES = [("language", language), ("toxicity", clean), ("near_duplicates", unique), ("mixing", mix), ("packing", pack)]

#: The text models and the token ids can't be expressed in SQL; tests compare the stages with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The last stage's rows. What a stage keeps is written to the shared folder that the session names, and deleted when
    the next stage's rows are written; the last written stage stays, since the result reads it."""
    shared = spark.conf.get("spark.checkpoint.dir", None)
    if shared is None:
        if not spark.sparkContext.master.startswith("local["):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        shared = tempfile.mkdtemp(prefix="salvage-pipeline-")
    folder = f"{shared}/pipeline-{uuid.uuid4().hex}"
    docs, before = table(spark, sf_dir, "documents"), None
    for name, stage in STAGES[:-1]:
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{name}")
        docs = spark.read.parquet(f"{folder}/{name}")
        if before:
            remove(spark, f"{folder}/{before}")
        before = name
    return STAGES[-1][1](spark, docs, sf_dir)
