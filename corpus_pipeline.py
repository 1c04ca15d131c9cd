"""A corpus pipeline: quality filter, near-duplicate removal, mixing to target weights, packing.

Each stage takes (spark, docs, sf_dir) and gives a DataFrame; all but the last give the columns of documents.
Between stages rows are written as Parquet in the session's shared checkpoint folder and read again.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from latticewalk.llm import mixing, near_dups, packing, quality
from latticewalk.llm.common import checkpoint_dir, table
from latticewalk.llm.queries import SEQUENCE, vocabulary


def keep_good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier accepts; it learns from labelled documents outside the test fold."""
    model = quality.train(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
    return quality.score_documents(docs, model).where("predicted = 1").select(*docs.columns)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group: the smallest id of each component. Repeated rows of an id that stays all stay."""
    kept = near_dups.near_duplicates(docs).where("kept").select(F.col("doc_id").alias("__id")).distinct()
    return docs.join(kept, F.col("doc_id").eqNullSafe(F.col("__id")), "left_semi")


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix takes them."""
    return mixing.mixed_rows(docs)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces with their places in sequences. Workers of earlier stages are still there, so none of them keeps an encoder."""
    return packing.pack(docs, vocabulary("word_bpe_49k.json"), SEQUENCE, memo=100_000)


STAGES = [("quality", keep_good), ("near_duplicates", drop_near_duplicates), ("mixing", mix_sources), ("packing", pack_sequences)]
#: Packing and the classifier have no SQL; tests compare the pipeline with a brute-force version.
ORACLE_SQL = None


def remove(spark: SparkSession, place: str) -> None:
    """Deletes a folder in whatever store it lies."""
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(place)
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents. A stage's folder is deleted once the next one is written; the last one's stays."""
    docs, before = table(spark, sf_dir, "documents"), None
    for name, stage in STAGES:
        place = f"{checkpoint_dir(spark)}/pipeline-{name}-{uuid.uuid4().hex}"
        stage(spark, docs, sf_dir).write.parquet(place)
        docs = spark.read.parquet(place)
        if before:
            remove(spark, before)
        before = place
    return docs
