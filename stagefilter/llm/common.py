"""Small helpers shared by the training-data operators."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: The white space that ends a word: space and U+0009 to U+000D.
OTHER_SPACE = "\t\n\x0b\x0c\r"
WORD_PATTERN = "[^\\x20\\x09-\\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def words(text: Column) -> Column:
    """The words of a text as an array; null and blank texts have none."""
    spaced = F.translate(F.coalesce(text, F.lit("")), OTHER_SPACE, " " * len(OTHER_SPACE))
    return F.array_remove(F.split(spaced, " "), "")


def without(text: Column, chars: str) -> Column:
    return F.translate(text, chars, "")


def let(value: Column, body) -> Column:
    """body(value) with value worked out once, however often the body names it."""
    return F.element_at(F.transform(F.array(value), body), 1)


def ensure_checkpoint_dir(spark: SparkSession) -> None:
    """The session's shared folder is used as given; a folder of our own only where none is named."""
    if spark.sparkContext.getCheckpointDir() is None:
        named = spark.conf.get("spark.checkpoint.dir", None)
        spark.sparkContext.setCheckpointDir(named or tempfile.mkdtemp(prefix="stagefilter-checkpoint-"))


def cut(df: DataFrame) -> DataFrame:
    """df with its lineage cut through the shared checkpoint folder."""
    ensure_checkpoint_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def written(df: DataFrame, name: str) -> DataFrame:
    """df as a compressed table in the shared checkpoint folder, which cuts its lineage in less room than checkpoint()."""
    ensure_checkpoint_dir(df.sparkSession)
    path = f"{df.sparkSession.sparkContext.getCheckpointDir()}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path, compression="zstd")
    return df.sparkSession.read.schema(df.schema).parquet(path)


def release_finished_shuffles(spark: SparkSession) -> None:
    """Let Spark's cleaner drop the shuffle files of frames that nobody holds any more."""
    import gc

    gc.collect()
    spark.sparkContext._jvm.System.gc()
