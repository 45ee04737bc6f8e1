"""Where intermediate tables and indexes go."""

from __future__ import annotations

import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def folder(spark: SparkSession) -> str:
    """The shared folder of spark.checkpoint.dir; where it is unset, a temporary one on a single machine only."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        named = spark.conf.get("spark.checkpoint.dir", None)
        if not named and not re.fullmatch(r"local(\[[^\]]*\])?", sc.master):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all machines share")
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="planegrid-"))
    return sc.getCheckpointDir()


def fresh_path(spark: SparkSession, name: str) -> str:
    """A path below the shared folder that nothing has yet."""
    return f"{folder(spark)}/{name}-{uuid.uuid4().hex}"


def cut(df: DataFrame) -> DataFrame:
    """The same rows, written once to the shared folder."""
    folder(df.sparkSession)
    return df.checkpoint(eager=True)


#: Rows of a batch's intermediate state that are held on the driver instead of in files.
MOST_HELD = 20_000


def settle(df: DataFrame) -> DataFrame:
    """The same rows, worked out once. For the state of a batch of questions, which grows with the batch, not the data.

    A small one is kept on the driver, where its size is known and joins broadcast it; a larger one goes to files.
    """
    found = df.limit(MOST_HELD + 1).toArrow()
    return df.sparkSession.createDataFrame(found, df.schema) if found.num_rows <= MOST_HELD else cut(df)


def stored(df: DataFrame, path: str, partition: str | None = None) -> DataFrame:
    """The same rows from Parquet files, of which a reader takes only the columns and partitions that it needs."""
    writer = df.write.partitionBy(partition) if partition else df.write
    writer.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
