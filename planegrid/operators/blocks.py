"""Numbered blocks in Parquet files, of which a batch of questions reads those it asks for.

Blocks 0, 1, ... of a table lie in order; a chunk is a run of them and a partition of the files. Rows that ask for
blocks by number meet them in an inner join: chunks that no row asks for aren't read, nor columns, and a batch of usual
size is broadcast, so blocks are never shuffled for it. A larger batch is joined as Spark sees fit.
"""

from __future__ import annotations

import json
from collections.abc import Iterator
from contextlib import contextmanager
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from planegrid.plans.storage import stored

#: While a list, every meeting adds (table, rows that ask for a block): the steps of a batch of questions.
TRACE: list[tuple[str, int]] | None = None
#: Blocks of a chunk at least, chunks of a table at most, chunks that are named in a filter.
SPAN, MOST_CHUNKS, MOST_NAMED = 4096, 4096, 1000


@dataclass
class Blocks:
    """rows: chunk (the partition column), gblk and what a block holds. span: blocks of a chunk."""

    rows: DataFrame
    path: str
    span: int
    chunks: int

    @property
    def about(self) -> dict:
        return {"path": self.path, "span": self.span, "chunks": self.chunks, "schema": self.rows.schema.json()}

    def meet(self, asked: DataFrame, at: str, columns: list[str], tag: str = "") -> DataFrame:
        """asked with the columns (their names ending in tag) of the block whose number is in column at."""
        part = self.rows
        if TRACE is not None:
            TRACE.append((self.path.rpartition("/")[2], asked.count()))
        if self.chunks > 1:
            wanted = [r.c for r in asked.select(F.floor(F.col(at) / self.span).alias("c")).distinct().limit(MOST_NAMED + 1).collect()]
            if len(wanted) <= MOST_NAMED:
                part = part.where(F.col("chunk").isin(wanted))
        part = part.select(F.col("gblk").alias(at), *(F.col(c).alias(f"{c}{tag}") for c in columns))
        return asked.join(part, at)


@contextmanager
def traced() -> Iterator[list[tuple[str, int]]]:
    """Collects the steps of what is built inside; counting them costs a job for each meeting."""
    global TRACE
    TRACE, before = [], TRACE
    try:
        yield TRACE
    finally:
        TRACE = before


def save(made: DataFrame, total: int, path: str) -> Blocks:
    """made: gblk and other columns, of which there are total."""
    span = SPAN
    while total > span * MOST_CHUNKS:
        span *= 2
    rows = made.withColumn("chunk", F.floor(F.col("gblk") / span))
    rows = rows.repartition("chunk", F.floor(F.col("gblk") / SPAN)).sortWithinPartitions("chunk", "gblk")
    return Blocks(stored(rows, path, "chunk"), path, span, max(1, -(-total // span)))


def load(spark: SparkSession, about: dict) -> Blocks:
    from pyspark.sql.types import StructType

    schema = StructType.fromJson(json.loads(about["schema"]))
    return Blocks(spark.read.schema(schema).parquet(about["path"]), about["path"], about["span"], about["chunks"])
