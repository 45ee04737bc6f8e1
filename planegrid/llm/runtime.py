"""What the operators share: shared storage, bounded Arrow chunks, tokenizer files."""

from __future__ import annotations

import re
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

#: Text that one worker turns into Python or numpy objects at a time; a single longer text makes a chunk of its own.
CHUNK_BYTES = 1 << 20
#: Rows of a narrow table that a task reads at least, where there are as many.
NARROW_ROWS = 10_000


def ensure_checkpoint_dir(spark: SparkSession) -> None:
    """Uses spark.checkpoint.dir; where it is unset, a temporary folder is set on a single machine only."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        folder = spark.conf.get("spark.checkpoint.dir", None)
        if not folder and not re.fullmatch(r"local(\[[^\]]*\])?", sc.master):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all machines share")
        sc.setCheckpointDir(folder or tempfile.mkdtemp(prefix="planegrid-checkpoint-"))


def cut(df: DataFrame) -> DataFrame:
    """The same rows, written once to the shared checkpoint folder."""
    ensure_checkpoint_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def narrow(df: DataFrame, rows: int | None = None) -> DataFrame:
    """cut() for tables of narrow rows, which later stages read by a task for each NARROW_ROWS rows.

    A shuffle has as many partitions for a hundred rows as for all texts, and each is a task and a file in every stage
    that reads them. rows: how many there are at most; they are counted if it isn't given.
    """
    out = cut(df)
    rows = out.count() if rows is None else rows
    return out.coalesce(max(1, -(-rows // NARROW_ROWS)))


def stored(df: DataFrame) -> DataFrame:
    """The same rows, written as Parquet below the shared checkpoint folder, so that readers take only the columns they need."""
    ensure_checkpoint_dir(df.sparkSession)
    path = f"{df.sparkSession.sparkContext.getCheckpointDir()}/stored-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def public_file(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def split_pattern() -> str:
    import public_tokenizers

    return public_tokenizers.PATTERN


def chunks(batch: pa.RecordBatch, text: int) -> Iterator[pa.RecordBatch]:
    """Slices of batch of about CHUNK_BYTES of the text column each; every row is in one slice."""
    n = batch.num_rows
    if n == 0:
        return
    column = batch.column(text)
    ends = np.frombuffer(column.buffers()[1], dtype=np.int64 if pa.types.is_large_string(column.type) else np.int32, count=n + 1, offset=column.offset * (8 if pa.types.is_large_string(column.type) else 4))
    at = 0
    while at < n:
        to = int(np.searchsorted(ends, ends[at] + CHUNK_BYTES, side="right")) - 1
        to = min(n, max(at + 1, to))
        yield batch.slice(at, to - at)
        at = to
    pa.default_memory_pool().release_unused()  # idle workers stay alive and would hold it


class BoundedCache(dict):
    """Memo of make(key) within a number of bytes, so a worker's memory stays bounded.

    When half of the bytes are in use, the entries become the older half and what was older goes; an older entry that
    is asked for again moves back. So frequent keys stay. size(key, value): bytes of an entry beside what any entry
    takes, or None if it is not to be kept.
    """

    #: What an entry takes at least: its place in the table, the headers of key and value.
    ENTRY = 200

    def __init__(self, make, most: int, size):
        super().__init__()
        self.make, self.most, self.size, self.held, self.older = make, most, size, 0, {}

    def __missing__(self, key):
        value = self.older.pop(key, None)
        if value is None:
            value = self.make(key)
        more = self.size(key, value)
        if more is None:
            return value
        self.held += more + self.ENTRY
        if 2 * self.held > self.most:
            self.older = dict(self)
            self.clear()
            self.held = more + self.ENTRY
        self[key] = value
        return value
