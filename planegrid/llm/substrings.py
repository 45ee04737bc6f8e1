"""Removal of passages that repeat across documents, by Rabin-Karp hashes of every window of words.

A window is `size` consecutive words of one document. A word goes if a window over it has the same words as a
window of a document with a smaller id; windows are judged on the input. Windows that repeat merge into maximal
intervals of words.

Every window is hashed, but only windows that may repeat are shuffled. A window's anchor is the smallest hash
among its runs of size // 2 words, so equal windows have equal anchors, and a window whose anchor occurs in one
document only can't repeat. Whole copies of a document are settled by a digest of their words beforehand. What is
left is counted in Spark on 96 bits from two independent hashes, and the anchors agree as well.

Rows: a null or empty text has no words and loses none. A null id is smaller than none: its row stays whole and
removes nothing. Rows that share an id are one document for the rule, and each is judged and returned. Other
columns are not carried along, whatever their names. Empty tables give empty results.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from . import runtime, vectext

U = np.uint64
#: Ids of copies up to this many are broadcast (16 bytes each); more are joined by id.
MOST_BROADCAST = 1_000_000


def _anchors(w: vectext.Words, hashes: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of every window: its place, its row, its anchor."""
    at, row = vectext.starts(w.first, size)
    if not len(at):
        return at, row, np.zeros(0, dtype=np.int64)
    gram = max(1, size // 2)
    least, have, want = vectext.windows(hashes, gram), 1, size - gram + 1
    while have < want:
        step = min(have, want - have)
        least = np.minimum(least[:-step], least[step:])
        have += step
    return at, row, least[at].view(np.int64)


def _documents(df: DataFrame, id_col: str, text_col: str) -> DataFrame:
    return df.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))


def _digests(docs: DataFrame) -> DataFrame:
    """(doc_id, d, e): rows with the same words have the same 128 bits."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in runtime.chunks(batch, 1):
                w = vectext.words(part.column(1))
                both = [vectext.rows(w.hashes(family), w.first)[family] for family in (0, 1)]
                yield pa.RecordBatch.from_arrays([part.column(0), *(pa.array(x.view(np.int64)) for x in both)], ["doc_id", "d", "e"])

    return docs.where("doc_id is not null").mapInArrow(run, "doc_id long, d long, e long")


def _tags(hashes: np.ndarray, first: np.ndarray) -> np.ndarray:
    """31 bits of each row's words, to tell rows with one id apart; shifted past a place."""
    return (vectext.rows(hashes, first)[0] >> U(33)).astype(np.int64) << 32


def _anchor_rows(docs: DataFrame, size: int) -> DataFrame:
    """(anchor, doc_id), once for each run of windows with the anchor."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in runtime.chunks(batch, 1):
                w = vectext.words(part.column(1))
                _, row, anchor = _anchors(w, w.hashes(), size)
                new = np.ones(len(anchor), dtype=bool)
                new[1:] = (anchor[1:] != anchor[:-1]) | (row[1:] != row[:-1])
                yield pa.RecordBatch.from_arrays([pa.array(anchor[new]), part.column(0).take(pa.array(row[new]))], ["anchor", "doc_id"])

    return docs.mapInArrow(run, "anchor long, doc_id long")


def _window_rows(docs: DataFrame, size: int) -> DataFrame:
    """(h, g, doc_id, spot, later) of the windows with an anchor among the document's shared anchors.

    later: the anchor also occurs in a smaller document. spot: the row's tag and the window's place in the row.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in runtime.chunks(batch, 1):
                w = vectext.words(part.column(1))
                hashes = w.hashes()
                at, row, anchor = _anchors(w, hashes, size)
                lists = part.column(2)
                owner = np.repeat(np.arange(len(lists)), np.diff(lists.offsets.to_numpy()))
                entries = lists.flatten()
                known, later = entries.field(0).to_numpy(), entries.field(1).to_numpy(zero_copy_only=False)
                # anchors are looked up among those of their own row: both are sorted by row and anchor
                order = np.lexsort((known, owner))
                keys = np.rec.fromarrays([owner[order], known[order]])
                sought = np.lexsort((anchor, row))
                place = _search(owner[order], known[order], row[sought], anchor[sought])
                hit = np.zeros(len(at), dtype=bool)
                late = np.zeros(len(at), dtype=bool)
                if len(keys):
                    safe = np.minimum(place, len(keys) - 1)
                    found = (place < len(keys)) & (owner[order][safe] == row[sought]) & (known[order][safe] == anchor[sought])
                    hit[sought] = found
                    late[sought] = found & later[order][safe]
                at, row, late = at[hit], row[hit], late[hit]
                one, two = vectext.windows(hashes, size), vectext.windows(w.hashes(1), size, 1)
                spot = _tags(hashes, w.first)[row] | (at - w.first[row])
                yield pa.RecordBatch.from_arrays(
                    [pa.array(one[at].view(np.int64)), pa.array((two[at] >> U(32)).astype(np.uint32).view(np.int32)), part.column(0).take(pa.array(row)), pa.array(spot), pa.array(late)],
                    ["h", "g", "doc_id", "spot", "later"],
                )

    return docs.mapInArrow(run, "h long, g int, doc_id long, spot long, later boolean")


def _search(owner: np.ndarray, known: np.ndarray, row: np.ndarray, anchor: np.ndarray) -> np.ndarray:
    """For sorted pairs (row, anchor): the place of the first pair of sorted (owner, known) that isn't smaller."""
    both_row, both_key = np.concatenate([row, owner]), np.concatenate([anchor, known])
    side = np.concatenate([np.zeros(len(row), dtype=np.int8), np.ones(len(owner), dtype=np.int8)])
    order = np.lexsort((side, both_key, both_row))
    seen = np.cumsum(side[order])
    out = np.empty(len(row), dtype=np.int64)
    asked = order < len(row)
    out[order[asked]] = seen[asked]
    return out


def _cut_rows(marked: DataFrame, size: int, carried: list[str]) -> DataFrame:
    """The carried columns, n_words, n_removed, removed (intervals of words), kept (the words left, joined by one space)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in runtime.chunks(batch, 0):
                w = vectext.words(part.column(0))
                total, n = w.first[-1], len(w)
                lists, copy = part.column(1).fill_null([]), part.column(2).to_numpy(zero_copy_only=False)
                owner = np.repeat(np.arange(n), np.diff(lists.offsets.to_numpy()))
                spots = lists.flatten().to_numpy()
                mine = (spots >> 32 << 32) == _tags(w.hashes(), w.first)[owner]
                begin = w.first[owner[mine]] + (spots[mine] & 0xFFFFFFFF)
                change = np.zeros(total + 1, dtype=np.int64)
                np.add.at(change, begin, 1)
                np.add.at(change, begin + size, -1)
                whole = copy & (w.counts >= size)
                np.add.at(change, w.first[:-1][whole], 1)
                np.add.at(change, w.first[1:][whole], -1)
                gone = np.cumsum(change)[:total] > 0
                text, lengths = join_words(w, ~gone)
                gone_at = np.concatenate([[0], np.cumsum(gone)])
                n_removed = gone_at[w.first[1:]] - gone_at[w.first[:-1]]
                spans = _intervals(w, gone)
                offsets = pa.py_buffer(np.concatenate([[0], np.cumsum(lengths)]).astype(np.int32))
                kept = pa.StringArray.from_buffers(n, offsets, pa.py_buffer(text))
                more = [pa.array(w.counts.astype(np.int64)), pa.array(n_removed.astype(np.int64)), spans, kept]
                yield pa.RecordBatch.from_arrays([*(part.column(3 + k) for k in range(len(carried))), *more], [*carried, "n_words", "n_removed", "removed", "kept"])

    more = StructType.fromDDL("n_words long, n_removed long, removed array<struct<first:int,stop:int>>, kept string")
    schema = StructType([*(marked.schema[c] for c in carried), *more])
    own = [F.col("text").alias("_words_of"), F.col("spots").alias("_spots"), F.col("copy").alias("_copy")]
    return marked.select(*own, *carried).mapInArrow(run, schema)


def join_words(w: vectext.Words, keep: np.ndarray) -> tuple[bytes, np.ndarray]:
    """The kept words of each row joined by one space, end to end, and the length of each row's."""
    row = np.searchsorted(w.first, np.arange(w.first[-1]), side="right") - 1
    start, end, row = w.start[keep], w.end[keep], row[keep]
    more = np.zeros(len(row), dtype=bool)
    more[:-1] = row[1:] == row[:-1]  # a word after which another of its row follows brings its space along
    data = np.append(w.data, np.uint8(32))
    data[end[more]] = 32
    change = np.zeros(len(data) + 1, dtype=np.int8)
    np.add.at(change, start, 1)
    np.add.at(change, end + more, -1)
    taken = np.cumsum(change[:-1], dtype=np.int8).view(bool)
    return data[taken].tobytes(), np.bincount(row, weights=end - start + more, minlength=len(w)).astype(np.int64)


def _intervals(w: vectext.Words, gone: np.ndarray) -> pa.Array:
    edge = np.zeros(len(gone) + 1, dtype=bool)
    edge[w.first] = True
    begins = gone.copy()
    begins[1:] &= ~gone[:-1] | edge[1:-1]
    ends = gone.copy()
    ends[:-1] &= ~gone[1:] | edge[1:-1]
    first, stop = np.flatnonzero(begins), np.flatnonzero(ends) + 1
    row = np.searchsorted(w.first, first, side="right") - 1
    offsets = np.concatenate([[0], np.cumsum(np.bincount(row, minlength=len(w)))]).astype(np.int32)
    fields = [pa.array((x - w.first[row]).astype(np.int32)) for x in (first, stop)]
    return pa.ListArray.from_arrays(pa.array(offsets), pa.StructArray.from_arrays(fields, ["first", "stop"]))


def remove_repeats(df: DataFrame, size: int = 50, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row for each row of df: doc_id, n_words, n_removed, removed, kept; see the module."""
    marked = _marked(_documents(df, id_col, text_col), size)
    return _cut_rows(marked, size, ["doc_id"]).select("doc_id", "n_words", "n_removed", "removed", "kept")


def without_repeats(df: DataFrame, size: int = 50, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """df with its columns, where texts that lose words are replaced by the words left; no row goes."""
    docs = df.select(F.col(f"`{id_col}`").cast("long").alias("doc_id"), F.col(f"`{text_col}`").cast("string").alias("text"), F.struct(*(F.col(f"`{c}`") for c in df.columns if c != text_col)).alias("rest"))
    cut = _cut_rows(_marked(docs, size), size, ["doc_id", "rest", "text"])
    text = F.when(F.col("n_removed") > 0, F.col("kept")).otherwise(F.col("text"))
    return cut.select(text.alias(text_col), "rest.*").select(df.columns)


def _turned(name: str) -> Column:
    return F.bitwise_not(F.col(name))


def _several(rows: DataFrame, keys: list[str]) -> DataFrame:
    """(keys, first_id) of the keys with more than one document, the first key turned.

    A turned key makes Spark shuffle these rows for a join with rows of the same key, rather than joining in the
    partitions of the count; only then can it split the partitions of frequent keys at run time.
    """
    found = rows.groupBy(*keys).agg(F.min("doc_id").alias("first_id"), F.max("doc_id").alias("last_id")).where("first_id < last_id")
    return found.select(_turned(keys[0]).alias(keys[0]), *keys[1:], "first_id")


def _marked(docs: DataFrame, size: int) -> DataFrame:
    """docs with spots (where windows to remove start, with the rows' tags) and copy (all of the words are an earlier document's)."""
    digests = _digests(docs.select("doc_id", "text"))
    firsts = _several(digests, ["d", "e"])
    copies = digests.withColumn("d", _turned("d")).join(firsts, ["d", "e"], "left").groupBy("doc_id").agg(F.bool_and(F.coalesce(F.col("doc_id") > F.col("first_id"), F.lit(False))).alias("copy")).where("copy")
    copies = runtime.cut(copies)
    named = docs.join(copies, "doc_id", "left").withColumn("copy", F.coalesce("copy", F.lit(False)))
    heads = named.where("doc_id is not null and not copy").select("doc_id", "text")

    # texts need no shuffle here: anchors of copies go afterwards
    anchors = _anchor_rows(docs.where("doc_id is not null").select("doc_id", "text"), size)
    gone = copies.select("doc_id")
    anchors = anchors.join(F.broadcast(gone) if gone.count() <= MOST_BROADCAST else gone, "doc_id", "left_anti")
    shared = _several(anchors, ["anchor"])
    met = anchors.withColumn("turned", _turned("anchor")).join(shared.withColumnRenamed("anchor", "turned"), "turned")
    held = met.groupBy("doc_id").agg(F.collect_set(F.struct("anchor", (F.col("doc_id") > F.col("first_id")).alias("later"))).alias("anchors"))
    held = runtime.cut(held)
    windows = _window_rows(heads.join(held, "doc_id").select("doc_id", "text", "anchors"), size)
    least = _several(windows, ["h", "g"])
    found = windows.where("later").withColumn("h", _turned("h")).join(least, ["h", "g"]).where("doc_id > first_id").groupBy("doc_id").agg(F.collect_set("spot").alias("spots"))
    return named.join(found, "doc_id", "left")
