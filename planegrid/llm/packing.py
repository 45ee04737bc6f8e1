"""Token packing by power-of-two decomposition.

A document's ids, its end id included, are cut into pieces whose lengths are powers of two: as many full ones of
`most` as fit, then the binary digits of the rest, largest first. Equal lengths form a bucket. A piece is a
sequence of its own, so no sequence crosses documents and none needs padding.

Ids are those of the whole text by a tokenizers file of the byte-level BPE kind. Strings of special tokens in a text
are ordinary text, as the tokenizers library treats them with encode_special_tokens (the setting that the public
files' description prescribes); so a document can't forge an end.

Rows: a null or empty text has the end id alone. Repeated rows are packed one by one. Sequence ids rise with
the bucket (longest first), the document's id and the piece's start; they are unique, not dense. Rows that agree
in these and in their ids may swap their sequence ids. Other columns are not carried along, whatever their names.
"""

from __future__ import annotations

import hashlib
import json
import zlib
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import runtime

_KEPT: dict[str, object] = {}


def _byte_characters() -> dict[str, int]:
    """The characters by which byte-level tokenizer files write bytes: printable ones as they are, others from 256 on."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    others = [b for b in range(256) if b not in plain]
    return {chr(b): b for b in plain} | {chr(256 + k): b for k, b in enumerate(others)}


def _encoder(digest: str, content: str, pattern: str):
    """Text to its ids as uint32.

    The file's merges stand in the order of their ids, so its vocabulary is also a rank table, which the tiktoken
    library applies several times faster than the tokenizers library; the ids are the same. A text on which its
    pattern engine gives up goes through the slower encoder of this package.
    """
    if digest not in _KEPT:
        import regex
        import tiktoken

        from .bpe import ByteVocabulary

        model, byte = json.loads(content), _byte_characters()
        special = {x["content"] for x in model["added_tokens"]}
        ranks = {bytes(byte[c] for c in token): i for token, i in model["model"]["vocab"].items() if token not in special}
        fast = tiktoken.Encoding("ranks", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})
        slow: list[ByteVocabulary] = []

        def encode(text: str) -> np.ndarray:
            try:
                return fast.encode_to_numpy(text, disallowed_special=())
            except BaseException as x:  # the engine's panics aren't Exceptions, and their type has no name to import
                if type(x).__name__ not in ("PanicException", "ValueError"):
                    raise
                if not slow:
                    slow.append(ByteVocabulary(ranks))
                return np.frombuffer(slow[0].encode(regex.findall(pattern, text)), dtype="<u4")

        _KEPT[digest] = encode
    return _KEPT[digest]


def piece_lengths(total: int, most: int = 2048) -> list[int]:
    """most must be a power of two. The lengths add up to total."""
    rest = total % most
    return [most] * (total // most) + [1 << k for k in range(rest.bit_length() - 1, -1, -1) if rest >> k & 1]


def pieces(df: DataFrame, tokenizer: str, pattern: str, end_id: int, most: int = 2048, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = True) -> DataFrame:
    """Rows (doc_id, start, length, ids_crc32, doc_tokens[, ids array<int>]): the pieces of each row's text.

    tokenizer: path on the driver of a tokenizers file, whose content (under 2 MB) is broadcast; pattern: the
    pre-token pattern that it uses. ids can be left out where only the digest is asked for.
    """
    if most < 1 or most & (most - 1):
        raise ValueError("most must be a power of two")
    with open(tokenizer, encoding="utf-8") as f:
        content = f.read()
    digest = hashlib.sha256(content.encode()).hexdigest()
    shared = df.sparkSession.sparkContext.broadcast(content)
    end = array("I", [end_id]).tobytes()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = _encoder(digest, shared.value, pattern)
        for batch in batches:
            for part in runtime.chunks(batch, 1):
                row, start, length, crc, total, blobs = [], [], [], [], [], []
                for k, text in enumerate(part.column(1).to_pylist()):
                    ids = encode(text).astype("<u4", copy=False).tobytes() + end if text else end
                    at, n = 0, len(ids) // 4
                    for size in piece_lengths(n, most):
                        piece = ids[4 * at : 4 * (at + size)]
                        row.append(k)
                        start.append(at)
                        length.append(size)
                        crc.append(zlib.crc32(piece))
                        total.append(n)
                        if with_ids:
                            blobs.append(piece)
                        at += size
                out = [part.column(0).take(pa.array(row, pa.int64())), *(pa.array(x, pa.int64()) for x in (start, length, crc, total))]
                names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens"]
                if with_ids:
                    flat = pa.array(np.frombuffer(b"".join(blobs), dtype="<u4").astype(np.int32))
                    offsets = pa.array(np.concatenate([[0], np.cumsum(length)]).astype(np.int32))
                    out.append(pa.ListArray.from_arrays(offsets, flat))
                    names.append("ids")
                yield pa.RecordBatch.from_arrays(out, names)

    kind = df.select(id_col).schema[0].dataType.simpleString()
    schema = f"doc_id {kind}, start long, length long, ids_crc32 long, doc_tokens long" + ", ids array<int>" * with_ids
    return df.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, schema)


def pack(found: DataFrame) -> DataFrame:
    """Adds sequence_id and offset to pieces: each is a sequence of its own, numbered through the buckets.

    The pieces are written once, as range-partitioning looks at them twice, then range-partitioned by bucket, document and start, so a bucket's sequences lie together and
    large buckets spread over partitions.
    """
    order = [F.col("length").desc(), F.col("doc_id"), F.col("start"), F.col("doc_tokens"), F.col("ids_crc32")]
    return runtime.cut(found).repartitionByRange(*order).sortWithinPartitions(*order).select("*", F.monotonically_increasing_id().alias("sequence_id"), F.lit(0).cast("long").alias("offset"))
