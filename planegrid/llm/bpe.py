"""Byte-level BPE encoding and decoding with an existing rank file.

A pre-token is encoded without simulating the merges: an Aho-Corasick automaton over the bytes (as Latin-1
characters) finds the longest vocabulary entry at every position, and a backtracking walk takes the longest
entry whose boundary with its left neighbour the merges would also leave alone. Whether two neighbours are
compatible is memoised. Each position is given up at most once, so the walk is linear in the text.

Rows: a null text counts as empty and encodes to no ids. Ids that are null or unknown cannot be decoded and
raise. Repeated rows stay. Other columns of the input are not carried along, whatever their names.
"""

from __future__ import annotations

import base64
import hashlib
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import runtime

#: Bytes that a worker's memos of pre-tokens and of neighbour pairs may take; pre-tokens beyond LONG characters are not kept.
WORD_BYTES, PAIR_BYTES, LONG = 48 << 20, 24 << 20, 64
#: Ids that are decoded at a time.
STEP = 1 << 17


class ByteTable:
    """The bytes of every id: all that decoding needs."""

    def __init__(self, ranks: dict[bytes, int]):
        bytes_of = {i: b for b, i in ranks.items()}
        size = max(bytes_of, default=-1) + 1
        self.sizes = np.array([len(bytes_of.get(i, b"")) for i in range(size)], dtype=np.int32)
        self.places = np.concatenate([[0], np.cumsum(self.sizes)])[:-1].astype(np.int32)
        self.blob = np.frombuffer(b"".join(bytes_of.get(i, b"") for i in range(size)), dtype=np.uint8)

    def lengths(self, ids: np.ndarray) -> np.ndarray:
        """How many bytes each id stands for."""
        if len(ids) and (ids.min() < 0 or ids.max() >= len(self.sizes)):
            raise ValueError("an id is not in the vocabulary")
        size = self.sizes[ids]
        if not size.all():
            raise ValueError("an id is not in the vocabulary")
        return size

    def decode(self, ids: np.ndarray, size: np.ndarray) -> bytes:
        """The bytes of all ids end to end; size: their lengths()."""
        out = []
        for at in range(0, len(ids), STEP):
            part, n = ids[at : at + STEP], size[at : at + STEP]
            ends = np.cumsum(n, dtype=np.int32)
            out.append(self.blob[np.repeat(self.places[part] - ends + n, n) + np.arange(ends[-1], dtype=np.int32)].tobytes())
        return b"".join(out)


class ByteVocabulary:
    """ranks: token bytes by id; an id is also the rank of the merge that makes the token."""

    def __init__(self, ranks: dict[bytes, int]):
        import ahocorasick

        self.id_of = ranks
        self.bytes_of = {i: b for b, i in ranks.items()}
        size = max(self.bytes_of, default=-1) + 1
        self.left, self.right = list(range(size)), list(range(size))
        self.joined: dict[tuple[int, int], int] = {}
        reachable = []
        for i in sorted(self.bytes_of):
            if len(token := self.bytes_of[i]) == 1:
                reachable.append(i)
            elif (parts := self._last_merge(token, i)) is not None:
                self.left[i], self.right[i] = parts
                self.joined[parts] = i
                reachable.append(i)
        made = {self.bytes_of[i] for i in reachable}
        self.shorter = [-1] * size
        self.automaton = ahocorasick.Automaton()
        for i in reachable:
            token = self.bytes_of[i]
            self.automaton.add_word(token.decode("latin-1"), (len(token), i))
            for n in range(len(token) - 1, 0, -1):
                if token[:n] in made:
                    self.shorter[i] = ranks[token[:n]]
                    break
        self.automaton.make_automaton()
        self.lengths = [len(self.bytes_of.get(i, b"")) for i in range(size)]
        self.fits = runtime.BoundedCache(self._fits, PAIR_BYTES, lambda pair, fits: 144)
        self.ids_of = runtime.BoundedCache(self._packed, WORD_BYTES, lambda piece, ids: 4 * len(piece) + len(ids) if len(piece) <= LONG else None)

    def _last_merge(self, token: bytes, rank: int) -> tuple[int, int] | None:
        """The two ids whose merge completes token, or None if the merges never build it."""
        parts = [self.id_of[token[k : k + 1]] for k in range(len(token))]
        while len(parts) > 2:
            best, at = min((self.joined.get(pair, rank), k) for k, pair in enumerate(zip(parts, parts[1:])))
            if best >= rank:
                return None
            parts[at : at + 2] = [best]
        return parts[0], parts[1]

    def _fits(self, pair: tuple[int, int]) -> bool:
        """Would the merges keep the boundary between two neighbours? Undo merges, latest first, and look across."""
        a, b = pair
        ceiling = len(self.left) + 1
        while True:
            if self.joined.get((a, b), ceiling) < ceiling:
                return False
            a_whole, b_whole = self.left[a] == a, self.left[b] == b
            if a_whole and b_whole:
                return True
            if b_whole or (not a_whole and a > b):
                ceiling, a = a, self.right[a]
            else:
                ceiling, b = b + 1, self.left[b]

    def encode_piece(self, piece: bytes) -> list[int]:
        """Ids of one pre-token, as repeated lowest-rank merges would give them."""
        if not piece:
            return []
        if (whole := self.id_of.get(piece)) is not None:
            return [whole]
        longest = [-1] * len(piece)
        for end, (length, token) in self.automaton.iter(piece.decode("latin-1")):
            longest[end - length + 1] = token  # matches come by their end, so the last is the longest
        size, shorter, fits, last = self.lengths, self.shorter, self.fits, len(piece)
        dead = bytearray(last + 1)
        out: list[int] = []
        at, token, before = 0, longest[0], -1
        while True:
            while token >= 0:
                to = at + size[token]
                if not dead[to] and (before < 0 or fits[before, token]):
                    break
                token = shorter[token]
            if token >= 0:
                out.append(token)
                if to == last:
                    return out
                at, before = to, token
                token = longest[at]
            else:
                dead[at] = 1
                token = out.pop()  # its end is dead now, so a shorter one takes its place
                at -= size[token]
                before = out[-1] if out else -1

    def _packed(self, piece: str) -> bytes:
        return array("I", self.encode_piece(piece.encode("utf-8"))).tobytes()

    def encode(self, pieces: list[str]) -> bytes:
        """Little-endian 32-bit ids of a text's pre-tokens."""
        return b"".join(map(self.ids_of.__getitem__, pieces))


def _ranks(content: bytes) -> dict[bytes, int]:
    return {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, content.splitlines())}


class _Shared:
    """A broadcast file; workers that stay alive build what they need of it once, by its digest."""

    def __init__(self, df: DataFrame, path: str):
        with open(path, "rb") as f:
            content = f.read()
        self.digest = hashlib.sha256(content).hexdigest()
        self.content = df.sparkSession.sparkContext.broadcast(content)

    def get(self, kind: type):
        found = _KEPT.get((kind.__name__, self.digest))
        if found is None:
            found = _KEPT[kind.__name__, self.digest] = kind(_ranks(self.content.value))
        return found


_KEPT: dict[tuple[str, str], ByteVocabulary | ByteTable] = {}


def encode(df: DataFrame, vocabulary: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows (doc_id, ids array<int>): the whole text's ids, each match of pattern encoded by itself.

    vocabulary: path of a rank file on the driver; its content (under 1 MB for 50,000 tokens) is broadcast.
    """
    shared = _Shared(df, vocabulary)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import regex

        vocab, find = shared.get(ByteVocabulary), regex.compile(pattern).findall
        for batch in batches:
            for part in runtime.chunks(batch, 1):
                rows = [vocab.encode(find(text)) if text else b"" for text in part.column(1).to_pylist()]
                flat = np.frombuffer(b"".join(rows), dtype="<u4").astype(np.int32)
                ends = np.cumsum([0, *(len(r) // 4 for r in rows)]).astype(np.int32)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.ListArray.from_arrays(pa.array(ends), pa.array(flat))], ["doc_id", "ids"])

    return df.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, _schema(df, id_col, "ids array<int>"))


def decode(df: DataFrame, vocabulary: str, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """Rows (doc_id, ids, decoded binary): the bytes that the ids stand for. Null ids decode to no bytes."""
    shared = _Shared(df, vocabulary)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = shared.get(ByteTable)
        for batch in batches:
            lists = batch.column(1).fill_null([])
            ends = lists.offsets.to_numpy()
            at = 0
            while at < batch.num_rows:
                to = max(at + 1, int(np.searchsorted(ends, ends[at] + STEP, side="right")) - 1)
                part = lists.slice(at, to - at)
                flat = part.flatten()
                if flat.null_count:
                    raise ValueError("an id is null")
                ids = flat.to_numpy()
                size = table.lengths(ids)
                places = np.concatenate([[0], np.cumsum(size, dtype=np.int64)])[ends[at : to + 1] - ends[at]]
                data = pa.py_buffer(table.decode(ids, size))
                decoded = pa.Array.from_buffers(pa.binary(), to - at, [None, pa.py_buffer(places.astype(np.int32)), data])
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(at, to - at), batch.column(1).slice(at, to - at), decoded], ["doc_id", "ids", "decoded"])
                at = to

    return df.select(F.col(id_col).alias("doc_id"), F.col(ids_col).alias("ids")).mapInArrow(run, _schema(df, id_col, "ids array<int>, decoded binary"))


def _schema(df: DataFrame, id_col: str, rest: str) -> str:
    return f"doc_id {df.select(id_col).schema[0].dataType.simpleString()}, {rest}"
