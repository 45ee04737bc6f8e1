"""Token counts under a unigram vocabulary, by dynamic programming shared along a trie's prefixes.

A pre-token is a word with the vocabulary's boundary mark before it; its token count is that of its best
segmentation, the one with the largest sum of piece scores (fewer tokens on ties). A worker inserts the distinct
pre-tokens into a trie. A node stands for a prefix and holds the prefix's forward score, worked out once when the
node is made: the pieces that the prefix's ends may still grow into go along from node to node, so each new character
only steps on in the vocabulary. It serves all pre-tokens below, also those that come later. Terminals' token counts
are stored by pre-token.

The vocabulary file gives pieces without probabilities. Scores are those that the language-model operator learns
for the same pieces from the training rows of a table, or any others given by piece id. A character without a
piece is spelled by the byte pieces, one token each.

Rows: a null or empty text has no pre-tokens and no tokens. Repeated rows and null ids are counted each. Texts
are handled where they lie: no text is shuffled. Other columns are not carried along, whatever their names.
"""

from __future__ import annotations

import gc
import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from . import runtime

#: Nodes that a worker's trie may have (about 700 bytes each) before it starts anew, characters of a pre-token that it
#: holds, bytes of stored terminal counts.
MOST_NODES, DEEP, TERMINAL_BYTES = 100_000, 200, 160 << 20
MARK = "▁"
_KEPT: dict[str, PrefixTrie] = {}


class PrefixTrie:
    """scores: of the pieces; byte_scores: of the 256 byte pieces.

    A node is [children by character, score, minus the tokens used, open pieces]; score and tokens are those of the
    best segmentation of the node's prefix. An open piece is (what may follow it in the vocabulary, score and minus
    tokens where it began).
    """

    def __init__(self, scores: dict[str, float], byte_scores: list[float]):
        self.scores, self.byte_scores = scores, byte_scores
        self.vocabulary: dict[str, list] = {}  # [what follows, score of the piece that ends here or None]
        for piece, score in scores.items():
            if not piece:
                continue
            here, last = self.vocabulary, None
            for char in piece:
                last = here.setdefault(char, [{}, None])
                here = last[0]
            last[1] = score
        self.terminals = runtime.BoundedCache(lambda w: self.count(MARK + w.decode()), TERMINAL_BYTES, lambda w, n: len(w))
        self.clear()

    def clear(self) -> None:
        self.root: list = [{}, 0.0, 0, [(self.vocabulary, 0.0, 0)]]
        self.nodes = 1

    @classmethod
    def from_model(cls, content: bytes, log_p: np.ndarray) -> PrefixTrie:
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_proto=content)
        byte, scores = [0.0] * 256, {}
        for i in range(model.get_piece_size()):
            if model.is_byte(i):
                byte[int(model.id_to_piece(i)[3:5], 16)] = float(log_p[i])
            elif not (model.is_control(i) or model.is_unknown(i) or model.is_unused(i)):
                scores[model.id_to_piece(i)] = float(log_p[i])
        return cls(scores, byte)

    def _below(self, node: list, char: str) -> list:
        """The node that char leads to."""
        most, fewest, going = None, 0, []
        for follows, score, tokens in node[3]:
            if char in follows:
                further, own = follows[char]
                if own is not None:
                    score_here = score + own
                    if most is None or score_here > most or (score_here == most and tokens - 1 > fewest):
                        most, fewest = score_here, tokens - 1
                if further:
                    going.append((further, score, tokens))
        if char not in self.scores:
            spelled = char.encode()
            score_here, tokens = node[1] + sum(self.byte_scores[b] for b in spelled), node[2] - len(spelled)
            if most is None or (score_here, tokens) > (most, fewest):
                most, fewest = score_here, tokens
        going.append((self.vocabulary, most, fewest))
        return [{}, most, fewest, going]

    def count(self, word: str) -> int:
        """Tokens of a pre-token; what is new of it is inserted, as far as it is not too deep."""
        if self.nodes > MOST_NODES:
            self.clear()
        node = self.root
        for char in word[:DEEP]:
            below = node[0].get(char)
            if below is None:
                below = node[0][char] = self._below(node, char)
                self.nodes += 1
            node = below
        for char in word[DEEP:]:
            node = self._below(node, char)
        return -node[2]

    def counts(self, texts: list[list[bytes]]) -> list[int]:
        """Tokens of each text's words. Nodes hold no cycles, so the collector needn't go through them."""
        known, on = self.terminals.__getitem__, gc.isenabled()
        gc.disable()
        try:
            return [sum(map(known, words)) for words in texts]
        finally:
            if on:
                gc.enable()


def count(df: DataFrame, vocabulary: str, log_p: np.ndarray, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row for each row of df: doc_id, n_pretokens, n_tokens.

    vocabulary: path on the driver of a sentencepiece model, whose content (under 1 MB) is broadcast; log_p: the
    score of each of its pieces, by id.
    """
    with open(vocabulary, "rb") as f:
        content = f.read()
    log_p = np.ascontiguousarray(log_p, dtype=np.float64)
    digest = hashlib.sha256(content + log_p.tobytes()).hexdigest()
    shared = df.sparkSession.sparkContext.broadcast((content, log_p))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if digest not in _KEPT:
            _KEPT.clear()
            _KEPT[digest] = PrefixTrie.from_model(*shared.value)
        trie = _KEPT[digest]
        for batch in batches:
            for part in runtime.chunks(batch, 1):
                # bytes.split() cuts at the same six bytes as words are defined by
                texts = [text.encode().split() if text else [] for text in part.column(1).to_pylist()]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(map(len, texts), pa.int64()), pa.array(trie.counts(texts), pa.int64())], ["doc_id", "n_pretokens", "n_tokens"])

    docs = df.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    schema = StructType([docs.schema["doc_id"], *StructType.fromDDL("n_pretokens long, n_tokens long")])
    return docs.mapInArrow(run, schema)
