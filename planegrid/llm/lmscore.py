"""Language-model scores by the likelihood of subword lattices.

A text is the sequence of its words, then one end. The pieces of an existing subword vocabulary each have a
probability, learned here from training rows; a word's probability is the sum over all its segmentations into
pieces, by a forward recursion in logarithms, and the text's is the product over words and the end. Piece
probabilities come from the counts of pieces in the vocabulary's own segmentation of every training word, each
raised by a half. Characters without a piece of their own are spelled with the vocabulary's byte pieces.

Beside it stands a plain baseline over whole words with half a count added to each.

Words are counted over the whole corpus. The most frequent ones, up to a fixed number, go to every worker, so a
word of any frequency is looked up in place; rows of the others meet their counts by a join, in which no key can
be hot. Sums are of integers (terms rounded at ten decimals), so results don't depend on the order of rows.

Rows: a null or empty text has the end alone. A null id counts as training. Repeated rows are counted each and
scored each. Other columns are not carried along, whatever their names. Without training rows, counts are 0.
"""

from __future__ import annotations

import hashlib
import math
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import runtime

#: Most frequent words that workers hold (about 200 bytes each), and words that a worker counts before it passes them on.
HEAD, FLUSH = 100_000, 200_000
SCALE = 10**10
_LOWER = bytes(range(65)) + bytes(range(97, 123)) + bytes(range(91, 256))


def is_training(id_col: Column) -> Column:
    """Rows whose crc32 of the id as text leaves no remainder 1 by 5."""
    return F.crc32(F.coalesce(id_col.cast("string"), F.lit(""))) % 5 != 1


def words_of(text: str | None) -> list[bytes]:
    """Runs of bytes other than ASCII white space, ASCII capitals lowered."""
    return text.encode().translate(_LOWER).split() if text else []


def _counted(docs: DataFrame, training_only: bool = False) -> DataFrame:
    """(word, c, n): every word, its occurrences in training rows and in all rows, which may be the same."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        every: Counter[bytes] = Counter()
        train: Counter[bytes] = Counter()

        def out():
            keys = list(every)
            batch = pa.RecordBatch.from_arrays([pa.array(keys, pa.binary()), pa.array(every.values() if training_only else [train[k] for k in keys], pa.int64()), pa.array(every.values(), pa.int64())], ["word", "c", "n"])
            every.clear()
            train.clear()
            return batch

        for batch in batches:
            for part in runtime.chunks(batch, 1):
                for text, use in zip(part.column(1).to_pylist(), part.column(2).to_pylist()):
                    found = words_of(text)
                    every.update(found)
                    if use and not training_only:
                        train.update(found)
                    if len(every) >= FLUSH:
                        yield out()
        yield out()

    return docs.select("doc_id", "text", "train").mapInArrow(run, "word binary, c long, n long").groupBy("word").agg(F.sum("c").alias("c"), F.sum("n").alias("n"))


_MODELS: dict[str, object] = {}


def _model(content: bytes):
    digest = hashlib.sha256(content).hexdigest()
    if digest not in _MODELS:
        import sentencepiece

        _MODELS[digest] = sentencepiece.SentencePieceProcessor(model_proto=content)
    return _MODELS[digest]


def _piece_counts(counts: DataFrame, shared) -> np.ndarray:
    """Occurrences of every piece in the training words; one row for each piece and task comes to be added up."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = _model(shared.value)
        total = np.zeros(model.get_piece_size(), dtype=np.int64)
        for batch in batches:
            for at in range(0, batch.num_rows, 5000):
                part = batch.slice(at, 5000)
                pieces = model.encode([w.decode() for w in part.column(0).to_pylist()], num_threads=1)
                weight = np.repeat(part.column(1).to_numpy(), [len(p) for p in pieces])
                np.add.at(total, np.array([i for p in pieces for i in p], dtype=np.int64), weight)
        used = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(used), pa.array(total[used])], ["piece", "c"])

    found = counts.where("c > 0").select("word", "c").mapInArrow(run, "piece long, c long").groupBy("piece").agg(F.sum("c").alias("c"))
    out = np.zeros(_model(shared.value).get_piece_size(), dtype=np.int64)
    for r in found.collect():  # at most one row for each piece of the vocabulary
        out[r.piece] = r.c
    return out


def _learned(counts: DataFrame, shared, ends: int) -> tuple[np.ndarray, float]:
    """Natural logarithms of the probabilities of all pieces, by id, and of the end."""
    pieces = _piece_counts(counts, shared) + 0.5
    total = pieces.sum() + ends + 0.5
    return np.log(pieces / total), math.log((ends + 0.5) / total)


def _training(df: DataFrame, id_col: str, text_col: str) -> DataFrame:
    text = F.col(text_col).cast("string")
    return df.select(F.col(id_col).alias("doc_id"), text.alias("text"), is_training(F.col(id_col)).alias("train"), F.xxhash64(F.coalesce(text, F.lit(""))).alias("mark"))


def learned_scores(df: DataFrame, vocabulary: str, id_col: str = "doc_id", text_col: str = "text") -> np.ndarray:
    """Natural logarithms of the probabilities of the vocabulary's pieces, by id, learned from df's training rows."""
    with open(vocabulary, "rb") as f:
        shared = df.sparkSession.sparkContext.broadcast(f.read())
    docs = _training(df, id_col, text_col).where("train")
    return _learned(runtime.cut(_counted(docs, training_only=True)), shared, docs.count())[0]


class Lattice:
    """log_p: natural logarithms of the probabilities of all pieces, by id."""

    def __init__(self, model, log_p: np.ndarray):
        import ahocorasick

        self.automaton, self.byte, self.single = ahocorasick.Automaton(), {}, set()
        for i in range(model.get_piece_size()):
            piece = model.id_to_piece(i)
            if model.is_byte(i):
                self.byte[int(piece[3:5], 16)] = float(log_p[i])
            elif not (model.is_control(i) or model.is_unknown(i) or model.is_unused(i)) and piece:
                self.automaton.add_word(piece, (len(piece), float(log_p[i])))
                if len(piece) == 1:
                    self.single.add(piece)
        self.automaton.make_automaton()

    def log_marginal(self, word: str) -> float:
        """Natural logarithm of the summed probability of all segmentations of a word, its boundary mark before it."""
        text = "▁" + word
        ends: list[list] = [[] for _ in text]
        for end, edge in self.automaton.iter(text):
            ends[end].append(edge)
        forward = [0.0]
        for k, (char, edges) in enumerate(zip(text, ends)):
            terms = [forward[k + 1 - n] + p for n, p in edges]
            if char not in self.single:
                terms.append(forward[k] + sum(self.byte[b] for b in char.encode()))
            top = max(terms)
            forward.append(top + math.log(sum(math.exp(x - top) for x in terms)) if len(terms) > 1 else top)
        return forward[-1]


def _scored(counts: DataFrame, shared, log_p: np.ndarray, total: int, kinds: int) -> DataFrame:
    """(word, n, known, base, score): base and score are logarithms to base 10, as integers."""
    weights = counts.sparkSession.sparkContext.broadcast(log_p)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lattice = Lattice(_model(shared.value), weights.value)
        for batch in batches:
            for at in range(0, batch.num_rows, 10_000):
                part = batch.slice(at, 10_000)
                c = part.column(1).to_numpy()
                base = np.rint(np.log10((c + 0.5) / (total + 0.5 * (kinds + 1))) * SCALE).astype(np.int64)
                score = [round(lattice.log_marginal(w.decode()) / math.log(10) * SCALE) for w in part.column(0).to_pylist()]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(2), pa.array((c > 0).astype(np.int64)), pa.array(base), pa.array(score, pa.int64())], ["word", "n", "known", "base", "score"])

    return counts.select("word", "c", "n").mapInArrow(run, "word binary, n long, known long, base long, score long")


def _frequent(scored: DataFrame) -> dict[bytes, tuple[int, int, int]]:
    """known, base and score of the most frequent words: all above a count, at most HEAD of them."""
    grade = F.floor(F.log2("n") * 8).cast("int")
    held, least = 0, None
    for r in scored.groupBy(grade.alias("grade")).count().orderBy(F.desc("grade")).collect():  # some hundreds of grades
        held += r["count"]
        if held > HEAD:
            break
        least = r.grade
    if least is None:
        return {}
    top = scored.where(grade >= least).select("word", "known", "base", "score").toArrow()
    return dict(zip(top.column(0).to_pylist(), zip(*(top.column(c).to_pylist() for c in (1, 2, 3)))))


def _rows(docs: DataFrame, head) -> DataFrame:
    """A row for each text with the sums of its frequent words, and one for each of its other words.

    (doc_id, train, mark, key, rows, tokens, known, base, score); key is the word, or for sums what no word can be.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known_words = head.value
        for batch in batches:
            for part in runtime.chunks(batch, 1):
                of, keys, rows, tokens, sums = [], [], [], [], []
                for k, (text, mark) in enumerate(zip(part.column(1).to_pylist(), part.column(3).to_pylist())):
                    n = known = base = score = 0
                    for word, times in Counter(words_of(text)).items():
                        n += times
                        if (found := known_words.get(word)) is not None:
                            known += times * found[0]
                            base += times * found[1]
                            score += times * found[2]
                        else:
                            of.append(k)
                            keys.append(word)
                            rows.append(0)
                            tokens.append(times)
                            sums.append((0, 0, 0))
                    of.append(k)
                    keys.append(b" %d" % mark)
                    rows.append(1)
                    tokens.append(n)
                    sums.append((known, base, score))
                table = np.array(sums, dtype=np.int64).reshape(-1, 3)
                index = pa.array(of, pa.int64())
                yield pa.RecordBatch.from_arrays(
                    [*(part.column(c).take(index) for c in (0, 2, 3)), pa.array(keys, pa.binary()), pa.array(rows, pa.int64()), pa.array(tokens, pa.int64()), *(pa.array(np.ascontiguousarray(table[:, c])) for c in range(3))],
                    ["doc_id", "train", "mark", "key", "rows", "tokens", "known", "base", "score"],
                )

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", "text", "train", "mark").mapInArrow(run, f"doc_id {kind}, train boolean, mark long, key binary, rows long, tokens long, known long, base long, score long")


def score(df: DataFrame, vocabulary: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row for each row of df: doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score.

    vocabulary: path on the driver of a sentencepiece model, whose content (under 1 MB) is broadcast.
    """
    spark = df.sparkSession
    with open(vocabulary, "rb") as f:
        content = f.read()
    shared = spark.sparkContext.broadcast(content)
    docs = _training(df, id_col, text_col)
    counts = runtime.cut(_counted(docs))
    ends = docs.where("train").count()
    words, kinds = counts.agg(F.coalesce(F.sum("c"), F.lit(0)), F.count_if(F.col("c") > 0)).first()
    total, kinds = words + ends, kinds + (ends > 0)
    log_p, log_end = _learned(counts, shared, ends)
    base_end = math.log10((ends + 0.5) / (total + 0.5 * (kinds + 1)))
    scored = runtime.cut(_scored(counts, shared, log_p, total, kinds))
    head = spark.sparkContext.broadcast(_frequent(scored))
    rows = _rows(docs, head).join(scored.select(F.col("word").alias("key"), F.col("known").alias("k"), F.col("base").alias("b"), F.col("score").alias("s")), "key", "left")
    own = {x: F.when(F.col("rows") == 1, F.col(x)).otherwise(F.col("tokens") * F.col(x[0])) for x in ("known", "base", "score")}
    found = rows.groupBy("doc_id", "train", "mark").agg(F.sum("rows").alias("rows"), F.sum(F.when(F.col("rows") == 1, F.col("tokens"))).alias("tokens"), *(F.sum(c).alias(x) for x, c in own.items()))
    # equal rows have been added up: each has its share
    each = found.withColumn("copy", F.explode(F.sequence(F.lit(1), F.col("rows").cast("int"))))
    whole = lambda x: F.expr(f"{x} div rows")
    return each.select(
        "doc_id",
        (~F.col("train")).alias("held_out"),
        (whole("tokens") + 1).alias("n_tokens"),
        (whole("known") + F.lit(int(ends > 0))).alias("n_known"),
        F.lit(total).cast("long").alias("train_tokens"),
        ((whole("base") + F.lit(round(base_end * SCALE))) / float(SCALE)).alias("base_score"),
        ((whole("score") + F.lit(round(log_end / math.log(10) * SCALE))) / float(SCALE)).alias("score"),
    )
