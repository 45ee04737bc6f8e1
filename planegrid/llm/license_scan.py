"""License notices in texts: MinHash bands over overlapping word windows, verified by shingle containment.

Words are runs of letters, digits and bytes beyond ASCII, ASCII capitals lowered; a shingle is two words. For
every length among the templates a window slides over the text word by word. A window and a template are
compared if their smallest shingle hashes agree in at least one band (a band is one MinHash value). The number of
bands follows from the templates, the least containment and the chance of a miss that is allowed. A candidate
counts if the window holds at least `containment` of the template's distinct shingles; of overlapping matches of a
template the best one, then the first one, is reported.

Rows: null and empty texts have no matches. Repeated rows and null ids are scanned each. Templates need two
words. Texts are handled where they lie: nothing is shuffled. Other columns are not carried along.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from . import runtime, vectext
from .license_texts import TEXTS

U = np.uint64
_NONE = U(0xFFFFFFFFFFFFFFFF)


def bands_for(length: int, containment: float, miss: float) -> int:
    """Bands after which a window with the least containment collides but for a chance of miss."""
    shingles, inside = length - 1, window_of(length) - 1
    likeness = containment * shingles / (inside + (1 - containment) * shingles)
    return math.ceil(math.log(miss) / math.log(1 - likeness)) if likeness < 1 else 1


def window_of(length: int) -> int:
    return length + max(1, length // 5)


def _shingles(w: vectext.Words) -> np.ndarray:
    """A hash at every word for it and the next; none at a row's last word."""
    h = w.hashes()
    out = np.full(len(h), _NONE, dtype=np.uint64)
    if len(h) > 1:
        out[:-1] = vectext.windows(h, 2)
    last = w.first[1:][np.diff(w.first) > 0] - 1
    out[last] = _NONE
    return out


def _lane(shingles: np.ndarray, k: int) -> np.ndarray:
    """MinHash values of lane k, of which there are as many as asked for."""
    out = vectext.mix(vectext.mix(shingles ^ U((k + 1) * 0x9E3779B97F4A7C15 % (1 << 64))) * U(0xC2B2AE3D27D4EB4F))
    out[shingles == _NONE] = _NONE
    return out


def _sliding(values: np.ndarray, width: int) -> np.ndarray:
    """The least of width values from every place on; beyond the end there is nothing."""
    least, have = np.append(values, np.full(width - 1, _NONE, dtype=np.uint64)), 1
    while have < width:
        step = min(have, width - have)
        least = np.minimum(least[:-step], least[step:])
        have += step
    return least


def scan(df: DataFrame, templates: dict[str, str] = TEXTS, containment: float = 0.8, miss: float = 1e-5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row for each row of df: doc_id, matches (license, first and stop word, containment), by place."""
    names = sorted(templates)
    known = []
    for name in names:
        w = vectext.words(pa.array([templates[name]]), lower=True, space=vectext.PLAIN)
        if len(w.start) < 2:
            raise ValueError(f"{name} has fewer than two words")
        known.append((len(w.start), np.unique(_shingles(w)[:-1])))
    lengths = sorted({n for n, _ in known})
    bands = {n: bands_for(n, containment, miss) for n in lengths}
    signature = [[_lane(s, k).min() for k in range(bands[n])] for n, s in known]

    every = np.unique(np.concatenate([x for _, x in known])) if known else np.zeros(0, dtype=np.uint64)

    def candidates(shingles: np.ndarray, first: np.ndarray) -> dict[int, np.ndarray]:
        """By template: places of windows that agree in a band, in rows that have enough of its shingles anywhere."""
        out = {}
        hit = np.flatnonzero(np.isin(shingles, every))
        found, row = shingles[hit], np.searchsorted(first, hit, side="right") - 1
        for t, (n, wanted) in enumerate(known):
            mine = np.isin(found, wanted)
            enough = np.bincount(row[mine], minlength=len(first) - 1) >= containment * len(wanted)
            if not enough.any():
                continue
            at = np.flatnonzero(np.repeat(enough, np.diff(first)))
            some = shingles[at]
            agree = [np.flatnonzero(_sliding(_lane(some, k), window_of(n) - 1) == signature[t][k]) for k in range(bands[n])]
            out[t] = at[np.unique(np.concatenate(agree))]
        return out

    def of_rows(w: vectext.Words) -> list[list[tuple]]:
        shingles = _shingles(w)
        found: list[list[tuple]] = [[] for _ in range(len(w))]
        for t, places in candidates(shingles, w.first).items():
            n, wanted = known[t]
            rows = np.searchsorted(w.first, places, side="right") - 1
            best: tuple | None = None
            for row, at in zip(rows.tolist(), places.tolist()):
                stop = min(at + window_of(n) - 1, int(w.first[row + 1]) - 1)
                inside = np.flatnonzero(np.isin(shingles[at:stop], wanted))
                held = len(np.unique(shingles[at:stop][inside])) / len(wanted)
                if held < containment:
                    continue
                base = int(w.first[row])
                new = (row, at + int(inside[0]) - base, at + int(inside[-1]) + 2 - base, held)
                if best and best[0] == row and new[1] < best[2]:
                    best = new if held > best[3] else best
                else:
                    if best:
                        found[best[0]].append((best[1], best[2], names[t], best[3]))
                    best = new
            if best:
                found[best[0]].append((best[1], best[2], names[t], best[3]))
        return [sorted(x) for x in found]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = pa.list_(pa.struct([("license", pa.string()), ("first_word", pa.int32()), ("stop_word", pa.int32()), ("containment", pa.float64())]))
        for batch in batches:
            for part in runtime.chunks(batch, 1):
                rows = of_rows(vectext.words(part.column(1), lower=True, space=vectext.PLAIN))
                made = [[{"license": name, "first_word": a, "stop_word": b, "containment": held} for a, b, name, held in x] for x in rows]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(made, kind)], ["doc_id", "matches"])

    docs = df.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    schema = StructType([docs.schema["doc_id"], *StructType.fromDDL("matches array<struct<license:string,first_word:int,stop_word:int,containment:double>>")])
    return docs.mapInArrow(run, schema)
