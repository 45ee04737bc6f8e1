"""Near duplicates by an LSH forest over MinHash signatures, confirmed on full shingle sets.

A document's set holds its distinct runs of `width` words (ASCII capitals lowered); a text of fewer words has its
whole word sequence as one shingle, and one without words has an empty set and no links. Documents link if
100 * |intersection| >= percent * |union|; a component is what links reach.

Equal sets form a class first, so groups of copies collapse before anything is compared. Each class has a
signature; each tree of the forest sorts the classes by its own stretch of the signature. In a sorted order the
candidates of a class are the nearest rows before it and the first row of every region it lies in, from the
least depth down to the longest prefix it shares: sparse regions are compared at a shallow depth, dense ones at
a deep depth, and no region is ever expanded into pairs or gathered in one task. The order is range-partitioned;
what a partition needs of the one before it follows from a table with a few rows for each partition.

Candidates that a sketch of the whole signature rules out by more than five standard deviations are dropped, the
others are confirmed on the full sets: first the likeliest one of each class, then those whose ends the links so
far leave apart. Other columns of the input are not carried along, whatever their names.

Then the forest's least-depth regions that still hold several components are gone through in full: components
whose sketches allow a link anywhere in a region form a family, and in a family all texts of different components
are compared by their full sets. Large regions and families are dealt over tasks as pairs of blocks, a large
component's own blocks are not paired with each other, and only edges that join components come out. So a link is
missed only if its ends share no region at the least depth in any tree, or if the sketch rules it out.

Rows: null and empty texts have empty sets. A row with a null id gets a null component and is kept. Rows that
share an id are each judged by their own text; kept holds if the id is its component's smallest.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import runtime, vectext
from .components import of_few

U = np.uint64
#: The forest: trees, values in a tree's order, the depth from which rows count as neighbours, rows looked back.
TREES, DEPTH, LEAST, BACK = 16, 6, 2, 3
LANES = TREES * DEPTH
#: A block of a large region or family: rows and bytes of text; columns of a matrix of shingles.
BLOCK_ROWS, BLOCK_BYTES, COLUMNS = 2000, 8 << 20, 4096
#: Regions or members up to this many are broadcast (about 40 bytes each); more are joined by key.
MOST_BROADCAST = 300_000
_rng = np.random.default_rng(20240229)
_MULTIPLY = _rng.integers(0, 1 << 63, LANES, dtype=np.uint64) * U(2) + U(1)
_ADD = _rng.integers(0, 1 << 63, LANES, dtype=np.uint64)


def shingle_sets(column: pa.Array, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct shingle hashes of all rows end to end, and each row's first place, with the total."""
    w = vectext.words(column, lower=True)
    h = w.hashes()
    at, row = vectext.starts(w.first, width)
    short = np.flatnonzero((w.counts > 0) & (w.counts < width))
    values = np.concatenate([vectext.windows(h, width)[at], vectext.rows(h, w.first)[0][short]])
    row = np.concatenate([row, short])
    if len(short):
        order = np.argsort(row, kind="stable")
        values, row = values[order], row[order]
    first = np.searchsorted(row, np.arange(len(w) + 1))
    for a, b in zip(first[:-1], first[1:]):
        values[a:b].sort()
    new = np.ones(len(values), dtype=bool)
    new[1:] = (values[1:] != values[:-1]) | (row[1:] != row[:-1])
    return values[new], np.concatenate([[0], np.cumsum(np.bincount(row[new], minlength=len(w)))]).astype(np.int64)


def _fixed(data: np.ndarray, width: int) -> pa.Array:
    n = len(data)
    return pa.Array.from_buffers(pa.binary(), n, [None, pa.py_buffer((np.arange(n + 1) * width).astype(np.int32)), pa.py_buffer(np.ascontiguousarray(data).tobytes())])


def _bytes_of(column: pa.Array, width: int) -> np.ndarray:
    """A binary column whose values are all width long, as rows of bytes."""
    if not len(column):
        return np.zeros((0, width), dtype=np.uint8)
    at = np.frombuffer(column.buffers()[1], dtype=np.int32, count=1, offset=4 * column.offset)[0]
    return np.frombuffer(column.buffers()[2], dtype=np.uint8, count=len(column) * width, offset=at).reshape(-1, width)


def text_mark(text_col: str) -> Column:
    """Tells the rows of one id apart by their texts."""
    return F.xxhash64(F.coalesce(F.col(text_col).cast("string"), F.lit("")))


def sketches(docs: DataFrame, width: int) -> DataFrame:
    """(doc_id, mark, n, d, e, labels, bits): set size, 128 bits of the set, sort labels of all trees, two bits a lane."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in runtime.chunks(batch, 1):
                values, first = shingle_sets(part.column(1), width)
                size = np.diff(first)
                full = size > 0
                lanes = np.zeros((len(size), LANES), dtype=np.uint32)
                d, e = np.zeros(len(size), dtype=np.uint64), np.zeros(len(size), dtype=np.uint64)
                if len(values):
                    begin = first[:-1][full]
                    for k in range(LANES):
                        lanes[full, k] = np.minimum.reduceat(((values * _MULTIPLY[k] + _ADD[k]) >> U(32)).astype(np.uint32), begin)
                    d[full], e[full] = np.add.reduceat(vectext.mix(values), begin), np.bitwise_xor.reduceat(vectext.mix(values ^ U(0x5851F42D4C957F2D)), begin)
                spread = vectext.mix(lanes.astype(np.uint64) + U(0x9E37))
                labels = (spread >> U(48)).astype(">u2").view(np.uint8).reshape(len(size), 2 * LANES)
                two = (spread & U(3)).astype(np.uint8).reshape(len(size), LANES // 4, 4)
                bits = two[..., 0] | two[..., 1] << 2 | two[..., 2] << 4 | two[..., 3] << 6
                yield pa.RecordBatch.from_arrays(
                    [part.column(0), part.column(2), pa.array(size), pa.array(d.view(np.int64)), pa.array(e.view(np.int64)), _fixed(labels, 2 * LANES), _fixed(bits, LANES // 4)],
                    ["doc_id", "mark", "n", "d", "e", "labels", "bits"],
                )

    return docs.select("doc_id", "text", text_mark("text").alias("mark")).mapInArrow(run, "doc_id long, mark long, n long, d long, e long, labels binary, bits binary")


def _most_apart(percent: int) -> int:
    """Lanes of the two-bit sketch that may differ: five and a half deviations beyond the mean at the threshold."""
    p = (1 - percent / 100) * 0.75
    return int(np.ceil(LANES * p + 5.5 * np.sqrt(LANES * p * (1 - p))))


def _candidates(classes: DataFrame, percent: int) -> DataFrame:
    """(kind, part, tree, label, a, b, n, apart): pairs (kind 0), each partition's first row (1), its last regions (2)."""
    pieces = [F.struct(F.lit(t).alias("tree"), F.substring("labels", 2 * DEPTH * t + 1, 2 * DEPTH).alias("label")) for t in range(TREES)]
    rows = classes.select(F.explode(F.array(*pieces)).alias("at"), "doc_id", "n", "bits").select("at.tree", "at.label", "doc_id", "n", "bits")
    rows = rows.repartitionByRange("tree", "label", "doc_id").sortWithinPartitions("tree", "label", "doc_id")
    depths, limit = DEPTH - LEAST + 1, _most_apart(percent)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, began = TaskContext.get().partitionId(), False
        kept: list[np.ndarray] = []

        def out(kind, tree, label, a, b, n, apart):
            m = len(a)
            return pa.RecordBatch.from_arrays(
                [pa.array(np.full(m, kind, dtype=np.int32)), pa.array(np.full(m, part, dtype=np.int32)), pa.array(tree), _fixed(label, label.shape[1]), pa.array(a), pa.array(b), pa.array(n), pa.array(apart.astype(np.int32))],
                ["kind", "part", "tree", "label", "a", "b", "n", "apart"],
            )

        for batch in batches:
            if not batch.num_rows:
                continue
            new = [batch.column(0).to_numpy(), _bytes_of(batch.column(1), 2 * DEPTH), batch.column(2).to_numpy(), batch.column(3).to_numpy(), _bytes_of(batch.column(4), LANES // 4)]
            # before the batch stand the first rows of the open regions, by depth, and the last rows
            old = kept[0].shape[0] if kept else 0
            tree, label, ids, n, bits = [np.concatenate(x) for x in zip(kept, new)] if kept else new
            same = np.zeros((len(ids), DEPTH), dtype=bool)
            words = label.reshape(-1, DEPTH, 2)
            same[1:] = (words[1:] == words[:-1]).all(axis=2) & (tree[1:] == tree[:-1])[:, None]
            shared = np.minimum.accumulate(same, axis=1).sum(axis=1)
            shared[: min(len(shared), max(old - BACK, 0) + 1)] = 0
            here = np.arange(len(ids))
            if not began:
                yield out(1, tree[:1], label[:1], ids[:1], ids[:1], n[:1], np.zeros(1))
                began = True
            partners = []
            least = shared.copy()
            for back in range(1, BACK + 1):
                if back > 1:
                    least[back - 1 :] = np.minimum(least[back - 1 :], shared[: 1 - back])
                reach = least >= LEAST
                reach[:back] = False
                partners.append(np.where(reach, here - back, here))
            pivots = []
            for k in range(depths):
                begin = np.where(shared < LEAST + k, here, -1)
                if old:
                    begin[:old] = -1
                    begin[old - 1] = k  # the region that is open at this depth
                pivot = np.maximum.accumulate(begin)  # rows of the batch stand behind k, so the last begin wins
                pivots.append(pivot)
                partners.append(pivot)
            a, b = np.concatenate(partners), np.tile(here, len(partners))
            use = (a < b) & (b >= old) & (ids[a] != ids[b])
            a, b = a[use], b[use]
            fits = 100 * np.minimum(n[a], n[b]) >= percent * np.maximum(n[a], n[b])
            a, b = a[fits], b[fits]
            x = bits[a] ^ bits[b]
            apart = np.bitwise_count((x | x >> 1) & 0x55).sum(axis=1)
            near = apart <= limit
            a, b, apart = a[near], b[near], apart[near]
            lo, hi = np.minimum(ids[a], ids[b]), np.maximum(ids[a], ids[b])
            _, once = np.unique(np.stack([lo, hi]), axis=1, return_index=True)
            yield out(0, tree[b[once]], np.zeros((len(once), 0), dtype=np.uint8), lo[once], hi[once], n[b[once]], apart[once])
            last = np.arange(max(depths if old else 0, len(ids) - BACK), len(ids))
            take = np.concatenate([[p[-1] for p in pivots], np.repeat(last[:1], BACK - len(last)), last])
            kept = [x[take] for x in (tree, label, ids, n, bits)]
        if kept:
            yield out(2, *(kept[k] for k in (0, 1, 2, 2, 3)), np.zeros(depths + BACK))

    return rows.mapInArrow(run, "kind int, part int, tree int, label binary, a long, b long, n long, apart int")


def _pairs(classes: DataFrame, percent: int) -> DataFrame:
    """Distinct candidate pairs (a, b, apart), a < b."""
    found = runtime.cut(_candidates(classes, percent))
    heads = found.where("kind = 1").select("part", "tree", F.substring("label", 1, 2 * LEAST).alias("near"), F.col("a").alias("head"), F.col("n").alias("m"))
    heads = heads.withColumn("before", F.lag("part").over(Window.orderBy("part")))  # one row for each partition that has any
    tails = found.where("kind = 2").select(F.col("part").alias("before"), "tree", F.substring("label", 1, 2 * LEAST).alias("near"), F.col("a").alias("tail"), "n")
    crossing = heads.join(tails, ["before", "tree", "near"]).where(f"head != tail and 100 * least(m, n) >= {percent} * greatest(m, n)")
    pairs = found.where("kind = 0").select("a", "b", "apart").union(crossing.select(F.least("head", "tail"), F.greatest("head", "tail"), F.lit(LANES)))
    return pairs.groupBy("a", "b").agg(F.min("apart").alias("apart"))


def _confirmed(pairs: DataFrame, texts: DataFrame, width: int, percent: int) -> DataFrame:
    """The pairs (a, b) whose full sets link."""
    one = texts.toDF("a", "text_a")
    two = texts.toDF("b", "text_b")
    rows = pairs.select("a", "b").join(two, "b").join(one, "a").select("a", "b", "text_a", "text_b")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in runtime.chunks(batch, 3):
                whole = part.column(2)
                fresh = np.ones(len(whole), dtype=bool)  # rows of one document stand together: its set is made once
                fresh[1:] = pc.not_equal(whole.slice(1), whole.slice(0, len(whole) - 1)).fill_null(True).to_numpy(zero_copy_only=False)
                sets_a, at_a = shingle_sets(whole.filter(pa.array(fresh)), width)
                sets_b, at_b = shingle_sets(part.column(3), width)
                which = np.cumsum(fresh) - 1
                good = np.zeros(len(whole), dtype=bool)
                for k in range(len(whole)):
                    x, y = sets_a[at_a[which[k]] : at_a[which[k] + 1]], sets_b[at_b[k] : at_b[k + 1]]
                    both = len(np.intersect1d(x, y, assume_unique=True))
                    good[k] = both > 0 and 100 * both >= percent * (len(x) + len(y) - both)
                yield part.select([0, 1]).filter(pa.array(good))

    return rows.mapInArrow(run, "a long, b long")


def _small(rows: DataFrame) -> DataFrame:
    return F.broadcast(rows) if rows.count() <= MOST_BROADCAST else rows


def _dealt(rows: DataFrame, extra: list[str]) -> DataFrame:
    """Rows (key, comp, doc_id, bytes, *extra) of keys with several components, as (g, side, comp, doc_id, *extra), sorted by g.

    A small key is one group. Of a large one each two blocks are a group, side 0 and 1, so that every two rows of
    different components meet in a group (within side 0 if there is no side 1).
    """
    whole = rows.groupBy("key").agg(F.count("*").alias("c"), F.sum("bytes").alias("w"), F.min("comp").alias("lo"), F.max("comp").alias("hi")).where("lo != hi")
    whole = runtime.narrow(whole.select("key", F.greatest(F.ceil(F.col("c") / BLOCK_ROWS), F.ceil(F.col("w") / BLOCK_BYTES)).alias("parts")))
    columns = ["g", "side", "comp", "doc_id", *extra]
    out = rows.join(_small(whole.where("parts <= 1").select("key")), "key").select(F.col("key").alias("g"), F.lit(0).alias("side"), "comp", "doc_id", *extra)
    crowded = whole.where("parts > 1").select("key")
    if not crowded.isEmpty():
        many = runtime.cut(rows.join(_small(crowded), "key"))
        parts = lambda c, w: F.greatest(F.ceil(c / BLOCK_ROWS), F.ceil(w / BLOCK_BYTES)).cast("int")
        each = runtime.narrow(many.groupBy("key", "comp").agg(F.count("*").alias("c"), F.sum("bytes").alias("w")).withColumn("k", parts(F.col("c"), F.col("w"))))
        large = each.where("k > 1").select("key", "comp", "k")
        mixed = each.where("k <= 1").groupBy("key").agg(F.sum("c").alias("c"), F.sum("w").alias("w")).select("key", parts(F.col("c"), F.col("w")).alias("k"))
        block = lambda owner, part: F.struct(F.lit(owner is not None).alias("large"), (owner if owner is not None else F.lit(0).cast("long")).alias("owner"), part.alias("part"))
        at = lambda c: F.pmod(F.xxhash64(c), F.col("k")).cast("int")
        placed = many.join(large, ["key", "comp"]).select(*many.columns, block(F.col("comp"), at("doc_id")).alias("block"))
        rest = many.join(large, ["key", "comp"], "left_anti").join(mixed, "key").select(*many.columns, block(None, at("comp")).alias("block"))
        placed = runtime.cut(placed.unionByName(rest))
        blocks = runtime.narrow(placed.select("key", "block").distinct())
        two = blocks.withColumnRenamed("block", "x").join(blocks.withColumnRenamed("block", "y"), "key")
        two = runtime.narrow(two.where("x < y and not (x.large and y.large and x.owner = y.owner) or x = y and not x.large").withColumn("g", F.xxhash64("key", "x", "y")))
        for side, name in enumerate("xy"):
            pairs = two.where("x != y" if side else "true").select("key", F.col(name).alias("block"), "g")
            out = out.unionByName(placed.join(pairs, ["key", "block"]).withColumn("side", F.lit(side)).select(columns))
    return out.select(columns).repartition("g").sortWithinPartitions("g")


def _groups(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Batches sorted by their first column, dealt anew so that no value is in two of them."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        g = batch.column(0).to_numpy()
        last = int(np.flatnonzero(g != g[-1])[-1]) + 1 if (g != g[-1]).any() else 0
        if last or held and held[-1].column(0)[-1].as_py() != g[-1]:
            yield pa.Table.from_batches([*held, batch.slice(0, last)]).combine_chunks().to_batches()[0]
            held = []
        held.append(batch.slice(last))
    if held:
        yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]


def _join(root: np.ndarray, a: np.ndarray, b: np.ndarray) -> list[int]:
    """Joins a[k] and b[k] in root, whose entries point at their ends; the places k that joined two parts."""
    used = []
    for k, (x, y) in enumerate(zip(a.tolist(), b.tolist())):
        while root[x] != x:
            x = root[x]
        while root[y] != y:
            y = root[y]
        if x != y:
            root[max(x, y)] = min(x, y)
            used.append(k)
    if used:
        while (root[root] != root).any():
            root[:] = root[root]
    return used


def _edges(comp: np.ndarray, a: np.ndarray, b: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(comp[a]), pa.array(comp[b])], ["a", "b"])


def _families(classes: DataFrame, percent: int) -> DataFrame:
    """Edges (a, b) between components that a region and the sketches allow to link; classes with comp."""
    keys = F.array(*(F.xxhash64(F.lit(t), F.substring("labels", 2 * DEPTH * t + 1, 2 * LEAST)) for t in range(TREES)))
    rows = classes.select(F.explode(keys).alias("key"), "comp", "doc_id", F.lit(0).alias("bytes"), "n", "bits")
    limit = _most_apart(percent)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in _groups(batches):
            g, side, comp = (batch.column(k).to_numpy() for k in (0, 1, 2))
            n, bits = batch.column(4).to_numpy(), _bytes_of(batch.column(5), LANES // 4)
            two = np.isin(g, g[side == 1])
            _, start, root = np.unique(np.stack([g, comp]), axis=1, return_index=True, return_inverse=True)
            root = start[root.ravel()]
            here, d = np.arange(len(g)), 0
            while len(here):
                d += 1
                here = here[here < len(g) - d]
                here = here[g[here] == g[here + d]]
                a, b = here, here + d
                use = (root[a] != root[b]) & (~two[a] | (side[a] != side[b])) & (100 * np.minimum(n[a], n[b]) >= percent * np.maximum(n[a], n[b]))
                a, b = a[use], b[use]
                x = bits[a] ^ bits[b]
                near = np.bitwise_count((x | x >> 1) & 0x55).sum(axis=1) <= limit
                a, b = a[near], b[near]
                used = _join(root, a, b)
                if used:
                    yield _edges(comp, a[used], b[used])

    return _dealt(rows, ["n", "bits"]).mapInArrow(run, "a long, b long").distinct()


def _common(values: np.ndarray, first: np.ndarray, left: np.ndarray, right: np.ndarray) -> np.ndarray:
    """Sizes of the intersections of the sets of left with those of right."""
    _, column, times = np.unique(values, return_inverse=True, return_counts=True)
    row, shared = np.repeat(np.arange(len(first) - 1), np.diff(first)), times[column] > 1
    row, column = row[shared], (np.cumsum(times > 1) - 1)[column[shared]]
    order = np.argsort(column, kind="stable")
    row, column = row[order], column[order]
    out = np.zeros((len(left), len(right)), dtype=np.float32)
    at = np.full((2, len(first) - 1), -1)
    at[0, left], at[1, right] = np.arange(len(left)), np.arange(len(right))
    for low in range(0, int(column[-1]) + 1 if len(column) else 0, COLUMNS):
        a, b = np.searchsorted(column, [low, low + COLUMNS])
        sides = []
        for k, members in enumerate((left, right)):
            inside = at[k, row[a:b]]
            one = np.zeros((len(members), min(COLUMNS, int(column[-1]) + 1 - low)), dtype=np.float32)
            one[inside[inside >= 0], column[a:b][inside >= 0] - low] = 1
            sides.append(one)
        out += sides[0] @ sides[1].T
    return out


def _exact(members: DataFrame, width: int, percent: int) -> DataFrame:
    """Edges (a, b) between components with a link, from members (key, comp, doc_id, bytes, text): all texts of a key."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in _groups(batches):
            g = batch.column(0).to_numpy()
            bounds = [0, *(np.flatnonzero(g[1:] != g[:-1]) + 1).tolist(), len(g)]
            for begin, stop in zip(bounds[:-1], bounds[1:]):
                side, comp = (batch.column(k).to_numpy()[begin:stop] for k in (1, 2))
                values, first = shingle_sets(batch.column(4).slice(begin, stop - begin), width)
                n, here = np.diff(first), np.arange(stop - begin)
                left, right = (here[side == 0], here[side == 1]) if side.any() else (here, here)
                both = _common(values, first, left, right).astype(np.int64)
                links = (both > 0) & (100 * both >= percent * (n[left][:, None] + n[right][None, :] - both)) & (comp[left][:, None] != comp[right][None, :])
                a, b = np.nonzero(links)
                _, once = np.unique(np.stack([comp[left[a]], comp[right[b]]]), axis=1, return_index=True)
                _, start, root = np.unique(comp, return_index=True, return_inverse=True)
                root, a, b = start[root], left[a[once]], right[b[once]]
                used = _join(root, a, b)
                if used:
                    yield _edges(comp, a[used], b[used])

    return _dealt(members, ["text"]).mapInArrow(run, "a long, b long").distinct()


def _completed(docs: DataFrame, classes: DataFrame, joined: DataFrame, width: int, percent: int) -> DataFrame:
    """joined (node, component) with the links that crowded regions hold besides the candidates."""
    found = classes.join(joined.withColumnRenamed("node", "doc_id"), "doc_id", "left").select("doc_id", "n", "bits", "labels", F.coalesce("component", "doc_id").alias("comp"))
    found = runtime.narrow(found)
    maybe = runtime.narrow(_families(found, percent))
    if maybe.isEmpty():
        return joined
    family = of_few(maybe)
    named = runtime.narrow(maybe.select(F.explode(F.array("a", "b")).alias("comp")).distinct().join(family.withColumnRenamed("node", "comp"), "comp", "left").select("comp", F.coalesce("component", "comp").alias("key")))
    members = runtime.narrow(found.select("doc_id", "comp").join(named, "comp"))
    members = runtime.cut(docs.join(_small(members), "doc_id").select("key", "comp", "doc_id", F.octet_length("text").alias("bytes"), "text"))
    links = runtime.narrow(_exact(members, width, percent))
    if links.isEmpty():
        return joined
    moved = of_few(links).toDF("component", "to")
    return found.select(F.col("doc_id").alias("node"), F.col("comp").alias("component")).join(moved, "component", "left").select("node", F.coalesce("to", "component").alias("component"))


def near_duplicates(df: DataFrame, percent: int = 80, width: int = 5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row for each row of df: doc_id, n_shingles, component_id, kept, mark (text_mark() of the row); see the module."""
    docs = df.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    sketch = runtime.cut(sketches(docs, width))
    classes = runtime.narrow(sketch.where("n > 0 and doc_id is not null").groupBy("d", "e").agg(F.min("doc_id").alias("doc_id"), *(F.first(c).alias(c) for c in ("n", "labels", "bits"))))
    pairs = runtime.narrow(_pairs(classes, percent))
    wanted = pairs.select(F.explode(F.array("a", "b")).alias("doc_id")).distinct()
    texts = runtime.cut(docs.join(wanted, "doc_id").select("doc_id", "text"))
    best = pairs.groupBy("b").agg(F.min(F.struct("apart", "a")).alias("best")).select("best.a", "b")
    tree = runtime.narrow(_confirmed(best, texts, width, percent))
    first = runtime.narrow(of_few(tree))
    a, b = first.toDF("a", "at_a"), first.toDF("b", "at_b")
    ends = pairs.join(best, ["a", "b"], "left_anti").join(a, "a", "left").join(b, "b", "left").select("a", "b", F.coalesce("at_a", "a").alias("at_a"), F.coalesce("at_b", "b").alias("at_b"))
    apart = ends.where("at_a != at_b")
    linked = runtime.narrow(_confirmed(apart, texts, width, percent))
    joined = _completed(docs, classes, of_few(tree.union(linked)), width, percent)
    member = sketch.select("doc_id", "mark", "n", "d", "e")
    rep = classes.select("d", "e", F.col("doc_id").alias("node")).join(joined, "node", "left").select("d", "e", F.coalesce("component", "node").alias("component"))
    component = F.when(F.col("doc_id").isNotNull(), F.coalesce("component", "doc_id"))
    return member.join(runtime.narrow(rep), ["d", "e"], "left").select("doc_id", F.col("n").alias("n_shingles"), component.alias("component_id"), F.coalesce(F.col("doc_id") == F.coalesce("component", "doc_id"), F.lit(True)).alias("kept"), "mark")


def without_near_duplicates(df: DataFrame, percent: int = 80, width: int = 5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of df that are kept: a row goes if its own text is in a component with a smaller id.

    Rows that share an id but not a text are told apart.
    """
    found = near_duplicates(df, percent, width, id_col, text_col)
    gone = runtime.narrow(found.where("not kept").select(F.col("doc_id").alias("_gone_id"), F.col("mark").alias("_gone_mark")).distinct())
    # few enough are broadcast, so that texts needn't be shuffled
    return df.join(_small(gone), (F.col(f"`{id_col}`").cast("long") == F.col("_gone_id")) & (text_mark(f"`{text_col}`") == F.col("_gone_mark")), "left_anti")
