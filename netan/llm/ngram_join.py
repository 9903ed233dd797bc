"""N-gram Jaccard join with a count-vector R-tree.

A document's set holds its 4-word shingles; documents of equal sets are one class. Two classes link when the sets' Jaccard
similarity is the threshold or more. There are two forms. `similar` gives membership in components, exactly, from links enough to
join them; op8's query and the pipeline use it. `every_link` gives all links between classes, and `link_counts` their number
for each class; their pairs are all that pass the bounds, so groups of near copies cost their size squared.

Joined first. Every class has a few signatures, each the hash of some least shingles. Classes of one signature are verified
against the group's first and last class, and those that link are contracted: a large group of near copies is mostly one
component before any pairs are sought. This step decides nothing but which pairs need no look.

Routing. Under any order of all shingles that is the same for all documents, two sets that link share one of their first
n - ceil(t n) + 1 shingles. The order puts common shingles last: a count sketch of fixed size over all shingles of the corpus
gives coarse levels of frequency; within a level long shingles come before short ones, then hashes decide. So documents are
dealt by rare shingles, and boilerplate makes no large groups. At the first shingle that two sets share, what is left of
either holds their whole overlap, so a pair whose rest is too short there is left to its other shingles.

Count vectors. Shingles are hashed into groups; a class is the point of its group counts. The sum of the coordinates' minima
of two points is at least their overlap. The points of each dealt shingle make an R-tree (up to LEAF of them are one leaf), which is
asked for every point; nodes whose bounding box can't reach the bound are left out. Pairs within a component that is
already known are left out too; what the tree finds is verified on the whole sets. At first only the best pair of each class
that is not in its shingle's largest component is, then, with what that has joined, all pairs still apart. A shingle with more than BLOCK classes is
dealt in blocks: classes of its largest component meet the others only, block by block.

Nulls, and texts without words, have no shingles and link with nothing; fewer words than four make one shingle. Rows that
repeat are one class. The component of a row with a null id is the smallest id that is not null, if there is one. Columns
beside id and text, those with names used here included, are not read. Very long texts are one set like any other. Empty
tables give no rows.
"""

from __future__ import annotations

import zlib
from itertools import chain

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from netan.contraction import contract
from netan.llm.common import arrow_map, fields, keyed, row_key, same_row
from netan.llm.substring_dedup import BASE, WordHashes, mixed
from netan.storage import drop, lasting, scratch, written

GROUPS = 128
#: Signatures of a class, and least shingles in each.
SIGNATURES, MINIMA = 8, 3
#: Characters of texts that are cut in shingles at once.
TEXT_CHARS = 1 << 20
SKETCH_BITS = 22
SKETCH_BLOCK = 1 << 14
LEAF = 32
#: Classes of a key that are looked at together; those of larger keys are dealt in blocks of about as many.
BLOCK = 4000
#: Rows with count vectors that a worker gathers before it looks at them, and pairs of vectors (1 KB each) that it compares at once.
HELD_ROWS, COMPARED = 16_000, 8_000
#: Classes, 24 bytes each, that are broadcast at most.
SENT_CLASSES = 500_000


def _lowered(text: str | None) -> list[bytes]:
    return text.encode().lower().split() if text else []


def _pieces(column):
    """(texts, a, b): a column's texts in ranges of about TEXT_CHARS bytes; only one range is out of its Arrow array at a time."""
    import pyarrow.compute as pc

    sizes = pc.fill_null(pc.binary_length(column), 0).to_numpy(zero_copy_only=False).astype(np.int64)
    lot = (np.cumsum(sizes) - sizes) // TEXT_CHARS
    starts = np.flatnonzero(np.concatenate(([True], lot[1:] != lot[:-1]))) if len(lot) else lot
    for a, b in zip(starts.tolist(), [*starts[1:].tolist(), len(lot)]):
        yield column.slice(a, b - a).to_pylist(), a, b


def shingle_sets(hashes: WordHashes, split: list[list[bytes]], size: int, lengths: bool = False):
    """For each text: its different shingle hashes in ascending order, and the lengths in bytes of these shingles (63 at most)."""
    words = hashes.of(split)
    h = np.zeros(max(0, len(words) - size + 1), np.uint64)
    for j in range(size):
        h = h * BASE + words[j : len(h) + j]
    h = mixed(h)
    none = length = np.zeros(0, np.int64)
    if lengths:
        long = np.fromiter(map(len, chain.from_iterable(split)), np.int64, len(words))
        total = np.concatenate(([0], np.cumsum(long)))
        length = np.minimum(63, total[size:] - total[:-size])[: len(h)] if len(h) else none
    at = 0
    for x in split:
        n = len(x)
        if n >= size and lengths:
            u, first = np.unique(h[at : at + n - size + 1], return_index=True)
            yield u, length[at + first]
        elif n >= size:
            u = np.sort(h[at : at + n - size + 1])
            yield u[np.concatenate(([True], u[1:] != u[:-1]))], none
        elif n:
            short = np.array([n], np.uint64)
            for k in range(at, at + n):
                short = short * BASE + words[k]
            yield mixed(short), np.array([min(63, sum(map(len, x)))])
        else:
            yield np.zeros(0, np.uint64), np.zeros(0, np.int64)
        at += n


def _class_of(u: np.ndarray) -> int:
    """Number of a set of shingles: a hash of their xor, sum and count."""
    parts = np.array([np.bitwise_xor.reduce(mixed(u + np.uint64(1))), u.sum(dtype=np.uint64), len(u)], np.uint64)
    return int(mixed(parts[:1] * BASE + mixed(parts[1:2] + mixed(parts[2:]))).view(np.int64)[0])


def _bounds(parts: int) -> np.ndarray:
    """Least hash of each of so many equal ranges."""
    return (np.arange(parts, dtype=np.float64) / parts * 2.0**64).astype(np.uint64)


GROUP_BOUNDS = _bounds(GROUPS)
RANGE_BOUNDS = _bounds(SIGNATURES * MINIMA)
#: Tells signatures of different places apart.
PLACES = mixed(np.arange(1, SIGNATURES + 1, dtype=np.uint64))


def point(u: np.ndarray) -> bytes:
    """Group counts of sorted shingles."""
    return np.diff(np.append(np.searchsorted(u, GROUP_BOUNDS), len(u))).astype("<u4").tobytes()


def signatures(u: np.ndarray) -> np.ndarray:
    """Hashes of the least shingles of ranges; an empty range takes that of the next."""
    least = u[np.searchsorted(u, RANGE_BOUNDS) % len(u)].reshape(SIGNATURES, MINIMA)
    h = PLACES.copy()
    for j in range(MINIMA):
        h = mixed(h * BASE + least[:, j])
    return h.view(np.int64)


def profile(rows: DataFrame, size: int) -> DataFrame:
    """One table of documents (doc_id, rid, n, sid, vec, marks) and of a count sketch of their shingles (block, counts)."""

    def work(batches):
        hashes, sketch = WordHashes(), np.zeros(1 << SKETCH_BITS, np.uint32)
        none = None
        mask = np.uint64((1 << SKETCH_BITS) - 1)
        for batch in batches:
            for texts, a, b in _pieces(batch.column(1)):
                ns, sids, vecs, marks = [], [], [], []
                for u, _ in shingle_sets(hashes, [_lowered(t) for t in texts], size):
                    ns.append(len(u))
                    sids.append(_class_of(u) if len(u) else None)
                    vecs.append(point(u) if len(u) else None)
                    marks.append(signatures(u) if len(u) else None)
                    np.add.at(sketch, (u & mask).astype(np.int32), np.uint32(1))
                yield {"doc_id": batch.column(0).slice(a, b - a), "rid": batch.column(2).slice(a, b - a), "n": ns, "sid": sids, "vec": vecs, "marks": marks, "block": [none] * (b - a), "counts": [none] * (b - a)}
        if sketch.any():
            k = len(sketch) // SKETCH_BLOCK
            yield {c: [none] * k for c in ("doc_id", "rid", "n", "sid", "vec", "marks")} | {"block": list(range(k)), "counts": [zlib.compress(sketch[i * SKETCH_BLOCK : (i + 1) * SKETCH_BLOCK].tobytes(), 1) for i in range(k)]}

    long, binary = T.LongType(), T.BinaryType()
    schema = T.StructType([*fields(rows, "doc_id", "rid"), T.StructField("n", long), T.StructField("sid", long), T.StructField("vec", binary), T.StructField("marks", T.ArrayType(long)), T.StructField("block", T.IntegerType()), T.StructField("counts", binary)])
    return arrow_map(rows, work, schema)


def _levels(sketches: DataFrame) -> np.ndarray:
    """Frequency level of each counter: 0 up to twice the mean, then one more each time the count doubles."""
    import pyarrow as pa

    def summed(batches):
        total: dict[int, np.ndarray] = {}
        for batch in batches:
            for block, raw in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                part = np.frombuffer(zlib.decompress(raw), "<u4").astype(np.uint64) if len(raw) != 8 * SKETCH_BLOCK else np.frombuffer(raw, "<u8")
                total[block] = total[block] + part if block in total else part
        yield {"block": list(total), "counts": [x.astype("<u8").tobytes() for x in total.values()]}

    schema = T.StructType([T.StructField("block", T.IntegerType()), T.StructField("counts", T.BinaryType())])
    part = arrow_map(sketches, summed, schema)

    def met(found: pa.Table) -> pa.Table:
        """A block's sum, and the logarithm of each counter, in quarters of a power of two."""
        total = sum(np.frombuffer(x, "<u8") for x in found.column("counts").to_pylist())
        size = np.round(4 * np.log2(np.maximum(total, 1))).astype(np.uint8)
        return pa.table({"block": pa.array([found.column("block")[0].as_py()], pa.int32()), "sum": pa.array([int(total.sum())], pa.int64()), "sizes": pa.array([size.tobytes()], pa.binary())})

    sizes, total = np.zeros(1 << SKETCH_BITS, np.uint8), 0
    for r in part.groupBy("block").applyInArrow(met, "block int, sum long, sizes binary").collect():
        sizes[r["block"] * SKETCH_BLOCK : (r["block"] + 1) * SKETCH_BLOCK] = np.frombuffer(r["sizes"], np.uint8)
        total += r["sum"]
    table = np.clip(np.ceil(np.arange(256) / 4 - np.log2(2 * total / len(sizes) + 8)), 0, 60).astype(np.uint8)
    return table[sizes]


def route(rows: DataFrame, levels: np.ndarray, size: int, per_cent: int) -> DataFrame:
    """(key, sid, n, at) for the first shingles of each document under the common order; a task gives each class once."""
    sent = rows.sparkSession.sparkContext.broadcast(levels)

    def work(batches):
        hashes, level, seen = WordHashes(), sent.value, set()
        mask, low = np.uint64((1 << SKETCH_BITS) - 1), np.uint64((1 << 50) - 1)
        for batch in batches:
            for texts, a, b in _pieces(batch.column(1)):
                keys, sids, ns, each = [], [], [], []
                for u, length in shingle_sets(hashes, [_lowered(t) for t in texts], size, True):
                    n = len(u)
                    if not n or (sid := _class_of(u)) in seen:
                        continue
                    seen.add(sid)
                    most = n - -(-per_cent * n // 100) + 1
                    order = level[(u & mask).astype(np.int64)].astype(np.uint64) << np.uint64(56) | (63 - length).astype(np.uint64) << np.uint64(50) | u & low
                    if most < n // 2:  # only the first ones need be put in order; equal places are settled by u
                        some = np.flatnonzero(order <= np.partition(order, most - 1)[most - 1])
                        some = some[np.argsort(order[some], kind="stable")[:most]]
                    else:
                        some = np.argsort(order, kind="stable")[:most]
                    keys.append(u[some])
                    sids.append(sid)
                    ns.append(n)
                    each.append(most)
                if keys:
                    yield {"key": np.concatenate(keys).view(np.int64), "sid": np.repeat(sids, each), "n": np.repeat(ns, each), "at": np.concatenate([np.arange(k) for k in each])}

    schema = T.StructType([T.StructField("key", T.LongType()), T.StructField("sid", T.LongType()), T.StructField("n", T.IntegerType()), T.StructField("at", T.IntegerType())])
    return arrow_map(rows, work, schema)


class CountTree:
    """R-tree over count vectors, packed by splits at medians of the widest coordinate."""

    def __init__(self, points: np.ndarray, leaf: int = LEAF) -> None:
        self.order = np.arange(len(points))
        cuts = self._split(points, 0, len(points), leaf)
        self.points = points[self.order]
        self.sizes = self.points.sum(axis=1)
        starts = np.array(cuts)
        self.levels = []  # from the leaves up: first child, last child + 1, greatest coordinates, least and greatest size
        first, last = starts, np.append(starts[1:], len(points))
        hi, lo_n, hi_n = np.maximum.reduceat(self.points, first), np.minimum.reduceat(self.sizes, first), np.maximum.reduceat(self.sizes, first)
        self.levels.append((first, last, hi, lo_n, hi_n))
        while len(first) > 16:
            first = np.arange(0, len(hi), 8)
            last = np.append(first[1:], len(hi))
            hi, lo_n, hi_n = np.maximum.reduceat(hi, first), np.minimum.reduceat(lo_n, first), np.maximum.reduceat(hi_n, first)
            self.levels.append((first, last, hi, lo_n, hi_n))

    def _split(self, points: np.ndarray, a: int, b: int, leaf: int) -> list[int]:
        if b - a <= leaf:
            return [a]
        mine = self.order[a:b]
        wide = np.ptp(points[mine], axis=0).argmax()
        self.order[a:b] = mine[np.argsort(points[mine, wide], kind="stable")]
        m = (a + b) // 2
        return self._split(points, a, m, leaf) + self._split(points, m, b, leaf)

    def near(self, point: np.ndarray, per_cent: int) -> np.ndarray:
        """Numbers of the points whose summed minima with this one allow for the similarity."""
        n = int(point.sum())
        nodes = np.arange(len(self.levels[-1][0]))
        for first, last, hi, lo_n, hi_n in reversed(self.levels):
            bound = np.minimum(hi[nodes], point).sum(axis=1)
            ok = ((100 + per_cent) * bound >= per_cent * (n + lo_n[nodes])) & (100 * hi_n[nodes] >= per_cent * n) & (100 * n >= per_cent * lo_n[nodes])
            nodes = nodes[ok]
            if not len(nodes):
                return nodes
            nodes = np.concatenate([np.arange(first[k], last[k]) for k in nodes])
        ok = (100 + per_cent) * np.minimum(self.points[nodes], point).sum(axis=1) >= per_cent * (n + self.sizes[nodes])
        return self.order[nodes[ok]]


def _points(column) -> np.ndarray:
    """Count vectors of a binary column, from its own memory: all have one length, so they lie one after another."""
    at = 4 * GROUPS * column.offset
    return np.frombuffer(column.buffers()[2], np.uint8)[at : at + 4 * GROUPS * len(column)].view("<u4").reshape(-1, GROUPS).astype(np.int32) if len(column) else np.zeros((0, GROUPS), np.int32)


def _close(points: np.ndarray, others: np.ndarray, i: np.ndarray, j: np.ndarray, per_cent: int) -> np.ndarray:
    """Which pairs (points[i], others[j]) allow for the similarity, by sizes and summed minima."""
    ok = np.zeros(len(i), bool)
    for k in range(0, len(i), COMPARED):
        x, y = points[i[k : k + COMPARED]], others[j[k : k + COMPARED]]
        m, n = x.sum(axis=1, dtype=np.int64), y.sum(axis=1, dtype=np.int64)
        least = np.minimum(x, y).sum(axis=1, dtype=np.int64)
        ok[k : k + COMPARED] = ((100 + per_cent) * least >= per_cent * (m + n)) & (100 * np.minimum(m, n) >= per_cent * np.maximum(m, n))
    return ok


PAIRS = T.StructType([T.StructField("a", T.LongType()), T.StructField("b", T.LongType())])


def _tree_pairs(dealt: DataFrame, per_cent: int, best: bool = False) -> DataFrame:
    """(a, b): pairs of different components and sides within each key that pass the bounds; dealt: sorted by key within partitions.

    best: of these, for each class outside the key's largest component only the one with the highest bound.
    """

    def room(n: np.ndarray, at: np.ndarray, i, j) -> np.ndarray:
        """Whether an overlap that begins with this shingle can be large enough."""
        return (100 + per_cent) * np.minimum(n[i] - at[i], n[j] - at[j]) >= per_cent * (n[i] + n[j])

    def nearest(key: np.ndarray, others: np.ndarray, points: np.ndarray, n: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Which pairs (a, b) of places are the best of either end, if that is one of the others."""
        score = np.concatenate([np.minimum(points[a[k : k + COMPARED]], points[b[k : k + COMPARED]]).sum(axis=1) for k in range(0, len(a), COMPARED)])
        score = score / (n[a] + n[b])
        end, pair = np.concatenate((a, b)), np.tile(np.arange(len(a)), 2)
        mine = others[end]
        end, pair = end[mine], pair[mine]
        order = np.lexsort((-score[pair], end))
        first = np.concatenate(([True], np.diff(end[order]) != 0)) if len(order) else np.zeros(0, bool)
        return np.unique(pair[order][first])

    def pairs(key: np.ndarray, sid: np.ndarray, comp: np.ndarray, side: np.ndarray, n: np.ndarray, at: np.ndarray, others: np.ndarray, points: np.ndarray) -> dict:
        """Trees of one leaf are read side by side, as many as there are."""
        n, at = n.astype(np.int64), at.astype(np.int64)
        first = np.flatnonzero(np.concatenate(([True], key[1:] != key[:-1])))
        sizes = np.diff(np.append(first, len(key)))
        leaf = np.repeat(sizes <= LEAF, sizes)
        a, b = [], []
        for d in range(1, min(LEAF, len(key))):
            i = np.flatnonzero(leaf[:-d] & (key[:-d] == key[d:]) & (comp[:-d] != comp[d:]) & (side[:-d] != side[d:]))
            if not len(i) and d >= sizes.max():
                break
            i = i[room(n, at, i, i + d)]
            i = i[_close(points, points, i, i + d, per_cent)]
            a.append(i)
            b.append(i + d)
        for start, m in zip(first[sizes > LEAF], sizes[sizes > LEAF]):
            tree = CountTree(points[start : start + m])
            for k in range(start, start + m):
                near = start + tree.near(points[k], per_cent)
                near = near[(near > k) & (comp[near] != comp[k]) & (side[near] != side[k])]
                near = near[room(n, at, k, near)]
                a.append(np.repeat(k, len(near)))
                b.append(near)
        x, y = (np.concatenate(z).astype(np.int64) if z else np.zeros(0, np.int64) for z in (a, b))
        if best and len(x):
            some = nearest(key, others, points, n, x, y)
            x, y = x[some], y[some]
        x, y = sid[x], sid[y]
        both = np.unique(np.stack((np.minimum(x, y), np.maximum(x, y)), axis=1), axis=0)
        return {"a": both[:, 0], "b": both[:, 1]}

    def work(batches):
        held: list[tuple] = []
        for batch in batches:
            others = batch.column("others").to_numpy(zero_copy_only=False)
            held.append((*(batch.column(c).to_numpy() for c in ("key", "sid", "component", "side", "n", "at")), others, _points(batch.column("vec"))))
            if sum(len(x[0]) for x in held) < HELD_ROWS or held[0][0][0] == held[-1][0][-1]:
                continue
            rows = [np.concatenate(x) for x in zip(*held)]
            cut = int(np.flatnonzero(rows[0] != rows[0][-1])[-1]) + 1  # the last key may go on in the next batch
            yield pairs(*(x[:cut] for x in rows))
            held = [tuple(x[cut:] for x in rows)]
        rows = [np.concatenate(x) for x in zip(*held)] if held else []
        if rows and len(rows[0]):
            yield pairs(*rows)

    return arrow_map(dealt, work, PAIRS).distinct()


def _verify(pairs: DataFrame, sets: DataFrame, per_cent: int) -> DataFrame:
    """(src, dst) of the pairs (a, b) whose whole sets are similar enough."""
    x = sets.select(F.col("sid").alias("a"), F.col("set").alias("x"))
    y = sets.select(F.col("sid").alias("b"), F.col("set").alias("y"))

    def work(batches):
        for batch in batches:
            keep = []
            for x, y in zip(batch.column("x"), batch.column("y")):  # read where they lie, not copied
                x, y = np.frombuffer(x.as_buffer(), "<u8"), np.frombuffer(y.as_buffer(), "<u8")
                at = np.searchsorted(y, x)
                both = int((y[np.minimum(at, len(y) - 1)] == x).sum())
                keep.append(100 * both >= per_cent * (len(x) + len(y) - both))
            yield {"src": batch.column("a").filter(_mask(keep)), "dst": batch.column("b").filter(_mask(keep))}

    return arrow_map(pairs.join(x, "a").join(y, "b").select("a", "b", "x", "y"), work, T.StructType([T.StructField("src", T.LongType()), T.StructField("dst", T.LongType())]))


def _mask(keep: list[bool]):
    import pyarrow as pa

    return pa.array(keep, pa.bool_())


def _sets(rows: DataFrame, wanted: DataFrame, size: int) -> DataFrame:
    """(sid, set): sorted shingles of wanted classes; wanted: (doc_id, rid, sid), a row for each.

    Few wanted classes are sent to the texts, many are met by a shuffle of both.
    """
    if wanted.count() <= SENT_CLASSES:
        wanted = F.broadcast(wanted)
    joined = rows.join(wanted, same_row(rows, wanted)).select(rows["text"], wanted["sid"])

    def work(batches):
        hashes = WordHashes()
        for batch in batches:
            for texts, a, b in _pieces(batch.column(0)):
                yield {"sid": batch.column(1).slice(a, b - a), "set": [u.astype("<u8").tobytes() for u, _ in shingle_sets(hashes, [_lowered(t) for t in texts], size)]}

    return arrow_map(joined, work, T.StructType([T.StructField("sid", T.LongType()), T.StructField("set", T.BinaryType())]))


def _profiled(rows: DataFrame, size: int) -> tuple[DataFrame, DataFrame, np.ndarray]:
    """(doc_id, rid, n, sid, vec, marks) of all documents; of one document for each class; levels of the shingles' counters."""
    both = written(profile(rows, size), "profiles")
    docs = both.where("block IS NULL").drop("block", "counts")
    levels = _levels(both.where("block IS NOT NULL").select("block", "counts"))
    classes = docs.where("sid IS NOT NULL").groupBy("sid").agg(F.min_by(F.struct("doc_id", "rid", "vec"), "rid").alias("r")).select("sid", "r.*")
    return docs, written(classes, "classes"), levels


def _dealt(rows: DataFrame, levels: np.ndarray, size: int, per_cent: int) -> DataFrame:
    """(key, sid, n, at) of the keys that several classes have. Routes are dealt by key once, and never stored."""
    of_key = Window.partitionBy("key")
    routed = route(rows, levels, size, per_cent).withColumns({"lo": F.min("sid").over(of_key), "hi": F.max("sid").over(of_key)})
    return written(routed.where("lo <> hi").groupBy("key", "sid").agg(F.min("n").alias("n"), F.min("at").alias("at")), "dealt")


def _bounded(pairs: DataFrame, classes: DataFrame, per_cent: int) -> DataFrame:
    """The pairs (a, b) whose count vectors allow for the similarity."""
    a, b = (classes.select(F.col("sid").alias(c), F.col("vec").alias(f"v{c}")) for c in ("a", "b"))

    def work(batches):
        for batch in batches:
            each = np.arange(batch.num_rows)
            ok = _mask(_close(_points(batch.column("va")), _points(batch.column("vb")), each, each, per_cent))
            yield {"a": batch.column("a").filter(ok), "b": batch.column("b").filter(ok)}

    return arrow_map(pairs.join(a, "a").join(b, "b").select("a", "b", "va", "vb"), work, PAIRS)


def _verified(rows: DataFrame, classes: DataFrame, pairs: DataFrame, size: int, per_cent: int) -> DataFrame:
    """Links among the pairs, whose classes' sets are made for this and dropped."""
    pairs = written(pairs, "pairs")
    sids = pairs.select(F.col("a").alias("sid")).union(pairs.select("b")).distinct()
    wanted = written(classes.join(sids, "sid", "left_semi").select("doc_id", "rid", "sid"), "wanted")
    sets = written(_sets(rows, wanted, size), "sets")
    out = written(_verify(pairs, sets, per_cent), "links")
    drop(sets, wanted, pairs)
    return out


def _first_links(rows: DataFrame, docs: DataFrame, classes: DataFrame, size: int, per_cent: int) -> DataFrame:
    """Links of classes with the first or last class that has a signature of theirs."""
    marked = docs.where("sid IS NOT NULL").select("sid", F.explode("marks").alias("mark"))
    ends = marked.groupBy("mark").agg(F.min("sid").alias("lo"), F.max("sid").alias("hi")).where("lo <> hi")
    met = marked.join(ends, "mark")
    pairs = met.select("sid", F.col("lo").alias("other")).union(met.select("sid", "hi")).where("sid <> other")
    pairs = pairs.select(F.least("sid", "other").alias("a"), F.greatest("sid", "other").alias("b")).distinct()
    return _verified(rows, classes, _bounded(pairs, classes, per_cent), size, per_cent)


def _in_groups(labelled: DataFrame, classes: DataFrame) -> DataFrame:
    """(key, sid, component, side, n, at, others, vec) of keys with several components, each group of a key under a key of its own.

    labelled: (key, sid, n, at, component). A key of up to BLOCK classes is one group. In larger ones, the classes of the largest
    component are cut in blocks, those of all others too; groups are one block of the others with each block of either
    kind. Only classes of different sides are to be compared; within one block every class is a side of its own.
    """
    each = labelled.groupBy("key", "component").agg(F.count("*").alias("c"))
    keys = each.groupBy("key").agg(F.sum("c").alias("all"), F.max(F.struct("c", "component")).alias("top"), F.count("*").alias("kinds")).where("kinds > 1")
    keys = keys.select("key", F.col("top.component").alias("top"), F.col("top.c").alias("most"), F.col("all").alias("all_"))
    blocks = lambda n: F.ceil(F.col(n) / BLOCK)
    keys = keys.withColumn("rest", F.col("all_") - F.col("most")).withColumn("large", F.col("all_") > BLOCK)
    mine = labelled.join(keys, "key").withColumn("others", F.col("component") != F.col("top"))
    mine = mine.withColumn("own", F.pmod(F.xxhash64("sid", "key"), F.when(F.col("others"), blocks("rest")).otherwise(blocks("most"))))
    among_rest = F.sequence(F.lit(0).cast("long"), blocks("rest") - 1)
    among_top = F.sequence(F.lit(0).cast("long"), blocks("most") - 1)
    # a group: (block of the others, kind of the second block, its number)
    with_rest = F.transform(among_rest, lambda k: F.struct(F.least(k, "own").alias("x"), F.lit(True).alias("rest"), F.greatest(k, "own").alias("y")))
    with_top = F.transform(among_top, lambda k: F.struct(F.col("own").alias("x"), F.lit(False).alias("rest"), k.alias("y")))
    top_with = F.transform(among_rest, lambda k: F.struct(k.alias("x"), F.lit(False).alias("rest"), F.col("own").alias("y")))
    one = F.array(F.struct(F.lit(0).cast("long").alias("x"), F.lit(True).alias("rest"), F.lit(0).cast("long").alias("y")))
    groups = F.when(~F.col("large"), one).when(F.col("others"), F.concat(with_rest, with_top)).otherwise(top_with)
    mine = mine.withColumn("g", F.explode(groups))
    alone = ~F.col("large") | (F.col("g.rest") & (F.col("g.x") == F.col("g.y")))
    side = F.when(alone, F.col("sid")).when(F.col("g.rest"), F.col("own")).otherwise(F.col("others").cast("long"))
    key = F.when(F.col("large"), F.xxhash64("key", "g.x", "g.rest", "g.y")).otherwise(F.col("key"))
    out = mine.select(key.alias("key"), "sid", "component", side.alias("side"), "n", "at", "others")
    return out.join(classes.select("sid", "vec"), "sid").repartition("key").sortWithinPartitions("key", "sid")


def every_link(docs: DataFrame, size: int = 4, per_cent: int = 85, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(src, dst): every link between two classes, by class number, src < dst, once."""
    return _all_links(row_key(keyed(docs, id_col, text_col)), size, per_cent)[1]


def _all_links(rows: DataFrame, size: int, per_cent: int) -> tuple[DataFrame, DataFrame]:
    """Profiles of all documents, and (src, dst) of every link between classes: each is a component of its own here."""
    docs, classes, levels = _profiled(rows, size)
    dealt = _dealt(rows, levels, size, per_cent)
    found = _verified(rows, classes, _tree_pairs(_in_groups(dealt.withColumn("component", F.col("sid")), classes), per_cent), size, per_cent)
    drop(dealt, classes)
    return docs, found


def link_counts(docs: DataFrame, size: int = 4, per_cent: int = 85, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, rid, n_shingles, sid, n_links) of each row: its class, and how many other classes that links with."""
    docs, found = _all_links(row_key(keyed(docs, id_col, text_col)), size, per_cent)
    n = found.select(F.col("src").alias("sid")).union(found.select("dst")).groupBy("sid").agg(F.count("*").alias("n_links"))
    out = docs.select("doc_id", "rid", F.col("n").alias("n_shingles"), "sid").join(n, "sid", "left")
    return out.select("doc_id", "rid", "n_shingles", "sid", F.coalesce("n_links", F.lit(0)).alias("n_links"))


def links(rows: DataFrame, size: int, per_cent: int) -> tuple[DataFrame, DataFrame]:
    """Profiles of all documents, and (src, dst) links that join all classes of a component, not every link."""
    docs, classes, levels = _profiled(rows, size)
    known = _first_links(rows, docs, classes, size, per_cent)
    comp = contract(known).withColumnsRenamed({"id": "sid"})
    dealt = _dealt(rows, levels, size, per_cent)
    for best in (True, False):
        if best is False:
            comp = contract(known).withColumnsRenamed({"id": "sid"})
        labelled = dealt.join(comp, "sid", "left").withColumn("component", F.coalesce("component", "sid"))
        labelled = written(labelled, "labelled")
        known = known.union(_verified(rows, classes, _tree_pairs(_in_groups(labelled, classes), per_cent, best), size, per_cent))
        drop(labelled)
    drop(dealt, classes)
    return docs, known


def similar(docs: DataFrame, size: int = 4, per_cent: int = 85, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, rid, n_shingles, component_id, component) of each row; component is null for rows without shingles."""
    rows = row_key(keyed(docs, id_col, text_col))
    with scratch():
        docs, known = links(rows, size, per_cent)
        comp = contract(known).withColumnsRenamed({"id": "sid"})
        out = docs.select("doc_id", "rid", F.col("n").alias("n_shingles"), "sid").join(comp, "sid", "left")
        out = lasting(out.select("doc_id", "rid", "n_shingles", F.coalesce("component", "sid").alias("component")), "members")
    least = out.where("component IS NOT NULL").groupBy("component").agg(F.min("doc_id").alias("least"))
    return out.join(least, "component", "left").select("doc_id", "rid", "n_shingles", F.when(F.col("component").isNull(), F.col("doc_id")).otherwise(F.col("least")).alias("component_id"), "component")
