"""Clustering coefficients of the undirected view, exact and sampled."""

from __future__ import annotations

import math
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from netan.engines import gas as gas_engine
from netan.engines.dataflow import Plan
from netan.engines.loop import draw
from netan.network import Network
from netan.ordering import running
from netan.partition import by_modulo
from netan.stats import degrees
from netan.storage import written

#: Edges of a task that counts triangles, of a lot that is packed at once, and wedges that are looked at together.
TASK_EDGES, LOT_EDGES, WEDGES = 4_000_000, 1_000_000, 1_000_000
METHODS = ("ordered", "dataflow", "bsp", "gas", "block", "msr", "shm")


def _corners(net: Network, method: str) -> DataFrame:
    """(id, t): number of triangles of each vertex that has one, by method."""
    net = net.undirected()
    edges = net.edges.select("src", "dst")
    arcs = net.mirrored().select("src", "dst")
    if method == "ordered":
        return _coloured_corners(net)
    if method == "dataflow":
        # neighbours of neighbours by one join of the edges with themselves, closed by a second
        second = arcs.toDF("id", "u").join(arcs.toDF("id", "w"), "id").where("u < w")
        return second.join(edges.toDF("u", "w"), ["u", "w"]).groupBy("id").agg(F.count("*").alias("t"))
    lists = net.adjacency()
    if method == "bsp":
        # superstep 1: every vertex sends its neighbourhood to its neighbours; superstep 2: hits are counted
        sent = lists.join(arcs, lists["id"] == arcs["src"]).select(F.col("dst").alias("id"), F.col("nbrs").alias("msg"))
        return sent.join(lists, "id").select("id", F.size(F.array_intersect("nbrs", "msg")).alias("h")).groupBy("id").agg(F.expr("sum(h) div 2").alias("t")).where("t > 0")
    if method == "gas":
        # common neighbours of each edge's ends, then sums over a vertex's edges
        a, b = lists.toDF("src", "x"), lists.toDF("dst", "y")
        common = edges.join(a, "src").join(b, "dst").select("src", "dst", F.size(F.array_intersect("x", "y")).alias("c"))
        return common.select(F.explode(F.array("src", "dst")).alias("id"), "c").groupBy("id").agg(F.expr("sum(c) div 2").alias("t")).where("t > 0")
    if method == "block":
        return _block_corners(net, by_modulo(net, 4))
    if method == "msr":
        # round 1: pairs of neighbours with their centre, and edges, meet by key; round 2: sums by centre
        pairs = lists.select("id", F.explode("nbrs").alias("u"), "nbrs").select("id", "u", F.explode("nbrs").alias("w")).where("u < w")
        keyed = pairs.select("u", "w", F.col("id").alias("v")).unionByName(edges.select(F.col("src").alias("u"), F.col("dst").alias("w"), F.lit(None).cast("long").alias("v")))
        met = keyed.groupBy("u", "w").agg(F.collect_list("v").alias("vs"), F.count_if(F.col("v").isNull()).alias("edge"))
        return met.where("edge > 0").select(F.explode("vs").alias("id")).groupBy("id").agg(F.count("*").alias("t"))
    if method == "shm":
        from netan.baselines import shared_memory

        return shared_memory.triangles(net)
    raise ValueError(method)


def _packed(src: np.ndarray, dst: np.ndarray) -> bytes:
    """Edges (src < dst), sorted by src: steps from one src to the next and distances of the ends, byte by byte, deflated."""
    parts = np.stack((np.diff(src, prepend=src[:1]), dst - src)).view(np.uint8).reshape(2, -1, 8)
    return src[0].tobytes() + zlib.compress(parts.transpose(0, 2, 1).tobytes(), 1)


def _unpacked(raw: bytes) -> tuple[np.ndarray, np.ndarray]:
    parts = np.frombuffer(zlib.decompress(raw[8:]), np.uint8).reshape(2, 8, -1).transpose(0, 2, 1)
    step, far = np.ascontiguousarray(parts).view(np.int64)[..., 0]
    src = np.frombuffer(raw[:8], np.int64)[0] + np.cumsum(step)
    return src, src + far


def _corners_of(src: np.ndarray, dst: np.ndarray, other: int | None, cuts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(ids, t) of some edges, once each; edges point to the end of higher degree, so that hubs open few wedges. other: a colour
    that one corner at least must have."""
    ids = np.unique(np.concatenate((src, dst)))
    n = len(ids)
    s, d = np.searchsorted(ids, src), np.searchsorted(ids, dst)
    ids = ids[order := np.argsort(np.bincount(s, minlength=n) + np.bincount(d, minlength=n), kind="stable")]
    rank = np.empty(n, np.int64)
    rank[order] = np.arange(n)
    s, d = rank[s], rank[d]
    keys = np.minimum(s, d) * n + np.maximum(s, d)
    keys.sort()
    a, b = np.divmod(keys, n)
    starts = np.searchsorted(a, np.arange(n + 1))
    lens = starts[b + 1] - starts[b]
    ends, t = np.cumsum(lens), np.zeros(n, np.int64)
    right = None if other is None else np.searchsorted(cuts, ids, side="right") == other
    at = 0
    while at < len(a):  # lots of edges with about WEDGES wedges
        to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + WEDGES, side="right")))
        some = lens[at:to]
        edge = np.repeat(np.arange(at, to), some)
        c = b[np.arange(len(edge)) + np.repeat(starts[b[at:to]] - (np.cumsum(some) - some), some)]
        near = keys[starts[a[at]] : starts[a[to - 1] + 1]]
        asks = a[edge] * n + c
        ok = near[np.minimum(np.searchsorted(near, asks), len(near) - 1)] == asks
        if right is not None:
            ok &= right[a[edge]] | right[b[edge]] | right[c]
        t += np.bincount(np.concatenate((a[edge[ok]], b[edge[ok]], c[ok])), minlength=n)
        at = to
    return ids[t > 0], t[t > 0]


def _coloured_corners(net: Network) -> DataFrame:
    """(id, t): vertices are coloured by ranges of ids; a triangle is found where the edges between its corners' colours are.

    An edge goes, packed, to a task for each third colour that has edges with both of its own: to as many as there are colours
    at most, to few if ids that lie together link. No wedge is written or dealt.
    """
    edges = net.edges.select("src", "dst")
    if not hasattr(net.edges, "_netan_path"):
        edges = written(edges, "edges")
    n = max(3, math.ceil(math.sqrt(6 * edges.count() / TASK_EDGES)))
    cuts = np.unique(np.array(net.vertices().approxQuantile("id", [k / n for k in range(1, n)], 0.001), np.float64).astype(np.int64))

    def colours(batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        src, dst = batch.column("src").to_numpy(), batch.column("dst").to_numpy()
        return src, dst, np.searchsorted(cuts, src, side="right"), np.searchsorted(cuts, dst, side="right")

    def kinds(batches):
        for batch in batches:
            _, _, i, j = colours(batch)
            seen = np.unique(i * (len(cuts) + 1) + j)
            yield pa.RecordBatch.from_pydict({"i": seen // (len(cuts) + 1), "j": seen % (len(cuts) + 1)})

    met = {(r["i"], r["j"]) for r in edges.mapInArrow(kinds, "i long, j long").distinct().collect()}
    linked = lambda i, j: (min(i, j), max(i, j)) in met
    to = {(i, j): [tuple(sorted((i, j, k))) for k in range(len(cuts) + 1) if linked(i, k) and linked(j, k)] for i, j in met}
    triples = sorted({x for some in to.values() for x in some})
    place = {x: g for g, x in enumerate(triples)}

    def lots(batches):
        held, size = [], 0
        for batch in batches:
            held.append(colours(batch))
            size += batch.num_rows
            if size >= LOT_EDGES:
                yield from sent(held)
                held, size = [], 0
        if size:
            yield from sent(held)

    def sent(held):
        src, dst, i, j = (np.concatenate(x) for x in zip(*held))
        by = np.lexsort((dst, src, j, i))
        src, dst, i, j = src[by], dst[by], i[by], j[by]
        first = np.flatnonzero(np.concatenate(([True], (i[1:] != i[:-1]) | (j[1:] != j[:-1]))))
        for x, y in zip(first.tolist(), [*first[1:].tolist(), len(src)]):
            some = to[int(i[x]), int(j[x])]
            raw = _packed(src[x:y], dst[x:y]) if some else None
            for triple in some:  # a row each, so that few copies are held at once
                yield pa.RecordBatch.from_pydict({"g": pa.array([place[triple]], pa.int32()), "raw": pa.array([raw], pa.binary())})

    def solve(key: tuple, rows: pa.Table) -> pa.Table:
        p, q, r = triples[key[0].as_py()]
        src, dst = (np.concatenate(x) for x in zip(*map(_unpacked, rows.column("raw").to_pylist())))
        ids, t = _corners_of(src, dst, None if p == q == r or p < q < r else r if p == q else p, cuts)
        return pa.table({"id": ids, "t": t})

    found = edges.mapInArrow(lots, "g int, raw binary").groupBy("g").applyInArrow(solve, "id long, t long")
    return found.groupBy("id").agg(F.sum("t").alias("t"))


def _block_corners(net: Network, blocks: DataFrame) -> DataFrame:
    """(id, t) in two parts: a triangle with an edge inside a block is found there, where both ends' neighbours are known; one whose
    corners lie in three blocks is found by joins over the edges between blocks."""
    arcs = net.mirrored().select("src", "dst").join(blocks.toDF("src", "s"), "src").join(blocks.toDF("dst", "d"), "dst")

    def inside(rows: pa.Table) -> pa.Table:
        src, dst = rows.column("src").to_numpy(), rows.column("dst").to_numpy()
        mine = rows.column("s").to_numpy() == rows.column("d").to_numpy()
        order = np.lexsort((dst, src))
        src, dst, mine = src[order], dst[order], mine[order]
        ids, first = np.unique(src, return_index=True)
        near = dict(zip(ids.tolist(), np.split(dst, first[1:])))
        own = dict(zip(ids.tolist(), np.split(mine, first[1:])))
        corners = []
        for u, v in zip(src[mine & (src < dst)].tolist(), dst[mine & (src < dst)].tolist()):
            third, at, _ = np.intersect1d(near[u], near[v], assume_unique=True, return_indices=True)
            third = third[~own[u][at] | (third > v)]  # inside the block, by the two lower corners only
            if len(third):
                corners += [np.full(len(third), u), np.full(len(third), v), third]
        ids, t = np.unique(np.concatenate(corners) if corners else src[:0], return_counts=True)
        return pa.table({"id": ids, "t": t.astype(np.int64)})

    local = arcs.groupBy("s").applyInArrow(inside, "id long, t long")
    cross = arcs.where("s <> d AND src < dst").select("src", "dst", "s", "d")
    first, second = cross.toDF("a", "b", "p", "q"), cross.toDF("b", "c", "q2", "r")
    wedges = first.join(second, "b").where("p <> r").select("a", "b", "c")
    closed = wedges.join(cross.select(F.col("src").alias("a"), F.col("dst").alias("c")), ["a", "c"], "left_semi")
    apart = closed.select(F.explode(F.array("a", "b", "c")).alias("id")).groupBy("id").agg(F.count("*").alias("t"))
    return local.union(apart).groupBy("id").agg(F.sum("t").alias("t"))


def local(net: Network, method: str = "ordered") -> DataFrame:
    """(id, degree, triangles, coefficient): the coefficient is null below degree 2."""
    rows = degrees(net).join(_corners(net, method), "id", "left")
    pairs = F.col("degree") * (F.col("degree") - 1) / 2
    t = F.coalesce("t", F.lit(0)).cast("long")
    return rows.select("id", "degree", t.alias("triangles"), F.when(F.col("degree") >= 2, t / pairs).alias("coefficient"))


def average_local(net: Network, method: str = "ordered") -> DataFrame:
    if net.closed:
        return net.average_local()
    return local(net, method).agg(F.round(F.avg("coefficient"), 6).alias("coefficient"))


def global_coefficient(net: Network, method: str = "ordered") -> DataFrame:
    """Three times the triangles over the connected triplets; null if there are none."""
    sums = local(net, method).agg(F.sum("triangles").alias("t"), F.sum(F.expr("degree * (degree - 1) div 2")).alias("w"))
    return sums.select(F.round(F.when(F.col("w") > 0, F.col("t") / F.col("w")), 6).alias("coefficient"))


def triangles(net: Network, method: str = "ordered") -> DataFrame:
    return local(net, method).agg(F.expr("sum(triangles) div 3").alias("triangles"))


def samples_for(epsilon: float, delta: float) -> int:
    """Draws after which the estimate is off by more than epsilon with a chance of at most delta (Hoeffding's bound)."""
    return math.ceil(math.log(2 / delta) / (2 * epsilon**2))


def _numbered(rows: DataFrame, weight: Column) -> DataFrame:
    """rows (id, ...) by id, with before, the sum of the weights before, and weight."""
    columns = rows.columns
    rows = rows.withColumn("weight", weight.cast("long"))
    return written(running(rows, [F.col("id").asc()], F.col("weight"), "before").select(*columns, F.col("before").cast("long").alias("before"), "weight"), "numbered")


def _closed(net: Network, drawn: DataFrame, seed: int) -> DataFrame:
    """(k, id, closed): for drawn (k, id, degree), two different neighbours by hash, and whether they are linked."""
    net = net.undirected()
    asked = _asked(drawn, seed)
    if net.closed:
        return net.joined(net.named(asked, _spans(net, drawn))).select("k", "id", "closed")
    drawn = net.owned(asked)
    pairs = drawn.join(net.lists(drawn.select("owner").distinct()), "owner").select("k", "id", net.pick("i").alias("a"), net.pick("j").alias("b"))
    edges = net.edges.select("src", "dst").withColumn("hit", F.lit(True))
    return _named(net, pairs).join(edges, ["src", "dst"], "left").select("k", "id", F.coalesce("hit", F.lit(False)).alias("closed"))


def _spans(net: Network, drawn: DataFrame) -> DataFrame:
    """Where the neighbours of drawn vertices lie: as counted for their degrees, or of all."""
    return getattr(drawn, "_netan_spans", None) or net.spans


def _named(net: Network, pairs: DataFrame) -> DataFrame:
    """pairs (a, b, ...) with src and dst, under which the edges have them."""
    pairs = net.kin(net.kin(pairs.withColumn("dst", F.col("a"))).withColumn("x", F.col("kin")).drop("kin").withColumn("dst", F.col("b")))
    return pairs.withColumns({"src": F.least("x", "kin"), "dst": F.greatest("x", "kin")})


def _draws(net: Network, weight: Column | None, samples: int, seed: int, wide: bool = True) -> DataFrame:
    """(k, id, degree) of `samples` draws with replacement, with a chance in proportion to weight; alike if there is none.

    Draws meet the intervals of the vertices by buckets of the weight's range, so that no join is over all pairs. wide: draws have
    52 bits if the weights' sum is above 2^31; else always 32 bits, which reach no further than the first 2^32 of the sum. Where
    degrees take the union of groups, alike draws have only those counted that are drawn.
    """
    late = net.closed and weight is None
    rows = _numbered(net.sociable() if late else degrees(net).where("degree >= 2").select("id", "degree"), F.lit(1) if weight is None else weight)
    total = rows.agg(F.sum("weight")).first()[0] or 0
    if not total:
        return rows.limit(0).select(F.col("id").alias("k"), "id", F.lit(0).cast("long").alias("degree"))
    width = max(1, total // max(1, min(samples, 1 << 20)))
    at = F.pmod(draw(seed, F.col("id"), F.lit("v")) * (1 << 20) + draw(seed, F.col("id"), F.lit("x")) % (1 << 20), F.lit(total)) if wide and total > 1 << 31 else F.pmod(draw(seed, F.col("id"), F.lit("v")), F.lit(total))
    draws = net.spark.range(samples).select(F.col("id").alias("k"), at.alias("at")).withColumn("bucket", F.expr(f"at div {width}"))
    spans = rows.withColumn("after", F.col("before") + F.col("weight")).drop("weight")
    spans = spans.withColumn("bucket", F.explode(F.sequence(F.expr(f"before div {width}"), F.expr(f"(after - 1) div {width}"))))
    drawn = draws.join(spans, "bucket").where("at >= before AND at < after").drop("bucket", "at", "before", "after")
    if not late:
        return drawn
    drawn = written(net.owned(drawn), "draws")
    spans = net.spans_of(drawn.select("owner").distinct())
    out = drawn.join(spans.groupBy("owner").agg((F.sum("n") - 1).alias("degree")), "owner").select("k", "id", "degree")
    out._netan_spans = spans
    return out


def _estimate(closed: DataFrame, samples: int, delta: float = 0.05) -> DataFrame:
    eps = math.sqrt(math.log(2 / delta) / (2 * samples)) if samples else None
    sums = closed.agg(F.count_if("closed").alias("links"), F.count("*").alias("samples"))
    return sums.select(F.round(F.when(F.col("samples") > 0, F.col("links") / F.col("samples")), 6).alias("coefficient"), "samples", "links", F.lit(round(eps, 6) if eps else None).cast("double").alias("epsilon"))


def approx_average_local(net: Network, samples: int = 100_000, seed: int = 1) -> DataFrame:
    """(coefficient, samples, links, epsilon): vertices drawn alike, a pair of neighbours each."""
    return _estimate(_closed(net, _draws(net, None, samples, seed), seed), samples)


def approx_global(net: Network, samples: int = 100_000, seed: int = 1, wide: bool = True) -> DataFrame:
    """As approx_average_local, vertices drawn in proportion to degree * (degree - 1)."""
    return _estimate(_closed(net, _draws(net, F.expr("degree * (degree - 1)"), samples, seed, wide), seed), samples)


def _asked(drawn: DataFrame, seed: int) -> DataFrame:
    """drawn (k, id, degree) with i and j, the places of two different neighbours in the sorted list."""
    d = F.col("degree")
    i = F.pmod(draw(seed, F.col("k"), F.lit("i")), d).cast("int")
    j = F.pmod(draw(seed, F.col("k"), F.lit("j")), d - 1).cast("int")
    return drawn.select("k", "id", i.alias("i"), (j + F.when(j >= i, 1).otherwise(0)).alias("j"))


def approx_dataflow(net: Network, samples: int = 100_000, seed: int = 1, weight: Column | None = None) -> DataFrame:
    """The draws as an operator graph: joined with grouped neighbour lists, mapped to pairs, joined with the edges."""
    net = net.undirected()
    drawn = Plan.source(net.owned(_asked(_draws(net, weight, samples, seed), seed)))
    arcs = Plan.map(Plan.source(net.mirrored()), F.col("src").alias("owner"), "dst")
    lists = Plan.group(arcs, ["owner"], F.array_sort(F.collect_list("dst")).alias("nbrs"))
    pairs = Plan.map(Plan.join(drawn, lists, "owner"), net.pick("i").alias("a"), net.pick("j").alias("b"))
    if net.closed:
        members = Plan.source(net.members)
        pairs = Plan.map(Plan.join(pairs, Plan.map(members, F.col("id").alias("a"), F.col("rep").alias("x")), "a"), F.col("x").alias("a"), "b")
        pairs = Plan.map(Plan.join(pairs, Plan.map(members, F.col("id").alias("b"), F.col("rep").alias("y")), "b"), "a", F.col("y").alias("b"))
    pairs = Plan.map(pairs, F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst"))
    edges = Plan.map(Plan.source(net.edges), "src", "dst", F.lit(True).alias("hit"))
    found = Plan.map(Plan.join(pairs, edges, ["src", "dst"], "left"), F.coalesce("hit", F.lit(False)).alias("closed"))
    return _estimate(Plan.result(found), samples)


def approx_gas(net: Network, samples: int = 100_000, seed: int = 1, weight: Column | None = None) -> DataFrame:
    """Drawn vertices pull their neighbours' ids, unfolded; then each pair is looked for among the edges' ends."""
    net = net.undirected()
    drawn = written(_draws(net, weight, samples, seed), "draws")
    asks = net.owned(_asked(drawn, seed))
    arcs = net.mirrored().select(F.col("dst").alias("src"), F.col("src").alias("dst")).join(asks.select(F.col("owner").alias("dst")).distinct(), "dst", "left_semi")
    state = net.vertices().select("id", F.lit(None).cast("array<bigint>").alias("value"))
    lists = gas_engine.run(arcs, state, F.col("src"), None, F.col("msg"), signal=F.lit(False), max_steps=1)
    pairs = asks.join(lists.toDF("owner", "nbrs"), "owner").select(net.pick("i").alias("a"), net.pick("j").alias("b"))
    hits = _named(net, pairs).join(net.edges.select("src", "dst").withColumn("hit", F.lit(True)), ["src", "dst"], "left")
    return _estimate(hits.select(F.coalesce("hit", F.lit(False)).alias("closed")), samples)


def approx_block(net: Network, samples: int = 100_000, seed: int = 1, blocks: DataFrame | None = None, weight: Column | None = None) -> DataFrame:
    """In two supersteps of blocks: the block that holds a drawn vertex names two of its neighbours and answers itself if it holds the
    first; other pairs go by message to the block that does."""
    net = net.undirected()
    blocks = by_modulo(net, 4) if blocks is None else blocks
    drawn = _draws(net, weight, samples, seed)
    if net.closed:
        return _estimate(_block_of_groups(net, blocks, drawn, seed), samples)
    drawn = _asked(drawn, seed)
    arcs = net.mirrored().select("src", "dst").join(blocks.toDF("src", "block"), "src").select("src", "dst", "block")
    asks = drawn.join(blocks, "id").select("block", "k", "id", "i", "j")

    def lists(rows: pa.Table) -> dict:
        """The neighbours of each vertex, in order."""
        src, dst = (rows.column(c).to_numpy() for c in ("src", "dst"))
        order = np.lexsort((dst, src))
        ids, first = np.unique(src[order], return_index=True)
        return dict(zip(ids.tolist(), np.split(dst[order], first[1:]))) if len(ids) else {}

    def linked(near: np.ndarray, b: int) -> bool:
        at = int(np.searchsorted(near, b))
        return at < len(near) and int(near[at]) == b

    def first(asks: pa.Table, arcs: pa.Table) -> pa.Table:
        near, out = lists(arcs), []
        for k, v, i, j in zip(*(asks.column(c).to_pylist() for c in ("k", "id", "i", "j"))):
            a, b = int(near[v][i]), int(near[v][j])
            out.append((k, a, b, linked(near[a], b) if a in near else None))
        return pa.table(dict(zip(("k", "a", "b", "closed"), map(list, zip(*out)))) if out else {c: [] for c in ("k", "a", "b", "closed")}, pa.schema([("k", pa.int64()), ("a", pa.int64()), ("b", pa.int64()), ("closed", pa.bool_())]))

    def second(asks: pa.Table, arcs: pa.Table) -> pa.Table:
        near = lists(arcs)
        return pa.table({"closed": pa.array([linked(near[a], b) for a, b in zip(asks.column("a").to_pylist(), asks.column("b").to_pylist())], pa.bool_())})

    met = written(asks.groupBy("block").cogroup(arcs.groupBy("block")).applyInArrow(first, "k long, a long, b long, closed boolean"), "asked")
    sent = met.where("closed IS NULL").join(blocks.withColumnRenamed("id", "a"), "a").select("block", "a", "b")
    told = sent.groupBy("block").cogroup(arcs.groupBy("block")).applyInArrow(second, "closed boolean")
    return _estimate(met.where("closed IS NOT NULL").select("closed").union(told), samples)


def _block_of_groups(net: Network, blocks: DataFrame, drawn: DataFrame, seed: int) -> DataFrame:
    """(closed) by the same two supersteps where blocks hold the groups of their vertices, and the groups' members as boundary, slice
    by slice, instead of lists of neighbours."""
    asked = _asked(drawn, seed).join(blocks, "id")
    pairs = net.named(asked, _spans(net, drawn)).join(blocks.withColumnRenamed("block", "own"), "id").join(blocks.toDF("a", "block"), "a")
    pairs = written(pairs, "named")
    here = net.told(pairs.where("block = own"))
    met = written(pairs.join(here, "k", "left"), "asked")
    sent = met.where("closed IS NULL").select("block", "k", "a", "b")
    return met.where("closed IS NOT NULL").select("closed").union(net.told(sent).select("closed"))


def approx_bsp(net: Network, samples: int = 100_000, seed: int = 1) -> DataFrame:
    """In two supersteps: vertices learn how many pairs fall to them and send these; receivers look for them in their lists."""
    drawn = _draws(net, F.lit(1), samples, seed)
    d = F.col("degree")
    i = F.pmod(draw(seed, F.col("k"), F.lit("i")), d).cast("int")
    j = F.pmod(draw(seed, F.col("k"), F.lit("j")), d - 1).cast("int")
    lists = net.undirected().adjacency()
    own = drawn.groupBy("id", "degree").agg(F.collect_list("k").alias("ks")).join(lists, "id")
    sent = own.select("id", "nbrs", "degree", F.explode("ks").alias("k")).withColumn("i", i).withColumn("j", j + F.when(j >= i, 1).otherwise(0))
    sent = sent.select("k", F.col("nbrs")[F.col("i")].alias("to"), F.col("nbrs")[F.col("j")].alias("asks"))
    met = sent.join(lists.toDF("to", "have"), "to").select(F.array_contains("have", F.col("asks")).alias("closed"))
    return _estimate(met, samples)


def approx_fixed_pairs(net: Network, pairs: int = 4, seed: int = 1) -> DataFrame:
    """(coefficient, samples, links, epsilon): the same number of pairs for every vertex of degree 2 or more."""
    rows = degrees(net).where("degree >= 2").select("id", "degree", F.explode(F.sequence(F.lit(0), F.lit(pairs - 1))).alias("p"))
    closed = _closed(net, rows.select((F.col("id") * pairs + F.col("p")).alias("k"), "id", "degree"), seed)
    sums = closed.agg(F.count_if("closed").alias("links"), F.count("*").alias("samples"))
    return sums.select(F.round(F.when(F.col("samples") > 0, F.col("links") / F.col("samples")), 6).alias("coefficient"), "samples", "links")
