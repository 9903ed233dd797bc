"""Networks of common groups, kept by classes and by the members of each group.

Members of the same groups are twins: each other's neighbours, and alike in all others. A class stands for them under its least
member, and two classes link if they share a group. Nothing is lost: a member's neighbours are all members of the classes that
its own links with, itself left out. Where no two members are alike, classes are members and their links all pairs; so links are
made only for methods that go along them. Degrees, neighbours by place and links of given pairs come from the groups themselves:
ids are cut into slices of about as many memberships each, and a task unites the groups of a lot of classes within one slice.
What is stored and dealt grows with the memberships and those asked for, not with pairs.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import cached_property

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from netan.network import Network
from netan.storage import drop, written

#: Memberships of a slice of ids; memberships and questions of a lot; questions that are put to one class's neighbours at a time.
SLICE, LOT, PART = 1 << 20, 1 << 19, 1 << 17


class Twins(Network):
    """Its edges (src <= dst) lead between classes, from each to itself too; mirrored() from classes to all members near them."""

    closed = True

    def __init__(self, rows: DataFrame, member: str, *group: str) -> None:
        key = [f"key{k}" for k in range(len(group))]
        rows = rows.select(F.col(member).cast("long").alias("id"), *(F.col(c).alias(k) for c, k in zip(group, key)))
        for c in rows.columns:
            rows = rows.where(F.col(c).isNotNull())
        rows = written(rows.distinct(), "memberships")
        named = rows.groupBy(*key).agg(F.count("*").alias("n"), F.min("id").alias("lo"), F.max("id").alias("hi"))
        named = written(named.where("n >= 2").withColumn("g", F.monotonically_increasing_id()), "groups")  # a group of one ties nobody
        # a member has two neighbours or more if it is in a group of three, or meets two others in groups of two
        other = F.when(F.col("n") == 2, F.when(F.col("id") == F.col("lo"), F.col("hi")).otherwise(F.col("lo")))
        many = (F.max("n") >= 3) | (F.min(other) != F.max(other))
        each = rows.join(named, key).groupBy("id").agg(F.array_sort(F.collect_list("g")).alias("gs"), many.alias("many"))
        classes = each.groupBy("gs").agg(F.min("id").alias("rep"), F.count("*").alias("size"), F.collect_list("id").alias("ids"), F.bool_or("many").alias("many"))
        self.classes = written(classes, "classes")
        drop(rows, named)
        self.directed, self.isolated = False, None

    @property
    def spark(self):
        return self.classes.sparkSession

    @cached_property
    def links(self) -> DataFrame:
        """(src, dst): classes that share a group, each with itself too."""
        of = self.classes.select(F.col("rep").alias("src"), F.explode("gs").alias("g"))
        return written(of.join(of.withColumnRenamed("src", "dst"), "g").select("src", "dst").distinct(), "class-links")

    @property
    def edges(self) -> DataFrame:
        return self.links.where("src <= dst")

    @cached_property
    def near(self) -> DataFrame:
        """(rep, size, degree) of all classes."""
        near = self.spans.groupBy(F.col("owner").alias("rep")).agg((F.sum("n") - 1).alias("degree"))
        return written(self.classes.select("rep", "size").join(near, "rep"), "class-degrees")

    @cached_property
    def cuts(self) -> list[int]:
        """Ids at which slices begin, but for the first."""
        n = math.ceil((self.classes.agg(F.sum(F.col("size") * F.size("gs"))).first()[0] or 0) / SLICE)
        if n <= 1:
            return []
        rows = self.classes.select(F.explode("ids").alias("id"), "gs").select("id", F.explode("gs"))
        return sorted({int(x) for x in rows.approxQuantile("id", [k / n for k in range(1, n)], min(0.01, 1 / (8 * n)))})

    def _slice(self, of: str) -> Column:
        return F.size(F.filter(F.array(*map(F.lit, self.cuts)), lambda c: c <= F.col(of))) if self.cuts else F.lit(0)

    @cached_property
    def held(self) -> DataFrame:
        """(slice, g, ids): members of each group within each slice."""
        rows = self.classes.select(F.explode("ids").alias("id"), "gs").withColumn("slice", self._slice("id"))
        return written(rows.select("slice", "id", F.explode("gs").alias("g")).groupBy("slice", "g").agg(F.collect_list("id").alias("ids")), "members")

    def _meet(self, asks: DataFrame, solve, schema: str, block: list[str] = []) -> DataFrame:
        """solve(asks, members) for each lot of asks (owner, part, slice, ...), those of a block apart, and each slice."""
        gs = self.classes.select(F.col("rep").alias("owner"), "gs")
        asks = written(asks, "asks")
        size = F.size("rows") if "rows" in asks.columns else F.lit(0)
        asked = asks.groupBy("owner", "part", *block).agg(F.sum(size).alias("size")).join(gs.select("owner", F.size("gs").alias("n")), "owner")
        lots = max(1, math.ceil((asked.agg(F.sum(F.col("n") + F.col("size"))).first()[0] or 0) / LOT))
        lot, key = F.pmod(F.xxhash64("owner", "part"), F.lit(lots)).cast("int").alias("lot"), [*block, "lot", "slice"]
        lots = written(asked.select(*block, lot).distinct(), "lots")
        members = self.held.crossJoin(F.broadcast(lots))
        return asks.join(gs, "owner").withColumn("lot", lot).groupBy(*key).cogroup(members.groupBy(*key)).applyInArrow(solve, schema)

    @staticmethod
    def _part(rows: DataFrame) -> Column:
        return F.pmod(F.xxhash64("k"), F.lit(max(1, math.ceil(rows.count() / PART)))).cast("int").alias("part")

    def spans_of(self, owners: DataFrame) -> DataFrame:
        """(owner, slice, before, n): of the members around each owner, itself included, how many are in a slice and in those before."""
        every = F.explode(F.sequence(F.lit(0), F.lit(len(self.cuts)))).alias("slice")
        found = self._meet(owners.select("owner", F.lit(0).alias("part"), every), _counts, "owner long, slice int, n long")
        before = Window.partitionBy("owner").orderBy("slice").rowsBetween(Window.unboundedPreceding, -1)
        return written(found.withColumn("before", F.coalesce(F.sum("n").over(before), F.lit(0))), "spans")

    @cached_property
    def spans(self) -> DataFrame:
        return self.spans_of(self.classes.select(F.col("rep").alias("owner")))

    def sociable(self) -> DataFrame:
        """(id) of all members of degree 2 or more."""
        return self.classes.where("many").select(F.explode("ids").alias("id"))

    def named(self, asked: DataFrame, spans: DataFrame) -> DataFrame:
        """asked (k, id, i, j; block) with a and b, the neighbours of id at the places i and j of its sorted list."""
        block = [c for c in asked.columns if c == "block"]
        at = [F.struct(F.lit(s).alias("s"), c.cast("long").alias("at")) for s, c in enumerate((F.col("i"), F.col("i") + 1, F.col("j"), F.col("j") + 1))]
        places = self.owned(asked).select("owner", self._part(asked), "k", "id", *block, F.inline(F.array(*at)))
        met = places.join(spans, "owner").where("before <= at AND at < before + n")
        rows = F.collect_list(F.struct("k", "id", "s", (F.col("at") - F.col("before")).alias("at"))).alias("rows")
        found = self._meet(met.groupBy("owner", "part", "slice", *block).agg(rows), _places, "k long, id long, s int, near long", block)
        found = found.groupBy("k", "id").agg(*(F.max(F.when(F.col("s") == s, F.col("near"))).alias(f"n{s}") for s in range(4)))
        # the list has id itself, which is left out
        pick = lambda s: F.when(F.col(f"n{s}") < F.col("id"), F.col(f"n{s}")).otherwise(F.col(f"n{s + 1}"))
        return found.select("k", "id", pick(0).alias("a"), pick(2).alias("b"))

    def joined(self, pairs: DataFrame) -> DataFrame:
        """pairs (a, b, ...) with closed: whether a and b share a group."""
        gs = self.classes.select(F.explode("ids").alias("id"), "gs")
        both = pairs.join(gs.toDF("a", "ga"), "a").join(gs.toDF("b", "gb"), "b")
        return both.withColumn("closed", F.arrays_overlap("ga", "gb")).drop("ga", "gb")

    def told(self, pairs: DataFrame) -> DataFrame:
        """(k, closed) of pairs (k, a, b, block), each looked for in the groups of a by a's block."""
        asks = self.owned(pairs.withColumnRenamed("a", "id")).select("owner", self._part(pairs), self._slice("b").alias("slice"), "block", "k", "b")
        asks = asks.groupBy("owner", "part", "slice", "block").agg(F.collect_list(F.struct("k", "b")).alias("rows"))
        return self._meet(asks, _hits, "k long, closed boolean", ["block"])

    def kept(self, storage=None) -> "Twins":
        return self

    @property
    def members(self) -> DataFrame:
        """(id, rep) of all members that have a neighbour."""
        return self.classes.select(F.explode("ids").alias("id"), "rep")

    def vertices(self) -> DataFrame:
        return self.members.select("id")

    def degrees(self) -> DataFrame:
        return self.members.join(self.near.select("rep", "degree"), "rep").select("id", "degree")

    def mirrored(self) -> DataFrame:
        return self.links.join(self.classes.select(F.col("rep").alias("dst"), "ids"), "dst").select("src", F.explode("ids").alias("dst"))

    def owned(self, asked: DataFrame) -> DataFrame:
        return asked.join(self.members.withColumnRenamed("rep", "owner"), "id")

    def lists(self, wanted: DataFrame) -> DataFrame:
        some = self.links.join(wanted.select(F.col("owner").alias("src")), "src", "left_semi")
        met = some.join(self.classes.select(F.col("rep").alias("dst"), "ids"), "dst")
        return met.groupBy(F.col("src").alias("owner")).agg(F.array_sort(F.flatten(F.collect_list("ids"))).alias("nbrs"))

    def pick(self, at: str) -> Column:
        here = F.col("nbrs")[F.col(at)]
        return F.when(here < F.col("id"), here).otherwise(F.col("nbrs")[F.col(at) + 1])

    def kin(self, arcs: DataFrame) -> DataFrame:
        return arcs.join(self.members.toDF("dst", "kin"), "dst")

    def average_local(self) -> DataFrame:
        """Mean coefficient of all members of degree 2 or more, from triangles of classes and from pairs within them."""
        size = self.classes.select("rep", "size")
        arcs = self.links.where("src <> dst").join(size.toDF("src", "s"), "src").join(size.toDF("dst", "t"), "dst")
        pairs = arcs.groupBy(F.col("src").alias("rep")).agg(F.expr("sum(t * (t - 1) div 2 + (s - 1) * t)").alias("pairs"), F.count("*").alias("d"))
        d = pairs.select("rep", "d")
        both = arcs.join(d.toDF("src", "ds"), "src").join(d.toDF("dst", "dd"), "dst")
        low = written(both.where("ds < dd OR ds = dd AND src < dst").select(F.col("src").alias("a"), "s", F.col("dst").alias("b"), "t"), "oriented-classes")
        wedges = low.join(low.select("a", F.col("b").alias("c"), F.col("t").alias("u")), "a").where("b < c")
        met = wedges.join(self.edges.toDF("b", "c"), ["b", "c"], "left_semi")
        part = lambda c, n: F.struct(F.col(c).alias("rep"), F.expr(n).alias("n"))
        corners = met.select(F.inline(F.array(part("a", "t * u"), part("b", "s * u"), part("c", "s * t")))).groupBy("rep").agg(F.sum("n").alias("three"))
        rows = self.near.where("degree >= 2").join(pairs, "rep", "left").join(corners, "rep", "left")
        linked = F.expr("(size - 1) * (size - 2) div 2") + F.coalesce("pairs", F.lit(0)) + F.coalesce("three", F.lit(0))
        rows = rows.select("size", (linked / (F.col("degree") * (F.col("degree") - 1) / 2)).alias("c"))
        return rows.agg(F.round(F.sum(F.col("size") * F.col("c")) / F.sum("size"), 6).alias("coefficient"))


def _around(asks: pa.Table, members: pa.Table) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """For each ask (gs, ...): the ids of the slice in order, and marks on those that are in one of the groups."""
    ids, at = np.unique(_flat(members, "ids"), return_inverse=True)
    ends = np.cumsum(_lengths(members, "ids"))
    order, g = np.argsort(members.column("g").to_numpy()), np.sort(members.column("g").to_numpy())
    parts = np.split(at, ends[:-1]) if len(ends) else []
    parts = [parts[x] for x in order.tolist()]
    wants = _flat(asks, "gs")
    found = np.searchsorted(g, wants)
    there = (g[np.minimum(found, len(g) - 1)] == wants) if len(g) else np.zeros(len(wants), bool)
    seen, start = np.zeros(len(ids), bool), 0
    for n in _lengths(asks, "gs").tolist():
        some = found[start : start + n][there[start : start + n]].tolist()
        start += n
        seen[:] = False
        if some:
            seen[np.concatenate([parts[x] for x in some])] = True
        yield ids, seen


def _array(rows: pa.Table, column: str) -> pa.ListArray:
    found = rows.column(column).combine_chunks()
    return found if isinstance(found, pa.ListArray) else pa.concat_arrays(found.chunks) if found.num_chunks else pa.array([], found.type)


def _flat(rows: pa.Table, column: str) -> np.ndarray:
    return _array(rows, column).flatten().to_numpy(zero_copy_only=False)


def _lengths(rows: pa.Table, column: str) -> np.ndarray:
    return pc.list_value_length(_array(rows, column)).to_numpy(zero_copy_only=False).astype(np.int64)


def _counts(asks: pa.Table, members: pa.Table) -> pa.Table:
    n = [np.count_nonzero(seen) for _, seen in _around(asks, members)]
    return pa.table({"owner": asks.column("owner"), "slice": asks.column("slice").cast(pa.int32()), "n": pa.array(n, pa.int64())})


def _each(asks: pa.Table, members: pa.Table, of: str, answer) -> tuple[pa.StructArray, np.ndarray]:
    """The questions (rows) of all asks, and what answer(ids, marks, values) gives for their field `of`."""
    rows = _array(asks, "rows").flatten()
    values = rows.field(of).to_numpy(zero_copy_only=False)
    ends = np.cumsum(_lengths(asks, "rows"))
    found = [answer(ids, seen, x) for (ids, seen), x in zip(_around(asks, members), np.split(values, ends[:-1]) if len(ends) else [])]
    return rows, np.concatenate(found) if found else np.zeros(0, np.int64)


def _places(asks: pa.Table, members: pa.Table) -> pa.Table:
    rows, near = _each(asks, members, "at", lambda ids, seen, at: ids[np.flatnonzero(seen)[at]])
    return pa.table({"k": rows.field("k"), "id": rows.field("id"), "s": rows.field("s").cast(pa.int32()), "near": pa.array(near, pa.int64())})


def _hits(asks: pa.Table, members: pa.Table) -> pa.Table:
    def hit(ids, seen, b):
        at = np.minimum(np.searchsorted(ids, b), len(ids) - 1)
        return seen[at] & (ids[at] == b) if len(ids) else np.zeros(len(b), bool)

    rows, closed = _each(asks, members, "b", hit)
    return pa.table({"k": rows.field("k"), "closed": pa.array(closed.astype(bool), pa.bool_())})
