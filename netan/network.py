"""A network as two DataFrames: edges (src, dst[, weight]) and, if isolated vertices matter, vertices (id)."""

from __future__ import annotations

from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from netan.storage import written

EDGE = T.StructType([T.StructField("src", T.LongType(), False), T.StructField("dst", T.LongType(), False), T.StructField("weight", T.DoubleType(), True)])


class Network:
    """Normalised on entry: no null ends (they are refused by a filter), no loops, no repeats; undirected edges as src < dst."""

    #: Whether lists of neighbours hold the vertex itself, which others share (netan.twins).
    closed = False

    def __init__(self, edges: DataFrame, directed: bool = False, vertices: DataFrame | None = None) -> None:
        weight = F.col("weight").cast("double") if "weight" in edges.columns else F.lit(1.0)
        rows = edges.select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst"), weight.alias("weight"))
        rows = rows.where("src IS NOT NULL AND dst IS NOT NULL AND src <> dst")
        if not directed:
            rows = rows.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"), "weight")
        self.edges = rows.groupBy("src", "dst").agg(F.sum("weight").alias("weight"))
        self.directed = directed
        self.isolated = vertices

    @property
    def spark(self):
        return self.edges.sparkSession

    def kept(self, storage: StorageLevel | None = None) -> "Network":
        """The same network with its edges as a written table, so that loops don't derive them again; or, with a storage level, as
        blocks that executors hold in memory, on their disks or both, and make again if they are lost."""
        out = object.__new__(Network)
        out.edges = written(self.edges, "edges") if storage is None else self.edges.persist(storage)
        out.directed, out.isolated = self.directed, self.isolated
        return out

    def vertices(self) -> DataFrame:
        ends = self.edges.select(F.col("src").alias("id")).union(self.edges.select(F.col("dst").alias("id")))
        if self.isolated is not None:
            ends = ends.union(self.isolated.select(F.col("id").cast("long")))
        return ends.distinct()

    def arcs(self) -> DataFrame:
        """Edges as messages run: as they are if directed, both ways if not."""
        return self.edges if self.directed else self.mirrored()

    def mirrored(self) -> DataFrame:
        both = self.edges.union(self.edges.select("dst", "src", "weight").toDF("src", "dst", "weight"))
        return both.groupBy("src", "dst").agg(F.sum("weight").alias("weight")) if self.directed else both

    def undirected(self) -> "Network":
        return self if not self.directed else Network(self.edges, False, self.isolated)

    def reversed(self) -> "Network":
        out = object.__new__(Network)
        out.edges, out.directed, out.isolated = self.edges.select("dst", "src", "weight").toDF("src", "dst", "weight"), self.directed, self.isolated
        return out

    def subgraph(self, vertex: Column | None = None, edge: Column | None = None) -> "Network":
        """Vertices by a condition on id, edges by one on src, dst, weight; an edge needs both ends."""
        rows = self.edges if edge is None else self.edges.where(edge)
        if vertex is not None:
            keep = self.vertices().where(vertex)
            rows = rows.join(keep.toDF("src"), "src", "left_semi").join(keep.toDF("dst"), "dst", "left_semi").select("src", "dst", "weight")
        return Network(rows, self.directed)

    def min_degree(self, k: int) -> "Network":
        """The edges both of whose ends have k neighbours or more in this network; taken once, not until nothing more falls."""
        degree = self.undirected().mirrored().groupBy(F.col("src").alias("id")).agg(F.count("*").alias("d"))
        keep = degree.where(F.col("d") >= k).select("id")
        rows = self.edges.join(keep.toDF("src"), "src", "left_semi").join(keep.toDF("dst"), "dst", "left_semi")
        return Network(rows.select("src", "dst", "weight"), self.directed)

    def owned(self, asked: DataFrame) -> DataFrame:
        """asked (id, ...) with the owner of each vertex's list of neighbours."""
        return asked.withColumn("owner", F.col("id"))

    def lists(self, wanted: DataFrame) -> DataFrame:
        """(owner, nbrs): sorted lists of the wanted owners."""
        rows = self.mirrored().join(wanted.select(F.col("owner").alias("src")), "src", "left_semi")
        return rows.groupBy(F.col("src").alias("owner")).agg(F.array_sort(F.collect_list("dst")).alias("nbrs"))

    def pick(self, at: str) -> Column:
        """The neighbour of `id` at a place, out of its owner's `nbrs`."""
        return F.col("nbrs")[F.col(at)]

    def kin(self, arcs: DataFrame) -> DataFrame:
        """arcs with the end that edges name for dst."""
        return arcs.withColumn("kin", F.col("dst"))

    def adjacency(self) -> DataFrame:
        """(id, nbrs): sorted lists, for methods that intersect them."""
        return self.arcs().groupBy(F.col("src").alias("id")).agg(F.array_sort(F.collect_list("dst")).alias("nbrs"))

    def register(self, prefix: str) -> None:
        self.edges.createOrReplaceTempView(f"{prefix}_edges")
        self.vertices().createOrReplaceTempView(f"{prefix}_vertices")
