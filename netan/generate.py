"""Generated networks for weak scaling: scale-free growth by edge attachment."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from netan.engines.loop import cut, draw
from netan.network import Network
from netan.storage import drop


def edge_attachment(spark: SparkSession, n: int, seed: int = 1) -> Network:
    """n vertices and 2(n - 3) + 3 edges: a triangle, then each new vertex is tied to both ends of an earlier edge by hash.

    Edge 2j + 3 + b of vertex 3 + j leads to end b of edge e(j) < 2j + 3. Ends are found by jumping along these references,
    which halves every chain in each round, so the rounds grow with the logarithm of n.
    """
    if n < 3:
        raise ValueError("three vertices at least")
    steps = spark.range(n - 3).select(F.col("id").alias("j"), F.pmod(draw(seed, "id"), 2 * F.col("id") + 3).alias("e"))
    # the far end of an edge: a vertex, once known, or else the far or near end of another edge
    new = steps.select("j", "e", F.explode(F.array(F.lit(0), F.lit(1))).alias("b"))
    far = new.select((2 * F.col("j") + 3 + F.col("b")).alias("edge"), (3 + F.col("j")).alias("near"), "e", "b")
    # end 0 of an edge is its near (new) vertex, end 1 its far one; the triangle's edges are 0-1, 1-2, 0-2
    first = spark.createDataFrame([(0, 0, 1), (1, 1, 2), (2, 0, 2)], "edge long, near long, far long")
    known = F.when(F.col("e") < 3, F.when(F.col("b") == 0, F.when(F.col("e") == 1, 1).otherwise(0)).otherwise(F.when(F.col("e") == 0, 1).otherwise(2)))
    known = F.when((F.col("b") == 0) & (F.col("e") >= 3), 3 + F.expr("(e - 3) div 2")).otherwise(known)
    state = far.select("edge", "near", known.cast("long").alias("far"), F.when(known.isNull(), F.col("e")).alias("ref"))
    state, seen = cut(state, "grown-0", open=F.count_if(F.col("ref").isNotNull()))
    k = 0
    while seen["open"]:
        k += 1
        other = state.select(F.col("edge").alias("ref"), F.col("far").alias("far2"), F.col("ref").alias("ref2"))
        after = state.join(other, "ref", "left").select("edge", "near", F.coalesce("far", "far2").alias("far"), F.when(F.coalesce("far", "far2").isNull(), F.col("ref2")).alias("ref"))
        after, seen = cut(after, f"grown-{k}", open=F.count_if(F.col("ref").isNotNull()))
        drop(state)
        state = after
    edges = state.select(F.col("near").alias("src"), F.col("far").alias("dst")).union(first.select("near", "far"))
    return Network(edges)


def weak_scaling(spark: SparkSession, workers: int, per_worker: int = 10_000, seed: int = 1) -> Network:
    """About 2 * per_worker edges for each worker."""
    return edge_attachment(spark, per_worker * workers, seed)


def rows_of(net: Network) -> DataFrame:
    return net.edges.select("src", "dst")
