"""Degree tables and the overview of a network."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from netan.network import Network


def degrees(net: Network) -> DataFrame:
    """(id, degree) with all edges of a vertex; isolated vertices have degree 0 if the network names them."""
    if net.closed:
        return net.degrees()
    out = net.undirected().mirrored().groupBy(F.col("src").alias("id")).agg(F.count("*").alias("degree"))
    if net.isolated is None:
        return out
    return net.vertices().join(out, "id", "left").select("id", F.coalesce("degree", F.lit(0)).alias("degree"))


def out_degrees(net: Network) -> DataFrame:
    return net.arcs().groupBy(F.col("src").alias("id")).agg(F.count("*").alias("degree"))


def in_degrees(net: Network) -> DataFrame:
    return net.arcs().groupBy(F.col("dst").alias("id")).agg(F.count("*").alias("degree"))


def degree_histogram(net: Network) -> DataFrame:
    return degrees(net).groupBy("degree").agg(F.count("*").alias("vertices"))


def overview(net: Network) -> DataFrame:
    """(n, m, dmax, wedges): one row; edges and degrees of the undirected view, m of the network as it is."""
    d = degrees(net).agg(F.count("*").alias("n"), F.max("degree").alias("dmax"), F.sum(F.expr("degree * (degree - 1) div 2")).alias("wedges"))
    return d.crossJoin(net.edges.agg(F.count("*").alias("m"))).select("n", "m", F.col("dmax").cast("long").alias("dmax"), F.col("wedges").cast("long").alias("wedges"))


def degree_skew(net: Network) -> DataFrame:
    """(max, mean, ratio): how far the largest degree is above the mean."""
    d = degrees(net).agg(F.max("degree").alias("largest"), F.avg("degree").alias("mean"))
    return d.select("largest", F.round("mean", 6).alias("mean"), F.round(F.col("largest") / F.col("mean"), 6).alias("ratio"))
