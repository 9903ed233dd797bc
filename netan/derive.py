"""Networks derived from the given relational tables (edges only; `network` wraps them)."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from netan.network import Network
from netan.ordering import numbered
from netan.twins import Twins

DIRECTED = {"trade", "handoff", "hyperlink"}
NAMES = ("copurchase", "copurchase2", "supply", "trade", "cosupply", "handoff", "coactivity", "covalue", "chat", "geo", "sharedline", "hyperlink", "colink", "nearest", "sharedline_star")
#: Keeps suppliers' ids apart from parts' and customers'.
OFFSET = 10_000_000


def _read(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet").select(*columns)


def _pairs(rows: DataFrame, member: str, *group: str) -> DataFrame:
    """(src, dst, weight): two different members of one group, with the number of their common groups."""
    rows = rows.select(*group, F.col(member).alias("src")).distinct()
    other = rows.withColumnRenamed("src", "dst")
    return rows.join(other, list(group)).where("src < dst").groupBy("src", "dst").agg(F.count("*").cast("double").alias("weight"))


def copurchase(spark, sf_dir):
    return _pairs(_read(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey"), "l_partkey", "l_orderkey")


def copurchase2(spark, sf_dir):
    return copurchase(spark, sf_dir).where("weight >= 2")


def supply(spark, sf_dir):
    rows = _read(spark, sf_dir, "lineitem", "l_partkey", "l_suppkey").distinct()
    return rows.select(F.col("l_partkey").alias("src"), (F.col("l_suppkey") + OFFSET).alias("dst"))


def trade(spark, sf_dir):
    orders = _read(spark, sf_dir, "orders", "o_orderkey", "o_custkey")
    lines = _read(spark, sf_dir, "lineitem", "l_orderkey", "l_suppkey")
    rows = orders.join(lines, orders["o_orderkey"] == lines["l_orderkey"])
    return rows.select(F.col("o_custkey").alias("src"), (F.col("l_suppkey") + OFFSET).alias("dst")).distinct()


def cosupply(spark, sf_dir):
    return _pairs(_read(spark, sf_dir, "lineitem", "l_orderkey", "l_suppkey"), "l_suppkey", "l_orderkey")


def handoff(spark, sf_dir):
    """The event after the next is sought within each hour; the last of an hour is followed by the first of the next hour with events."""
    rows = _read(spark, sf_dir, "events", "ts", "event_id", "user_id").withColumn("hour", F.date_trunc("hour", "ts"))
    firsts = rows.groupBy("hour").agg(F.min(F.struct("ts", "event_id", "user_id")).alias("e"))
    later = firsts.select("hour", F.lead(F.col("e.user_id")).over(Window.orderBy("hour")).alias("later"))  # a row for each hour
    after = F.lead("user_id").over(Window.partitionBy("hour").orderBy("ts", "event_id"))
    rows = rows.withColumn("after", after).join(later, "hour").select(F.col("user_id").alias("src"), F.coalesce("after", "later").alias("dst"))
    return rows.where("dst IS NOT NULL AND src <> dst").distinct()


def _slots(spark, sf_dir):
    slot = F.floor(F.unix_timestamp(F.col("ts").cast("timestamp")) / 600).alias("slot")
    return _read(spark, sf_dir, "events", "ts", "user_id").select(slot, "user_id")


def coactivity(spark, sf_dir):
    return _pairs(_slots(spark, sf_dir), "user_id", "slot")


def covalue(spark, sf_dir):
    return _pairs(_read(spark, sf_dir, "events", "event_type", "value", "user_id"), "user_id", "event_type", "value")


def chat(spark, sf_dir):
    turns = _read(spark, sf_dir, "conversations", "conv_id", "turn")
    later = turns.select("conv_id", (F.col("turn") - 1).alias("turn"))
    here = (F.col("conv_id") * 1000 + F.col("turn")).alias("src")
    return turns.join(later, ["conv_id", "turn"]).select(here, (F.col("conv_id") * 1000 + F.col("turn") + 1).alias("dst"))


def geo(spark, sf_dir):
    nation = _read(spark, sf_dir, "nation", "n_nationkey", "n_regionkey")
    customer, supplier = _read(spark, sf_dir, "customer", "c_custkey", "c_nationkey"), _read(spark, sf_dir, "supplier", "s_suppkey", "s_nationkey")
    edge = lambda df, a, b: df.select(a.cast("long").alias("src"), b.cast("long").alias("dst"))
    rows = edge(nation, F.col("n_regionkey"), F.col("n_nationkey") + 1000)
    rows = rows.union(edge(customer, F.col("c_nationkey") + 1000, F.col("c_custkey") + 1_000_000))
    return rows.union(edge(supplier, F.col("s_nationkey") + 1000, F.col("s_suppkey") + 50_000_000))


def _lines(spark, sf_dir):
    """(doc_id, line): different trimmed lines of 20 characters or more."""
    docs = _read(spark, sf_dir, "documents", "doc_id", "text")
    lines = docs.select("doc_id", F.explode(F.split("text", "\n")).alias("line")).select("doc_id", F.trim("line").alias("line"))
    return lines.where(F.length("line") >= 20).distinct()


def sharedline(spark, sf_dir):
    """Lines that more documents share tie nobody here, by definition; sharedline_star has them all."""
    lines = _lines(spark, sf_dir)
    some = lines.groupBy("line").count().where("count BETWEEN 2 AND 50").select("line")
    return _pairs(lines.join(some, "line"), "doc_id", "line")


def sharedline_star(spark, sf_dir):
    """Every line ties its documents to the least of them: the components of all pairs, whatever a line's documents number."""
    lines = _lines(spark, sf_dir)
    hubs = lines.groupBy("line").agg(F.min("doc_id").alias("src"))
    rows = lines.join(hubs, "line").where("src <> doc_id")
    return rows.groupBy("src", F.col("doc_id").alias("dst")).agg(F.count("*").cast("double").alias("weight"))


def _links(spark, sf_dir):
    pages = _read(spark, sf_dir, "pages", "page_id", "html")
    return pages.select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("link")).distinct()


def hyperlink(spark, sf_dir):
    links = _links(spark, sf_dir)
    names = numbered(links, "link", "k")
    return links.join(names, "link").select(F.col("page_id").alias("src"), (F.col("k") + 1_000_000).alias("dst")).distinct()


def colink(spark, sf_dir):
    return _pairs(_links(spark, sf_dir), "page_id", "link")


def colink_star(spark, sf_dir):
    """Every link ties its pages to the least of them: the components of all pairs, in as many edges as there are links of pages."""
    links = _links(spark, sf_dir)
    hubs = links.groupBy("link").agg(F.min("page_id").alias("src"))
    return links.join(hubs, "link").where("src <> page_id").select("src", F.col("page_id").alias("dst"))


#: Networks with the same components, and the same vertices, as the pairs of these.
STARS = {"colink": colink_star}


def nearest(spark, sf_dir, k: int = 8, block_rows: int = 2000):
    """Each vector's k nearest by cosine, ties by id. Vectors are the queries, in blocks; each pair of blocks is one task's group and
    gives k of each query, so a vector travels as often as there are blocks and nothing grows with the number of pairs."""
    rows = _read(spark, sf_dir, "embeddings", "vec_id", "embedding").where("embedding IS NOT NULL")
    blocks = max(1, -(-rows.count() // block_rows))
    own, every = F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int"), F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    rows = rows.withColumn("own", own)
    asks = rows.select("vec_id", "embedding", F.lit(True).alias("asks"), F.col("own").alias("q"), every.alias("d"))
    has = rows.select("vec_id", "embedding", F.lit(False).alias("asks"), every.alias("q"), F.col("own").alias("d"))

    def best(part: pa.Table) -> pa.Table:
        part = part.sort_by("vec_id")
        e = np.array(part.column("embedding").to_pylist(), np.float64)
        e /= np.linalg.norm(e, axis=1, keepdims=True)
        ids, mine = part.column("vec_id").to_numpy(), part.column("asks").to_numpy()
        q, d = np.flatnonzero(mine), np.flatnonzero(~mine)
        near = np.round(e[q] @ e[d].T, 9)
        near[ids[q][:, None] == ids[d][None]] = -2
        top = np.argsort(-near, axis=1, kind="stable")[:, :k]
        out = pa.table({"src": np.repeat(ids[q], top.shape[1]), "dst": ids[d][top].ravel(), "near": np.take_along_axis(near, top, 1).ravel()})
        return out.filter(pa.compute.greater(out.column("near"), -2))

    found = asks.unionByName(has).groupBy("q", "d").applyInArrow(best, "src long, dst long, near double")
    order = Window.partitionBy("src").orderBy(F.col("near").desc(), "dst")
    return found.withColumn("r", F.row_number().over(order)).where(F.col("r") <= k).select("src", "dst")


def network(spark: SparkSession, sf_dir: str, name: str) -> Network:
    if name not in NAMES:
        raise ValueError(f"no fixture named {name}")
    return Network(globals()[name](spark, sf_dir), name in DIRECTED)


#: Members and groups of networks that can be had by classes.
GROUPED = {"colink": (_links, "page_id", "link"), "coactivity": (_slots, "user_id", "slot"), "covalue": (lambda spark, sf_dir: _read(spark, sf_dir, "events", "event_type", "value", "user_id"), "user_id", "event_type", "value")}


def for_samples(spark: SparkSession, sf_dir: str, name: str) -> Network:
    """The network, by classes of twins if it is one of common groups."""
    if name not in GROUPED:
        return network(spark, sf_dir, name).kept()
    rows, *columns = GROUPED[name]
    return Twins(rows(spark, sf_dir), *columns)


def for_components(spark: SparkSession, sf_dir: str, name: str) -> Network:
    """The network, or a smaller one with its vertices and components."""
    if name not in STARS:
        return network(spark, sf_dir, name)
    return Network(STARS[name](spark, sf_dir))
