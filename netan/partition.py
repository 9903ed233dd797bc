"""Blocks of vertices, and what they cost: cut, balance, boundary, replicas."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from netan.engines.loop import cut, draw, placed_arcs, slim
from netan.network import Network
from netan.storage import drop, written


def by_hash(net: Network, k: int) -> DataFrame:
    return net.vertices().select("id", F.pmod(F.xxhash64("id"), F.lit(k)).cast("int").alias("block"))


def by_modulo(net: Network, k: int) -> DataFrame:
    return net.vertices().select("id", F.pmod("id", F.lit(k)).cast("int").alias("block"))


def by_range(net: Network, k: int) -> DataFrame:
    ids = net.vertices()
    cuts = ids.approxQuantile("id", [j / k for j in range(1, k)], 0.001)
    block = F.lit(0)
    for c in cuts:
        block = block + (F.col("id") > c).cast("int")
    return ids.select("id", block.cast("int").alias("block"))


def by_label_propagation(net: Network, k: int, slack: float = 0.1, rounds: int = 8, seed: int = 3) -> DataFrame:
    """(id, block): vertices move to the block of most neighbours as long as it has room; half of them may move in a round."""
    arcs = net.undirected().mirrored().select("src", "dst")
    state = written(net.vertices().select("id", F.pmod(F.xxhash64("id"), F.lit(k)).cast("int").alias("block")), "blocks-0")
    room = (1 + slack) * state.count() / k
    for r in range(1, rounds + 1):
        near = arcs.join(state, arcs["src"] == state["id"]).groupBy(F.col("dst").alias("id"), "block").agg(F.count("*").alias("c"))
        best = near.groupBy("id").agg(F.max(F.struct("c", (-F.col("block")).alias("b"))).alias("m")).select("id", (-F.col("m.b")).cast("int").alias("to"))
        sizes = state.groupBy("block").agg(F.count("*").alias("size"))
        moves = state.join(best, "id").where("to <> block").where(draw(seed, F.lit(r), "id") % 2 == 0)
        wants = moves.groupBy("to").agg(F.count("*").alias("wants"))
        free = wants.join(sizes.withColumnRenamed("block", "to"), "to", "left").select("to", ((F.lit(room) - F.coalesce("size", F.lit(0))) / F.col("wants")).alias("chance"))
        go = moves.join(free, "to").where(draw(seed, F.lit(-r), "id") < F.col("chance") * (1 << 32)).select("id", "to")
        after, seen = cut(state.join(go, "id", "left").select("id", F.coalesce("to", "block").alias("block"), F.col("to").isNotNull().alias("moved")), f"blocks-{r}", moved=F.count_if("moved"))
        drop(state)
        state = slim(after, "id", "block")
        if not seen["moved"]:
            break
    return state


def boundary(net: Network, blocks: DataFrame) -> DataFrame:
    """(block, internal, boundary): vertices of each block, and neighbours of them in other blocks."""
    arcs = net.undirected().mirrored().join(blocks.toDF("src", "block"), "src").join(blocks.toDF("dst", "other"), "dst")
    near = arcs.where("block <> other").groupBy("block").agg(F.count_distinct("dst").alias("boundary"))
    return blocks.groupBy("block").agg(F.count("*").alias("internal")).join(near, "block", "left").select("block", "internal", F.coalesce("boundary", F.lit(0)).alias("boundary"))


def edge_cut(net: Network, blocks: DataFrame) -> DataFrame:
    """(edges, cross, share) of edges whose ends lie in two blocks."""
    both = net.edges.join(blocks.toDF("src", "s"), "src").join(blocks.toDF("dst", "d"), "dst")
    return both.agg(F.count("*").alias("edges"), F.count_if(F.col("s") != F.col("d")).alias("cross")).withColumn("share", F.round(F.col("cross") / F.col("edges"), 6))


def balance(blocks: DataFrame) -> DataFrame:
    """(blocks, largest, ratio): the largest block against the mean."""
    sizes = blocks.groupBy("block").agg(F.count("*").alias("n"))
    return sizes.agg(F.count("*").alias("blocks"), F.max("n").alias("largest"), F.round(F.max("n") / F.avg("n"), 6).alias("ratio"))


def replication(net: Network, part: Column, name: str = "factor") -> DataFrame:
    """One row: mean number of parts in which a vertex has an edge, when edges are dealt by `part` (of src and dst)."""
    ends = net.edges.select(part.alias("p"), F.explode(F.array("src", "dst")).alias("id")).distinct()
    return ends.groupBy("id").agg(F.count("*").alias("c")).agg(F.round(F.avg("c"), 6).alias(name))


def messages(net: Network, blocks: DataFrame) -> DataFrame:
    """(raw, combined, cross) messages if every vertex tells all its neighbours: all, after folding per block and receiver, across blocks."""
    arcs = net.undirected().mirrored().join(blocks.toDF("src", "s"), "src").join(blocks.toDF("dst", "d"), "dst")
    per = arcs.groupBy("s", "dst").agg(F.count("*").alias("c"), F.count_if(F.col("s") != F.col("d")).alias("x"))
    return per.agg(F.sum("c").alias("raw"), F.count("*").alias("combined"), F.sum("x").alias("cross"))


def colouring(net: Network, seed: int = 5, max_rounds: int = 1000) -> DataFrame:
    """(id, colour): no two neighbours have one colour. In each round, open vertices whose hash is above those of all their open
    neighbours take the round's colour; so two neighbours never take it together."""
    arcs = placed_arcs(net.undirected().mirrored().select("src", "dst"))
    state, seen = cut(net.vertices().select("id", F.lit(None).cast("int").alias("colour")), "colours-0", arcs, open=F.count("*"))
    for k in range(max_rounds):
        if not seen["open"]:
            return state
        rank = F.struct(draw(seed, F.lit(k), "id"), F.col("id"))
        open_ = state.where("colour IS NULL").select("id", rank.alias("rank"))
        above = open_.join(arcs, open_["id"] == arcs["src"]).groupBy(arcs["dst"].alias("id")).agg(F.max("rank").alias("top"))
        wins = F.col("colour").isNull() & (F.col("top").isNull() | (rank > F.col("top")))
        after = state.join(above, "id", "left").select("id", F.when(wins, k).otherwise(F.col("colour")).cast("int").alias("colour"))
        after, seen = cut(after, f"colours-{k + 1}", arcs, open=F.count_if(F.col("colour").isNull()))
        drop(state)
        state = after
    raise RuntimeError(f"vertices are left without a colour after {max_rounds} rounds")


def clashes(net: Network, colours: DataFrame) -> DataFrame:
    """(vertices, clashes): vertices that have a colour, and edges whose ends have the same."""
    ends = net.undirected().edges.join(colours.toDF("src", "a"), "src").join(colours.toDF("dst", "b"), "dst")
    return colours.agg(F.count("colour").alias("vertices")).crossJoin(ends.agg(F.count_if(F.col("a") == F.col("b")).alias("clashes")))
