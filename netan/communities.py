"""Communities by label propagation: (id, community). Each vertex takes the label that most of its neighbours hold."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from netan.engines import block as block_engine
from netan.engines import gas as gas_engine
from netan.engines.dataflow import Plan
from netan.engines.loop import cut, draw, placed_arcs, slim, sweep_class
from netan.measures import RunLedger
from netan.network import Network
from netan.storage import drop, written


def start(net: Network, init: str = "self", seed: int = 1) -> tuple[DataFrame, DataFrame]:
    """Arcs both ways, and the first labels: "self", "random_neighbour" or "min_neighbour"."""
    arcs = placed_arcs(net.undirected().mirrored().select("src", "dst", "weight"))
    if init == "self":
        state = arcs.select(F.col("src").alias("id")).distinct().select("id", F.col("id").alias("value"))
    elif init == "min_neighbour":
        state = arcs.groupBy(F.col("src").alias("id")).agg(F.min("dst").alias("value"))
    elif init == "random_neighbour":
        state = arcs.groupBy(F.col("src").alias("id")).agg(F.min_by("dst", F.struct(draw(seed, "src", "dst"), "dst")).alias("value"))
    else:
        raise ValueError(init)
    return arcs, state


def best_label(tie: str = "min", seed: int = 1, step: int = 0, weighted: bool = False) -> Callable[[DataFrame], DataFrame]:
    """Folds rows (id, msg[, own, w]) to (id, msg): the most frequent label. Ties: "min", "random" (by hash), or "keep" one's own."""

    def fold(rows: DataFrame) -> DataFrame:
        count = F.sum("w") if weighted else F.count("*")
        counts = rows.groupBy("id", "msg").agg(count.alias("c"), *([F.max("own").alias("own")] if tie == "keep" else []))
        order = {"min": [(-F.col("msg")).alias("l")], "random": [draw(seed, F.lit(step), "id", "msg").alias("h"), (-F.col("msg")).alias("l")], "keep": [(F.col("msg") == F.col("own")).alias("k"), (-F.col("msg")).alias("l")]}[tie]
        return counts.groupBy("id").agg((-F.max(F.struct("c", *order))["l"]).alias("msg"))

    return fold


def _told(arcs: DataFrame, state: DataFrame, tie: str) -> DataFrame:
    """(id, msg, w[, own]): what each vertex hears from its neighbours."""
    rows = arcs.join(state, arcs["src"] == state["id"]).select(F.col("dst").alias("id"), F.col("value").alias("msg"), F.col("weight").alias("w"))
    return rows.join(state.select("id", F.col("value").alias("own")), "id") if tie == "keep" else rows


def bsp(net: Network, steps: int = 10, init: str = "self", tie: str = "min", seed: int = 1, weighted: bool = False, halt: str = "no_change", theta: float = 0.0, ledger: RunLedger | None = None, history: list | None = None, on_cycle: str = "stop") -> DataFrame:
    """Synchronous propagation. halt: "fixed"; "no_change"; "share" (at most theta of the vertices change); or "cycle", which
    also ends when the labels are those of any step before (on_cycle "sweep" then goes on in class sweeps)."""
    arcs, state = start(net, init, seed)
    ledger = ledger or RunLedger("lpa-bsp")
    state, first = cut(state, "lpa-0", arcs, print=F.bit_xor(F.xxhash64("id", "value")))
    prints: list = [first["print"]]
    for k in range(1, steps + 1):
        heard = best_label(tie, seed, k, weighted)(_told(arcs, state, tie))
        after = state.join(heard, "id", "left").select("id", F.coalesce("msg", "value").alias("value"), (F.coalesce("msg", "value") != F.col("value")).alias("diff"))
        after, seen = cut(after, f"lpa-{k}", arcs, changed=F.count_if("diff"), all=F.count("*"), print=F.bit_xor(F.xxhash64("id", "value")))
        ledger.note(active=seen["all"], changed=seen["changed"], updates=seen["all"])
        if history is None:
            drop(state)
        else:
            history.append((after.select("id", "value"), seen["changed"]))
        state = slim(after, "id", "value")
        prints.append(seen["print"])
        if halt != "fixed" and seen["changed"] <= (theta * seen["all"] if halt == "share" else 0):
            ledger.close("converged")
            break
        if halt == "cycle" and prints[-1] in prints[:-1]:
            ledger.close("oscillating")
            if on_cycle == "sweep":
                return sweep(net, sweeps=50, tie="keep", seed=seed, state=state)
            break
    else:
        ledger.close("fixed" if halt == "fixed" else "cut off")
    return state.select("id", F.col("value").alias("community"))


def dataflow(net: Network, iterations: int = 10, init: str = "self", seed: int = 1) -> DataFrame:
    """Join; group by vertex and label and sum; reduce each vertex's group to its best label, in an operator graph."""
    arcs, state = start(net, init, seed)
    state, _ = cut(state, "lpa-flow-0", arcs)
    for k in range(1, iterations + 1):
        labels = Plan.source(state)
        pairs = Plan.map(Plan.join(Plan.map(labels, F.col("id").alias("src"), "value"), Plan.source(arcs), "src"), F.col("dst").alias("id"), "value")
        counts = Plan.group(pairs, ["id", "value"], F.count("*").alias("c"))
        first = Window.partitionBy("id").orderBy(F.col("c").desc(), F.col("value"))
        best = Plan.reduce(counts, ["id"], lambda df: df.withColumn("r", F.row_number().over(first)).where("r = 1").select("id", "value"))
        after, _ = cut(Plan.result(best), f"lpa-flow-{k}", arcs)
        drop(state)
        state = after
    return state.select("id", F.col("value").alias("community"))


def gas(net: Network, steps: int = 10, mode: str = "sync", classes: int = 2, seed: int = 7, init: str = "self", ledger: RunLedger | None = None) -> DataFrame:
    """The histogram of neighbours' labels is the fold; a vertex whose label has changed signals its neighbours."""
    arcs, state = start(net, init, seed)

    def histogram(rows: DataFrame) -> DataFrame:
        counts = rows.groupBy("id", "msg").agg(F.count("*").alias("c"))
        lists = counts.groupBy("id").agg(F.map_from_entries(F.collect_list(F.struct("msg", "c"))).alias("h"))
        top = F.array_max(F.transform(F.map_entries("h"), lambda e: F.struct(e["value"].alias("c"), (-e["key"]).alias("l"))))
        return lists.select("id", (-top["l"]).alias("msg"))

    out = gas_engine.run(arcs.select("src", "dst"), state, F.col("value"), histogram, F.coalesce("msg", "value"), classes=classes if mode == "async" else 1, seed=seed, max_steps=steps, ledger=ledger, fold_rows=True)
    return out.select("id", F.col("value").alias("community"))


def sweep(net: Network, sweeps: int = 10, classes: int = 2, seed: int = 7, tie: str = "min", init: str = "self", sides: Column | None = None, colours: DataFrame | None = None, weighted: bool = False, state: DataFrame | None = None, ledger: RunLedger | None = None) -> DataFrame:
    """Class sweeps: classes run one after another and see each other's labels. They are hashed anew in each sweep; or fixed, by
    `sides` (a column over id, from 0 on) or by `colours` (id, colour). With a proper colouring, as of partition.colouring, no two
    neighbours move at once, so that the run is one that some order of single vertices gives."""
    arcs, first = start(net, init, seed)
    ledger = ledger or RunLedger("lpa-sweep")
    state, _ = cut(first if state is None else state.select("id", "value"), "lpa-sweep-0", arcs)
    if colours is not None:
        classes = (colours.agg(F.max("colour")).first()[0] or 0) + 1
    for s in range(1, sweeps + 1):
        changed = updates = 0
        for k in range(classes):
            which = sweep_class(seed, s, classes) if sides is None else sides
            mine = state.select("id").where(which == k) if colours is None else colours.where(F.col("colour") == k).select("id")
            heard = _told(arcs, state, tie).join(mine, "id", "left_semi")
            heard = best_label(tie, seed, s, weighted)(heard)
            after = state.join(heard, "id", "left").select("id", F.coalesce("msg", "value").alias("value"), (F.coalesce("msg", "value") != F.col("value")).alias("diff"), F.col("msg").isNotNull().alias("turn"))
            after, seen = cut(after, f"lpa-sweep-{s}-{k}", arcs, changed=F.count_if("diff"), updates=F.count_if("turn"))
            drop(state)
            state = slim(after, "id", "value")
            changed, updates = changed + seen["changed"], updates + seen["updates"]
        ledger.note(changed=changed, updates=updates)
        if not changed:
            ledger.close("converged")
            break
    else:
        ledger.close("cut off")
    return state.select("id", F.col("value").alias("community"))


def _block_kernel(ids, old, src, dst, share, outside):
    """Vertices by ascending id take their best label at once, until the block is stable or ten rounds are over."""
    label = old.copy()
    starts = np.searchsorted(dst, np.arange(len(ids) + 1))
    for _ in range(10):
        moved = False
        for v in range(len(ids)):
            a, b = starts[v], starts[v + 1]
            if a == b:
                continue
            near = np.where(src[a:b] >= 0, label[src[a:b]], outside[a:b])
            names, counts = np.unique(near, return_counts=True)
            best = names[counts == counts.max()]
            if label[v] not in best:
                label[v], moved = best[0], True
        if not moved:
            break
    return label


def block(net: Network, blocks: DataFrame, supersteps: int = 5, init: str = "self", ledger: RunLedger | None = None) -> DataFrame:
    arcs, state = start(net, init)
    placed = written(block_engine.arcs_by_block(arcs.select("src", "dst", F.lit(1.0).alias("share")), blocks), "block-arcs")
    out = block_engine.run(placed, written(state.join(blocks, "id").select("id", "block", "value"), "block-0"), _block_kernel, "id long, block int, value long, old long", supersteps, 0, ledger)
    return out.select("id", F.col("value").alias("community"))


def msr(net: Network, rounds: int = 10, init: str = "self", ledger: RunLedger | None = None) -> DataFrame:
    from netan.engines import msr as engine

    arcs, state = start(net, init)
    lists = arcs.groupBy(F.col("src").alias("id")).agg(F.collect_list("dst").alias("nbrs"))

    def best(msgs: Column) -> Column:
        kinds = F.array_distinct(msgs)
        counted = F.transform(kinds, lambda x: F.struct(F.size(F.filter(msgs, lambda y: y == x)).alias("c"), (-x).alias("l")))
        return -F.array_max(counted)["l"]

    out = engine.iterate(state.join(lists, "id"), F.col("value"), best, F.coalesce("msg", "value"), rounds, ledger=ledger)
    return out.select("id", F.col("value").alias("community"))


def oscillation(history: list) -> tuple[int, int]:
    """(period, vertices that flip) from bsp()'s history with labels of each step; (1, 0) at rest, (0, changed) if no period is seen.

    The period is the least number of steps after which the newest labels have stood before.
    """
    if not history or history[-1][1] == 0:
        return 1, 0
    now = history[-1][0]
    for period in range(2, len(history)):
        before = history[-1 - period][0].withColumnRenamed("value", "old")
        if now.join(before, "id").where("value <> old").isEmpty():
            return period, history[-1][1]
    return 0, history[-1][1]


def sizes(labels: DataFrame) -> DataFrame:
    return labels.groupBy("community").agg(F.count("*").alias("size"))


def purity(labels: DataFrame, truth: DataFrame) -> DataFrame:
    """(vertices, purity): share of vertices that have the most frequent truth (id, label) of their community."""
    counts = labels.join(truth, "id").groupBy("community", "label").agg(F.count("*").alias("c"))
    best = counts.groupBy("community").agg(F.max("c").alias("top"), F.sum("c").alias("all"))
    return best.agg(F.sum("all").alias("vertices"), F.round(F.sum("top") / F.sum("all"), 6).alias("purity"))


def modularity(net: Network, labels: DataFrame) -> DataFrame:
    """One row: share of edges within communities, less what degrees alone would give."""
    arcs = net.undirected().mirrored().join(labels.toDF("src", "a"), "src").join(labels.toDF("dst", "b"), "dst")
    per = arcs.groupBy("a").agg(F.count_if(F.col("a") == F.col("b")).alias("i"), F.count("*").alias("d"))
    all_ = per.agg(F.sum("i").alias("i"), F.sum("d").alias("m"), F.sum(F.col("d").cast("double") * F.col("d")).alias("q"))
    return all_.select(F.round(F.col("i") / F.col("m") - F.col("q") / (F.col("m").cast("double") * F.col("m")), 6).alias("modularity"))


def unstable(net: Network, labels: DataFrame) -> DataFrame:
    """(vertices, unstable): how many vertices there are, and how many hold a label that is not one of their neighbours' most frequent."""
    arcs = net.undirected().mirrored().select("src", "dst")
    told = arcs.join(labels.toDF("src", "msg"), "src").groupBy(F.col("dst").alias("id"), "msg").agg(F.count("*").alias("c"))
    top = told.groupBy("id").agg(F.max("c").alias("top"))
    own = labels.join(told, (labels["id"] == told["id"]) & (labels["community"] == told["msg"]), "left").select(labels["id"], F.coalesce("c", F.lit(0)).alias("c"))
    return own.join(top, "id").agg(F.count("*").alias("vertices"), F.count_if(F.col("c") < F.col("top")).alias("unstable"))
