"""Connected components of the undirected view: (id, component), component being the least id that a vertex reaches."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from netan.contraction import contract as _contract
from netan.engines import block as block_engine
from netan.engines import bsp as bsp_engine
from netan.engines import gas as gas_engine
from netan.engines import msr as msr_engine
from netan.engines.dataflow import Plan
from netan.engines.loop import cut, placed_arcs, slim, sweep_class
from netan.measures import RunLedger
from netan.network import Network
from netan.recovery import Checkpointer
from netan.storage import drop, written


def _start(net: Network) -> tuple[DataFrame, DataFrame]:
    """Arcs both ways, and each vertex as its own component."""
    net = net.undirected()
    arcs = placed_arcs(net.mirrored().select("src", "dst"))
    ids = arcs.select(F.col("src").alias("id")).distinct() if net.isolated is None else net.vertices()
    return arcs, ids.select("id", F.col("id").alias("value"))


def _done(state: DataFrame) -> DataFrame:
    return state.select("id", F.col("value").alias("component"))


def bsp(net: Network, max_supersteps: int = 1000, combiner: bool = True, ledger: RunLedger | None = None, keeper: Checkpointer | None = None) -> DataFrame:
    """Each vertex sends its label when it has changed and takes the least that comes; without combiner, every message travels."""
    arcs, state = _start(net)
    least = F.least(F.col("value"), F.coalesce("msg", "value"))
    return _done(bsp_engine.run(arcs, state, F.col("value"), F.min, least, max_supersteps=max_supersteps, combiner=combiner, ledger=ledger, keeper=keeper))


def dataflow(net: Network, workset: bool = False, max_rounds: int = 1000, ledger: RunLedger | None = None) -> DataFrame:
    """Join labels to edges, least per vertex, join to the old ones; with workset, only labels that have just changed are joined."""
    arcs, state = _start(net)
    ledger = ledger or RunLedger("dataflow-workset" if workset else "dataflow")
    state, _ = cut(state.withColumn("moved", F.lit(True)), "flow-0", arcs)
    for k in range(1, max_rounds + 1):
        labels = Plan.source(state)
        sent = Plan.map(labels, F.col("id").alias("src"), "value", where=F.col("moved") if workset else None)
        told = Plan.map(Plan.join(sent, Plan.source(arcs), "src"), F.col("dst").alias("id"), "value")
        least = Plan.group(told, ["id"], F.min("value").alias("msg"))
        both = Plan.join(labels, least, "id", "left")
        new = F.least("value", F.coalesce("msg", "value"))
        step = Plan.map(both, "id", new.alias("value"), (new < F.col("value")).alias("moved"))
        after, seen = cut(Plan.result(step), f"flow-{k}", arcs, changed=F.count_if("moved"), all=F.count("*"))
        ledger.note(active=seen["all"], changed=seen["changed"], updates=seen["all"])
        drop(state)
        state = after
        if not seen["changed"]:
            ledger.close("converged")
            break
    else:
        ledger.close("cut off")
    return _done(state)


def gas(net: Network, variant: str = "standard", mode: str = "sync", classes: int = 4, seed: int = 7, ledger: RunLedger | None = None, keeper: Checkpointer | None = None) -> DataFrame:
    """variant: "standard", "message" or "delta"; mode: "sync", or "async" by class sweeps."""
    arcs, state = _start(net)
    least = F.least(F.col("value"), F.coalesce("msg", "value"))
    if variant != "standard" and mode == "async":
        return _done(_sweeps(arcs, state, variant == "delta", classes, seed, ledger))
    out = gas_engine.run(arcs, state, F.col("value"), F.min, least, mode=variant, classes=classes if mode == "async" else 1, seed=seed, max_steps=1000, change=F.col("value"), merge=F.least, ledger=ledger, keeper=keeper)
    return _done(out)


def _sweeps(arcs: DataFrame, state: DataFrame, cached: bool, classes: int, seed: int, ledger: RunLedger | None) -> DataFrame:
    """Class sweeps in which values are sent, not pulled; `inbox` holds the least that has come to a vertex.

    With messages, a vertex takes its turn whenever one waits for it, and its inbox is empty afterwards. With a cache, the inbox
    stays, and only a neighbour's change that lowers it calls the vertex up.
    """
    ledger = ledger or RunLedger("gas-delta-async" if cached else "gas-message-async")
    none = F.lit(None).cast("long")
    state, _ = cut(state.select("id", "value", none.alias("inbox"), F.lit(True).alias("tells")), "sweep-0", arcs)
    calls = (F.coalesce(F.col("inbox") < F.col("value"), F.lit(False)) if cached else F.col("inbox").isNotNull()) | F.col("tells")
    for sweep in range(1, 1000):
        sums = {c: 0 for c in ("updates", "changed", "messages_raw", "messages_combined", "messages_cross")}
        for k in range(classes):
            turn = calls & (sweep_class(seed, sweep, classes) == k)
            moved = state.withColumn("turn", turn).withColumn("new", F.when(F.col("turn"), F.least("value", F.coalesce("inbox", "value"))).otherwise(F.col("value")))
            moved = moved.withColumn("fires", F.col("turn") & (F.col("tells") | (F.col("new") < F.col("value"))))
            sent = moved.where("fires").join(arcs, F.col("id") == arcs["src"]).select(arcs["dst"].alias("id"), F.col("new").alias("msg"), arcs["src"].alias("from"))
            kept = F.col("inbox") if cached else F.when(~F.col("turn"), F.col("inbox"))
            met = moved.join(bsp_engine.inbox(sent, F.min, False, ledger), "id", "left")
            counted = ["raw", "cross"] if ledger.messages else []
            after = met.select("id", F.col("new").alias("value"), F.least(kept, "msg").alias("inbox"), (F.col("tells") & ~F.col("turn")).alias("tells"), "turn", (F.col("new") < F.col("value")).alias("diff"), F.col("msg").isNotNull().alias("got"), *counted)
            counters = {c: F.sum(c) for c in counted}
            after, seen = cut(after, f"sweep-{sweep}-{k}", arcs, updates=F.count_if("turn"), n_changed=F.count_if("diff"), combined=F.count_if("got"), left=F.count_if(calls), **counters)
            drop(state)
            state = slim(after, "id", "value", "inbox", "tells")
            for name, of in (("updates", "updates"), ("changed", "n_changed"), ("messages_combined", "combined"), ("messages_raw", "raw"), ("messages_cross", "cross")):
                sums[name] += seen.get(of, 0)
        ledger.note(active=sums["updates"], **sums)
        if not seen["left"]:
            ledger.close("converged")
            break
    else:
        ledger.close("cut off")
    return state


def block(net: Network, blocks: DataFrame, ledger: RunLedger | None = None) -> DataFrame:
    """Local components once; then labels travel between local components only, and whole ones move at the end."""
    arcs, state = _start(net)
    placed = block_engine.arcs_by_block(arcs, blocks)
    local = block_engine.local_components(placed)
    local = written(state.select("id").join(local, "id", "left").select("id", F.coalesce("label", "id").alias("label")), "local")
    cross = placed.where("sblock <> dblock").join(local.toDF("src", "a"), "src").join(local.toDF("dst", "b"), "dst").select(F.col("a").alias("src"), F.col("b").alias("dst"))
    cross = written(cross.where("src <> dst").distinct(), "quotient")
    quotient = cross.select(F.col("src").alias("id")).distinct().select("id", F.col("id").alias("value"))
    least = F.least(F.col("value"), F.coalesce("msg", "value"))
    top = bsp_engine.run(cross, quotient, F.col("value"), F.min, least, max_supersteps=1000, ledger=ledger or RunLedger("block"))
    return local.join(top.select(F.col("id").alias("label"), "value"), "label", "left").select("id", F.coalesce("value", "label").alias("component"))


def msr(net: Network, max_rounds: int = 1000, ledger: RunLedger | None = None) -> DataFrame:
    arcs, state = _start(net)
    lists = arcs.groupBy(F.col("src").alias("id")).agg(F.collect_list("dst").alias("nbrs"))
    state = state.join(lists, "id", "left").withColumn("nbrs", F.coalesce("nbrs", F.array().cast("array<bigint>")))
    return _done(msr_engine.iterate(state, F.col("value"), F.array_min, F.least(F.col("value"), F.coalesce("msg", "value")), max_rounds, True, ledger))


def contract(net: Network) -> DataFrame:
    """Star contraction, for long diameters and the largest networks."""
    out = _contract(net.edges.select("src", "dst"))
    if net.isolated is None:
        return out
    return net.vertices().join(out, "id", "left").select("id", F.coalesce("component", "id").alias("component"))


def sql(net: Network) -> DataFrame:
    """By a recursive query that walks away from every vertex; a walk meets no vertex twice, and none below its start. For small
    networks with few cycles: Spark's recursion neither drops repeats nor aggregates."""
    arcs, _ = _start(net)
    return net.spark.sql(
        """WITH RECURSIVE walk(id, label, path) MAX RECURSION LEVEL 1000 AS (
             SELECT DISTINCT src, src, array(src) FROM {arcs}
             UNION ALL
             SELECT a.dst, w.label, array_append(w.path, a.dst) FROM walk w JOIN {arcs} a ON a.src = w.id
             WHERE w.label < a.dst AND NOT array_contains(w.path, a.dst))
           SELECT id, min(label) AS component FROM walk GROUP BY id""",
        arcs=arcs,
    )


def sizes(labels: DataFrame) -> DataFrame:
    return labels.groupBy("component").agg(F.count("*").alias("size"))


def giant(labels: DataFrame) -> DataFrame:
    """(component, size, share): the largest component, of equals the one with the least id."""
    all_ = sizes(labels).agg(F.max(F.struct("size", (-F.col("component")).alias("c"))).alias("m"), F.sum("size").alias("n"))
    return all_.select((-F.col("m.c")).alias("component"), F.col("m.size").alias("size"), F.round(F.col("m.size") / F.col("n"), 6).alias("share"))


def in_giant(labels: DataFrame) -> DataFrame:
    top = giant(labels).select(F.col("component").alias("giant"))
    return labels.crossJoin(F.broadcast(top)).select("id", (F.col("component") == F.col("giant")).alias("in_giant"))
