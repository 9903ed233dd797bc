"""PageRank: (id, score). next(v) = jump r(v) + (1 - jump) sum over neighbours u of score(u) / degree(u), with r = 1."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from netan.engines import block as block_engine
from netan.engines import bsp as bsp_engine
from netan.engines import gas as gas_engine
from netan.engines import msr as msr_engine
from netan.engines.dataflow import Plan
from netan.engines.loop import cut, placed_arcs, slim
from netan.measures import RunLedger
from netan.network import Network
from netan.recovery import Checkpointer
from netan.storage import drop, written

JUMP = 0.15


def shares(net: Network, degree: str = "out") -> DataFrame:
    """Arcs with share = 1 / degree of src: its out-degree, or with "total" its number of neighbours in the undirected view."""
    arcs = (net if degree == "out" else net.undirected()).arcs().select("src", "dst")
    d = arcs.groupBy("src").agg((1.0 / F.count("*")).alias("share"))
    return placed_arcs(arcs.join(d, "src"), "shares")


def _start(net: Network, degree: str) -> tuple[DataFrame, DataFrame]:
    return shares(net, degree), net.vertices().select("id", F.lit(1.0).alias("value"))


def _done(state: DataFrame) -> DataFrame:
    return state.select("id", F.col("value").alias("score"))


def _rule(jump: float):
    return jump + (1 - jump) * F.coalesce("msg", F.lit(0.0))


def power(net: Network, iterations: int = 10, jump: float = JUMP, degree: str = "out", restart: DataFrame | None = None, dangling: str = "drop", tolerance: float | None = None, ledger: RunLedger | None = None) -> DataFrame:
    """Power iteration. restart: (id, r), 0 for others. dangling: vertices without arcs lose their score ("drop"), or it is
    spread over all ("spread"). tolerance: ends when no score moves by more."""
    arcs, state = _start(net, degree)
    ledger = ledger or RunLedger("pagerank-power")
    ends = arcs.select(F.col("src").alias("id")).distinct().withColumn("gives", F.lit(True))
    state = state.join(ends, "id", "left").select("id", "value", F.coalesce("gives", F.lit(False)).alias("gives"))
    state = state.withColumn("r", F.lit(1.0)) if restart is None else state.join(restart, "id", "left").withColumn("r", F.coalesce("r", F.lit(0.0)))
    state, seen = cut(state, "power-0", arcs, lost=F.sum(F.when(~F.col("gives"), F.col("value"))), n=F.count("*"))
    for k in range(1, iterations + 1):
        got = state.join(arcs, F.col("id") == arcs["src"]).groupBy(arcs["dst"].alias("id")).agg(F.sum(F.col("value") * F.col("share")).alias("msg"))
        extra = seen["lost"] / seen["n"] if dangling == "spread" else 0.0
        new = jump * F.col("r") + (1 - jump) * (F.coalesce("msg", F.lit(0.0)) + extra)
        after = state.join(got, "id", "left").select("id", new.alias("value"), "gives", "r", F.abs(new - F.col("value")).alias("d"))
        after, seen = cut(after, f"power-{k}", arcs, lost=F.sum(F.when(~F.col("gives"), F.col("value"))), n=F.count("*"), dmax=F.max("d"), dsum=F.sum("d"))
        ledger.note(active=seen["n"], updates=seen["n"], delta_max=seen["dmax"], delta_l1=seen["dsum"])
        drop(state)
        state = slim(after, "id", "value", "gives", "r")
        if tolerance is not None and seen["dmax"] <= tolerance:
            ledger.close("converged")
            break
    else:
        ledger.close("fixed" if tolerance is None else "cut off")
    return _done(state)


def dataflow(net: Network, iterations: int = 10, jump: float = JUMP, degree: str = "out") -> DataFrame:
    """Scores joined with neighbour lists, shares summed by vertex, as an operator graph in a bulk iteration."""
    arcs, state = _start(net, degree)
    lists = written(arcs.groupBy(F.col("src").alias("id")).agg(F.collect_list("dst").alias("nbrs")), "lists")
    state = written(state, "flow-0")
    for k in range(1, iterations + 1):
        scores = Plan.source(state)
        met = Plan.join(scores, Plan.source(lists), "id")
        given = Plan.map(met, F.explode("nbrs").alias("to"), (F.col("value") / F.size("nbrs")).alias("part"))
        sums = Plan.group(given, ["to"], F.sum("part").alias("msg"))
        named = Plan.map(sums, F.col("to").alias("id"), "msg")
        after = written(Plan.result(Plan.map(Plan.join(scores, named, "id", "left"), "id", _rule(jump).alias("value"))), f"flow-{k}")
        drop(state)
        state = after
    return _done(state)


def gas(net: Network, tolerance: float = 1e-3, jump: float = JUMP, degree: str = "out", mode: str = "sync", variant: str = "standard", classes: int = 4, seed: int = 7, max_steps: int = 200, salt: int = 1, ledger: RunLedger | None = None, keeper: Checkpointer | None = None) -> DataFrame:
    """Pull over in-arcs; a vertex that moves by more than tolerance signals its out-neighbours. variant "delta": a vertex's sum
    is kept, and neighbours send what their share has changed by. A negative tolerance runs all max_steps. salt: parts in which
    the sums of vertices with many in-arcs are made first."""
    arcs, state = _start(net, degree)
    out = gas_engine.run(
        arcs, state, F.col("value") * F.col("share"), F.sum, _rule(jump), F.abs(F.col("new") - F.col("value")) > tolerance,
        mode=variant, classes=classes if mode == "async" else 1, seed=seed, max_steps=max_steps,
        change=(F.col("value") - F.col("old")) * F.col("share"), merge=lambda a, b: a + b, salt=salt, ledger=ledger, keeper=keeper,
    )
    return _done(out)


def bsp(net: Network, iterations: int = 10, halt: str = "fixed", tolerance: float = 1e-3, jump: float = JUMP, degree: str = "out", ledger: RunLedger | None = None, keeper: Checkpointer | None = None) -> DataFrame:
    """All vertices stay active until the global criterion holds: a number of supersteps, or the largest change."""
    arcs, state = _start(net, degree)
    return _done(bsp_engine.run(arcs, state, F.col("value") * F.col("share"), F.sum, _rule(jump), halt=halt, max_supersteps=iterations, tolerance=tolerance, ledger=ledger, keeper=keeper))


def _sweep_kernel(jump: float):
    def kernel(ids, old, src, dst, share, outside):
        """Scores by ascending id, each seeing the block's newest, until the block rests; boundary scores stay as they came."""
        score = old.copy()
        starts = np.searchsorted(dst, np.arange(len(ids) + 1))
        fixed = np.bincount(dst, np.where(src < 0, outside * share, 0.0), len(ids)) if len(dst) else np.zeros(len(ids))
        for _ in range(50):
            most = 0.0
            for v in range(len(ids)):
                a, b = starts[v], starts[v + 1]
                s, w = src[a:b], share[a:b]
                new = jump + (1 - jump) * (fixed[v] + float((score[s[s >= 0]] * w[s >= 0]).sum()))
                most, score[v] = max(most, abs(new - score[v])), new
            if most < 1e-12:
                break
        return score

    return kernel


def block(net: Network, blocks: DataFrame, supersteps: int = 1000, tolerance: float = 1e-9, jump: float = JUMP, degree: str = "out", ledger: RunLedger | None = None, keeper: Checkpointer | None = None) -> DataFrame:
    """Fresh scores inside a block, those of the superstep before from other blocks; ends when no score moves by more than tolerance."""
    arcs, state = _start(net, degree)
    placed = written(block_engine.arcs_by_block(arcs, blocks), "block-shares")
    state = written(state.join(blocks, "id").select("id", "block", "value"), "block-0")
    return _done(block_engine.run(placed, state, _sweep_kernel(jump), "id long, block int, value double, old double", supersteps, tolerance, ledger, keeper))


def accumulative(net: Network, tolerance: float = 1e-9, jump: float = JUMP, degree: str = "out", max_steps: int = 300, ledger: RunLedger | None = None) -> DataFrame:
    """Scores grow by residuals: each step adds a vertex's residual and passes on its damped shares, until little is left."""
    arcs, state = _start(net, degree)
    ledger = ledger or RunLedger("pagerank-accumulative")
    state, _ = cut(state.select("id", F.lit(0.0).alias("value"), F.lit(jump).alias("rest")), "rest-0", arcs)
    for k in range(1, max_steps + 1):
        got = state.where("rest > 0").join(arcs, F.col("id") == arcs["src"]).groupBy(arcs["dst"].alias("id")).agg(F.sum(F.col("rest") * F.col("share")).alias("msg"))
        after = state.join(got, "id", "left").select("id", (F.col("value") + F.col("rest")).alias("value"), ((1 - jump) * F.coalesce("msg", F.lit(0.0))).alias("rest"))
        after, seen = cut(after, f"rest-{k}", arcs, rest=F.sum("rest"), n=F.count("*"), active=F.count_if(F.col("rest") > 0))
        ledger.note(active=seen["active"], updates=seen["active"], delta_l1=seen["rest"])
        drop(state)
        state = after
        if seen["rest"] < tolerance * seen["n"]:
            ledger.close("converged")
            break
    else:
        ledger.close("cut off")
    return _done(state.withColumn("value", F.col("value") + F.col("rest")))


def msr(net: Network, iterations: int = 10, jump: float = JUMP, degree: str = "out", ledger: RunLedger | None = None) -> DataFrame:
    arcs, state = _start(net, degree)
    lists = arcs.groupBy(F.col("src").alias("id")).agg(F.collect_list("dst").alias("nbrs"))
    state = state.join(lists, "id", "left").withColumn("nbrs", F.coalesce("nbrs", F.array().cast("array<bigint>")))
    total = lambda msgs: F.aggregate(msgs, F.lit(0.0), lambda a, x: a + x)
    return _done(msr_engine.iterate(state, F.col("value") / F.size("nbrs"), total, _rule(jump), iterations, ledger=ledger))


def top(scores: DataFrame, k: int = 20) -> DataFrame:
    return scores.orderBy(F.col("score").desc(), "id").limit(k)


def residual(net: Network, scores: DataFrame, jump: float = JUMP, degree: str = "out") -> DataFrame:
    """(delta_max): how far one more step would move the scores."""
    arcs = shares(net, degree)
    got = scores.join(arcs, F.col("id") == arcs["src"]).groupBy(arcs["dst"].alias("id")).agg(F.sum(F.col("score") * F.col("share")).alias("msg"))
    return scores.join(got, "id", "left").agg(F.round(F.max(F.abs(_rule(jump) - F.col("score"))), 6).alias("delta_max"))
