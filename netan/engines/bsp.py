"""Synchronous vertex supersteps: active vertices send along their arcs, messages are combined, receivers commit."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from netan.engines.loop import cut, slim
from netan.measures import RunLedger
from netan.recovery import Checkpointer
from netan.storage import drop


def inbox(sent: DataFrame, fold: Callable, fold_rows: bool, ledger: RunLedger) -> DataFrame:
    """(id, msg[, raw, cross]): what each receiver gets of (id, msg, from); counted one by one if the ledger asks for it."""
    if not ledger.messages:
        return fold(sent.select("id", "msg")) if fold_rows else sent.groupBy("id").agg(fold(F.col("msg")).alias("msg"))
    cross = F.lit(0).cast("long")
    if ledger.apart is not None:
        sent = sent.withColumnsRenamed({"from": "src"}).withColumn("dst", F.col("id"))
        cross = F.count_if(ledger.apart)
    counts = (F.count("*").alias("raw"), cross.alias("cross"))
    if fold_rows:
        return fold(sent.select("id", "msg")).join(sent.groupBy("id").agg(*counts), "id")
    return sent.groupBy("id").agg(fold(F.col("msg")).alias("msg"), *counts)


def run(
    arcs: DataFrame,
    state: DataFrame,
    send: Column,
    combine: Callable[[Column], Column] | Callable[[DataFrame], DataFrame],
    commit: Column,
    wake: Column | None = None,
    halt: str = "no_active",
    max_supersteps: int = 100,
    tolerance: float = 0.0,
    ledger: RunLedger | None = None,
    fold_rows: bool = False,
    combiner: bool = True,
    aggregators: dict[str, Column] | None = None,
    master: Callable[[int, dict], bool] | None = None,
    keeper: Checkpointer | None = None,
) -> DataFrame:
    """State after the run.

    arcs (src, dst, ...), state (id, value, ...); send is computed on a sender's state and arc, combine folds `msg` (or, with
    fold_rows, all rows (id, msg) to one per id), commit gives the new value from value and msg (null: none came). A vertex
    stays active if `wake` holds on value and new; without it, if its value has changed. halt: "no_active", "fixed" (all
    supersteps, all active), or "tolerance" (all active until the largest change is below it). Without combiner, messages
    travel one by one. aggregators: named aggregates over (id, value, active, changed) of all vertices, kept in the ledger and
    shown to the master after each superstep, who may end the run. keeper: keeps checkpoints, and goes on from the newest it has.
    """
    ledger = ledger or RunLedger("bsp")
    more = [c for c in state.columns if c not in ("id", "value", "active")]
    if "active" not in state.columns:
        state = state.withColumn("active", F.lit(True))
    done, state = keeper.begin(state) if keeper else (0, state)
    state, seen = cut(state, "bsp-0", arcs, active=F.count_if("active"))
    named = {f"agg_{k}": c for k, c in (aggregators or {}).items()}
    for k in range(done + 1, max_supersteps + 1):
        sent = state.where("active").join(arcs, F.col("id") == arcs["src"]).select(arcs["dst"].alias("id"), send.alias("msg"), arcs["src"].alias("from"))
        if not combiner:
            sent = sent.repartition("id")
        got = inbox(sent, combine, fold_rows, ledger)
        after = state.join(got, "id", "left").withColumn("new", commit)
        changed = ~F.col("new").eqNullSafe(F.col("value"))
        stay = F.lit(True) if halt in ("fixed", "tolerance") else changed if wake is None else wake
        counted = ["raw", "cross"] if ledger.messages else []
        after = after.select("id", *more, F.col("new").alias("value"), stay.alias("active"), changed.alias("changed"), (F.col("new") - F.col("value")).cast("double").alias("_d"), F.col("msg").isNotNull().alias("_got"), *counted)
        counters = {c: F.sum(c) for c in counted} | named
        after, now = cut(after, f"bsp-{k}", arcs, active=F.count_if("active"), n_changed=F.count_if("changed"), got=F.count_if("_got"), dmax=F.max(F.abs("_d")), dsum=F.sum(F.abs("_d")), all=F.count("*"), **counters)
        ledger.note(active=seen["active"], changed=now["n_changed"], updates=now["got"], messages_raw=now.get("raw", 0), messages_combined=now["got"], messages_cross=now.get("cross", 0), delta_max=now["dmax"], delta_l1=now["dsum"])
        drop(state)
        state, seen = slim(after, "id", *more, "value", "active"), now
        if keeper:
            keeper.after(state, k)
        if named:
            ledger.aggregates.append({c[4:]: now[c] for c in named})
        if master is not None and master(k, ledger.aggregates[-1] if named else {}):
            ledger.close("converged")
            break
        if halt == "no_active" and not now["active"] or halt == "tolerance" and now["dmax"] < tolerance:
            ledger.close("converged")
            break
    else:
        ledger.close("fixed" if halt == "fixed" else "cut off")
    return state
