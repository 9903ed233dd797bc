"""Pull, fold, commit, notify: signalled vertices pull from all their neighbours; those that change signal the other side.

Modes: "standard" pulls anew each time; "message" sends values straight to the receivers; "delta" keeps each vertex's folded
value and adds to it what neighbours send when they change. Asynchronous execution is emulated by class sweeps: vertices fall
in `classes` classes, hashed anew for each sweep, that run one after another, each seeing what those before it have done.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from netan.engines.bsp import inbox
from netan.engines.loop import cut, sweep_class
from netan.measures import RunLedger
from netan.recovery import Checkpointer
from netan.storage import drop

#: Vertices whose ids are sent to the arcs that they pull over; with more, all arcs are pulled and the others' folds are left.
SENT_VERTICES = 500_000


def turned(arcs: DataFrame, side: str, same: str) -> DataFrame:
    """arcs as they are for the side `same`, the other way for its opposite, or both ways."""
    if side not in ("in", "out", "both"):
        raise ValueError(side)
    if side == same:
        return arcs
    other = {"src": "dst", "dst": "src"}
    swapped = arcs.select(*(F.col(other.get(c, c)).alias(c) for c in arcs.columns))
    return swapped if side != "both" else arcs.union(swapped)


def run(
    arcs: DataFrame,
    state: DataFrame,
    pull: Column,
    fold: Callable[[Column], Column] | Callable[[DataFrame], DataFrame] | None,
    commit: Column,
    signal: Column | None = None,
    mode: str = "standard",
    classes: int = 1,
    seed: int = 7,
    max_steps: int = 100,
    change: Column | None = None,
    merge: Callable[[Column, Column], Column] | None = None,
    ledger: RunLedger | None = None,
    fold_rows: bool = False,
    salt: int = 1,
    pull_over: str = "in",
    notify_over: str = "out",
    keeper: Checkpointer | None = None,
) -> DataFrame:
    """State (id, value, ...) after the run; a step is a superstep or, with classes > 1, a sweep.

    pull is computed on a neighbour's state and arc (src is the neighbour); fold folds `msg` (None: msg is the list of all);
    commit gives `new` from value and msg; signal says, on value and new, who notifies (default: changed). For mode "delta",
    change is what is sent (on `old` and value) and merge puts it into the cached fold. salt > 1 folds hubs in that many parts
    first. pull_over: vertices pull over arcs that come "in", that go "out", or "both"; notify_over: whom they signal. keeper: keeps checkpoints of whole steps.
    """
    ledger = ledger or RunLedger(f"gas-{mode}")
    if mode != "standard" and {"in": "out", "out": "in", "both": "both"}[pull_over] != notify_over:
        raise ValueError("values are sent to those who would pull them: notify over the other side")
    pulls, tells = turned(arcs, pull_over, "in"), turned(arcs, notify_over, "out")
    fold = fold or (lambda msg: F.sort_array(F.collect_list(msg)))
    more = [c for c in state.columns if c not in ("id", "value")]
    kind = state.schema["value"].dataType
    old = [F.col("value").alias("old"), F.lit(None).cast(kind).alias("cache")] if mode == "delta" else []
    state = state.select("id", *more, "value", F.lit(False).alias("fired"), F.lit(True).alias("signalled"), *old)
    extra = ["old", "cache"] if mode == "delta" else []
    done, state = keeper.begin(state) if keeper else (0, state)
    state, left = cut(state, "gas-0", arcs, signalled=F.count_if("signalled"))
    first = not done

    def folded(rows: DataFrame) -> DataFrame:
        if salt > 1 and not fold_rows and not ledger.messages:
            rows = rows.groupBy("id", F.pmod(F.xxhash64("from"), F.lit(salt)).alias("s")).agg(fold(F.col("msg")).alias("msg"))
        return inbox(rows, fold, fold_rows, ledger)

    for step in range(done + 1, max_steps + 1):
        sums = {"updates": 0, "changed": 0, "messages_raw": 0, "messages_combined": 0, "messages_cross": 0, "delta_max": 0.0}
        for k in range(classes):
            turn = F.col("signalled") if classes == 1 else F.col("signalled") & (sweep_class(seed, step, classes) == k)
            if mode != "standard" and not first:
                given = change if mode == "delta" else pull
                sent = state.where("fired").join(tells, F.col("id") == tells["src"]).select(tells["dst"].alias("id"), given.alias("msg"), tells["src"].alias("from"))
            else:
                over = pulls
                if left["signalled"] <= SENT_VERTICES:
                    over = pulls.join(F.broadcast(state.where(turn).select(F.col("id").alias("dst"))), "dst", "left_semi")
                pulled = over.join(state, F.col("src") == state["id"])
                sent = pulled.select(F.col("dst").alias("id"), pull.alias("msg"), F.col("src").alias("from"))
            after = state.join(folded(sent), "id", "left").withColumn("turn", turn)
            msg = F.col("msg")
            if mode == "delta":
                both = msg if first else F.when(msg.isNull(), F.col("cache")).when(F.col("cache").isNull(), msg).otherwise(merge(F.col("cache"), msg))
                after = after.withColumn("cache", both).withColumn("got", msg.isNotNull()).withColumn("msg", F.col("cache"))
            else:
                after = after.withColumn("got", msg.isNotNull() & (F.col("turn") if mode == "standard" or first else F.lit(True)))
            after = after.withColumn("new", F.when(F.col("turn"), commit).otherwise(F.col("value")))
            fires = F.col("turn") & (~F.col("new").eqNullSafe(F.col("value")) if signal is None else signal)
            changed = ~F.col("new").eqNullSafe(F.col("value"))
            keep = [F.col("value").alias("old"), "cache"] if mode == "delta" else []
            moved = F.abs(F.col("new") - F.col("value")).cast("double") if isinstance(kind, T.NumericType) else F.lit(0.0)
            counted = [F.when(F.col("got"), F.col(c)).alias(c) for c in ("raw", "cross")] if ledger.messages else []
            after = after.select("id", *more, F.col("new").alias("value"), fires.alias("fired"), (F.col("signalled") & ~F.col("turn")).alias("waits"), "turn", "got", changed.alias("diff"), moved.alias("d"), *keep, *counted)
            counters = {"raw": F.sum("raw"), "cross": F.sum("cross")} if ledger.messages else {}
            after, seen = cut(after, f"gas-{step}-{k}", arcs, updates=F.count_if("turn"), n_changed=F.count_if("diff"), combined=F.count_if("got"), dmax=F.max("d"), **counters)
            woken = tells.join(after.where("fired").select(F.col("id").alias("src")), "src", "left_semi").select(F.col("dst").alias("id")).distinct().withColumn("woken", F.lit(True))
            state_next = after.join(woken, "id", "left").select("id", *more, "value", "fired", (F.col("waits") | F.coalesce("woken", F.lit(False))).alias("signalled"), *extra)
            state_next, left = cut(state_next, f"gas-{step}-{k}-signals", arcs, signalled=F.count_if("signalled"))
            drop(state, after)
            state, first = state_next, False
            for name, value in (("updates", seen["updates"]), ("changed", seen["n_changed"]), ("messages_combined", seen["combined"]), ("messages_raw", seen.get("raw", 0)), ("messages_cross", seen.get("cross", 0))):
                sums[name] += value
            sums["delta_max"] = max(sums["delta_max"], seen["dmax"])
            if not left["signalled"]:
                break
        ledger.note(active=sums["updates"], **sums)
        if keeper:
            keeper.after(state, step)
        if not left["signalled"]:
            ledger.close("converged")
            break
    else:
        ledger.close("cut off")
    return state.select("id", *more, "value")
