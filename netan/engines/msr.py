"""Rounds of map, shuffle and reduce: the rejected baseline. Each round ships state and adjacency lists again, uncombined."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from netan.engines.loop import cut, slim
from netan.measures import RunLedger
from netan.storage import drop


def iterate(state: DataFrame, emit: Column, fold: Callable[[Column], Column], commit: Column, rounds: int, until_stable: bool = False, ledger: RunLedger | None = None) -> DataFrame:
    """State (id, value, nbrs) after the rounds; emit: what a vertex tells each neighbour; fold: of the list `msgs`; commit: on value, msg."""
    ledger = ledger or RunLedger("msr")
    for k in range(1, rounds + 1):
        structure = state.select("id", F.struct("value", "nbrs").alias("vertex"), F.lit(None).alias("msg"))
        messages = state.select(F.explode("nbrs").alias("id"), F.lit(None).alias("vertex"), emit.alias("msg"))
        met = structure.union(messages).groupBy("id").agg(F.max("vertex").alias("vertex"), F.collect_list("msg").alias("msgs"))
        after = met.select("id", F.col("vertex.value").alias("value"), F.col("vertex.nbrs").alias("nbrs"), F.when(F.size("msgs") > 0, fold(F.col("msgs"))).alias("msg"), F.size("msgs").alias("n"))
        after = after.select("id", commit.alias("value"), "nbrs", (~commit.eqNullSafe(F.col("value"))).alias("diff"), "n")
        after, seen = cut(after, f"msr-{k}", changed=F.count_if("diff"), all=F.count("*"), raw=F.sum("n"))
        ledger.note(active=seen["all"], changed=seen["changed"], updates=seen["all"], messages_raw=seen["raw"], messages_combined=seen["raw"] + seen["all"])
        drop(state)
        state = slim(after, "id", "value", "nbrs")
        if until_stable and not seen["changed"]:
            ledger.close("converged")
            break
    else:
        ledger.close("cut off" if until_stable else "fixed")
    return state
