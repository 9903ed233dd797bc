"""Block programs: a kernel sees all of a block and its boundary, changes internal vertices at once, and only what crosses
blocks is exchanged at the end of a superstep."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from netan.engines.loop import cut, slim
from netan.measures import RunLedger
from netan.recovery import Checkpointer
from netan.storage import drop


def arcs_by_block(arcs: DataFrame, blocks: DataFrame) -> DataFrame:
    """arcs with the blocks of their ends (sblock, dblock); a vertex is internal to one block."""
    s, d = blocks.toDF("src", "sblock"), blocks.toDF("dst", "dblock")
    return arcs.join(s, "src").join(d, "dst")


def local_components(net_arcs: DataFrame) -> DataFrame:
    """(id, label): least id of each vertex's component within its block; arcs (src, dst, sblock, dblock)."""
    inside = net_arcs.where("sblock = dblock").select(F.col("sblock").alias("block"), "src", "dst")

    def solve(rows: pa.Table) -> pa.Table:
        src, dst = rows.column("src").to_numpy(), rows.column("dst").to_numpy()
        ids, inverse = np.unique(np.concatenate((src, dst)), return_inverse=True)
        a, b = inverse[: len(src)], inverse[len(src) :]
        label = np.arange(len(ids))
        while True:  # minimum of neighbours, then jumps, until nothing moves
            before = label.copy()
            np.minimum.at(label, a, label[b])
            np.minimum.at(label, b, label[a])
            label = label[label]
            if (label == before).all():
                break
        return pa.table({"id": ids, "label": ids[label]})

    return inside.groupBy("block").applyInArrow(solve, T.StructType([T.StructField("id", T.LongType()), T.StructField("label", T.LongType())]))


def run(arcs: DataFrame, state: DataFrame, kernel: Callable, schema: str, max_supersteps: int, tolerance: float = 0.0, ledger: RunLedger | None = None, keeper: Checkpointer | None = None) -> DataFrame:
    """State (id, block, value) after the supersteps.

    arcs (src, dst, share, sblock, dblock). kernel(ids, values, src, dst, share, outside) gets one block: its internal vertices
    in ascending order, arcs that end inside it as positions (src -1: a boundary vertex, its value in outside), and returns the
    new values. Boundary values are those of the superstep before.
    """
    ledger = ledger or RunLedger("block")
    done, state = keeper.begin(state) if keeper else (0, state)
    for k in range(done + 1, max_supersteps + 1):
        values = state.select(F.col("id").alias("src"), "value")
        inflow = arcs.join(values, "src").select(F.col("dblock").alias("block"), "src", "dst", "share", (F.col("sblock") == F.col("dblock")).alias("inside"), "value")
        # one group for both: a block's vertices as rows without src
        vertices = state.select("block", F.lit(None).cast("long").alias("src"), F.col("id").alias("dst"), F.lit(None).cast("double").alias("share"), F.lit(True).alias("inside"), "value")

        def solve(rows: pa.Table) -> pa.Table:
            own = rows.filter(pa.compute.is_null(rows.column("src")))
            order = np.argsort(own.column("dst").to_numpy())
            ids, old = own.column("dst").to_numpy()[order], own.column("value").to_numpy()[order]
            flow = rows.filter(pa.compute.is_valid(rows.column("src")))
            src, dst, share = flow.column("src").to_numpy(), flow.column("dst").to_numpy(), flow.column("share").to_numpy()
            inside = flow.column("inside").to_numpy(zero_copy_only=False)
            by = np.lexsort((src, dst))
            src, dst, share, inside, outside = src[by], dst[by], share[by], inside[by], flow.column("value").to_numpy()[by]
            new = kernel(ids, old, np.where(inside, np.searchsorted(ids, src), -1), np.searchsorted(ids, dst), share, outside)
            return pa.table({"id": ids, "block": pa.array([rows.column("block")[0].as_py()] * len(ids), pa.int32()), "value": new, "old": old})

        after = inflow.unionByName(vertices).groupBy("block").applyInArrow(solve, schema)
        after, seen = cut(after, f"block-{k}", all=F.count("*"), changed=F.count_if(F.col("value") != F.col("old")), dmax=F.max(F.abs(F.col("value") - F.col("old"))))
        ledger.note(active=seen["all"], changed=seen["changed"], updates=seen["all"], delta_max=seen["dmax"])
        drop(state)
        state = slim(after, "id", "block", "value")
        if keeper:
            keeper.after(state, k)
        if seen["dmax"] <= tolerance:
            ledger.close("converged")
            break
    else:
        ledger.close("cut off")
    return state
