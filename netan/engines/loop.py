"""What all iterative engines share: one job per superstep that writes the new state and counts on the way.

Arcs don't change, so a superstep should not deal them out again. Once they are more than BUCKETED_ROWS, they are stored in
buckets by the vertex they leave, and states in as many buckets by id: then sending along arcs needs no exchange, and the only
one left in a superstep is that of the combined messages. Smaller arcs stay plain: Spark broadcasts or merges them.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F

from netan.storage import bucketed, drop, written

BUCKETED_ROWS = 5_000_000


def placed_arcs(arcs: DataFrame, name: str = "arcs", key: str = "src") -> DataFrame:
    """arcs as a table, in buckets by key if there are many."""
    seen = Observation()
    out = written(arcs.observe(seen, F.count("*").alias("n")), name)
    if seen.get["n"] <= BUCKETED_ROWS:
        return out
    buckets = int(arcs.sparkSession.conf.get("spark.sql.shuffle.partitions"))  # as many as an exchange of messages has parts
    dealt = bucketed(out.repartition(buckets, key), name, key, buckets)
    drop(out)
    return dealt


def cut(df: DataFrame, name: str, beside: DataFrame | None = None, **counters: Column) -> tuple[DataFrame, dict]:
    """df as a written table, and its counters, from the same job; beside: arcs whose buckets it shares, by id."""
    buckets = getattr(beside, "_netan_buckets", None)
    store = (lambda x: bucketed(x, name, "id", buckets)) if buckets else (lambda x: written(x, name))
    if not counters:
        return store(df), {}
    if buckets:  # observed metrics don't reach us from a table's creation
        out = store(df)
        seen = out.agg(*(c.alias(k) for k, c in counters.items())).first().asDict()
        return out, {k: v or 0 for k, v in seen.items()}
    seen = Observation()
    out = store(df.observe(seen, *(c.alias(k) for k, c in counters.items())))
    return out, {k: v or 0 for k, v in seen.get.items()}


def slim(df: DataFrame, *columns: Column | str) -> DataFrame:
    """Some columns of a stored table, which can still be dropped by them."""
    out = df.select(*columns)
    out._netan_path = df._netan_path
    return out


def bulk(state: DataFrame, step: Callable[[DataFrame], DataFrame], iterations: int, name: str = "bulk") -> DataFrame:
    """The step applied to the whole state, a fixed number of times."""
    for k in range(iterations):
        after = written(step(state), f"{name}-{k}")
        drop(state)
        state = after
    return state


def draw(seed: int, *parts: Column | str) -> Column:
    """A number from 0 to 2^32 - 1 out of the seed and columns: the first 8 hex digits of their md5, the same in any engine."""
    text = F.concat_ws(":", F.lit(str(seed)), *(F.col(p).cast("string") if isinstance(p, str) else p.cast("string") for p in parts))
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("long")


def sweep_class(seed: int, sweep: int, classes: int, vertex: str = "id") -> Column:
    """Class of a vertex in one sweep; hashed anew for each sweep, since fixed classes may cycle."""
    return F.pmod(draw(seed, F.lit(sweep), vertex), F.lit(classes))
