"""Checkpoints of a run every k supersteps, automatic resumption, and snapshots of a network.

Every engine's state is a written table after each superstep, so lost executors cost nothing; a lost driver does. A Checkpointer
given to an engine keeps its state under a folder of its own, and the next run that is given the same folder goes on from there.
"""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from netan.network import Network


class Checkpointer:
    """Keeps a run's state as Parquet beside a manifest of its superstep, in a folder that all executors share.

    fail_at: a fault in this superstep, for tests.
    """

    def __init__(self, path: str, every: int = 5, fail_at: int | None = None) -> None:
        self.path, self.every, self.fail_at = path.rstrip("/"), every, fail_at
        self.saved = 0

    def save(self, state: DataFrame, superstep: int, **facts) -> None:
        state.write.mode("overwrite").parquet(f"{self.path}/state-{superstep}")
        manifest = json.dumps({"superstep": superstep, **facts})
        state.sparkSession.createDataFrame([(superstep, manifest)], "superstep int, manifest string").coalesce(1).write.mode("append").parquet(f"{self.path}/manifest")
        self.saved += 1

    def resume_point(self, spark: SparkSession | None = None) -> tuple[int, str | None]:
        """(superstep, state path) of the newest checkpoint, or (0, None)."""
        spark = spark or SparkSession.getActiveSession()
        where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{self.path}/manifest")
        if not where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(where):
            return 0, None
        k = spark.read.schema("superstep int, manifest string").parquet(f"{self.path}/manifest").agg(F.max("superstep")).first()[0]
        return k, f"{self.path}/state-{k}"

    def begin(self, state: DataFrame) -> tuple[int, DataFrame]:
        """(supersteps done, state) to go on from: the newest checkpoint, or the state given."""
        done, at = self.resume_point(state.sparkSession)
        return (done, state.sparkSession.read.parquet(at)) if at else (0, state)

    def after(self, state: DataFrame, superstep: int, **facts) -> None:
        """To be called after each superstep."""
        if superstep % self.every == 0:
            self.save(state, superstep, **facts)
        if superstep == self.fail_at:
            raise RuntimeError(f"lost in superstep {superstep}")


def snapshot(net: Network, path: str) -> Network:
    """The network written under path and read again: a manual restart begins there."""
    net.edges.write.mode("overwrite").parquet(f"{path}/edges")
    out = Network(net.spark.read.parquet(f"{path}/edges"), net.directed, net.isolated)
    return out
