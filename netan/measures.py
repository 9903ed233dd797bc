"""The ledger of a run: one row per superstep with its counters and seconds; what the cluster has spent; comparisons of runs."""

from __future__ import annotations

import threading
import time
from collections.abc import Callable
from dataclasses import asdict, dataclass, field, fields

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass
class Step:
    method: str
    superstep: int
    active: int = 0
    changed: int = 0
    updates: int = 0
    messages_raw: int = 0
    messages_combined: int = 0
    messages_cross: int = 0
    delta_max: float = 0.0
    delta_l1: float = 0.0
    seconds: float = 0.0
    status: str = "running"


@dataclass
class RunLedger:
    method: str = ""
    messages: bool = False  # count messages, one by one and those that cross from one block to another
    apart: Column | None = None  # whether an arc (src, dst) crosses blocks
    aggregates: list[dict] = field(default_factory=list)  # of each superstep, what an engine's named aggregators gave
    max_seconds: float | None = None  # a run beyond it is given up, status "infeasible"
    steps: list[Step] = field(default_factory=list)
    _began: float = field(default_factory=time.perf_counter)
    _last: float = field(default_factory=time.perf_counter)

    def note(self, **counters) -> Step:
        now = time.perf_counter()
        kinds = {f.name: float if f.type == "float" else int for f in fields(Step)}  # counters of empty tables come as null
        step = Step(self.method, len(self.steps) + 1, seconds=now - self._last, **{k: kinds[k](v or 0) for k, v in counters.items()})
        self._last = now
        self.steps.append(step)
        if self.max_seconds and now - self._began > self.max_seconds:
            step.status = "infeasible"
            raise TimeoutError(f"{self.method}: over {self.max_seconds} s after {step.superstep} supersteps")
        return step

    def close(self, status: str) -> None:
        """How the run ended: "converged", "oscillating", "cut off" (its limit came first), or "fixed" (as many steps as asked for)."""
        if self.steps:
            self.steps[-1].status = status

    def total(self, counter: str):
        return sum(getattr(s, counter) for s in self.steps)

    def df(self, spark: SparkSession) -> DataFrame:
        schema = "method string, superstep int, active long, changed long, updates long, messages_raw long, messages_combined long, messages_cross long, delta_max double, delta_l1 double, seconds double, status string"
        return spark.createDataFrame([tuple(asdict(s).values()) for s in self.steps], schema)


class ClusterMeter:
    """What all executors have done between enter and exit, by Spark's own counters of them, not by the driver's machine.

    use gives cpu (task time over cores and wall seconds), network_kbs (shuffle bytes read and written a second), evenness (least
    over greatest task time of an executor), gc_share, input_mb, and memory_mb (the greatest peak of an executor's
    storage and execution memory, where the executors report it).
    """

    def __init__(self, spark: SparkSession, period: float = 1.0) -> None:
        self.spark, self.period = spark, period
        self.use: dict[str, float] = {}
        self.samples: list[dict[str, float]] = []  # one for each period: seconds, cpu, network_kbs
        self._stop = threading.Event()

    def _now(self) -> dict[str, dict[str, float]]:
        sc = self.spark.sparkContext._jsc.sc()
        try:
            sc.listenerBus().waitUntilEmpty(10_000)
        except Exception:  # counters may lag behind
            pass
        found, all_ = {}, sc.statusStore().executorList(True)
        for k in range(all_.size()):
            x = all_.apply(k)
            peak = x.peakMemoryMetrics()
            memory = sum(peak.get().getMetricValue(m) for m in ("OnHeapUnifiedMemory", "OffHeapUnifiedMemory")) if peak.isDefined() else 0
            found[x.id()] = {"tasks": x.totalDuration(), "gc": x.totalGCTime(), "read": x.totalShuffleRead(), "written": x.totalShuffleWrite(), "input": x.totalInputBytes(), "cores": x.totalCores(), "memory": memory}
        return found

    @staticmethod
    def _between(a: dict, b: dict, seconds: float) -> dict[str, float]:
        gone = lambda name: [x[name] - a.get(k, {}).get(name, 0) for k, x in b.items()]
        cores = sum(x["cores"] for x in b.values()) or 1
        tasks = [t for t, x in zip(gone("tasks"), b.values()) if x["cores"]]
        return {
            "seconds": seconds,
            "cpu": sum(tasks) / 1000 / (cores * seconds) if seconds else 0.0,
            "network_kbs": (sum(gone("read")) + sum(gone("written"))) / 1024 / seconds if seconds else 0.0,
            "evenness": min(tasks) / max(tasks) if tasks and max(tasks) else 1.0,
            "gc_share": sum(gone("gc")) / max(1, sum(tasks)),
            "input_mb": sum(gone("input")) / 1e6,
            "memory_mb": max((x["memory"] for x in b.values()), default=0) / 1e6,
        }

    def __enter__(self) -> "ClusterMeter":
        self._first, self._began = self._now(), time.perf_counter()

        def sample() -> None:
            last, at = self._first, self._began
            while not self._stop.wait(self.period):
                now, t = self._now(), time.perf_counter()
                self.samples.append(self._between(last, now, t - at))
                last, at = now, t

        self._thread = threading.Thread(target=sample, daemon=True)
        self._thread.start()
        return self

    def __exit__(self, *_) -> None:
        self._stop.set()
        self._thread.join()
        self.use = self._between(self._first, self._now(), time.perf_counter() - self._began)

    @property
    def network_peak(self) -> float:
        return max((x["network_kbs"] for x in self.samples), default=self.use.get("network_kbs", 0.0))


def on_disk(spark: SparkSession, path: str) -> int:
    """Bytes of all files under a path, in whatever store."""
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getContentSummary(where).getLength()


def edge_list_bytes(edges: DataFrame) -> DataFrame:
    """(edges, text_bytes): what the edges take as lines of two numbers."""
    return edges.agg(F.count("*").alias("edges"), F.sum(F.length(F.col("src").cast("string")) + F.length(F.col("dst").cast("string")) + 2).alias("text_bytes"))


def timed(run: Callable[[], DataFrame]) -> tuple[float, str]:
    """Seconds of a run whose result is read to the end, and "ok", "infeasible" (its limits came first) or "failed"."""
    began = time.perf_counter()
    try:
        run().write.format("noop").mode("overwrite").save()
    except (TimeoutError, MemoryError):
        return time.perf_counter() - began, "infeasible"
    except Exception as e:  # a matrix of runs goes on; the reason is kept
        return time.perf_counter() - began, f"failed: {type(e).__name__}"
    return time.perf_counter() - began, "ok"


def factors(rows: DataFrame, base: str) -> DataFrame:
    """(fixture, method, seconds, factor) of rows (fixture, method, seconds): each method's time over that of the base."""
    by = rows.where(F.col("method") == base).select("fixture", F.col("seconds").alias("base"))
    return rows.join(by, "fixture").select("fixture", "method", "seconds", F.round(F.col("seconds") / F.col("base"), 3).alias("factor"))


def speedups(rows: DataFrame) -> DataFrame:
    """(method, workers, seconds, speedup) of rows (method, workers, seconds): the time at the fewest workers over each."""
    one = rows.groupBy("method").agg(F.min_by("seconds", "workers").alias("one"))
    return rows.join(one, "method").select("method", "workers", "seconds", F.round(F.col("one") / F.col("seconds"), 3).alias("speedup"))


def score_distance(a: DataFrame, b: DataFrame) -> DataFrame:
    """(delta_max, delta_l1, vertices) of two score tables (id, score)."""
    both = a.join(b.withColumnRenamed("score", "other"), "id", "full").select(F.abs(F.coalesce("score", F.lit(0.0)) - F.coalesce("other", F.lit(0.0))).alias("d"))
    return both.agg(F.round(F.max("d"), 9).alias("delta_max"), F.round(F.sum("d"), 9).alias("delta_l1"), F.count("*").alias("vertices"))


def agreement(a: DataFrame, b: DataFrame, label_a: str, label_b: str) -> DataFrame:
    """(vertices, same_both, rand): pairs of vertices that two labelings both hold together, and the Rand index."""
    both = a.join(b, "id").groupBy(F.col(label_a).alias("a"), F.col(label_b).alias("b")).agg(F.count("*").alias("c"))
    pairs = lambda c: F.sum(c * (c - 1) / 2)
    joint = both.agg(F.sum("c").alias("n"), pairs(F.col("c")).alias("ab"))
    left = both.groupBy("a").agg(F.sum("c").alias("c")).agg(pairs(F.col("c")).alias("pa"))
    right = both.groupBy("b").agg(F.sum("c").alias("c")).agg(pairs(F.col("c")).alias("pb"))
    all_ = joint.crossJoin(left).crossJoin(right).withColumn("t", F.col("n") * (F.col("n") - 1) / 2)
    rand = F.when(F.col("t") > 0, (F.col("t") + 2 * F.col("ab") - F.col("pa") - F.col("pb")) / F.col("t")).otherwise(1.0)
    return all_.select(F.col("n").alias("vertices"), F.col("ab").cast("long").alias("same_both"), F.round(rand, 6).alias("rand"))
