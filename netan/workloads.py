"""The experiments as runs: scaling, modes, feasibility, use of the cluster, approximation, checkpoints.

    python -m netan.workloads NAME [--sf DIR] [--workers 1,2,4] [--seconds N]

NAME is strong, weak, modes, matrix, use, samples or checkpoints. Each prints JSON lines, one a run; `strong` and `weak` start a
session of their own for each number of workers, the others use one. On a cluster, call the functions with its session.
"""

from __future__ import annotations

import argparse
import json
import subprocess
import sys
import uuid
from collections.abc import Callable, Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from netan import clustering, communities, components, generate, pagerank, partition
from netan.baselines import shared_memory
from netan.derive import network
from netan.measures import ClusterMeter, RunLedger, timed
from netan.network import Network
from netan.recovery import Checkpointer
from netan.storage import shared_dir

Method = Callable[[Network, RunLedger], DataFrame]

COMPONENTS: dict[str, Method] = {
    "dataflow": lambda n, x: components.dataflow(n, ledger=x),
    "bsp": lambda n, x: components.bsp(n, ledger=x),
    "gas": lambda n, x: components.gas(n, ledger=x),
    "block": lambda n, x: components.block(n, partition.by_hash(n, 8), ledger=x),
    "msr": lambda n, x: components.msr(n, ledger=x),
    "shm": lambda n, x: shared_memory.components(n),
}
COMMUNITIES: dict[str, Method] = {
    "dataflow": lambda n, x: communities.dataflow(n, 10),
    "bsp": lambda n, x: communities.bsp(n, 10, ledger=x),
    "gas": lambda n, x: communities.gas(n, 10, "async", ledger=x),
    "block": lambda n, x: communities.block(n, partition.by_hash(n, 8), 10, ledger=x),
    "shm": lambda n, x: shared_memory.communities(n),
}
RANKS: dict[str, Method] = {
    "dataflow": lambda n, x: pagerank.dataflow(n),
    "bsp": lambda n, x: pagerank.bsp(n, ledger=x),
    "gas": lambda n, x: pagerank.gas(n, -1.0, max_steps=10, ledger=x),
    "block": lambda n, x: pagerank.block(n, partition.by_hash(n, 8), 10, ledger=x),
    "msr": lambda n, x: pagerank.msr(n, ledger=x),
    "shm": lambda n, x: shared_memory.pagerank(n, 1e-9),
}
TRIANGLES: dict[str, Method] = {m: (lambda n, x, m=m: clustering.average_local(n, m)) for m in clustering.METHODS}
SAMPLED: dict[str, Method] = {
    "draws": lambda n, x: clustering.approx_average_local(n),
    "dataflow": lambda n, x: clustering.approx_dataflow(n),
    "bsp": lambda n, x: clustering.approx_bsp(n),
    "gas": lambda n, x: clustering.approx_gas(n),
    "block": lambda n, x: clustering.approx_block(n),
}
#: Problem, its methods, and the networks that stand for those of the experiments.
PROBLEMS: dict[str, tuple[dict[str, Method], tuple[str, ...]]] = {
    "components": (COMPONENTS, ("sharedline", "colink", "copurchase")),
    "communities": (COMMUNITIES, ("copurchase", "colink", "nearest")),
    "pagerank": (RANKS, ("handoff", "hyperlink", "trade")),
    "clustering": (TRIANGLES, ("colink", "sharedline")),
    "sampled": (SAMPLED, ("colink", "cosupply", "coactivity")),
}
#: Published ratios that `modes` is read beside: of asynchronous to synchronous updates and times for components by pull and by
#: messages and for ranks, and of message and delta times to those of the standard mode, at one node and at eight.
PUBLISHED = {
    "updates async/sync": {"standard": (0.30, 0.53), "message": (0.43, 0.59), "pagerank": (0.52, 0.53)},
    "seconds async/sync": {"standard": (0.89, 1.26), "message": (1.76, 1.88), "pagerank": (1.08, 1.32)},
    "seconds of standard": {"message": (0.90, None), "delta": (0.85, None)},
}


def run_all(spark: SparkSession, sf_dir: str, problems: tuple[str, ...] = tuple(PROBLEMS), max_seconds: float | None = None, warm: bool = True) -> Iterator[dict]:
    """One run of each method on each network of its problem, with status and what the cluster has spent on it."""
    for problem in problems:
        methods, fixtures = PROBLEMS[problem]
        for fixture in fixtures:
            net = network(spark, sf_dir, fixture).kept()
            edges = net.edges.count()
            if warm:
                timed(lambda: next(iter(methods.values()))(net, RunLedger()))
            for method, make in methods.items():
                ledger = RunLedger(method, max_seconds=max_seconds)
                with ClusterMeter(spark) as meter:
                    seconds, status = timed(lambda make=make, ledger=ledger: make(net, ledger))
                yield {"problem": problem, "fixture": fixture, "edges": edges, "method": method, "seconds": round(seconds, 3), "status": status, "supersteps": len(ledger.steps), "ended": ledger.steps[-1].status if ledger.steps else None, "peak_mb": round(meter.use["memory_mb"], 1), "cpu": round(meter.use["cpu"], 3), "network_kbs": round(meter.use["network_kbs"], 1)}


def modes(spark: SparkSession, sf_dir: str, fixtures: tuple[str, ...] = ("sharedline", "copurchase"), classes: int = 4) -> Iterator[dict]:
    """Standard, message and delta runs, synchronous and in class sweeps, for components, and ranks in both modes, on each network."""
    apart = F.pmod(F.xxhash64("src"), F.lit(8)) != F.pmod(F.xxhash64("dst"), F.lit(8))
    for fixture in fixtures:
        net = network(spark, sf_dir, fixture).kept()
        timed(lambda: components.gas(net))  # compiled code, and files in the system's cache
        found: dict[tuple, dict] = {}
        runs = [("components", v, m) for v in ("standard", "message", "delta") for m in ("sync", "async")] + [("pagerank", "standard", m) for m in ("sync", "async")]
        for problem, variant, mode in runs:

            def make(ledger: RunLedger) -> DataFrame:
                if problem == "components":
                    return components.gas(net, variant, mode, classes, ledger=ledger)
                return pagerank.gas(net, 1e-3, degree="total", mode=mode, classes=classes, ledger=ledger)

            plain, counted = RunLedger(), RunLedger(messages=True, apart=apart)
            seconds, status = timed(lambda: make(plain))
            make(counted)
            row = {"problem": problem, "fixture": fixture, "variant": variant, "mode": mode, "seconds": round(seconds, 3), "status": status, "supersteps": len(plain.steps), "updates": plain.total("updates")}
            row |= {c: counted.total(c) for c in ("messages_raw", "messages_combined", "messages_cross")}
            found[problem, variant, mode] = row
            sync, name = found[problem, variant, "sync"], "pagerank" if problem == "pagerank" else variant
            if mode == "async":
                row |= {"updates_of_sync": round(row["updates"] / sync["updates"], 3), "seconds_of_sync": round(row["seconds"] / sync["seconds"], 3), "published_updates": PUBLISHED["updates async/sync"].get(name), "published_seconds": PUBLISHED["seconds async/sync"].get(name)}
            elif variant != "standard":
                row |= {"seconds_of_standard": round(row["seconds"] / found[problem, "standard", "sync"]["seconds"], 3), "published": PUBLISHED["seconds of standard"][variant]}
            yield row


def weak(spark: SparkSession, workers: int, per_worker: int = 10_000) -> Iterator[dict]:
    """Components of a generated network whose size grows with the workers."""
    net = generate.weak_scaling(spark, workers, per_worker).kept()
    edges = net.edges.count()
    timed(lambda: components.bsp(net))
    for method in ("dataflow", "bsp", "gas", "block"):
        seconds, status = timed(lambda method=method: COMPONENTS[method](net, RunLedger()))
        yield {"workers": workers, "edges": edges, "method": method, "seconds": round(seconds, 3), "status": status}


def use(spark: SparkSession, sf_dir: str, fixture: str = "hyperlink") -> Iterator[dict]:
    """CPU and network of ten iterations of ranks on the web links."""
    net = network(spark, sf_dir, fixture).kept()
    timed(lambda: pagerank.power(net))
    for method in ("dataflow", "bsp", "gas", "block"):
        with ClusterMeter(spark) as meter:
            seconds, status = timed(lambda method=method: RANKS[method](net, RunLedger()))
        yield {"method": method, "seconds": round(seconds, 3), "status": status, "network_peak_kbs": round(meter.network_peak, 1)} | {k: round(v, 4) for k, v in meter.use.items() if k != "seconds"}


def checkpoints(spark: SparkSession, sf_dir: str, fixture: str = "sharedline", every: int = 1) -> Iterator[dict]:
    """What checkpoints cost: the same run without and with them."""
    net = network(spark, sf_dir, fixture).kept()
    timed(lambda: components.bsp(net))
    for name, run in (("components bsp", components.bsp), ("components gas", components.gas)):
        without, _ = timed(lambda run=run: run(net))
        keeper = Checkpointer(f"{shared_dir(spark)}/netan/kept-{uuid.uuid4().hex}", every)
        kept, _ = timed(lambda run=run, keeper=keeper: run(net, keeper=keeper))
        yield {"run": name, "seconds": round(without, 3), "with_checkpoints": round(kept, 3), "checkpoints": keeper.saved, "overhead": round(kept / without - 1, 3)}


def session(workers: int) -> SparkSession:
    """A session of so many threads on this machine."""
    builder = SparkSession.builder.master(f"local[{workers}]").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false")
    builder = builder.config("spark.sql.shuffle.partitions", str(2 * workers)).config("spark.driver.memory", "6g").config("spark.sql.session.timeZone", "UTC").config("spark.executor.processTreeMetrics.enabled", "false")
    spark = builder.getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def main(args: list[str]) -> None:
    parser = argparse.ArgumentParser(description=__doc__)
    parser.add_argument("name", choices=["strong", "weak", "modes", "matrix", "use", "samples", "checkpoints"])
    parser.add_argument("--sf", default="/root/testdata/sf0.01")
    parser.add_argument("--workers", default="1,2,4")
    parser.add_argument("--seconds", type=float, default=120.0)
    parser.add_argument("--child", action="store_true")
    found = parser.parse_args(args)
    workers = [int(x) for x in found.workers.split(",")]
    if found.name in ("strong", "weak") and not found.child:
        for p in workers:  # a session's threads are fixed when it starts
            subprocess.run([sys.executable, "-m", "netan.workloads", found.name, "--sf", found.sf, "--workers", str(p), "--seconds", str(found.seconds), "--child"], check=True)
        return
    spark = session(workers[-1])
    rows = {
        "strong": lambda: run_all(spark, found.sf, ("components", "pagerank"), found.seconds),
        "weak": lambda: weak(spark, workers[-1]),
        "modes": lambda: modes(spark, found.sf),
        "matrix": lambda: run_all(spark, found.sf, max_seconds=found.seconds),
        "use": lambda: use(spark, found.sf),
        "samples": lambda: run_all(spark, found.sf, ("clustering", "sampled"), found.seconds),
        "checkpoints": lambda: checkpoints(spark, found.sf),
    }[found.name]()
    for row in rows:
        print(json.dumps({"workload": found.name, "workers": workers[-1]} | row), flush=True)
    spark.stop()


if __name__ == "__main__":
    main(sys.argv[1:])
