"""Tiny networks with known answers, and methods held against each other."""

import hashlib

import numpy as np
import pytest
from pyspark import StorageLevel
from pyspark.sql import Window
from pyspark.sql import functions as F

from netan import clustering, communities, components, derive, measures, ordering, pagerank, partition, stats, storage
from netan.baselines import shared_memory
from netan.catalogue import COMPONENT_METHODS
from netan.engines import bsp as bsp_engine
from netan.engines import gas as gas_engine
from netan.engines import loop
from netan.engines.dataflow import BrokenContract, Plan
from netan.engines.loop import bulk
from netan.generate import edge_attachment
from netan.measures import RunLedger
from netan.network import Network
from netan.recovery import Checkpointer, snapshot
from netan.twins import Twins

TWO = [(1, 2), (2, 3), (1, 3), (3, 4), (4, 5), (5, 6), (4, 6), (10, 11), (2**40, -7)]


def net(spark, pairs, directed=False, vertices=None):
    extra = spark.createDataFrame([(v,) for v in vertices], "id long") if vertices else None
    return Network(spark.createDataFrame(pairs, "src long, dst long"), directed, extra)


def rows(df):
    return sorted(map(tuple, df.collect()))


def test_normal_form(spark):
    n = net(spark, [(1, 1), (2, 1), (1, 2), (1, 2), (None, 3), (3, None)])
    assert rows(n.edges) == [(1, 2, 3.0)]
    assert rows(n.vertices()) == [(1,), (2,)]
    assert rows(net(spark, [(2, 1), (1, 2)], True).edges) == [(1, 2, 1.0), (2, 1, 1.0)]


def test_empty_network(spark):
    n = net(spark, [])
    assert rows(components.bsp(n)) == [] and rows(components.contract(n)) == [] and rows(pagerank.power(n, 2)) == []
    assert rows(clustering.average_local(n)) == [(None,)] and rows(clustering.global_coefficient(n)) == [(None,)]
    assert clustering.approx_average_local(n, 10).first()["coefficient"] is None


@pytest.mark.parametrize("method", sorted(COMPONENT_METHODS))
def test_components(spark, method):
    want = [(-7, -7), (1, 1), (2, 1), (3, 1), (4, 1), (5, 1), (6, 1), (10, 10), (11, 10), (2**40, -7)]
    assert rows(COMPONENT_METHODS[method](net(spark, TWO)).select("id", "component")) == want


def test_components_of_pages_need_no_pairs(spark, tmp_path):
    """Pages of common links are tied to the least of each link's; pages alone with their links are no vertices."""
    pages = [(k, "".join(f'<a href="{x}">' for x in x)) for k, x in ((9, "ab"), (4, "b"), (7, "bc"), (2, "c"), (5, "d"), (6, ""), (8, "ee"), (3, "e"))]
    pages += [(100 + k, '<a href="z">') for k in range(300)]
    spark.createDataFrame(pages, "page_id long, html string").write.parquet(f"{tmp_path}/pages.parquet")
    star = derive.for_components(spark, str(tmp_path), "colink")
    assert star.edges.count() < 310
    assert rows(components.contract(star)) == rows(components.contract(derive.network(spark, str(tmp_path), "colink")))
    assert rows(components.bsp(star).where("id < 100")) == [(2, 2), (3, 3), (4, 2), (7, 2), (8, 3), (9, 2)]


def test_components_keep_isolated_vertices(spark):
    n = net(spark, [(1, 2)], vertices=[2, 9])
    for found in (components.bsp(n), components.contract(n), shared_memory.components(n), components.msr(n)):
        assert rows(found) == [(1, 1), (2, 1), (9, 9)]


def test_supersteps_stay_within_the_diameter(spark):
    path = net(spark, [(k, k + 1) for k in range(8)])
    ledger, blocked = RunLedger(), RunLedger()
    components.bsp(path, ledger=ledger)
    components.block(path, partition.by_range(path, 2), ledger=blocked)
    assert len(ledger.steps) <= 9 and len(blocked.steps) <= len(ledger.steps) + 1
    assert ledger.df(spark).count() == len(ledger.steps) and ledger.steps[-1].status == "converged"


def test_giant(spark):
    labels = components.contract(net(spark, TWO))
    assert rows(components.giant(labels)) == [(1, 6, 0.6)]
    assert {r.id for r in components.in_giant(labels).where("in_giant").collect()} == {1, 2, 3, 4, 5, 6}


def test_square_oscillates_and_sweeps_end(spark):
    square = net(spark, [(1, 2), (2, 3), (3, 4), (1, 4)])
    history, ledger = [], RunLedger()
    communities.bsp(square, 8, halt="cycle", history=history, ledger=ledger)
    assert ledger.steps[-1].status == "oscillating" and communities.oscillation(history) == (2, 4)
    ledger = RunLedger()
    communities.sweep(square, 20, ledger=ledger)
    assert ledger.steps[-1].status == "converged"


def test_two_triangles_are_two_communities(spark):
    n = net(spark, TWO[:7])
    got = dict(rows(shared_memory.communities(n)))
    assert got[1] == got[2] == got[3] and got[4] == got[5] == got[6]
    assert rows(communities.bsp(n, 6, halt="fixed")) == rows(communities.dataflow(n, 6)) == rows(communities.msr(n, 6))


def test_cycle_has_equal_ranks(spark):
    ring = net(spark, [(1, 2), (2, 3), (3, 1)], True)
    for found in (pagerank.power(ring), pagerank.bsp(ring), pagerank.dataflow(ring), pagerank.msr(ring), pagerank.gas(ring), pagerank.accumulative(ring), shared_memory.pagerank(ring)):
        assert [round(s, 6) for _, s in rows(found)] == [1.0, 1.0, 1.0]


def test_ranks_agree_at_the_fixed_point(spark):
    rng = np.random.default_rng(2)
    n = net(spark, [(int(a), int(b)) for a, b in rng.integers(0, 30, (120, 2))], True).kept()
    want = shared_memory.pagerank(n, 1e-12, 0.5)  # with this jump the rest halves in each step
    some = (pagerank.power(n, 200, 0.5, tolerance=1e-9), pagerank.gas(n, 1e-9, 0.5), pagerank.gas(n, 1e-9, 0.5, variant="delta"), pagerank.block(n, partition.by_modulo(n, 3), jump=0.5), pagerank.accumulative(n, 1e-9, 0.5))
    for found in some:
        assert measures.score_distance(want, found).first()["delta_max"] < 1e-7
    assert pagerank.residual(n, want, 0.5).first()[0] == 0


def test_dangling_score_is_spread(spark):
    chain = net(spark, [(1, 2), (2, 3)], True)
    assert abs(pagerank.power(chain, 30, dangling="spread").agg(F.sum("score")).first()[0] - 3) < 1e-9
    assert pagerank.power(chain, 30).agg(F.sum("score")).first()[0] < 3


@pytest.mark.parametrize("method", clustering.METHODS)
def test_clustering(spark, method):
    got = {r.id: (r.degree, r.triangles, r.coefficient) for r in clustering.local(net(spark, TWO), method).collect()}
    assert got[3] == (3, 1, pytest.approx(1 / 3)) and got[1] == (2, 1, 1.0) and got[10] == (1, 0, None)
    five = net(spark, [(a, b) for a in range(5) for b in range(a)])
    assert rows(clustering.average_local(five, method)) == [(1.0,)] and rows(clustering.triangles(five, method)) == [(10,)]
    star = net(spark, [(0, k) for k in range(1, 51)])
    assert rows(clustering.global_coefficient(star, method)) == [(0.0,)]


def test_sampled_clustering_within_its_bound(spark):
    rng = np.random.default_rng(4)
    n = net(spark, [(int(a), int(b)) for a, b in rng.integers(0, 25, (120, 2))]).kept()
    exact = clustering.average_local(n).first()[0], clustering.global_coefficient(n).first()[0]
    for found, want in ((clustering.approx_average_local(n, 4000), exact[0]), (clustering.approx_global(n, 4000), exact[1]), (clustering.approx_bsp(n, 4000), exact[0])):
        row = found.first()
        assert row["samples"] == 4000 and abs(row["coefficient"] - want) <= row["epsilon"]
    assert abs(shared_memory.approx_average_local(n, 4000) - exact[0]) < 0.05
    assert clustering.samples_for(0.0043, 0.05) > 99_000


def test_classes_of_twins_give_what_all_pairs_give(spark):
    """Members of the same groups are one class; draws, hits and the mean are those of the network of all pairs."""
    rng = np.random.default_rng(6)
    kinds = [sorted(set(rng.integers(0, 12, 3).tolist())) for _ in range(9)] + [[50], [51]]
    member = [(m * 7 % 83, g) for m in range(60) for g in kinds[m % 9]] + [(200, 50), (201, 51), (202, 51), (None, 3), (203, None)]
    groups = spark.createDataFrame(member, "id long, g long")
    plain, classes = Network(derive._pairs(groups, "id", "g")).kept(), Twins(groups, "id", "g")
    assert classes.links.count() <= 11**2 and classes.near.count() == 10
    assert rows(stats.degrees(classes)) == rows(stats.degrees(plain))
    assert rows(clustering.average_local(classes)) == rows(clustering.average_local(plain))
    forms = [clustering.approx_average_local, clustering.approx_global, clustering.approx_dataflow, clustering.approx_gas, clustering.approx_block]
    for form in forms:
        assert rows(form(classes, 500)) == rows(form(plain, 500))
    assert rows(clustering.approx_fixed_pairs(classes)) == rows(clustering.approx_fixed_pairs(plain))
    assert abs(shared_memory.approx_average_local(classes, 4000) - clustering.average_local(plain).first()[0]) < 0.05


def test_draws_of_32_bits_whatever_the_weights(spark):
    hubs = net(spark, [(h, 100_000 * (h + 1) + k) for h, n in ((0, 50_000), (1, 30_000)) for k in range(n)])
    weights = [50_000 * 49_999, 30_000 * 29_999]
    hit = [int(hashlib.md5(f"1:{k}:v".encode()).hexdigest()[:8], 16) % sum(weights) for k in range(40)]
    got = clustering._draws(hubs, F.expr("degree * (degree - 1)"), 40, 1, wide=False)
    assert rows(got.select("k", "id")) == [(k, int(at >= weights[0])) for k, at in enumerate(hit)]


def test_asynchronous_runs_need_fewer_updates(spark):
    rng = np.random.default_rng(5)
    n = net(spark, [(int(a), int(b)) for a, b in rng.integers(0, 60, (90, 2))]).kept()
    sync, swept = RunLedger(), RunLedger()
    a = pagerank.gas(n, 1e-6, degree="total", ledger=sync)
    b = pagerank.gas(n, 1e-6, degree="total", mode="async", ledger=swept)
    assert measures.score_distance(a, b).first()["delta_max"] < 1e-4
    assert swept.total("updates") < sync.total("updates")


def test_blocks(spark):
    n = net(spark, TWO[:7])
    assert rows(partition.edge_cut(n, partition.by_modulo(n, 1))) == [(7, 0, 0.0)]
    blocks = partition.by_label_propagation(n, 2)
    assert blocks.count() == 6 and rows(partition.balance(blocks))[0][1] <= 4
    assert sum(r.internal for r in partition.boundary(n, blocks).collect()) == 6
    assert partition.by_range(n, 3).select("block").distinct().count() == 3


def test_overview(spark):
    assert rows(stats.overview(net(spark, TWO))) == [(10, 9, 3, 10)]
    assert rows(stats.degree_histogram(net(spark, [(1, 2)], vertices=[3]))) == [(0, 1), (1, 2)]


def test_generator(spark):
    n = edge_attachment(spark, 500, 3)
    assert rows(n.edges.agg(F.count("*"))) == [(997,)] and n.vertices().count() == 500
    assert components.contract(n).select("component").distinct().count() == 1
    assert clustering.local(n).where("triangles = 0").count() == 0
    assert rows(n.edges) == rows(edge_attachment(spark, 500, 3).edges) != rows(edge_attachment(spark, 500, 4).edges)


def test_run_resumes_after_a_fault(spark, tmp_path):
    n = net(spark, [(k, k + 1) for k in range(8)]).kept()
    want = [(k, 0) for k in range(9)]
    for name, run in (("bsp", components.bsp), ("gas", components.gas), ("delta", lambda n, **o: components.gas(n, "delta", **o))):
        path, whole = f"file://{tmp_path}/{name}", RunLedger()
        with pytest.raises(RuntimeError):
            run(n, keeper=Checkpointer(path, every=2, fail_at=5))
        assert Checkpointer(path).resume_point(spark)[0] == 4
        assert rows(run(n, keeper=Checkpointer(path, every=2), ledger=whole)) == want
        assert whole.steps[-1].status == "converged" and len(whole.steps) <= 6  # what was kept is not done again
    ring = net(spark, [(1, 2), (2, 3), (3, 1), (1, 3)], True).kept()
    blocks, path = partition.by_modulo(ring, 2), f"file://{tmp_path}/block"
    with pytest.raises(RuntimeError):
        pagerank.block(ring, blocks, keeper=Checkpointer(path, every=2, fail_at=3))
    assert measures.score_distance(pagerank.block(ring, blocks, keeper=Checkpointer(path)), shared_memory.pagerank(ring, 1e-12)).first()["delta_max"] < 1e-7
    again = snapshot(n, f"file://{tmp_path}/snap")
    assert rows(again.edges) == rows(n.edges)


def test_bulk_iteration(spark):
    out = bulk(spark.createDataFrame([(1, 1)], "id long, v long"), lambda s: s.select("id", (F.col("v") * 2).alias("v")), 5)
    assert rows(out) == [(1, 32)]


def test_budget_marks_a_run_infeasible(spark):
    ledger = RunLedger("slow", max_seconds=0.0001)
    with pytest.raises(TimeoutError):
        components.bsp(net(spark, TWO), ledger=ledger)
    assert ledger.steps[-1].status == "infeasible"


def test_no_run_that_was_cut_off_calls_itself_converged(spark):
    path = net(spark, [(k, k + 1) for k in range(6)]).kept()
    square = net(spark, [(1, 2), (2, 3), (3, 4), (1, 4)]).kept()
    runs = {
        "bsp": lambda x: components.bsp(path, max_supersteps=2, ledger=x), "dataflow": lambda x: components.dataflow(path, max_rounds=2, ledger=x), "msr": lambda x: components.msr(path, 2, ledger=x),
        "power": lambda x: pagerank.power(path, 2, tolerance=1e-9, ledger=x), "bsp ranks": lambda x: pagerank.bsp(path, 2, "tolerance", 1e-9, ledger=x), "gas": lambda x: pagerank.gas(path, 1e-9, max_steps=2, ledger=x),
        "block": lambda x: pagerank.block(path, partition.by_modulo(path, 2), 2, ledger=x), "accumulative": lambda x: pagerank.accumulative(path, max_steps=2, ledger=x),
        "labels": lambda x: communities.bsp(square, 3, ledger=x), "sweep": lambda x: communities.sweep(path, 1, ledger=x), "labels by block": lambda x: communities.block(path, partition.by_modulo(path, 2), 1, ledger=x),
    }
    for name, run in runs.items():
        ledger = RunLedger(name)
        run(ledger)
        assert ledger.steps[-1].status == "cut off", name
        assert ledger.df(spark).count() == len(ledger.steps)
    ledger = RunLedger()
    pagerank.power(path, 2, ledger=ledger)
    assert ledger.steps[-1].status == "fixed"
    ledger = RunLedger()
    ledger.note(active=None, delta_max=0, updates=0.0, delta_l1=None)
    assert ledger.df(spark).first()["delta_max"] == 0.0


def test_period_of_labels(spark):
    history = []
    communities.bsp(net(spark, [(0, k) for k in range(1, 6)]), 6, halt="fixed", history=history)
    assert communities.oscillation(history) == (2, 6)
    communities.bsp(net(spark, TWO[:3]), 6, history=(history := []))
    assert communities.oscillation(history) == (1, 0)


def test_colours_and_sides(spark):
    rng = np.random.default_rng(6)
    n = net(spark, [(int(a), int(b)) for a, b in rng.integers(0, 20, (60, 2))]).kept()
    colours = partition.colouring(n)
    assert rows(partition.clashes(n, colours)) == [(n.vertices().count(), 0)]
    ledger = RunLedger()
    found = communities.sweep(n, 50, tie="keep", colours=colours, ledger=ledger)
    assert ledger.steps[-1].status == "converged" and communities.unstable(n, found).first()["unstable"] == 0
    star = net(spark, [(0, k) for k in range(1, 6)])
    assert {c for _, c in rows(communities.sweep(star, 9, sides=(F.col("id") > 0).cast("int"), tie="keep"))} == {1}


def test_pulling_over_either_side(spark):
    arcs = spark.createDataFrame([(1, 2), (2, 3), (4, 2)], "src long, dst long")
    state = spark.createDataFrame([(k, k) for k in range(1, 5)], "id long, value long")
    best = F.greatest("value", F.coalesce("msg", "value"))
    run = lambda **o: rows(gas_engine.run(arcs, state, F.col("value"), F.max, best, **o))
    assert run() == [(1, 1), (2, 4), (3, 4), (4, 4)]
    assert run(pull_over="out", notify_over="in") == [(1, 3), (2, 3), (3, 3), (4, 4)]
    assert run(pull_over="out", notify_over="in", mode="message") == [(1, 3), (2, 3), (3, 3), (4, 4)]
    assert run(pull_over="both", notify_over="both") == [(k, 4) for k in range(1, 5)]
    lists = gas_engine.run(arcs, state.withColumn("value", F.array("value")), F.col("src"), None, F.col("msg"), max_steps=1)
    assert {r.id: r.value for r in lists.collect()} == {1: None, 2: [1, 4], 3: [2], 4: None}
    with pytest.raises(ValueError):
        run(pull_over="out", mode="message")


def test_salted_folds_give_the_same(spark):
    star = net(spark, [(k, 0) for k in range(1, 40)] + [(0, 1)], True).kept()
    assert rows(pagerank.gas(star, -1.0, max_steps=4).withColumn("score", F.round("score", 9))) == rows(pagerank.gas(star, -1.0, max_steps=4, salt=5).withColumn("score", F.round("score", 9)))


def test_aggregators_and_master(spark):
    path = net(spark, [(k, k + 1) for k in range(6)]).kept()
    ledger, arcs = RunLedger(), path.mirrored().select("src", "dst")
    state = path.vertices().select("id", F.col("id").alias("value"))
    bsp_engine.run(arcs, state, F.col("value"), F.min, F.least("value", F.coalesce("msg", "value")), ledger=ledger, aggregators={"total": F.sum("value")}, master=lambda k, seen: seen["total"] < 12)
    assert [x["total"] for x in ledger.aggregates] == [15, 10] and ledger.steps[-1].status == "converged"


def test_messages_are_counted(spark):
    star = net(spark, [(0, k) for k in range(1, 5)]).kept()
    ledger = RunLedger(messages=True, apart=F.pmod("src", F.lit(2)) != F.pmod("dst", F.lit(2)))
    components.bsp(star, ledger=ledger)
    assert [(s.messages_raw, s.messages_combined, s.messages_cross) for s in ledger.steps] == [(8, 5, 4), (4, 1, 2)]
    for variant, mode in (("standard", "sync"), ("message", "sync"), ("delta", "sync"), ("message", "async"), ("delta", "async")):
        ledger = RunLedger(messages=True)
        components.gas(star, variant, mode, ledger=ledger)
        assert ledger.total("messages_raw") >= ledger.total("messages_combined") > 0


def exchanges(plan):
    return [x.strip() for x in plan.splitlines() if "Exchange hashpartitioning" in x or "BroadcastExchange" in x]


def test_supersteps_deal_out_messages_only(spark, monkeypatch):
    """With arcs and states in buckets, one exchange is left in a superstep: that of combined messages."""
    monkeypatch.setattr(loop, "BUCKETED_ROWS", 0)
    monkeypatch.setattr(gas_engine, "SENT_VERTICES", 0)
    plans, store = {}, loop.bucketed

    def spy(df, name, key, buckets):
        plans[name] = df._jdf.queryExecution().executedPlan().toString()
        return store(df, name, key, buckets)

    monkeypatch.setattr(loop, "bucketed", spy)
    n = net(spark, TWO).kept()
    want = rows(components.contract(n))
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        assert rows(components.bsp(n)) == rows(components.gas(n)) == rows(components.gas(n, "message", "async")) == rows(components.dataflow(n)) == want
        ranks = rows(pagerank.power(n, 2, degree="total").withColumn("score", F.round("score", 9)))
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)
    for name in ("bsp-1", "gas-1-0", "gas-1-0-signals", "flow-1", "power-1", "sweep-1-0"):
        assert len(exchanges(plans[name])) == 1, (name, plans[name])
    assert ranks == rows(pagerank.power(n, 2, degree="total").withColumn("score", F.round("score", 9)))


def test_contracts_are_held(spark):
    df = spark.createDataFrame([(1, 2), (1, 3), (2, 5)], "k long, v long")
    node = Plan.source(df)
    good = Plan.reduce(node, ["k"], lambda x: x.groupBy("k").agg(F.sum("v").alias("v")))
    assert rows(Plan.result(good, checked=True)) == [(1, 5), (2, 5)]
    window = Plan.reduce(node, ["k"], lambda x: x.withColumn("r", F.row_number().over(Window.partitionBy("k").orderBy("v"))).where("r = 1").drop("r"))
    assert rows(Plan.result(window, checked=True)) == [(1, 2), (2, 5)]
    for bad in (Plan.reduce(node, ["k"], lambda x: x.groupBy("v").count()), Plan.map(node, F.sum("v")), Plan.reduce(node, ["k"], lambda x: x.distinct())):
        with pytest.raises(BrokenContract):
            Plan.result(bad, checked=True)
    kept = Plan.stored(good.keeps("k"))
    assert rows(kept) == [(1, 5), (2, 5)]
    assert not exchanges(kept.groupBy("k").agg(F.max("v"))._jdf.queryExecution().executedPlan().toString())


def test_blocks_of_triangles(spark):
    rng = np.random.default_rng(9)
    n = net(spark, [(int(a), int(b)) for a, b in rng.integers(0, 22, (110, 2))]).kept()
    for k in (1, 2, 5):
        assert rows(clustering._block_corners(n, partition.by_modulo(n, k))) == rows(clustering._corners(n, "ordered"))


def test_meter_and_sizes(spark, tmp_path):
    with measures.ClusterMeter(spark, 0.2) as meter:
        spark.range(2_000_000).groupBy(F.col("id") % 7).count().collect()
    assert meter.use["cpu"] > 0 and meter.use["network_kbs"] > 0 and 0 <= meter.use["evenness"] <= 1
    spark.range(10).write.parquet(f"file://{tmp_path}/t")
    assert measures.on_disk(spark, f"file://{tmp_path}/t") > 0
    assert rows(measures.edge_list_bytes(net(spark, [(1, 20)]).edges)) == [(1, 5)]
    times = spark.createDataFrame([("f", "a", 2.0), ("f", "b", 6.0)], "fixture string, method string, seconds double")
    assert rows(measures.factors(times, "a")) == [("f", "a", 2.0, 1.0), ("f", "b", 6.0, 3.0)]
    runs = spark.createDataFrame([("a", 1, 8.0), ("a", 4, 2.0)], "method string, workers int, seconds double")
    assert rows(measures.speedups(runs)) == [("a", 1, 8.0, 1.0), ("a", 4, 2.0, 4.0)]
    assert measures.timed(lambda: (_ for _ in ()).throw(MemoryError()))[1] == "infeasible"


def test_storage_levels(spark):
    n = net(spark, TWO)
    for level in (StorageLevel.DISK_ONLY, StorageLevel.MEMORY_AND_DISK):
        held = n.kept(level)
        assert rows(components.bsp(held)) == rows(components.contract(n))
        held.edges.unpersist()


def test_running_sums_and_ranks(spark):
    df = spark.createDataFrame([(k, k % 5) for k in range(40)], "id long, v long").repartition(4)
    sums = dict(rows(ordering.running(df, [F.col("id")], F.col("v"), "s").select("id", "s")))
    assert all(sums[k] == sum(x % 5 for x in range(k)) for k in range(40))
    assert rows(ordering.numbered(df, "v", "k")) == [(k, k + 1) for k in range(5)]
    assert {r.id: r.p for r in ordering.ranked(df, "v", "p").collect()} == {k: 1 + 8 * (4 - k % 5) for k in range(40)}


def test_scratch_tables_go(spark):
    with storage.scratch():
        inner = storage.written(spark.range(3), "gone")
        with storage.scratch():
            outer = storage.lasting(spark.range(4), "gone-later")
        assert outer.count() == 4
    out = storage.written(spark.range(5), "stays")
    for df, there in ((inner, False), (outer, False), (out, True)):
        where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(df._netan_path)
        assert where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(where) == there


def test_plans(spark):
    n = net(spark, TWO).kept()
    plan = n.edges.where("src > 3").select("dst")._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(src), GreaterThan(src,3)]" in plan and "weight" not in plan.split("ReadSchema")[1]
    wedges = clustering._corners(n, "ordered")._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in wedges and "BroadcastNestedLoopJoin" not in wedges


def test_triangles_by_colours_deal_no_wedges(spark, monkeypatch):
    """A hub, groups in one colour and across colours, against all pairs; what is dealt are packed edges, a few rows."""
    import itertools
    import random

    monkeypatch.setattr(clustering, "TASK_EDGES", 200)
    monkeypatch.setattr(clustering, "WEDGES", 50)
    rng = random.Random(3)
    pairs = {tuple(sorted(rng.sample(range(60), 2))) for _ in range(500)} | {(0, k) for k in range(1, 60)} | {(10**12 + a, 10**12 + b) for a, b in itertools.combinations(range(5), 2)}
    near = {}
    for a, b in pairs:
        near.setdefault(a, set()).add(b)
        near.setdefault(b, set()).add(a)
    net = Network(spark.createDataFrame(sorted(pairs), "src long, dst long")).kept()
    found = clustering._corners(net, "ordered")
    want = {v: t for v, x in near.items() if (t := sum(b in near[a] for a, b in itertools.combinations(sorted(x), 2)))}
    assert {r.id: r.t for r in found.collect()} == want
    assert "Join" not in found._jdf.queryExecution().executedPlan().toString()
    none = Network(spark.createDataFrame([], "src long, dst long")).kept()
    assert clustering._corners(none, "ordered").count() == 0 and clustering.average_local(none).first()[0] is None
