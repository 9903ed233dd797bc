"""Sampled coefficients of networks of common groups, where no two members are alike: no links of classes are made."""

import datetime

import numpy as np
import pytest

from netan import catalogue, clustering, derive, twins
from netan.network import Network


@pytest.fixture(scope="module")
def events(spark, tmp_path_factory):
    """60 users with two events each and a common one; 8 more in groups of two or alone: degrees 0, 1 and 2."""
    rng = np.random.default_rng(3)
    pairs = rng.permutation([(a, b) for a in range(14) for b in range(a)])[:60]
    rows = [(u * 11 % 61, g) for u, two in enumerate(pairs.tolist()) for g in two]
    rows += [(100, 20), (101, 20), (102, 21), (103, 21), (103, 22), (104, 22), (105, 23), (None, 3)]
    at, start = str(tmp_path_factory.mktemp("events")), datetime.datetime(2024, 1, 1)
    rows = [(u, start + datetime.timedelta(minutes=10 * g, seconds=n % 600), "view", g + 0.5) for n, (u, g) in enumerate(rows)]
    spark.createDataFrame(rows, "user_id long, ts timestamp_ntz, event_type string, value double").write.parquet(f"{at}/events.parquet")
    return at


@pytest.fixture
def tables(monkeypatch):
    """Names of the tables that are written; slices, lots and parts are so small that there are many."""
    names, keep = [], twins.written
    monkeypatch.setattr(twins, "written", lambda df, name: names.append(name) or keep(df, name))
    for name, n in (("SLICE", 30), ("LOT", 40), ("PART", 30_000)):
        monkeypatch.setattr(twins, name, n, raising=False)
    return names


def test_alike_draws_need_no_links_of_classes(spark, events, tables):
    found = catalogue.queries()["clu_approx_100k_coactivity"](spark, events).collect()
    assert "class-links" not in tables
    plain = Network(derive.coactivity(spark, events)).kept()
    assert found == clustering.approx_average_local(plain, 100_000).collect() and 0 < found[0]["links"] < 100_000


def test_blocks_hold_groups_and_no_links_of_classes(spark, events, tables):
    found = catalogue.queries()["clu_approx_block_covalue"](spark, events).collect()
    assert "class-links" not in tables
    plain = Network(derive.covalue(spark, events)).kept()
    assert found == clustering.approx_block(plain, 10_000).collect() and 0 < found[0]["links"] < 10_000
