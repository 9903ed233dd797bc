"""Readers, writers and the entry point."""

import pytest

from netan.network import Network
from netan.sources import edges


def rows(df):
    return sorted(map(tuple, df.collect()))


def test_edge_list_text(spark, tmp_path):
    (tmp_path / "e.txt").write_text("# head\n1 2\n2\t3 0.5\n\nx y\n% end\n")
    path = f"file://{tmp_path}/e.txt"
    assert rows(edges.read_edges(spark, path, "edgelist")) == [(1, 2, 1.0), (2, 3, 0.5)]
    assert rows(edges.rejected(spark, path)) == [("x y",)]


def test_adjacency_text(spark, tmp_path):
    (tmp_path / "a.txt").write_text("1 2 3\n2\n")
    assert rows(edges.read_adjacency(spark, f"file://{tmp_path}/a.txt")) == [(1, 2), (1, 3)]


@pytest.mark.parametrize("kind", ["parquet", "csv", "json", "orc"])
def test_written_edges_come_back(spark, tmp_path, kind):
    df = Network(spark.createDataFrame([(1, 2), (3, 4)], "src long, dst long")).edges
    edges.write_result(df, f"file://{tmp_path}/{kind}", kind)
    assert rows(edges.read_edges(spark, f"file://{tmp_path}/{kind}", kind)) == [(1, 2, 1.0), (3, 4, 1.0)]
    with pytest.raises(Exception):
        edges.write_result(df, f"file://{tmp_path}/{kind}", kind)


def test_python_source(spark):
    spark.dataSource.register(edges.RingSource)
    df = spark.read.format("ring_lattice").option("n", 10).load()
    assert df.count() == 20 and rows(df)[0] == (0, 1)


def test_every_query_is_callable():
    import __spark_entry__ as entry

    queries, sql = entry.queries(), entry.oracle_sql()
    assert set(sql) <= set(queries) and len(queries) > 150 and all(map(callable, queries.values()))
