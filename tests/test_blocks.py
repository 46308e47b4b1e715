"""Graphs in blocks of arrays give what the joins over tables give, with one table written a round."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from cutfield.operators import blocks as B
from cutfield.operators import graph as G
from cutfield.operators import scale as L
from cutfield.storage import Stored


@pytest.fixture(scope="module")
def graph(spark):
    """Two models with ids that are far apart, parallel edges, an edge to itself, one to no node, and nodes without edges."""
    r = np.random.default_rng(5)
    rows = [(m, int(a) * step - 70, int(b) * step - 70, float(r.integers(1, 5)) / 4) for m, n, step in ((3, 60, 1), (9, 40, 1000)) for a, b in r.integers(0, n, (6 * n, 2))]
    nodes = [(3, i - 70) for i in range(63)] + [(9, 1000 * i - 70) for i in range(41)]
    edges = spark.createDataFrame([x for x in rows if x[1] != x[2]] + [(3, -60, 5000, 9.0)], "model_id long, src long, dst long, weight double")
    return Stored(spark.createDataFrame(nodes, "model_id long, var_id long")).read(), Stored(edges).read()


def _set(df):
    return sorted(tuple(r) for r in df.collect())


def _held(nodes, edges, cap=None):
    places = B.collected(nodes.withColumn("mass", F.lit(1.0)), nodes.count())
    return places, B.adjacency(places, edges, cap)


def test_hash_is_that_of_spark(spark):
    rows = [(0, 0), (-1, 2**40), (2**62, -(2**63)), (17, 5)]
    want = [r["h"] for r in spark.createDataFrame(rows, "a long, b long").select(F.xxhash64(F.lit(7), "a", "b").alias("h")).collect()]
    assert B.hashed(7, *np.array(rows).T).tolist() == want


@pytest.mark.parametrize("block_edges", [40, 10**6])
def test_matching_writes_one_table_a_round(graph, monkeypatch, block_edges):
    monkeypatch.setattr(B, "BLOCK_EDGES", block_edges)
    nodes, edges = graph
    want = _set(L._matched_tables(nodes.withColumn("mass", F.lit(1.0)), edges, 7.0, 5, 0, 0))
    written, init = [], Stored.__init__
    monkeypatch.setattr(Stored, "__init__", lambda self, df: (written.append(1), init(self, df))[1])
    got = L.heavy_matching(nodes, edges, 7.0, 5)
    assert len(written) <= 6
    assert _set(got) == want and len({r[2] for r in want}) < 60


def test_large_or_odd_graphs_go_by_tables(graph, monkeypatch):
    nodes, edges = graph
    want = _set(L.heavy_matching(nodes, edges, 7.0, 2))
    assert B.adjacency(_held(nodes, edges)[0], edges.withColumn("weight", F.when(F.col("src") > 0, F.col("weight"))), None) is None
    monkeypatch.setattr(B, "BROADCAST_NODES", 10)
    monkeypatch.setattr(B, "adjacency", None)
    assert _set(L.heavy_matching(nodes, edges, 7.0, 2)) == want


def test_ties_and_moves(graph):
    nodes, edges = graph
    places, first = _held(nodes, edges)
    known = edges.where("dst < 5000 or model_id = 9")
    a = Stored(G.random_partition(nodes, 3)).read()
    c = B.labels(a, places, "cluster")
    assert _set(B.ties(first, places, c)) == _set(L._ties(known, a))
    for sign in (1.0, -1.0):
        got, want = _set(B.moves(first, places, c, sign, 2)), _set(L._moves(known, a, 104, sign, 2).select("model_id", "var_id", "cluster", "to", "gain"))
        assert got == want and len(got) > 20
    group = a.withColumn("group", F.when(F.col("model_id") == 3, F.col("cluster") - 70).otherwise(1000 * F.col("cluster") - 70).cast("long"))
    at = places.finder()(places.model, B.labels(group, places, "group", long=True))
    assert _set(B.between(first, places, at)) == _set(L._between(known, group, 104))


def test_coarse_partition_turns_the_graph_once(graph, monkeypatch):
    """Edges meet nodes when the blocks are built; rounds of matching, the balance and rounds of swaps do not join them again."""
    nodes, edges = graph
    want = _set(L.refine(edges.where("dst < 5000 or model_id = 9"), G.random_partition(nodes, 4), "max", 3))
    monkeypatch.setattr(L, "both_ways", None)
    found = L.coarse_partition(nodes, edges, 4, coarse_nodes=8)
    assert G.check_equipartition(nodes, found, 4).where("ok").count() == 2
    assert _set(L.coarse_partition(nodes, edges, 4, "max", rounds=3)) == want
