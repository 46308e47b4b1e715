"""Cuts into prescribed sizes, the canonical solver, options that must not pass unheard, ranks without a task per key, owned tables."""

import os
import types

import numpy as np
import pytest
from pyspark.sql import functions as F

from cutfield import storage
from cutfield.model import Model
from cutfield.operators import dense as D
from cutfield.operators import inference as I
from cutfield.operators import partition as P
from cutfield.operators import scale as L
from cutfield.plans import experiments as X


def _graph(rng, n, p=0.7):
    a = np.triu(rng.random((n, n)) * (rng.random((n, n)) < p), 1)
    return a + a.T


@pytest.mark.parametrize("sizes", [(3, 3, 2), (5, 3), (4, 1), (4, 3, 2), (3, 3, 2, 2)])
@pytest.mark.parametrize("sense", ["min", "max"])
def test_prescribed_sizes_are_bounded(sizes, sense):
    """bound <= optimum <= cut for a minimum, the other way round for a maximum; the sizes hold."""
    rng = np.random.default_rng(sum(sizes))
    sign = 1.0 if sense == "min" else -1.0
    for _ in range(4):
        a = _graph(rng, sum(sizes))
        best = sign * D.brute_cut(a, len(sizes), sense, np.array(sizes))[0]
        for level in ("eigen", "psd", "psd_nonneg"):
            assert sign * D.relax_sizes(a, np.array(sizes), sense, level)[2] <= best + 1e-6
        for method in ("kmeans", "projection", "linearised", "spectral"):
            got = D.partition(a, len(sizes), sense, method, list(sizes))
            assert sorted(np.bincount(got["labels"])) == sorted(sizes)
            assert sign * got["bound"] <= best + 1e-6 <= sign * got["cut"] + 2e-6


def test_a_bound_is_never_the_cut_in_disguise():
    a = _graph(np.random.default_rng(1), 25, 0.3)
    got = D.partition(a, 4)
    assert got["bound"] < got["cut"] and got["ratio"] > 1.0
    raw = D.partition(_graph(np.random.default_rng(2), 12), 3, method="projection_raw")
    assert raw["bound"] is None and raw["ratio"] is None
    with pytest.raises(ValueError, match="two sides"):
        D.partition(a, 5, method="hyperplane")
    with pytest.raises(ValueError, match="no method"):
        D.partition(a, 5, method="guess")
    assert sorted(np.bincount(D.partition(a, 2, method="hyperplane", sizes=[20, 5])["labels"])) == [5, 20]


def test_every_partition_is_enumerated_once():
    for sizes, count in (((2, 2), 3), ((3, 2), 10), ((2, 2, 2), 15), ((3, 3, 2), 280), ((4, 1), 5)):
        found = list(D.partitions_of(np.array(sizes)))
        assert len(found) == len(set(found)) == count


def test_canonical_solver():
    """Trace one gives the least eigenvalue; the cut in canonical form stays below the relaxation that knows more."""
    rng = np.random.default_rng(3)
    c = rng.normal(size=(6, 6))
    c = c + c.T
    x, value, bound = D.solve_sdp(c, [np.eye(6)], np.array([1.0]), trace=1.0)
    least = np.linalg.eigvalsh(c)[0]
    assert value == pytest.approx(least, abs=1e-4) and bound <= least + 1e-9 and bound == pytest.approx(least, abs=1e-4) and np.trace(x) == pytest.approx(1, abs=1e-5)
    a = _graph(rng, 8)
    for k in (2, 4):
        rows, rhs, cost = D.canonical_cut(a, k, "min")
        bound = D.solve_sdp(cost, rows, rhs, trace=8.0)[2]
        assert bound <= D.relax(a, k, "min", "psd")[2] + 1e-3 <= D.brute_cut(a, k, "min")[0] + 2e-3


def _ring(spark):
    nodes = spark.createDataFrame([(0, i, t) for i, t in enumerate((0.1, -0.2, 0.3, 0.0))], "model_id long, var_id long, theta double")
    edges = spark.createDataFrame([(0, 0, 1, 1.0), (0, 2, 3, 1.0), (0, 1, 2, 0.25), (0, 0, 3, -0.25)], "model_id long, src long, dst long, theta double")
    return Model.pairwise(nodes, edges)


def test_options_are_honoured_or_refused(spark):
    m = _ring(spark)
    a = spark.createDataFrame([(0, i, i // 2) for i in range(4)], "model_id long, var_id long, cluster int")
    for bad in ({"schedule": "guess"}, {"executor": "sql", "schedule": "sequential"}, {"executor": "arrow", "restarts": 2}, {"tree": True, "damping": 0.5}, {"tree": True, "executor": "sql"}, {"executor": "gpu"}):
        with pytest.raises(ValueError):
            I.cluster_mean_field(m, a, **bad)
    with pytest.raises(Exception, match="joint states"):
        I.cluster_mean_field(m, a, budget_states=2).marginals.collect()
    fixed = I.cluster_mean_field(m, a, tol=1e-12).marginals.select("model_id", "var_id", "mean")
    warm = I.cluster_mean_field(m, a, tol=1e-8, init=fixed)
    assert warm.trace.count() < I.cluster_mean_field(m, a, tol=1e-8).trace.count()
    trace = I.cluster_mean_field(m, a, executor="sql", schedule="jacobi", tol=1e-3).trace
    assert trace.columns == ["model_id", "sweep", "delta", "bound"] == I.cluster_mean_field(m, a).trace.columns and trace.count() > 1
    with pytest.raises(Exception, match="budget"):
        P.infer(m, budget_states=4).collect()


def test_divergence_from_shared_cliques(spark):
    m = _ring(spark)
    a = spark.createDataFrame([(0, i, i // 2) for i in range(4)], "model_id long, var_id long, cluster int")
    r = I.cluster_mean_field(m, a, tol=1e-13)
    z = I.exact_log_z(m)
    assert I.kl_border_sum(m, a, r, z).first()["kl"] == pytest.approx(I.kl_divergence(r.diagnostics, z).first()["kl"], abs=1e-9)


def test_ranks(spark):
    df = spark.range(500).select((F.col("id") % 3).alias("model_id"), F.col("id").alias("v"), F.pmod(F.xxhash64("id"), F.lit(20)).alias("w"))
    got = L.ranked(df, ["model_id"], [F.desc("w"), F.col("v")], "r").collect()
    for m in range(3):
        mine = sorted((x for x in got if x["model_id"] == m), key=lambda x: x["r"])
        assert [x["r"] for x in mine] == list(range(1, len(mine) + 1))
        assert [(-x["w"], x["v"]) for x in mine] == sorted((-x["w"], x["v"]) for x in mine)
    assert L.ranked(df.limit(0), ["model_id"], [F.col("v")], "r").count() == 0


def test_halves_are_equal(spark):
    nodes = spark.range(31).select(F.lit(0).cast("long").alias("model_id"), F.col("id").alias("var_id"))
    edges = nodes.where("var_id < 30").select("model_id", F.col("var_id").alias("src"), (F.col("var_id") + 1).alias("dst"), F.lit(1.0).alias("weight"))
    found = sorted(r["count"] for r in L.spectral_bisection(nodes, edges, rounds=10).groupBy("cluster").count().collect())
    assert found == [15, 16]


def test_tables_have_owners(spark):
    with storage.Tables(spark) as own:
        held = storage.Stored(spark.range(5))
    assert held.read().count() == 5 and own.paths == [held.path] and os.path.isdir(held.path)
    own.drop()
    assert not os.path.exists(held.path)
    away = types.SimpleNamespace(conf=types.SimpleNamespace(get=lambda *_: None), sparkContext=types.SimpleNamespace(master="spark://host:7077"))
    with pytest.raises(RuntimeError, match="checkpoint"):
        storage.shared_dir(away)


def test_panels_and_the_stored_grid(spark):
    options = {"trials": 2, "n": 8, "couplings": ("mixed",), "strengths": ((1.0, 1.0), (1.0, 2.0)), "ks": (2, 4), "restarts": 1}
    trials = X.stored_trials(spark, **options)
    assert trials.count() == 2 * 2 * (1 + 2 * 7) and X.stored_trials(spark, **options).inputFiles() == trials.inputFiles()
    rows = X.panels(trials, 4).where("graphs = 'all'").collect()
    assert len(rows) == 2 * 2 * 8 and all(r["n"] == 2 for r in rows) and {r["l1_rank"] for r in rows} <= set(range(1, 9))
    assert {r["clustering"] for r in rows} >= {"naive", "random", "min_coupling"}
