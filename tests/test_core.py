"""Relations: models, graphs, structure, inference executors, partitions, streams, SQL functions."""

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from cutfield.model import Model, TabularModel
from cutfield.operators import dense as D
from cutfield.operators import graph as G
from cutfield.operators import inference as I
from cutfield.operators import partition as P
from cutfield.operators import scale as L
from cutfield.operators import structure as S
from cutfield.operators import tabular as T
from cutfield.sources import workloads as W


@pytest.fixture(scope="module")
def ring(spark):
    nodes = spark.createDataFrame([(1, i, t) for i, t in enumerate((0.1, -0.2, 0.3, 0.0))], "model_id long, var_id long, theta double")
    edges = spark.createDataFrame([(1, 0, 1, 1.0), (1, 3, 2, 1.0), (1, 1, 2, 0.25), (1, 0, 3, -0.25)], "model_id long, src long, dst long, theta double")
    return Model.pairwise(nodes, edges)


def _assignment(spark, labels):
    return spark.createDataFrame([(1, i, c) for i, c in enumerate(labels)], "model_id long, var_id long, cluster int")


def test_pairwise_cleans_edges(spark):
    nodes = spark.createDataFrame([(1, 0, 0.5), (1, 1, None), (1, 2, float("nan")), (None, 9, 1.0)], "model_id long, var_id long, theta double")
    edges = spark.createDataFrame(
        [(1, 0, 1, 1.0), (1, 1, 0, 0.5), (1, 0, 0, 3.0), (1, 1, 2, 0.0), (1, 0, 2, float("nan")), (1, 0, 7, 1.0), (1, None, 2, 1.0), (1, 1, 2, None)],
        "model_id long, src long, dst long, theta double",
    )
    m = Model.pairwise(nodes, edges)
    assert [tuple(r) for r in m.edges.collect()] == [(1, 0, 1, 1.5)]
    assert {r["var_id"]: r["theta"] for r in m.node_params.collect()} == {0: 0.5, 1: 0.0, 2: 0.0}
    assert Model.pairwise(nodes, edges, merge="max").edges.first()["theta"] == 1.0
    with pytest.raises(Exception, match="given twice"):
        Model.pairwise(nodes, edges, merge="error").edges.collect()
    with pytest.raises(ValueError):
        Model.pairwise(nodes.drop("theta"), edges)


@pytest.mark.parametrize("executor,schedule", [("local", "colour"), ("sql", "jacobi"), ("arrow", "colour")])
def test_executors_agree(spark, ring, executor, schedule):
    a = _assignment(spark, [0, 0, 1, 1])
    r = I.cluster_mean_field(ring, a, executor=executor, schedule=schedule, tol=1e-8)
    means = {x["var_id"]: x["mean"] for x in r.marginals.collect()}
    assert np.allclose([means[i] for i in range(4)], (-0.053431, -0.095357, 0.278757, 0.217894), atol=3e-6)
    d = r.diagnostics.first()
    assert d["bound"] == pytest.approx(3.689371, abs=3e-6) and d["w"] == pytest.approx(0.5) and d["kl_upper"] == pytest.approx(2.0)


def test_warm_start_and_naive(spark, ring):
    naive = I.naive_mean_field(ring).diagnostics.first()
    assert naive["bound"] == pytest.approx(2.970817, abs=2e-6)
    init = ring.node_params.select("model_id", "var_id", F.lit(0.3).alias("mean"))
    r = I.cluster_mean_field(ring, _assignment(spark, [0, 0, 1, 1]), executor="arrow", schedule="jacobi", damping=0.1, init=init, tol=1e-8)
    assert r.diagnostics.first()["bound"] == pytest.approx(3.689371, abs=1e-5)


def test_exact(spark, ring):
    assert I.exact_log_z(ring).first()["log_z"] == pytest.approx(3.714862, abs=1e-6)
    big = {r["var_id"]: r["prob"] for r in I.exact_large(ring, 1).collect()}
    small = {r["var_id"]: r["prob"] for r in I.exact_marginals(ring).collect()}
    assert all(big[i] == pytest.approx(small[i]) for i in range(4))
    with pytest.raises(Exception, match="states"):
        I.exact_log_z(ring, max_states=4).collect()


def test_structure(spark, ring):
    a = _assignment(spark, [0, 0, 1, 1])
    c = {tuple(r["members"]): r["is_border"] for r in S.classify_cliques(ring.cliques(), a).collect()}
    assert c == {(0, 1): False, (2, 3): False, (1, 2): True, (0, 3): True}
    assert {tuple(r) for r in S.markov_blanket(ring.cliques(), a).collect()} == {(1, 0, 2, 1), (1, 0, 3, 1), (1, 1, 0, 0), (1, 1, 1, 0)}
    w = G.affinity(ring.edges)
    assert G.cut_weight(w, a).first()["cut"] == pytest.approx(0.5) == G.cut_weight(w, a, "trace").first()["cut"]
    k = S.kl_bounds(ring, a).first()
    assert (k["a"], k["b"]) == (0.0, 4.0)
    one = S.cluster_conditional(ring, _assignment(spark, [0, 0, 0, 0]), ring.node_params.select("model_id", "var_id", F.lit(0.0).alias("mean")))
    assert one.agg(F.sum("prob")).first()[0] == pytest.approx(1.0)


def test_partition_schemes(spark, ring):
    got = P.partition(ring, "min_coupling", 2).orderBy("var_id").collect()
    assert [r["cluster"] for r in got] == [0, 0, 1, 1] and got[0]["cut"] == pytest.approx(0.5)
    assert P.brute_cut(ring.node_params, G.affinity(ring.edges), 2).first()["labels"] == "0011"
    top = P.brute_cut(ring.node_params, G.affinity(ring.edges), 2, "max").first()
    assert top["cut"] == pytest.approx(2.5) and top["labels"] == "0101"
    with pytest.raises(Exception, match="dense limit"):
        P.equi_cut(ring.node_params, G.affinity(ring.edges), 2, dense_limit=3).collect()
    auto = P.infer(ring, budget_states=8).collect()
    assert auto[0]["k"] == 2 and auto[0]["bound"] >= 3.689
    colours = I.cluster_colours(ring.edges, _assignment(spark, [0, 0, 1, 1])).collect()
    assert {r["colour"] for r in colours} == {0, 1}


def test_isolated_and_empty(spark):
    nodes = spark.createDataFrame([(1, i, 0.2) for i in range(4)], "model_id long, var_id long, theta double")
    none = spark.createDataFrame([], "model_id long, src long, dst long, theta double")
    m = Model.pairwise(nodes, none)
    assert G.degrees(m.node_params, G.affinity(m.edges)).agg(F.sum("d")).first()[0] == 0
    got = P.equi_cut(m.node_params, G.affinity(m.edges), 2).collect()
    assert len(got) == 4 and got[0]["cut"] == 0
    r = I.cluster_mean_field(m, _assignment(spark, [0, 0, 1, 1]))
    assert r.diagnostics.first()["bound"] == pytest.approx(4 * np.log(2 * np.cosh(0.2)))


def test_scale_path(spark):
    # two cliques of twelve with one bridge: the best halves are known
    edges = [(0, a, b, 1.0) for g in (0, 12) for a in range(g, g + 12) for b in range(a + 1, g + 12)] + [(0, 3, 15, 0.5)]
    w = spark.createDataFrame(edges, "model_id long, src long, dst long, weight double")
    nodes = spark.createDataFrame([(0, i) for i in range(24)], "model_id long, var_id long")
    found = L.coarse_partition(nodes, w, 2, coarse_nodes=8)
    assert G.cut_weight(w, found).first()["cut"] == pytest.approx(0.5)
    assert {r["count"] for r in found.groupBy("cluster").count().collect()} == {12}
    half = L.spectral_bisection(nodes, w, rounds=12)
    assert G.cut_weight(w, half).first()["cut"] == pytest.approx(0.5)
    assert G.check_equipartition(nodes, L.label_propagation(nodes, w, 3), 3).first()["ok"]
    c = L.components(nodes, w.where("weight = 1.0"))
    assert {r["component"] for r in c.collect()} == {0, 12}
    m = L.merged_clusters(nodes, w, 4.0)
    assert m.groupBy("cluster").count().agg(F.max("count")).first()[0] <= 4


def test_tabular_field_matches_enumeration():
    rng = np.random.default_rng(0)
    cards = {0: 3, 1: 2, 2: 2, 3: 3}
    cliques = [(m, 0.7, rng.normal(size=[cards[v] for v in m])) for m in ((0, 1), (1, 2, 3), (0, 2), (3,))]
    e = np.zeros([3, 2, 2, 3])
    for m, t, p in cliques:
        order = sorted(range(len(m)), key=lambda i: m[i])
        e = e + t * p.transpose(order).reshape([cards[v] if v in m else 1 for v in range(4)])
    log_z = np.log(np.exp(e).sum())
    one = T.TabularField(cards, cliques, dict.fromkeys(range(4), 0))
    one.run()
    assert one.bound() == pytest.approx(log_z)
    three = T.TabularField(cards, cliques, {0: 0, 1: 0, 2: 1, 3: 2})
    last = -np.inf
    for _ in range(30):
        three.run(sweeps=1)
        assert three.bound() >= last - 1e-10
        last = three.bound()
    assert last <= log_z + 1e-9


def test_tabular_model_rejects_large(spark, data):
    m = W.table6(spark, data)
    assert isinstance(m, TabularModel)
    with pytest.raises(Exception, match="limit"):
        T.joint_states(m, 10).collect()


def test_streams_equal_batches(spark, data, tmp_path):
    from cutfield.streaming import pair_counts as E

    batch = spark.read.parquet(f"{data}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    batch.repartition(3).write.parquet(str(tmp_path / "in"))
    stream = E.events_stream(spark, str(tmp_path / "in"), batch.schema)
    for name, f, delay in (("t", E.tumbling, "60 days"), ("s", E.sessions, "60 days"), ("v", E.view_then_purchase, "60 days")):
        q = f(stream, delay=delay).writeStream.format("memory").queryName(f"q_{name}").outputMode("append" if name == "v" else "complete").option("checkpointLocation", str(tmp_path / name)).trigger(availableNow=True).start()
        q.awaitTermination()
        assert sorted(map(tuple, spark.table(f"q_{name}").collect())) == sorted(map(tuple, f(batch).collect()))
    seen = []
    E.refresh(E.deduplicated(stream), lambda df, i: seen.append(df.count()), str(tmp_path / "r")).awaitTermination()
    assert sum(seen) == batch.count()


def test_sql_functions(spark):
    from cutfield.functions import registered

    registered.register(spark)
    assert spark.sql("SELECT count(*) FROM enumerate_states(5, 'spin')").first()[0] == 32
    assert spark.sql("SELECT entropy(array(0.5D, 0.5D))").first()[0] == pytest.approx(np.log(2))
    assert spark.sql("SELECT log_sum_exp(x) FROM VALUES (1.0D), (2.0D) AS t(x)").first()[0] == pytest.approx(np.log(np.e + np.e**2))
    assert spark.sql("SELECT kl_divergence(array(0.5D, 0.5D), softmax(array(0D, 0D)))").first()[0] == pytest.approx(0, abs=1e-12)
    spark.createDataFrame([(1, 0, 1, 1.0), (1, 2, 3, 1.0), (1, 1, 2, 0.1), (2, 0, 1, 1.0)], "model_id long, src long, dst long, weight double").createOrReplaceTempView("g")
    rows = spark.sql("SELECT * FROM partition_graph(TABLE(g) PARTITION BY (model_id), 2)").where("model_id = 1").orderBy("var_id").collect()
    assert [r["cluster"] for r in rows] == [0, 0, 1, 1]


def test_data_source(spark):
    from cutfield.sources.random_model_source import RandomModelSource

    spark.dataSource.register(RandomModelSource)
    got = spark.read.format("random_model").option("trials", 3).load().select("trial", "src", "dst")
    want = W.random_graphs(spark, 3)
    assert {tuple(r) for r in got.collect()} == {tuple(r) for r in want.collect()}


def test_experiment_shapes(spark):
    from cutfield.plans import experiments as X

    t = {(r["p"], r["sense"], r["k"], r["rounding"]): r for r in X.table_quality(spark, 6).collect()}
    published = {("min", 0.3): (1.10, 1.09, 1.06, 1.03), ("min", 0.5): (1.05, 1.05, 1.03, 1.02), ("max", 0.3): (0.96, 0.97, 0.97, 0.99), ("max", 0.5): (0.97, 0.97, 0.98, 0.99)}
    for (sense, p), ratios in published.items():
        for k, ratio in zip((3, 4, 6, 8), ratios):
            r = t[p, sense, k, "kmeans"]
            assert abs(r["ratio"] - ratio) < 0.05
            better = t[p, sense, k, "projection"]["ratio"]
            assert (r["ratio"] <= better) if sense == "min" else (r["ratio"] >= better)
    f = X.figure_trials(spark, 3, strengths=((1.0, 1.0),), ks=(3, 6)).cache()
    assert sum(r["violations"] for r in X.theorem_scatter(f).collect()) == 0
    wins = {r["clustering"]: r for r in X.win_rates(f).collect()}
    assert wins["min_coupling"]["l1"] < wins["random"]["l1"] and wins["min_coupling"]["l1"] <= wins["min_unit"]["l1"] + 0.01
    assert wins["min_coupling"]["beats_naive"] > 0.8


@pytest.mark.parametrize("name", ["trade_graph", "laplacian", "cut_weight_trace", "equi_maxcut_brute", "kl_divergence", "tabular_marginals", "event_windows_session", "theta_asof", "border_averages"])
def test_oracle(spark, data, name):
    con = duckdb.connect()
    for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{data}/{t}.parquet'")
    rel = con.sql(entry.oracle_sql()[name])
    df = entry.queries()[name](spark, data)
    cols = sorted(df.columns)
    assert cols == sorted(rel.columns)
    clean = lambda v: round(float(v), 9) + 0.0 if isinstance(v, float) else v
    want = sorted((tuple(clean(dict(zip(rel.columns, r))[c]) for c in cols) for r in rel.fetchall()), key=repr)
    got = sorted((tuple(clean(r[c]) for c in cols) for r in df.collect()), key=repr)
    assert got == want


def test_entry(spark):
    assert entry.entry(spark).count() == 6
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_files(spark, ring, tmp_path):
    from cutfield.sources import files

    files.export(ring.edges, str(tmp_path / "csv"), "csv")
    files.export(ring.edges, str(tmp_path / "json"), "json")
    ring.edges.write.orc(str(tmp_path / "orc"))
    want = sorted(map(tuple, ring.edges.collect()))
    assert sorted(map(tuple, files.read_relation(spark, "edges", str(tmp_path / "csv"), "csv", header="true").collect())) == want
    assert sorted(map(tuple, files.read_relation(spark, "edges", str(tmp_path / "json"), "json").collect())) == want
    renamed = files.read_relation(spark, "edges", str(tmp_path / "orc"), "orc", {"src": "src", "dst": "dst", "theta": "2 * theta"})
    assert sorted(r["theta"] for r in renamed.collect()) == sorted(2 * t for *_, t in want)
    files.write_by_model(ring.edges, str(tmp_path / "by"), 8)
    assert sorted(map(tuple, files.read_model(spark, str(tmp_path / "by"), 1, 8).select("model_id", "src", "dst", "theta").collect())) == want
    a = _assignment(spark, [0, 0, 1, 1])
    files.write_bucketed(a, "bucketed_assignment", 4)
    assert spark.table("bucketed_assignment").count() == 4
    spark.sql("DROP TABLE bucketed_assignment")


def test_presence_state(spark, data, tmp_path):
    from cutfield.streaming import pair_counts as E

    batch = spark.read.parquet(f"{data}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp")).limit(200)
    batch.coalesce(1).write.parquet(str(tmp_path / "in"))
    stored = spark.read.parquet(str(tmp_path / "in"))
    q = E.presence(E.events_stream(spark, str(tmp_path / "in"), batch.schema)).writeStream.format("memory").queryName("presence").outputMode("update").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    q.awaitTermination()
    want = {tuple(r) for r in stored.groupBy("user_id", "event_type").count().collect()}
    assert {tuple(r) for r in spark.table("presence").collect()} == want
