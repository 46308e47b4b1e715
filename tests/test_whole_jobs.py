"""Registered queries return the whole job, on inputs large enough that a part would show."""

import inspect
from itertools import combinations

import duckdb
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from cutfield.operators import graph as G
from cutfield.operators import partition as P
from cutfield.operators import scale as L
from cutfield.plans import experiments as X


def test_supplier_cut_has_every_supplier(spark, tmp_path):
    # four groups of 35 suppliers; an order holds neighbours of one group, and one order in twenty a supplier of the next
    n, lines = 140, []
    for o in range(700):
        g, at = o % 4, o // 4
        items = [g * 35 + at % 35, g * 35 + (at + 1) % 35, g * 35 + (at + 3) % 35]
        lines += [(o, s) for s in items + [(items[0] + 35) % n] * (o % 20 == 0)]
    spark.createDataFrame(lines, "l_orderkey long, l_suppkey long").write.parquet(str(tmp_path / "lineitem.parquet"))
    spark.range(n).withColumnRenamed("id", "s_suppkey").write.parquet(str(tmp_path / "supplier.parquet"))
    rows = entry.queries()["supplier_cut"](spark, str(tmp_path)).collect()
    label = {r["var_id"]: r["cluster"] for r in rows}
    assert len(rows) == n and set(label) == set(range(n))
    assert sorted(list(label.values()).count(c) for c in range(4)) == [35] * 4
    baskets = {}
    for o, s in lines:
        baskets.setdefault(o, set()).add(s)
    want = sum(label[a] != label[b] for items in baskets.values() for a, b in combinations(sorted(items), 2))
    assert {r["cut"] for r in rows} == {float(want)} and rows[0]["bound"] <= want + 1e-6


def test_cut_beyond_dense_limit(spark):
    # model 0 has two cliques of twelve and a bridge, model 1 four nodes in two pairs
    edges = [(0, a, b, 1.0) for g in (0, 12) for a in range(g, g + 12) for b in range(a + 1, g + 12)] + [(0, 3, 15, 0.5), (1, 0, 1, 1.0), (1, 2, 3, 1.0)]
    w = spark.createDataFrame(edges, "model_id long, src long, dst long, weight double")
    nodes = spark.createDataFrame([(0, i) for i in range(24)] + [(1, i) for i in range(4)], "model_id long, var_id long")
    found = P.cut_any_size(nodes, w, 2, dense_limit=16).cache()
    assert found.count() == 28
    large, small = found.where("model_id = 0").collect(), found.where("model_id = 1").collect()
    cut = G.cut_weight(w, found).where("model_id = 0").first()["cut"]
    assert {(r["cut"], r["bound"], r["ratio"]) for r in large} == {(cut, None, None)}
    assert {r["count"] for r in found.where("model_id = 0").groupBy("cluster").count().collect()} == {12}
    assert {r["cut"] for r in small} == {0.0} and all(r["bound"] is not None for r in small)


def _both(spark, data, name):
    """Rows of the query and of its SQL, with columns in the order of their names."""
    con = duckdb.connect()
    for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{data}/{t}.parquet'")
    rel, df = con.sql(entry.oracle_sql()[name]), entry.queries()[name](spark, data)
    cols = sorted(df.columns)
    assert cols == sorted(rel.columns)
    want = sorted(tuple(dict(zip(rel.columns, r))[c] for c in cols) for r in rel.fetchall())
    return [dict(zip(cols, r)) for r in sorted(tuple(r[c] for c in cols) for r in df.collect())], [dict(zip(cols, r)) for r in want]


def test_model_energy_all_has_every_state(spark, data):
    got, want = _both(spark, data, "model_energy_all")
    key = lambda rows: {(r["model_id"], r["state_id"]) for r in rows}
    assert key(got) == key(want) == {(m, s) for m in range(5) for s in range(32)} | {(100, s) for s in range(256)}
    assert len(got) == 416 and all(a["energy"] == pytest.approx(b["energy"], abs=1e-9) for a, b in zip(got, want))


def test_figures_have_the_whole_grid(monkeypatch):
    figure, quality, seen = inspect.signature(X.figure_trials), inspect.signature(X.table_quality), {}

    def record(name, signature, *args, **options):
        bound = signature.bind(*args, **options)
        bound.apply_defaults()
        seen[name] = bound.arguments

    for name, p in (("figure_marginals", 0.3), ("figure_bounds", 0.3), ("theorem_scatter", 0.3), ("win_rates", 0.3), ("figure_dense", 0.5)):
        monkeypatch.setattr(X, "figure_trials", lambda *a, n=name, **o: record(n, figure, *a, **o))
        for f in ("figure_marginals", "figure_bounds", "theorem_scatter", "win_rates"):
            monkeypatch.setattr(X, f, lambda trials: trials)
        entry.queries()[name](None, "")
        got = seen[name]
        assert (got["trials"], got["p"], len(got["couplings"]), len(got["strengths"]), got["ks"]) == (20, p, 3, 4, (2, 3, 4, 6, 8, 12))
    monkeypatch.setattr(X, "table_quality", lambda *a, **o: record("weighted", quality, *a, **o))
    entry.queries()["table_quality_weighted"](None, "")
    assert seen["weighted"]["trials"] == 100


@pytest.mark.parametrize("name", ["random_graph_md5", "random_params_repulsive", "random_params_mixed", "random_params_attractive", "random_singletons", "tabular_cliques"])
def test_data_comes_from_a_given_table(spark, data, name):
    got, want = _both(spark, data, name)
    assert got == want and len(got) > 100
    assert any(f.endswith("lineitem.parquet") for f in entry.queries()[name](spark, data).inputFiles())


def test_coarse_graph_is_bounded(spark):
    """What is cut densely has a bounded number of groups: matching goes on beyond its rounds, and nodes without edges are packed."""
    nodes = spark.range(400).selectExpr("0L AS model_id", "id AS var_id")
    path = spark.range(299).selectExpr("0L AS model_id", "id AS src", "id + 1 AS dst", "1.0D AS weight")  # 100 nodes are without edges
    loose = L.heavy_matching(nodes, path, 50.0, 1)
    matched = L.heavy_matching(nodes, path, 50.0, 1, at_most=130)
    count = lambda df: df.select("group").distinct().count()
    assert count(loose) > 150 and 100 < count(matched) <= 130
    packed = L.bounded(matched, 20)
    assert count(packed) <= 40 and packed.count() == 400 and packed.agg(F.sum("mass")).first()[0] == 400.0


def test_matching_follows_the_rule(spark):
    """Rounds of mutual proposals against a plain loop over dictionaries, with pairs left out once they no longer fit."""
    rows = [(0, i, (7 * i + 3) % 30, float(1 + i % 3)) for i in range(30)] + [(0, i, (i + 1) % 30, 2.0) for i in range(30)]
    edges = spark.createDataFrame([r for r in rows if r[1] != r[2]], "model_id long, src long, dst long, weight double")
    nodes = spark.range(31).selectExpr("0L AS model_id", "id AS var_id")
    got = {r["var_id"]: r["group"] for r in L.heavy_matching(nodes, edges, 5.0, 4).collect()}
    group, weight = {i: i for i in range(31)}, {}
    for _, a, b, w in rows:
        if a != b:
            weight[min(a, b), max(a, b)] = weight.get((min(a, b), max(a, b)), 0.0) + w
    single = {}  # in the first round, parallel edges are not yet one
    for _, a, b, w in rows:
        if a != b:
            single[min(a, b), max(a, b)] = max(single.get((min(a, b), max(a, b)), 0.0), w)
    for r in range(4):
        mass = {g: list(group.values()).count(g) for g in group.values()}
        pairs = spark.createDataFrame([(r, a, b) for a, b in weight], "r int, a long, b long").selectExpr("a", "b", "xxhash64(r, a, b) AS h").collect()
        best = {}
        for a, b, h in pairs:
            if mass[a] + mass[b] <= 5:
                w = (weight if r else single)[a, b] / (mass[a] * mass[b])
                for i, j in ((a, b), (b, a)):
                    best[i] = max(best.get(i, (-1.0, 0, 0)), (w, h, j))
        into = {j: i for i, (_, _, j) in best.items() if i < j and best[j][2] == i}
        group = {v: into.get(g, g) for v, g in group.items()}
        merged = {}
        for (a, b), w in weight.items():
            x, y = sorted((into.get(a, a), into.get(b, b)))
            if x != y:
                merged[x, y] = merged.get((x, y), 0.0) + w
        weight = merged
    assert got == group


def test_copurchase_graph_is_built_once(spark, data):
    """Rounds over the graph read its edges, not the lines that they are counted from."""
    from cutfield.plans.queries_more import _copurchase

    _, edges = _copurchase(spark, data)
    assert edges.inputFiles() and not any("lineitem" in f for f in edges.inputFiles())


def test_table_quality_reads_the_given_tables(spark, data):
    """Graphs of trade by shares of the orders: every line between two of the nations counts once, in Spark as in SQL."""
    con = duckdb.connect()
    names = ("lineitem", "orders", "supplier", "customer")
    l, o, s, c = (f"'{data}/{t}.parquet'" for t in names)
    want = con.execute(f"""SELECT l_orderkey % 7, least(s_nationkey, c_nationkey), greatest(s_nationkey, c_nationkey), count(*) FROM {l} JOIN {o} ON l_orderkey = o_orderkey
      JOIN {s} ON l_suppkey = s_suppkey JOIN {c} ON o_custkey = c_custkey WHERE s_nationkey <> c_nationkey AND s_nationkey < 24 AND c_nationkey < 24 GROUP BY ALL""").fetchall()
    trials = X.trade_trials(spark, data, 7).collect()
    assert len(trials) == 7 and {(r["trial"], *p) for r in trials for p in r["pairs"] or []} == set(want)
    a = X.trade_matrix(trials[0]["pairs"], 0, 24, 0.3, False)
    assert a.sum() == 2 * round(0.3 * 276) and (a == a.T).all()
    w = X.trade_matrix(trials[0]["pairs"], 0, 24, 0.3, True)
    assert ((w > 0) == (a > 0)).all() and w.max() == 1.0
    rows = X.table_quality(spark, 2, sf_dir=data, ks=(3,), densities=(0.5,)).collect()
    assert len(rows) == 8 and all(r["trials"] == 2 for r in rows)
    assert all((r["cut"] >= r["bound"] - 0.02) if r["sense"] == "min" else (r["cut"] <= r["bound"] + 0.02) for r in rows if r["bound"] is not None)


def test_similar_sets_loses_no_link(spark, monkeypatch):
    """Every link, with its similarity, of near copies at the threshold and of a shingle of many members, dealt over small blocks."""
    import random

    from cutfield.plans import similarity

    monkeypatch.setattr(similarity, "BLOCK", 8)
    r, texts = random.Random(3), {0: "", 1: None, 2: "one two", 3: "one  two", 4: "two one"}
    for g in range(40):
        base = [f"w{r.randrange(4000)}" for _ in range(r.randint(6, 80))]
        for k in range(20 if g < 2 else 4):
            words = base.copy()
            for _ in range(r.randint(0, 2)):
                words[r.randrange(len(words))] = f"x{r.randrange(10**6)}"
            texts[len(texts)] = " ".join(words[r.randint(0, 2) :])
    split = {i: (t or "").split() for i, t in texts.items()}
    sets = {i: frozenset(tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))) if w else frozenset() for i, w in split.items()}
    first = {s: min(i for i in sets if sets[i] == s) for s in sets.values()}
    want = {(i, j): round(len(a & b) / len(a | b), 6) for i, j in combinations(sorted(first.values()), 2) for a, b in [(sets[i], sets[j])] if a | b and len(a & b) / len(a | b) >= 0.8}
    got = similarity.similar_sets(spark.createDataFrame(list(texts.items()), "doc_id long, text string").coalesce(2))
    assert {x["doc_id"]: x["class_id"] for x in got.members.collect()} == {i: first[s] for i, s in sets.items()}
    links = {(x["src"], x["dst"]): x["jaccard"] for x in got.links.collect()}
    assert links == want and len(want) > 60
