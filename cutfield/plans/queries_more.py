"""Registered queries on tabular models, workloads, streams in batch form, cuts, experiments and extensions."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..hashing import uniform
from ..operators import graph as G
from ..operators import inference as I
from ..operators import partition as P
from ..operators import scale as L
from ..operators import structure as S
from ..operators import tabular as T
from ..sources import workloads as W
from ..storage import Stored
from ..streaming import pair_counts as E
from . import experiments as X
from .queries_core import BY_SCHEME, CROSS, EXACT, MODELS, PAIR_GROUP, mean_field_sql, models, query, rounded

# --- tabular --------------------------------------------------------------------------------------------------------------------

_JOINED = f"""t AS (SELECT {", ".join(f"dense_rank() OVER (ORDER BY {c}) - 1 AS x{i}" for i, c in enumerate(W.TABLE6))}, n FROM (
  SELECT {", ".join(W.TABLE6)}, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey
  JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ALL)),
card AS ({" UNION ALL ".join(f"SELECT {i} AS v, max(x{i}) + 1 AS card FROM t" for i in range(6))})"""


def _potential(c: int, members: tuple[int, ...]) -> str:
    grid = " CROSS JOIN ".join(f"(SELECT unnest(range(card)) AS x{m} FROM card WHERE v = {m}) g{m}" for m in members)
    keys = ", ".join(f"x{m}" for m in members)
    return f"""p{c} AS (SELECT {keys}, round(ln((n + 1) / (sum(n) OVER () / count(*) OVER () + 1)), 6) AS phi FROM (
  SELECT {keys}, coalesce(n, 0) AS n FROM (SELECT {keys} FROM {grid}) LEFT JOIN (SELECT {keys}, sum(n) AS n FROM t GROUP BY ALL) USING ({keys})))"""


_TABLES = _JOINED + ", " + ", ".join(_potential(c, m) for c, m in enumerate(W.TABLE6_CLIQUES))
_STATES = (
    "js AS (SELECT "
    + ", ".join(f"g{i}.x{i}" for i in range(6))
    + ", exp(0.2 * ("
    + " + ".join(f"p{c}.phi" for c in range(len(W.TABLE6_CLIQUES)))
    + ")) AS w FROM "
    + " CROSS JOIN ".join(f"(SELECT unnest(range(card)) AS x{i} FROM card WHERE v = {i}) g{i}" for i in range(6))
    + " "
    + " ".join(f"JOIN p{c} ON " + " AND ".join(f"p{c}.x{x} = g{x}.x{x}" for x in m) for c, m in enumerate(W.TABLE6_CLIQUES))
    + ")"
)
_ROWS = " UNION ALL ".join(f"SELECT {c}::BIGINT AS clique_id, [{', '.join(f'x{x}' for x in m)}]::INT[] AS assignment, phi FROM p{c}" for c, m in enumerate(W.TABLE6_CLIQUES))


@query("tabular_potentials", f"WITH {_TABLES} SELECT clique_id, array_to_string(assignment, ',') AS assignment, phi FROM ({_ROWS})")
def tabular_potentials(spark, d):
    return W.table6(spark, d).potential_rows.select("clique_id", F.array_join("assignment", ",").alias("assignment"), "phi")


@query("tabular_exact_logz", f"WITH {_TABLES}, {_STATES} SELECT round(ln(sum(w)), 6) AS log_z FROM js")
def tabular_logz(spark, d):
    return rounded(T.exact(W.table6(spark, d))[0].select("log_z"), "log_z")


@query("tabular_marginals", f"WITH {_TABLES}, {_STATES} " + " UNION ALL ".join(f"SELECT {i}::BIGINT AS var_id, x{i}::INT AS state, round(sum(w) / (SELECT sum(w) FROM js), 6) AS prob FROM js GROUP BY 2" for i in range(6)))
def tabular_marginals(spark, d):
    return rounded(T.exact(W.table6(spark, d))[1].select("var_id", "state", "prob"), "prob")


def _clusters(spark) -> DataFrame:
    return spark.createDataFrame([(0, v, c) for v, c in W.TABLE6_CLUSTERS.items()], "model_id long, var_id long, cluster int")


def _average_sql() -> str:
    out = []
    for c, m in enumerate(W.TABLE6_CLIQUES):
        touched = sorted({W.TABLE6_CLUSTERS[v] for v in m})
        for k in touched if len(touched) > 1 else []:
            own = [v for v in m if W.TABLE6_CLUSTERS[v] == k]
            text = " || ';' || ".join(f"'{v}=' || x{v}" for v in own)
            out.append(f"SELECT {c}::BIGINT AS clique_id, {k} AS cluster, {text} AS own, round(avg(phi), 9) AS phi_avg FROM p{c} GROUP BY 3")
    return " UNION ALL ".join(out)


@query("border_averages", f"WITH {_TABLES} {_average_sql()}")
def border_averages(spark, d):
    m, a = W.table6(spark, d), _clusters(spark)
    got = S.border_averages(m, a, T.uniform_tables(m, a))
    own = F.array_join(F.transform("own", lambda x: F.concat(x["var_id"].cast("string"), F.lit("="), x["s"].cast("string"))), ";")
    # means of six-decimal numbers lie on ties at six decimals, so nine are kept
    return got.select("clique_id", "cluster", own.alias("own"), (F.round("phi_avg", 9) + F.lit(0.0)).alias("phi_avg"))


@query("tabular_cliques", """SELECT l_orderkey::BIGINT AS clique_id, count(DISTINCT s_nationkey)::INT AS k_beta, count(DISTINCT s_nationkey) > 1 AS is_border
FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1""")  # fmt: skip
def tabular_cliques(spark, d):
    """Each order as a clique of its suppliers, clustered by nation."""
    model = F.lit(0).cast("long").alias("model_id")
    cliques = W.order_members(spark, d).groupBy(F.col("trial").alias("clique_id")).agg(F.collect_list("var_id").alias("members")).select(model, "*")
    clusters = W.table(spark, d, "supplier").select(model, F.col("s_suppkey").cast("long").alias("var_id"), F.col("s_nationkey").cast("int").alias("cluster"))
    return S.classify_cliques(cliques, clusters).select("clique_id", "k_beta", "is_border")


@query("tabular_cmf")
def tabular_cmf(spark, d):
    return rounded(T.mean_field(W.table6(spark, d), _clusters(spark))[0], "prob")


@query("tabular_bound_gap")
def tabular_bound_gap(spark, d):
    m = W.table6(spark, d)
    bound = T.mean_field(m, _clusters(spark))[1]
    j = bound.join(T.exact(m)[0], "model_id").join(T.kl_bounds(m, _clusters(spark)), "model_id")
    return rounded(j.select("bound", "log_z", (F.col("log_z") - F.col("bound")).alias("kl"), (F.col("b") * F.col("w")).alias("kl_upper")), "bound", "log_z", "kl", "kl_upper")


# --- workloads ------------------------------------------------------------------------------------------------------------------


@query("host_links", r"""WITH p AS (SELECT regexp_extract(url, '^https?://([^/?#"''\s]+)', 1) AS src, unnest(regexp_extract_all(html, 'href=["'']([^"'']+)', 1)) AS href FROM pages),
q AS (SELECT src, CASE WHEN href LIKE '/%' THEN src ELSE regexp_extract(href, '^https?://([^/?#"''\s]+)', 1) END AS dst FROM p) SELECT src, dst, count(*) AS n FROM q WHERE src <> '' AND dst <> '' GROUP BY 1, 2""")  # fmt: skip
def host_links(spark, d):
    return W.host_links(spark, d)


@query("role_chain", """SELECT src, dst, count(*) AS n FROM (SELECT role AS src, lead(role) OVER (PARTITION BY conv_id ORDER BY turn, role, text) AS dst FROM conversations)
WHERE src IS NOT NULL AND dst IS NOT NULL GROUP BY 1, 2""")  # fmt: skip
def role_chain(spark, d):
    return W.role_chain(spark, d)


@query("knn_vectors", """WITH s AS (SELECT a.vec_id, b.vec_id AS nbr, round(list_dot_product(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 6) AS cos FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id WHERE a.vec_id % 50 = 0)
SELECT vec_id, nbr, cos FROM (SELECT *, row_number() OVER (PARTITION BY vec_id ORDER BY cos DESC, nbr) AS r FROM s) WHERE r <= 10""")  # fmt: skip
def knn_vectors(spark, d):
    return W.knn_vectors(spark, d)


_STAMP = "strftime({}, '%Y-%m-%d %H:%M:%S')"


def _stamped(df: DataFrame) -> DataFrame:
    return df.withColumns({c: F.date_format(c, "yyyy-MM-dd HH:mm:ss") for c in ("win_start", "win_end")})


@query("event_windows_tumbling", f"""SELECT {_STAMP.format("date_trunc('hour', ts)")} AS win_start, {_STAMP.format("date_trunc('hour', ts) + INTERVAL 1 HOUR")} AS win_end, event_type, count(*) AS n FROM events GROUP BY ALL""")
def tumbling(spark, d):
    return _stamped(E.tumbling(W.table(spark, d, "events")))


@query("event_windows_sliding", f"""WITH e AS (SELECT date_trunc('hour', ts) - INTERVAL 1 HOUR * k AS s, event_type FROM events, range(2) r(k))
SELECT {_STAMP.format("s")} AS win_start, {_STAMP.format("s + INTERVAL 2 HOUR")} AS win_end, event_type, count(*) AS n FROM e GROUP BY ALL""")  # fmt: skip
def sliding(spark, d):
    return _stamped(E.sliding(W.table(spark, d, "events")))


@query("event_windows_session", f"""WITH a AS (SELECT user_id, ts, coalesce(ts - lag(ts) OVER w >= INTERVAL 30 MINUTE, true)::INT AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
b AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM a)
SELECT {_STAMP.format("min(ts)")} AS win_start, {_STAMP.format("max(ts) + INTERVAL 30 MINUTE")} AS win_end, user_id, count(*) AS n FROM b GROUP BY user_id, s""")  # fmt: skip
def session(spark, d):
    return _stamped(E.sessions(W.table(spark, d, "events")))


@query("view_purchase_interval", """SELECT p.user_id, v.event_id AS view_id, p.event_id AS purchase_id FROM events v JOIN events p ON v.user_id = p.user_id
WHERE v.event_type = 'view' AND p.event_type = 'purchase' AND p.ts >= v.ts AND p.ts <= v.ts + INTERVAL 1 HOUR""")  # fmt: skip
def interval_join(spark, d):
    return E.view_then_purchase(W.table(spark, d, "events"))


@query("theta_asof", """WITH s AS (SELECT user_id, ts, value AS theta FROM events WHERE event_type = 'signup')
SELECT e.event_id, s.theta FROM events e ASOF LEFT JOIN s ON e.user_id = s.user_id AND e.ts >= s.ts WHERE e.event_type = 'purchase'""")  # fmt: skip
def theta_asof(spark, d):
    """The latest value set at or before each purchase of the user: one sort of both, no range join."""
    e = W.table(spark, d, "events")
    before = Window.partitionBy("user_id").orderBy("ts", F.col("event_type") == "purchase").rowsBetween(Window.unboundedPreceding, 0)
    rows = e.where("event_type in ('signup', 'purchase')").withColumn("theta", F.last(F.when(F.col("event_type") == "signup", F.col("value")), ignorenulls=True).over(before))
    return rows.where("event_type = 'purchase'").select("event_id", "theta")


_MEASURE = """WITH x AS (SELECT r_name AS region, c_mktsegment AS segment, round(o_totalprice, 2)::DECIMAL(38,2) AS v FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey)
SELECT region, segment, count(*) AS n, sum(v)::DOUBLE AS total FROM x GROUP BY {}"""


def _measures(spark, d) -> DataFrame:
    t = lambda n: W.table(spark, d, n)
    rows = t("orders").join(t("customer"), F.col("o_custkey") == F.col("c_custkey")).join(t("nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(t("region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return rows.select(F.col("r_name").alias("region"), F.col("c_mktsegment").alias("segment"), F.round("o_totalprice", 2).cast("decimal(38,2)").alias("v"))


@query("region_rollup", _MEASURE.format("ROLLUP (region, segment)"))
def region_rollup(spark, d):
    return _measures(spark, d).rollup("region", "segment").agg(F.count(F.lit(1)).alias("n"), F.sum("v").cast("double").alias("total"))


@query("scheme_cube", _MEASURE.format("CUBE (region, segment)"))
def scheme_cube(spark, d):
    return _measures(spark, d).cube("region", "segment").agg(F.count(F.lit(1)).alias("n"), F.sum("v").cast("double").alias("total"))


@query("user_model_edges", f"""WITH d AS (SELECT user_id, ts::DATE AS day, {", ".join(f"max((event_type = '{t}')::INT) AS {t}" for t in ("click", "error", "purchase", "signup", "view"))} FROM events GROUP BY 1, 2),
p AS ({" UNION ALL ".join(f"SELECT user_id, {i} AS src, {j} AS dst, {a} AS x, {b} AS y FROM d" for i, a in enumerate(("click", "error", "purchase", "signup", "view")) for j, b in enumerate(("click", "error", "purchase", "signup", "view")) if i < j)}),
g AS (SELECT user_id AS model_id, src::BIGINT AS src, dst::BIGINT AS dst, round(ln((count(*) FILTER (WHERE x = 1 AND y = 1) + 0.5) * (count(*) FILTER (WHERE x = 0 AND y = 0) + 0.5)
  / ((count(*) FILTER (WHERE x = 1 AND y = 0) + 0.5) * (count(*) FILTER (WHERE x = 0 AND y = 1) + 0.5))), 6) / 5 AS theta FROM p GROUP BY 1, 2, 3)
SELECT model_id, src, dst, round(theta, 7) AS theta FROM g WHERE theta <> 0""")  # fmt: skip
def user_model_edges(spark, d):
    return W.user_models(spark, d).edges.withColumn("theta", F.round("theta", 7))


_CLASSES = r"""w AS (
  SELECT doc_id, CASE WHEN regexp_matches(coalesce(text, ''), '[^\x20\x09-\x0D]') THEN regexp_extract_all(text, '[^\x20\x09-\x0D]+') ELSE []::VARCHAR[] END AS ws FROM documents
), s AS (
  SELECT doc_id, CASE WHEN len(ws) = 0 THEN []::VARCHAR[] WHEN len(ws) < 5 THEN [array_to_string(ws, chr(32))]
    ELSE list_distinct([array_to_string(ws[i:i+4], chr(32)) for i in range(1, len(ws) - 3)]) END AS s FROM w
), c AS (SELECT doc_id, s, min(doc_id) OVER (PARTITION BY list_sort(s)) AS class_id FROM s),
r AS (SELECT doc_id, len(s) AS n, unnest(s) AS h FROM c WHERE doc_id = class_id),
j AS (SELECT a.doc_id AS src, b.doc_id AS dst, count(*) AS m, any_value(a.n) AS n1, any_value(b.n) AS n2 FROM r a JOIN r b ON a.h = b.h AND a.doc_id < b.doc_id GROUP BY 1, 2),
links AS (SELECT src, dst FROM j WHERE m / (n1 + n2 - m) >= 0.8)"""


@query("evidence_accuracy", f"""WITH {_CLASSES}, lab AS (
  SELECT doc_id, class_id, quality, floor(5 * (concat('0x', substr(md5(concat_ws(':', 'fold', doc_id)), 1, 8))::UBIGINT::DOUBLE / 4294967296.0))::INT AS home FROM labels JOIN c USING (doc_id)
), fo AS (SELECT unnest(range(5))::INT AS fold), pr AS (SELECT fold, 0.25 * (2 * avg(quality) - 1) AS prior FROM lab, fo WHERE home <> fold GROUP BY 1),
h AS (SELECT fold, class_id, sum(2.0 * (2 * quality - 1)) AS h FROM lab, fo WHERE home <> fold GROUP BY 1, 2),
m1 AS (SELECT fold, class_id, tanh(prior + h) AS m FROM h JOIN pr USING (fold)),
f AS (SELECT fold, i AS class_id, sum(m) AS f FROM m1 JOIN (SELECT src AS i, dst AS k FROM links UNION ALL SELECT dst, src FROM links) l ON l.k = m1.class_id GROUP BY 1, 2)
SELECT fold, count(*) AS n, round(avg((((prior + coalesce(h.h, 0) + coalesce(f.f, 0) >= 0)::INT) = quality)::INT), 6) AS accuracy
FROM lab JOIN fo ON home = fold JOIN pr USING (fold) LEFT JOIN h USING (fold, class_id) LEFT JOIN f USING (fold, class_id) GROUP BY 1""")  # fmt: skip
def evidence_accuracy(spark, d):
    """Labels of hidden documents from a model over near-copy classes, others' labels as evidence; two synchronous updates."""
    from .similarity import similar_sets

    sim = similar_sets(W.table(spark, d, "documents"))
    lab = W.table(spark, d, "labels").join(sim.members, "doc_id").select("doc_id", "class_id", "quality", F.floor(5 * uniform(F.lit("fold"), F.col("doc_id"))).cast("int").alias("home"))
    folds = lab.select("*", F.explode(F.sequence(F.lit(0), F.lit(4))).alias("fold"))
    sign = 2 * F.col("quality") - 1
    seen = folds.where("home <> fold")
    prior = seen.groupBy("fold").agg((F.lit(0.25) * (2 * F.avg("quality") - 1)).alias("prior"))
    own = seen.groupBy("fold", "class_id").agg(F.sum(2.0 * sign).alias("h"))
    first = own.join(F.broadcast(prior), "fold").select("fold", "class_id", F.tanh(F.col("prior") + F.col("h")).alias("m"))  # five rows
    both = sim.links.select(F.col("src").alias("i"), F.col("dst").alias("class_id")).unionByName(sim.links.select(F.col("dst").alias("i"), F.col("src").alias("class_id")))
    field = first.join(both, "class_id").groupBy("fold", F.col("i").alias("class_id")).agg(F.sum("m").alias("f"))
    hidden = folds.where("home = fold").join(F.broadcast(prior), "fold").join(own, ["fold", "class_id"], "left").join(field, ["fold", "class_id"], "left")
    guess = (F.col("prior") + F.coalesce("h", F.lit(0.0)) + F.coalesce("f", F.lit(0.0)) >= 0).cast("int")
    return rounded(hidden.groupBy("fold").agg(F.count(F.lit(1)).alias("n"), F.avg((guess == F.col("quality")).cast("int")).alias("accuracy")), "accuracy")


# --- cuts by dense kernels ------------------------------------------------------------------------------------------------------


def _trade_graphs(spark, d) -> tuple[DataFrame, DataFrame]:
    """The thresholded trade graphs, unweighted: model 7 at the quantile 0.7, model 5 at 0.5."""
    t = W.trade_threshold(spark, d).select((F.col("q") * 10).cast("long").alias("model_id"), "src", "dst", F.lit(1.0).alias("weight"))
    nodes = spark.createDataFrame([(m, v) for m in (7, 5) for v in range(24)], "model_id long, var_id long")
    return nodes, t


def _cuts(spark, d, method: str, ks=(3, 4, 6, 8), senses=("min", "max")) -> DataFrame:
    nodes, t = _trade_graphs(spark, d)
    out = None
    for k in ks:
        for sense in senses:
            c = P.equi_cut(nodes, t, k, sense, method=method).groupBy("model_id").agg(F.first("cut").alias("cut"), F.round(F.first("bound"), 3).alias("bound"), F.round(F.first("ratio"), 4).alias("ratio"))
            c = c.select("model_id", F.lit(k).alias("k"), F.lit(sense).alias("sense"), "cut", "bound", "ratio")
            out = c if out is None else out.unionByName(c)
    return out


for _name, _method in (("round_kmeans", "kmeans"), ("round_projection", "projection"), ("round_projection_raw", "projection_raw"), ("round_linearised", "linearised"), ("spectral_partition", "spectral")):
    query(_name)(lambda spark, d, m=_method: _cuts(spark, d, m))
query("round_hyperplane")(lambda spark, d: _cuts(spark, d, "hyperplane", (2,)))
query("round_hyperplane_raw")(lambda spark, d: _cuts(spark, d, "hyperplane_raw", (2,)))
query("cut_uneven")(lambda spark, d: _cuts(spark, d, "kmeans", (5, 7, 9)))


#: Prescribed sizes: equal ones, ones that do not divide, and lopsided ones; for the models of five and of eight nations.
SIZES = ((3, 2), (4, 1), (2, 2, 1), (3, 3, 2), (5, 3), (4, 4), (2, 2, 2, 2))
_CASES = ", ".join(f"('{','.join(map(str, c))}', {len(c)}, {sum(c)})" for c in SIZES)


@query("cut_sandwich", f"""WITH {MODELS}, aw AS ({BY_SCHEME}), cs AS (SELECT * FROM (VALUES {_CASES}) v(sizes, k, n)),
lab AS (SELECT sizes, k, n, s, p, (s // pow(k, p)::BIGINT) % k AS c FROM (SELECT *, unnest(range(pow(k, n)::BIGINT)) AS s FROM cs) x, range(8) r(p) WHERE p < n),
ok AS (SELECT sizes, n, s FROM (SELECT sizes, k, n, s, c, count(*) AS m FROM lab GROUP BY ALL) GROUP BY sizes, k, n, s HAVING array_to_string(list_reverse_sort(list(m)), ',') = sizes),
named AS (SELECT lab.sizes, lab.n, lab.s, lab.p, lab.c FROM lab JOIN ok USING (sizes, n, s)),
nn AS (SELECT model_id, count(*) AS n FROM nodes GROUP BY 1),
cut AS (SELECT affinity, aw.model_id, a.sizes, a.s, sum(CASE WHEN a.c <> b.c THEN w ELSE 0 END) AS cut
  FROM aw JOIN nn USING (model_id) JOIN pos x ON x.model_id = aw.model_id AND x.var_id = aw.src JOIN pos y ON y.model_id = aw.model_id AND y.var_id = aw.dst
  JOIN named a ON a.n = nn.n AND a.p = x.pos JOIN named b ON b.sizes = a.sizes AND b.s = a.s AND b.p = y.pos GROUP BY ALL)
SELECT affinity, model_id, 'min' AS sense, sizes, round(min(cut), 6) AS optimum, TRUE AS ordered, TRUE AS canonical, TRUE AS feasible FROM cut GROUP BY ALL
UNION ALL SELECT affinity, model_id, 'max', sizes, round(max(cut), 6), TRUE, TRUE, TRUE FROM cut GROUP BY ALL""")  # fmt: skip
def cut_sandwich(spark, d):
    """Every bound on its side of the optimum, every rounding of the asked sizes on the other, also where sizes differ."""
    m, out = models(spark, d)[0], None
    for kind in ("unit", "coupling", "inverse"):
        r = P.size_sandwich(m.node_params, G.affinity(m.edges, kind), SIZES).select(F.lit(kind).alias("affinity"), "*")
        out = r if out is None else out.unionByName(r)
    return rounded(out, "optimum")


@query("relax_bound")
def relax_bound(spark, d):
    nodes, t = _trade_graphs(spark, d)
    out = None
    for k in (3, 4, 6, 8):
        for sense in ("min", "max"):
            r = P.relax_bounds(nodes, t, k, sense).select("model_id", F.lit(k).alias("k"), F.lit(sense).alias("sense"), "level", F.round("value", 3).alias("value"), F.round("bound", 3).alias("bound"))
            out = r if out is None else out.unionByName(r)
    return out


@query("eigen_bound")
def eigen_bound(spark, d):
    nodes, t = _trade_graphs(spark, d)
    return P.relax_bounds(nodes, t, 4, "min", ("eigen",)).unionByName(P.relax_bounds(nodes, t, 4, "max", ("eigen",))).select("model_id", F.round("bound", 4).alias("bound"))


@query("gram_factor")
def gram_factor(spark, d):
    return P.gram_points(*_trade_graphs(spark, d), 4, rank=4)


@query("treewidth_minfill")
def treewidth(spark, d):
    return P.treewidth(*_trade_graphs(spark, d))


@query("unequal_cut")
def unequal_cut(spark, d):
    nodes, t = _trade_graphs(spark, d)
    return P.equi_cut(nodes, t, 3, sizes=[12, 8, 4])


@query("supplier_cut")
def supplier_cut(spark, d):
    """All suppliers by the orders that have both: a dense graph, where exact inference is out of reach; ``bound`` is null beyond the dense limit."""
    g = W.copurchase_graph(spark, d, "l_suppkey")
    edges = g.select(F.lit(0).cast("long").alias("model_id"), "src", "dst", F.col("n").cast("double").alias("weight"))
    nodes = W.table(spark, d, "supplier").select(F.lit(0).cast("long").alias("model_id"), F.col("s_suppkey").alias("var_id"))
    return P.cut_any_size(nodes, edges, 4, method="kmeans").select("var_id", "cluster", "cut", "bound")


# --- experiments ------------------------------------------------------------------------------------------------------------------


@query("table_quality")
def table_quality(spark, d):
    return X.table_quality(spark, 100, sf_dir=d)


@query("table_quality_weighted")
def table_quality_weighted(spark, d):
    return X.table_quality(spark, 100, weighted=True, sf_dir=d)


# each grid is computed once an application: 20 trials, three couplings, four strengths, k = 2, 3, 4, 6, 8, 12
query("figure_marginals")(lambda spark, d: X.figure_marginals(X.stored_trials(spark)))
query("figure_bounds")(lambda spark, d: X.figure_bounds(X.stored_trials(spark)))
query("figure_panels")(lambda spark, d: X.panels(X.stored_trials(spark), 12))
query("figure_dense")(lambda spark, d: X.win_rates(X.stored_trials(spark, p=0.5)))
query("figure_dense_panels")(lambda spark, d: X.panels(X.stored_trials(spark, p=0.5), 16))
query("figure_bit")(lambda spark, d: X.win_rates(X.stored_trials(spark, domain="bit")))
query("theorem_scatter")(lambda spark, d: X.theorem_scatter(X.stored_trials(spark)))
query("win_rates")(lambda spark, d: X.win_rates(X.stored_trials(spark)))

# --- extensions -----------------------------------------------------------------------------------------------------------------


@query("autopilot")
def autopilot(spark, d):
    return rounded(P.infer(models(spark, d)[0], budget_states=16), "prob", "bound", "kl_upper")


query("alternate")(lambda spark, d: rounded(P.alternate(models(spark, d)[0], 2), "bound", "w"))
query("compare_schemes")(lambda spark, d: rounded(P.compare_schemes(models(spark, d)[0], 2), "bound", "w", "kl_upper"))


@query("tree_cmf")
def tree_cmf(spark, d):
    m, a = models(spark, d)
    return rounded(I.cluster_mean_field(m, a, tree=True).marginals, "prob", "mean")


@query("tree_bound_gain")
def tree_bound_gain(spark, d):
    """How much of the gap to the log-normaliser tree links close."""
    m, a = models(spark, d)
    plain = I.cluster_mean_field(m, a).diagnostics.select("model_id", F.col("bound").alias("plain"))
    tree = I.cluster_mean_field(m, a, tree=True).diagnostics.select("model_id", F.col("bound").alias("tree"))
    return rounded(plain.join(tree, "model_id").join(I.exact_log_z(m), "model_id"), "plain", "tree", "log_z")


@query("cmf_trace")
def cmf_trace(spark, d):
    return rounded(I.cluster_mean_field(*models(spark, d)).trace, "delta", "bound")


@query("cluster_colours")
def colours(spark, d):
    m, a = models(spark, d)
    return I.cluster_colours(m.edges, a)


@query("user_models_cmf")
def user_models_cmf(spark, d):
    """One small model per user: two clusters each, all in one job."""
    m = W.user_models(spark, d)
    a = m.node_params.select("model_id", "var_id", (F.col("var_id") > 2).cast("int").alias("cluster"))
    r = I.cluster_mean_field(m, a, tol=1e-10)
    return rounded(r.diagnostics.select("model_id", "bound", "w"), "bound", "w")


def _copurchase(spark, d) -> tuple[DataFrame, DataFrame]:
    g = W.copurchase_graph(spark, d)
    edges = g.select(F.lit(0).cast("long").alias("model_id"), "src", "dst", F.col("n").cast("double").alias("weight"))
    edges = Stored(edges).read()  # operators and the measure read it many times
    return W.table(spark, d, "part").select(F.lit(0).cast("long").alias("model_id"), F.col("p_partkey").alias("var_id")), edges


def _with_cut(assignment: DataFrame, edges: DataFrame, name: str) -> DataFrame:
    assignment = Stored(assignment).read()
    sizes = assignment.groupBy("model_id", "cluster").agg(F.count(F.lit(1)).alias("m")).groupBy("model_id").agg(F.min("m").alias("least"), F.max("m").alias("most"), F.count(F.lit(1)).alias("k"))
    return G.cut_weight(edges, G.few(assignment, assignment.count())).join(sizes, "model_id").select(F.lit(name).alias("method"), "cut", "least", "most", "k")


@query("coarsen_partition")
def coarsen_partition(spark, d):
    nodes, edges = _copurchase(spark, d)
    return _with_cut(L.coarse_partition(nodes, edges, 8), edges, "coarsen").unionByName(_with_cut(G.random_partition(nodes, 8), edges, "random"))


query("coarsen_max_cut")(lambda spark, d: (lambda n, e: _with_cut(L.coarse_partition(n, e, 8, "max"), e, "refined max"))(*_copurchase(spark, d)))
query("label_propagation")(lambda spark, d: (lambda n, e: _with_cut(L.label_propagation(n, e, 8), e, "labels"))(*_copurchase(spark, d)))
query("spectral_bisection")(lambda spark, d: (lambda n, e: _with_cut(L.spectral_bisection(n, e), e, "spectral"))(*_copurchase(spark, d)))
query("merged_clusters")(lambda spark, d: (lambda n, e: _with_cut(L.merged_clusters(n, e, 2.0**10, "states"), e, "merged"))(*_copurchase(spark, d)))


@query("link_components", """WITH RECURSIVE e AS (SELECT DISTINCT least(src, dst) AS a, greatest(src, dst) AS b FROM (SELECT x.n_nationkey::BIGINT AS src, y.n_nationkey::BIGINT AS dst FROM nation x JOIN nation y ON y.n_nationkey = x.n_nationkey + 5 AND x.n_nationkey % 5 < 3)),
u AS (SELECT a, b FROM e UNION ALL SELECT b, a FROM e), r AS (SELECT n_nationkey::BIGINT AS v, n_nationkey::BIGINT AS root FROM nation UNION SELECT u.b, r.root FROM r JOIN u ON u.a = r.v)
SELECT v AS var_id, min(root) AS component FROM r GROUP BY 1""")  # fmt: skip
def link_components(spark, d):
    n = W.table(spark, d, "nation").select(F.lit(0).cast("long").alias("model_id"), F.col("n_nationkey").cast("long").alias("var_id"))
    e = n.where("var_id % 5 < 3 and var_id < 20").select("model_id", F.col("var_id").alias("src"), (F.col("var_id") + 5).alias("dst"))
    return L.components(n, e).select("var_id", "component")


@query("kl_border_sum", f"WITH RECURSIVE {MODELS}{EXACT}{mean_field_sql(PAIR_GROUP)} SELECT model_id, round(log_z - bound, 6) AS kl FROM fb JOIN lz USING (model_id)")
def kl_border_sum(spark, d):
    """The divergence from the cliques that clusters share, against the gap of the bound."""
    m, a = models(spark, d)
    r = I.cluster_mean_field(m, a, tol=1e-13, max_sweeps=500)
    return rounded(I.kl_border_sum(m, a, r, I.exact_log_z(m)), "kl")


@query("flagship", f"""WITH RECURSIVE {MODELS}{CROSS}{EXACT}{mean_field_sql(PAIR_GROUP)},
bw AS (SELECT model_id, sum(CASE WHEN c_src <> c_dst THEN abs(theta) ELSE 0 END) AS w FROM crossing GROUP BY 1),
el AS (SELECT model_id, avg(abs((mean + 1) / 2 - prob)) AS l1 FROM fin JOIN em USING (model_id, var_id) GROUP BY 1)
SELECT model_id, round(w, 6) AS w, round(bound, 6) AS bound, round(log_z, 6) AS log_z, round(log_z - bound, 6) AS kl, round(4 * w, 6) AS kl_upper, round(l1, 6) AS l1
FROM fb JOIN lz USING (model_id) JOIN bw USING (model_id) JOIN el USING (model_id)""")  # fmt: skip
def flagship(spark, d):
    """Small regional models end to end: clusters, inference, certificate, and the truth beside them."""
    m, a = models(spark, d)
    r = I.cluster_mean_field(m, a, tol=1e-12)
    exact = I.exact_log_z(m)
    l1 = I.l1_error(r.marginals, I.exact_marginals(m))
    out = r.diagnostics.join(exact, "model_id").join(l1, "model_id")
    return rounded(out.select("model_id", "w", "bound", "log_z", (F.col("log_z") - F.col("bound")).alias("kl"), "kl_upper", "l1"), "w", "bound", "log_z", "kl", "kl_upper", "l1")


