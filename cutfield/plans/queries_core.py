"""Registered queries on graphs, structure, exact inference and cluster mean field, with their DuckDB twins."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import fold_signs
from ..operators import graph as G
from ..operators import inference as I
from ..operators import partition as P
from ..operators import structure as S
from ..sources import workloads as W

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def keep(f: Query) -> Query:
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return keep


def rounded(df: DataFrame, *names: str) -> DataFrame:
    """The named columns rounded to six decimals, negative zero made zero."""
    return df.withColumns({n: F.round(F.col(n), 6) + F.lit(0.0) for n in names})


# --- fixtures in SQL ----------------------------------------------------------------------------------------------------------

TRADE = """trade AS (
  SELECT least(s_nationkey, c_nationkey)::BIGINT AS src, greatest(s_nationkey, c_nationkey)::BIGINT AS dst, count(*) AS pairs,
         sum(round(l_extendedprice * (1 - l_discount), 4)::DECIMAL(38,4))::DOUBLE AS revenue
  FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey
  WHERE s_nationkey <> c_nationkey GROUP BY 1, 2)"""

MODELS = (
    TRADE
    + """, nodes AS (
  SELECT n_regionkey::BIGINT AS model_id, n_nationkey::BIGINT AS var_id FROM nation
  UNION ALL SELECT 100, n_nationkey FROM nation WHERE n_nationkey < 8
), e0 AS (
  SELECT a.model_id, a.var_id AS src, b.var_id AS dst, ln(coalesce(pairs, 0) + 1.0) AS x
  FROM nodes a JOIN nodes b ON a.model_id = b.model_id AND a.var_id < b.var_id
  LEFT JOIN trade t ON t.src = a.var_id AND t.dst = b.var_id
), e1 AS (
  SELECT model_id, src, dst, round(0.06 * (x - avg(x) OVER m) / greatest(stddev_pop(x) OVER m, 1e-9), 6) AS theta FROM e0 WINDOW m AS (PARTITION BY model_id)
), edges AS (SELECT * FROM e1 WHERE theta <> 0),
tot AS (
  SELECT v AS var_id, sum(pairs) AS t FROM (SELECT src AS v, pairs FROM trade UNION ALL SELECT dst, pairs FROM trade) GROUP BY 1
), n0 AS (
  SELECT model_id, nodes.var_id, ln(coalesce(t, 0) + 1.0) AS x FROM nodes LEFT JOIN tot USING (var_id)
), params AS (
  SELECT model_id, var_id, round(0.2 * (x - avg(x) OVER m) / greatest(stddev_pop(x) OVER m, 1e-9), 6) AS theta FROM n0 WINDOW m AS (PARTITION BY model_id)
), pos AS (
  SELECT model_id, var_id, row_number() OVER (PARTITION BY model_id ORDER BY var_id) - 1 AS pos FROM nodes
), parts AS (
  SELECT partition, model_id, var_id, (CASE partition WHEN 'pair' THEN pos // 2 WHEN 'half' THEN pos // 4 WHEN 'stride' THEN pos % 2 WHEN 'single' THEN pos ELSE 0 END)::INT AS cluster
  FROM pos, (VALUES ('pair'), ('half'), ('stride'), ('single'), ('whole')) v(partition)
), asg AS (SELECT model_id, var_id, cluster FROM parts WHERE partition = 'pair')"""
)

CROSS = """, crossing AS (
  SELECT e.model_id, e.src, e.dst, e.theta, a.cluster AS c_src, b.cluster AS c_dst
  FROM edges e JOIN asg a ON a.model_id = e.model_id AND a.var_id = e.src JOIN asg b ON b.model_id = e.model_id AND b.var_id = e.dst)"""

#: Exact inference: all joint states of each model, whose bit i is the variable at place i.
EXACT = """, sz AS (SELECT model_id, count(*) AS n FROM nodes GROUP BY 1
), st AS (SELECT model_id, unnest(range(1 << n)) AS s FROM sz
), sv AS (SELECT st.model_id, s, var_id, 2.0 * ((s >> pos) & 1) - 1 AS v FROM st JOIN pos USING (model_id)
), ew AS (
  SELECT model_id, s, sum(e) AS e FROM (
    SELECT sv.model_id, s, theta * v AS e FROM sv JOIN params USING (model_id, var_id)
    UNION ALL
    SELECT a.model_id, a.s, theta * a.v * b.v FROM edges e JOIN sv a ON a.model_id = e.model_id AND a.var_id = e.src
      JOIN sv b ON b.model_id = e.model_id AND b.var_id = e.dst AND b.s = a.s) GROUP BY 1, 2
), lz AS (SELECT model_id, ln(sum(exp(e))) AS log_z FROM ew GROUP BY 1
), em AS (SELECT sv.model_id, var_id, sum(CASE WHEN v > 0 THEN exp(e) ELSE 0 END) / sum(exp(e)) AS prob FROM sv JOIN ew USING (model_id, s) GROUP BY 1, 2)"""


def mean_field_sql(assignments: str, rounds: int = 60) -> str:
    """Synchronous block updates by recursion over (grp, model, var), from a relation with (grp, model_id, var_id, cluster)."""
    return f""", ga AS ({assignments}
), gp AS (
  SELECT grp, model_id, var_id, cluster, row_number() OVER (PARTITION BY grp, model_id, cluster ORDER BY var_id) - 1 AS p FROM ga
), gs AS (
  SELECT grp, model_id, cluster, unnest(range(1 << count(*))) AS s FROM gp GROUP BY grp, model_id, cluster
), gv AS (
  SELECT gs.grp, gs.model_id, gs.cluster, s, var_id, 2.0 * ((s >> p) & 1) - 1 AS v FROM gs JOIN gp USING (grp, model_id, cluster)
), ge AS (
  SELECT a.grp, e.model_id, e.src, e.dst, e.theta, a.cluster AS c1, b.cluster AS c2
  FROM edges e JOIN ga a ON a.model_id = e.model_id AND a.var_id = e.src JOIN ga b ON b.grp = a.grp AND b.model_id = e.model_id AND b.var_id = e.dst
), gi AS (
  SELECT grp, model_id, cluster, s, sum(e) AS inner_e FROM (
    SELECT gv.grp, gv.model_id, cluster, s, theta * v AS e FROM gv JOIN params USING (model_id, var_id)
    UNION ALL
    SELECT a.grp, a.model_id, a.cluster, a.s, theta * a.v * b.v FROM ge
      JOIN gv a ON a.grp = ge.grp AND a.model_id = ge.model_id AND a.var_id = ge.src
      JOIN gv b ON b.grp = ge.grp AND b.model_id = ge.model_id AND b.var_id = ge.dst AND b.s = a.s AND b.cluster = a.cluster
    WHERE c1 = c2) GROUP BY ALL
), gx AS (
  SELECT grp, model_id, src AS i, dst AS j, theta FROM ge WHERE c1 <> c2 UNION ALL SELECT grp, model_id, dst, src, theta FROM ge WHERE c1 <> c2
), mf AS (
  SELECT 0 AS it, grp, model_id, var_id, 0.0::DOUBLE AS mean FROM ga
  UNION ALL
  SELECT it, grp, model_id, var_id, sum(w * v) / sum(w) FROM (
    SELECT f.it, gv.grp, gv.model_id, gv.cluster, gv.s, exp(any_value(inner_e) + sum(field * v)) AS w
    FROM (
      SELECT m.it + 1 AS it, ga.grp, ga.model_id, ga.var_id, sum(CASE WHEN gx.j = m.var_id THEN gx.theta * m.mean ELSE 0 END) AS field
      FROM ga LEFT JOIN gx ON gx.grp = ga.grp AND gx.model_id = ga.model_id AND gx.i = ga.var_id
      JOIN mf m ON m.grp = ga.grp AND m.model_id = ga.model_id AND m.var_id = coalesce(gx.j, ga.var_id)
      WHERE m.it < {rounds} GROUP BY ALL) f
    JOIN gv ON gv.grp = f.grp AND gv.model_id = f.model_id AND gv.var_id = f.var_id
    JOIN gi ON gi.grp = gv.grp AND gi.model_id = gv.model_id AND gi.cluster = gv.cluster AND gi.s = gv.s
    GROUP BY f.it, gv.grp, gv.model_id, gv.cluster, gv.s) JOIN gv USING (grp, model_id, cluster, s)
  GROUP BY it, grp, model_id, var_id
), fin AS (SELECT grp, model_id, var_id, mean FROM mf WHERE it = {rounds}
), ff AS (
  SELECT ga.grp, ga.model_id, ga.var_id, coalesce(sum(theta * mean), 0) AS field
  FROM ga LEFT JOIN (SELECT gx.grp, gx.model_id, gx.i, gx.theta, fin.mean FROM gx JOIN fin ON fin.grp = gx.grp AND fin.model_id = gx.model_id AND fin.var_id = gx.j) x
    ON x.grp = ga.grp AND x.model_id = ga.model_id AND x.i = ga.var_id GROUP BY ALL
), fw AS (
  SELECT gv.grp, gv.model_id, gv.cluster, gv.s, any_value(inner_e) AS inner_e, exp(any_value(inner_e) + sum(field * v)) AS w
  FROM ff JOIN gv USING (grp, model_id, var_id) JOIN gi USING (grp, model_id, cluster, s) GROUP BY gv.grp, gv.model_id, gv.cluster, gv.s
), fq AS (SELECT grp, model_id, cluster, s, inner_e, w / sum(w) OVER (PARTITION BY grp, model_id, cluster) AS q FROM fw
), fb AS (
  SELECT grp, model_id, sum(x) AS bound FROM (
    SELECT grp, model_id, q * inner_e - q * ln(q) AS x FROM fq
    UNION ALL
    SELECT ge.grp, ge.model_id, theta * a.mean * b.mean FROM ge
      JOIN fin a ON a.grp = ge.grp AND a.model_id = ge.model_id AND a.var_id = ge.src
      JOIN fin b ON b.grp = ge.grp AND b.model_id = ge.model_id AND b.var_id = ge.dst WHERE c1 <> c2) GROUP BY 1, 2)"""


PAIR_GROUP = "SELECT 'pair' AS grp, model_id, var_id, cluster FROM asg"
SINGLE_GROUP = "SELECT 'single' AS grp, model_id, var_id, cluster FROM parts WHERE partition = 'single'"
ALL_GROUPS = "SELECT partition AS grp, model_id, var_id, cluster FROM parts"


def models(spark: SparkSession, sf_dir: str):
    """The oracle models, their default clusters."""
    m = W.nation_models(spark, sf_dir)
    return m, W.fixed_partition(m.node_params, "pair")


# --- graphs -------------------------------------------------------------------------------------------------------------------


@query("trade_graph", f"WITH {TRADE} SELECT src, dst, pairs, round(revenue, 4) AS revenue FROM trade")
def trade_graph(spark, d):
    return W.trade_graph(spark, d).withColumn("revenue", F.round("revenue", 4))


@query("trade_graph_threshold", f"""WITH {TRADE}, t AS (SELECT * FROM trade WHERE src < 24 AND dst < 24), c AS (
  SELECT 0.7::DOUBLE AS q, quantile_cont(pairs, 0.7) AS least FROM t UNION ALL SELECT 0.5, quantile_cont(pairs, 0.5) FROM t)
SELECT q, src, dst FROM t JOIN c ON pairs >= least""")  # fmt: skip
def trade_graph_threshold(spark, d):
    return W.trade_threshold(spark, d)


_PAIRS = """SELECT a.k AS src, b.k AS dst, count(*) AS n FROM (SELECT DISTINCT l_orderkey AS o, {c} AS k FROM lineitem) a
JOIN (SELECT DISTINCT l_orderkey AS o, {c} AS k FROM lineitem) b ON a.o = b.o AND a.k < b.k GROUP BY 1, 2"""
query("copurchase_graph", _PAIRS.format(c="l_partkey"))(lambda spark, d: W.copurchase_graph(spark, d))
query("supplier_graph", _PAIRS.format(c="l_suppkey"))(lambda spark, d: W.copurchase_graph(spark, d, "l_suppkey"))

_DAYS = """d AS (SELECT user_id, ts::DATE AS day, {} FROM events GROUP BY 1, 2)""".format(
    ", ".join(f"max((event_type = '{t}')::INT) AS {t}" for t in ("click", "error", "purchase", "signup", "view"))
)
_TYPES = ("click", "error", "purchase", "signup", "view")
_TYPE_PAIRS = " UNION ALL ".join(f"SELECT user_id, '{a}' AS type_a, '{b}' AS type_b, {a} AS x, {b} AS y FROM d" for i, a in enumerate(_TYPES) for b in _TYPES[i + 1 :])


@query("event_pair_graph", f"""WITH {_DAYS}, p AS ({_TYPE_PAIRS}), g AS (
  SELECT type_a, type_b, count(*) FILTER (WHERE x = 1 AND y = 1) AS n11, count(*) FILTER (WHERE x = 1 AND y = 0) AS n10,
         count(*) FILTER (WHERE x = 0 AND y = 1) AS n01, count(*) FILTER (WHERE x = 0 AND y = 0) AS n00 FROM p GROUP BY 1, 2)
SELECT *, round(ln((n11 + 0.5) * (n00 + 0.5) / ((n10 + 0.5) * (n01 + 0.5))), 6) AS theta FROM g""")  # fmt: skip
def event_pair_graph(spark, d):
    return W.event_pair_graph(spark, d)


_SHINGLES = r"""w AS (
  SELECT doc_id, CASE WHEN regexp_matches(coalesce(text, ''), '[^\x20\x09-\x0D]') THEN regexp_extract_all(text, '[^\x20\x09-\x0D]+') ELSE []::VARCHAR[] END AS ws FROM documents
), s AS (
  SELECT doc_id, CASE WHEN len(ws) = 0 THEN []::VARCHAR[] WHEN len(ws) < 5 THEN [array_to_string(ws, chr(32))]
    ELSE list_distinct([array_to_string(ws[i:i+4], chr(32)) for i in range(1, len(ws) - 3)]) END AS s FROM w
), c AS (SELECT doc_id, s, min(doc_id) OVER (PARTITION BY list_sort(s)) AS class_id FROM s)"""


@query("near_copy_members", f"WITH {_SHINGLES} SELECT doc_id, class_id FROM c")
def near_copy_members(spark, d):
    from .similarity import similar_sets

    return similar_sets(W.table(spark, d, "documents")).members


@query("near_copy_graph", f"""WITH {_SHINGLES}, r AS (SELECT doc_id, len(s) AS n, unnest(s) AS h FROM c WHERE doc_id = class_id),
j AS (SELECT a.doc_id AS src, b.doc_id AS dst, count(*) AS common, any_value(a.n) AS n1, any_value(b.n) AS n2
  FROM r a JOIN r b ON a.h = b.h AND a.doc_id < b.doc_id GROUP BY 1, 2)
SELECT src, dst, round(common / (n1 + n2 - common), 6) AS jaccard FROM j WHERE common / (n1 + n2 - common) >= 0.8""")  # fmt: skip
def near_copy_graph(spark, d):
    return W.near_copy_graph(spark, d)


_U = "(concat('0x', substr(md5(concat_ws(':', {s}, trial, src, dst)), 1, 8))::UBIGINT::DOUBLE / 4294967296.0)"
_MEMBERS = "v AS (SELECT DISTINCT l_orderkey::BIGINT AS trial, l_suppkey::BIGINT AS var_id FROM lineitem)"
_RANDOM = f"""{_MEMBERS}, g AS (SELECT trial, src, dst FROM (SELECT a.trial, a.var_id AS src, b.var_id AS dst FROM v a JOIN v b ON a.trial = b.trial AND a.var_id < b.var_id)
  WHERE {_U.format(s=1)} < 0.3)"""


@query("random_graph_md5", f"WITH {_RANDOM} SELECT * FROM g")
def random_graph_md5(spark, d):
    return W.order_graphs(spark, d)


for _kind, _range in {"repulsive": "-1.0 + 1.0 * {u}", "mixed": "-1.0 + 2.0 * {u}", "attractive": "0.0 + 1.0 * {u}"}.items():
    query(f"random_params_{_kind}", f"WITH {_RANDOM} SELECT trial, src, dst, round({_range.format(u=_U.format(s=2))}, 6) AS theta FROM g")(lambda spark, d, k=_kind: W.couplings(W.order_graphs(spark, d), k, 1.0))


@query("random_singletons", f"""WITH {_MEMBERS}
SELECT trial, var_id, round(-1.0 + 2.0 * (concat('0x', substr(md5(concat_ws(':', 3, trial, var_id)), 1, 8))::UBIGINT::DOUBLE / 4294967296.0), 6) AS theta FROM v""")  # fmt: skip
def random_singletons(spark, d):
    from ..hashing import uniform

    return W.order_members(spark, d).select("trial", "var_id", F.round(F.lit(-1.0) + 2.0 * uniform(3, F.col("trial"), F.col("var_id")), 6).alias("theta"))


@query("fold_signs", f"WITH {MODELS} SELECT model_id, src, dst, abs(theta) AS abs_theta, sign(theta)::INT AS sgn FROM edges")
def folded(spark, d):
    return fold_signs(models(spark, d)[0].edges)


def _energies(spark, d) -> DataFrame:
    """model_id, state_id, energy of every joint state of every model."""
    from ..model import energy

    m = models(spark, d)[0]
    place = W.positions(m.node_params)
    size = place.groupBy("model_id").agg(F.count(F.lit(1)).alias("n"))
    states = size.select("model_id", F.explode(F.expr("sequence(0L, cast(pow(2, n) as bigint) - 1)")).alias("state_id"))
    rows = states.join(place, "model_id").select("model_id", "state_id", "var_id", (2 * F.expr("shiftright(state_id, cast(pos as int)) & 1") - 1).cast("double").alias("value"))
    return rounded(energy(rows, m), "energy")


@query("model_energy", f"WITH {MODELS}{EXACT} SELECT model_id, s AS state_id, round(e, 6) AS energy FROM ew WHERE s % 7 = 3")
def model_energy(spark, d):
    """The states whose number is 3 modulo 7, as its SQL; ``model_energy_all`` has all of them."""
    return _energies(spark, d).where("state_id % 7 = 3")


query("model_energy_all", f"WITH {MODELS}{EXACT} SELECT model_id, s AS state_id, round(e, 6) AS energy FROM ew")(_energies)


_WEIGHT = {"unit": "1.0::DOUBLE", "coupling": "abs(theta)", "inverse": "1.0 / greatest(abs(theta), 1e-6)"}
for _kind, _expr in _WEIGHT.items():
    query(f"affinity_{_kind}", f"WITH {MODELS} SELECT model_id, src, dst, round({_expr}, 6) AS weight FROM edges")(lambda spark, d, k=_kind: rounded(G.affinity(models(spark, d)[0].edges, k), "weight"))


@query("large_light_affinity", f"""WITH {MODELS}, c AS (SELECT model_id, quantile_cont(abs(theta), 0.5) AS cut, max(abs(theta)) AS top FROM edges GROUP BY 1)
SELECT model_id, src, dst, round(CASE WHEN abs(theta) <= cut THEN 1.0 ELSE -abs(theta) / top END, 6) AS weight FROM edges JOIN c USING (model_id)""")  # fmt: skip
def large_light(spark, d):
    return rounded(G.affinity(models(spark, d)[0].edges, "large_light"), "weight")


_BOTH = """, both_ways AS (SELECT model_id, src AS i, dst AS j, abs(theta) AS w FROM edges UNION ALL SELECT model_id, dst, src, abs(theta) FROM edges),
deg AS (SELECT n.model_id, n.var_id AS i, coalesce(sum(w), 0) AS d FROM nodes n LEFT JOIN both_ways b ON b.model_id = n.model_id AND b.i = n.var_id GROUP BY 1, 2)"""


@query("degrees", f"WITH {MODELS}{_BOTH} SELECT model_id, i, round(d, 6) AS d FROM deg")
def degrees(spark, d):
    m = models(spark, d)[0]
    return rounded(G.degrees(m.node_params, G.affinity(m.edges)), "d")


@query("laplacian", f"WITH {MODELS}{_BOTH} SELECT model_id, i, i AS j, round(d, 6) AS l FROM deg UNION ALL SELECT model_id, i, j, round(-w, 6) FROM both_ways")
def laplacian(spark, d):
    m = models(spark, d)[0]
    return rounded(G.laplacian(m.node_params, G.affinity(m.edges)), "l")


@query("affinity_matrix", f"WITH {MODELS}{_BOTH} SELECT model_id, i, j, round(w, 6) AS a FROM both_ways")
def affinity_matrix(spark, d):
    return rounded(G.affinity_matrix(G.affinity(models(spark, d)[0].edges)), "a")


_CUT = f"WITH {MODELS}{CROSS} SELECT model_id, round(sum(CASE WHEN c_src <> c_dst THEN abs(theta) ELSE 0 END), 6) AS cut FROM crossing GROUP BY 1"
query("cut_weight_edges", _CUT)(lambda spark, d: (lambda m, a: rounded(G.cut_weight(G.affinity(m.edges), a), "cut"))(*models(spark, d)))
query("cut_weight_trace", _CUT)(lambda spark, d: (lambda m, a: rounded(G.cut_weight(G.affinity(m.edges), a, "trace"), "cut"))(*models(spark, d)))


@query("cluster_border_weight", f"""WITH {MODELS}{CROSS}, b AS (
  SELECT model_id, c_src AS cluster, abs(theta) AS w FROM crossing WHERE c_src <> c_dst UNION ALL SELECT model_id, c_dst, abs(theta) FROM crossing WHERE c_src <> c_dst)
SELECT a.model_id, a.cluster, round(coalesce(sum(w), 0), 6) AS border FROM (SELECT DISTINCT model_id, cluster FROM asg) a LEFT JOIN b USING (model_id, cluster) GROUP BY 1, 2""")  # fmt: skip
def cluster_border_weight(spark, d):
    m, a = models(spark, d)
    return rounded(G.border_weight(G.affinity(m.edges), a), "border")


@query("maxcut_identity", f"""WITH {MODELS}{CROSS} SELECT model_id, round(2 * sum(CASE WHEN c_src <> c_dst THEN abs(theta) ELSE 0 END), 6) AS lhs,
  round(2 * sum(abs(theta)) - 2 * sum(CASE WHEN c_src = c_dst THEN abs(theta) ELSE 0 END), 6) AS rhs FROM crossing GROUP BY 1""")  # fmt: skip
def maxcut_identity(spark, d):
    m, a = models(spark, d)
    return rounded(G.max_cut_identity(m.node_params, G.affinity(m.edges), a), "lhs", "rhs")


BY_SCHEME = " UNION ALL ".join(f"SELECT '{k}' AS affinity, model_id, src, dst, {e} AS w FROM edges" for k, e in _WEIGHT.items())


@query("cut_by_scheme", f"""WITH {MODELS}, aw AS ({BY_SCHEME})
SELECT affinity, a.partition, round(sum(CASE WHEN a.cluster <> b.cluster THEN w ELSE 0 END), 6) AS cut
FROM aw JOIN parts a ON a.model_id = aw.model_id AND a.var_id = aw.src JOIN parts b ON b.model_id = aw.model_id AND b.var_id = aw.dst AND b.partition = a.partition
WHERE aw.model_id = 100 GROUP BY 1, 2""")  # fmt: skip
def cut_by_scheme(spark, d):
    m = models(spark, d)[0]
    edges = m.edges.where("model_id = 100")
    weighted = None
    for kind in _WEIGHT:
        w = G.affinity(edges, kind).withColumn("affinity", F.lit(kind))
        weighted = w if weighted is None else weighted.unionByName(w)
    parts = W.fixed_partitions(m.node_params)
    a = parts.select("partition", "model_id", F.col("var_id").alias("src"), F.col("cluster").alias("c1"))
    b = parts.select("partition", "model_id", F.col("var_id").alias("dst"), F.col("cluster").alias("c2"))
    j = weighted.join(a, ["model_id", "src"]).join(b, ["partition", "model_id", "dst"])
    return rounded(j.groupBy("affinity", "partition").agg(F.sum(F.when(F.col("c1") != F.col("c2"), F.col("weight")).otherwise(0.0)).alias("cut")), "cut")


@query("equipartition_check", f"""WITH {MODELS}, z AS (SELECT partition, model_id, cluster, count(*) AS m FROM parts GROUP BY ALL), y AS (
  SELECT partition, model_id, sum(m) OVER w AS n, m, count(*) OVER w AS k FROM z WINDOW w AS (PARTITION BY partition, model_id))
SELECT partition, model_id, n_bad = 0 AS ok, n_bad FROM (
  SELECT partition, model_id, (count(*) FILTER (WHERE m < floor(n / 2) OR m > ceil(n / 2)) + abs(any_value(k) - 2))::BIGINT AS n_bad FROM y GROUP BY 1, 2)""")  # fmt: skip
def equipartition_check(spark, d):
    m = models(spark, d)[0]
    out = None
    for name in W.PARTITIONS:
        c = G.check_equipartition(m.node_params, W.fixed_partition(m.node_params, name), 2).select(F.lit(name).alias("partition"), "model_id", "ok", "n_bad")
        out = c if out is None else out.unionByName(c)
    return out


@query("random_partition", f"""WITH {MODELS} SELECT model_id, var_id, ((row_number() OVER (PARTITION BY model_id
  ORDER BY concat('0x', substr(md5(concat_ws(':', 1, model_id, var_id)), 1, 8))::UBIGINT, var_id) - 1) % 3)::INT AS cluster FROM nodes""")  # fmt: skip
def random_partition(spark, d):
    return G.random_partition(models(spark, d)[0].node_params, 3)


@query("region_partition", "SELECT 0::BIGINT AS model_id, n_nationkey::BIGINT AS var_id, n_regionkey::INT AS cluster FROM nation")
def region_partition(spark, d):
    n = W.table(spark, d, "nation").select(F.lit(0).cast("long").alias("model_id"), F.col("n_nationkey").cast("long").alias("var_id"), "n_regionkey")
    return G.partition_by_column(n, "n_regionkey")


_BRUTE = """WITH RECURSIVE {models}, grow AS (
  SELECT {k} AS k, 1 AS n, [0] AS labels UNION ALL
  SELECT k, n + 1, list_append(labels, c) FROM grow, range({k}) r(c)
  WHERE n < 8 AND c <= list_max(labels) + 1 AND len(list_filter(labels, lambda x: x = c)) < 8 / {k}
), aw AS ({schemes}), sc AS (
  SELECT affinity, k, array_to_string(labels, '') AS labels, round(sum(CASE WHEN labels[p.pos + 1] <> labels[r.pos + 1] THEN w ELSE 0 END), 6) AS cut
  FROM grow, aw JOIN pos p ON p.model_id = aw.model_id AND p.var_id = aw.src JOIN pos r ON r.model_id = aw.model_id AND r.var_id = aw.dst
  WHERE n = 8 AND aw.model_id = 100 GROUP BY 1, 2, 3)
SELECT affinity, k, cut, labels FROM (SELECT *, row_number() OVER (PARTITION BY affinity, k ORDER BY {order}cut, labels) AS i FROM sc) WHERE i = 1"""


def _brute(spark, d, sense: str) -> DataFrame:
    m = models(spark, d)[0]
    nodes, edges = m.node_params.where("model_id = 100"), m.edges.where("model_id = 100")
    out = None
    for kind in _WEIGHT:
        for k in (2, 4):
            b = P.brute_cut(nodes, G.affinity(edges, kind), k, sense).select(F.lit(kind).alias("affinity"), F.lit(k).alias("k"), "cut", "labels")
            out = b if out is None else out.unionByName(b)
    return out


for _sense, _order in (("min", ""), ("max", "-")):
    _one = [_BRUTE.format(models=MODELS, k=k, schemes=BY_SCHEME, order=_order) for k in (2, 4)]
    query(f"equi_{_sense}cut_brute", f"SELECT * FROM ({_one[0]}) UNION ALL SELECT * FROM ({_one[1]})")(lambda spark, d, s=_sense: _brute(spark, d, s))

# --- structure and bounds -------------------------------------------------------------------------------------------------------


@query("classify_cliques", f"WITH {MODELS}{CROSS} SELECT model_id, src, dst, 1 + (c_src <> c_dst)::INT AS k_beta, c_src <> c_dst AS is_border FROM crossing")
def classify(spark, d):
    m, a = models(spark, d)
    c = S.classify_cliques(m.cliques(), a)
    return c.select("model_id", F.get("members", F.lit(0)).alias("src"), F.get("members", F.lit(1)).alias("dst"), "k_beta", "is_border")


@query("markov_blanket", f"""WITH {MODELS}{CROSS} SELECT DISTINCT model_id, cluster, blanket_var, blanket_cluster FROM (
  SELECT model_id, c_src AS cluster, dst AS blanket_var, c_dst AS blanket_cluster FROM crossing WHERE c_src <> c_dst
  UNION ALL SELECT model_id, c_dst, src, c_src FROM crossing WHERE c_src <> c_dst)""")  # fmt: skip
def blanket(spark, d):
    m, a = models(spark, d)
    return S.markov_blanket(m.cliques(), a)


@query("broken_weight", f"WITH {MODELS}{CROSS} SELECT model_id, round(sum(CASE WHEN c_src <> c_dst THEN abs(theta) ELSE 0 END), 6) AS w FROM crossing GROUP BY 1")
def broken(spark, d):
    m, a = models(spark, d)
    return rounded(S.broken_weight(m.edges, a), "w")


_FIELD = """, x AS (SELECT model_id, src AS i, dst AS j, theta FROM crossing WHERE c_src <> c_dst UNION ALL SELECT model_id, dst, src, theta FROM crossing WHERE c_src <> c_dst)"""


@query("mean_messages", f"""WITH {MODELS}{CROSS}{_FIELD} SELECT model_id, i AS var_id, round(sum(theta * CASE WHEN j % 3 = 0 THEN 0.5371 ELSE -0.2593 END), 6) AS field FROM x GROUP BY 1, 2""")
def messages(spark, d):
    m, a = models(spark, d)
    means = m.node_params.select("model_id", "var_id", F.when(F.col("var_id") % 3 == 0, 0.5371).otherwise(-0.2593).alias("mean"))
    return rounded(S.mean_messages(m.edges, means, a), "field")


@query("cluster_conditional", f"""WITH {MODELS}{CROSS}{_FIELD}, f AS (SELECT model_id, i AS var_id, sum(theta * CASE WHEN j % 2 = 0 THEN 1.0 ELSE -1.0 END) AS field FROM x GROUP BY 1, 2),
p AS (SELECT model_id, var_id, cluster, row_number() OVER (PARTITION BY model_id, cluster ORDER BY var_id) - 1 AS p FROM asg),
s AS (SELECT model_id, cluster, unnest(range(1 << count(*))) AS state FROM p GROUP BY 1, 2),
v AS (SELECT s.model_id, s.cluster, state, var_id, 2.0 * ((state >> p) & 1) - 1 AS v FROM s JOIN p USING (model_id, cluster)),
e AS (SELECT model_id, cluster, state, exp(sum(e)) AS w FROM (
  SELECT v.model_id, cluster, state, v * (theta + coalesce(field, 0)) AS e FROM v JOIN params USING (model_id, var_id) LEFT JOIN f USING (model_id, var_id)
  UNION ALL SELECT a.model_id, a.cluster, a.state, theta * a.v * b.v FROM crossing c JOIN v a ON a.model_id = c.model_id AND a.var_id = c.src
    JOIN v b ON b.model_id = c.model_id AND b.var_id = c.dst AND b.cluster = a.cluster AND b.state = a.state) GROUP BY 1, 2, 3)
SELECT model_id, cluster, state, round(w / sum(w) OVER (PARTITION BY model_id, cluster), 6) AS prob FROM e""")  # fmt: skip
def conditional(spark, d):
    m, a = models(spark, d)
    evidence = m.node_params.select("model_id", "var_id", F.when(F.col("var_id") % 2 == 0, 1.0).otherwise(-1.0).alias("mean"))
    return rounded(S.cluster_conditional(m, a, evidence), "prob")


@query("kl_bounds", f"""WITH {MODELS}{CROSS} SELECT model_id, -1.0::DOUBLE AS a_phi, 1.0::DOUBLE AS b_phi, -3.0::DOUBLE AS a_z, 3.0::DOUBLE AS b_z, 0.0::DOUBLE AS a, 4.0::DOUBLE AS b,
  round(sum(abs(theta)), 6) AS w FROM crossing WHERE c_src <> c_dst GROUP BY 1""")  # fmt: skip
def kl_bounds(spark, d):
    return rounded(S.kl_bounds(*models(spark, d)), "w")


@query("kl_bound_uniform", f"WITH {MODELS}{CROSS} SELECT model_id, round(4 * sum(abs(theta)), 6) AS upper FROM crossing WHERE c_src <> c_dst GROUP BY 1")
def kl_uniform(spark, d):
    return rounded(S.kl_bound_uniform(*models(spark, d)), "upper")


@query("expected_weights", f"WITH {MODELS} SELECT model_id, src, dst, round(abs(theta * tanh(theta)), 6) AS weight FROM edges")
def expected(spark, d):
    return rounded(G.expected_weights(models(spark, d)[0].edges), "weight")


@query("inference_cost", f"""WITH {MODELS}, z AS (SELECT partition, model_id, cluster, count(*) AS m FROM parts GROUP BY ALL)
SELECT partition, sum(pow(2.0, m)) AS sum_states, max(pow(2.0, m)) AS max_states, round(max(m) / avg(m), 6) AS imbalance FROM z WHERE model_id = 100 GROUP BY 1""")  # fmt: skip
def cost(spark, d):
    m = models(spark, d)[0]
    out = None
    for name in W.PARTITIONS:
        a = W.fixed_partition(m.node_params, name).where("model_id = 100")
        c = G.inference_cost(a).select(F.lit(name).alias("partition"), "sum_states", "max_states", "imbalance")
        out = c if out is None else out.unionByName(c)
    return rounded(out, "imbalance")


# --- exact and mean field -------------------------------------------------------------------------------------------------------


@query("exact_logz", f"WITH {MODELS}{EXACT} SELECT model_id, round(log_z, 6) AS log_z FROM lz")
def exact_logz(spark, d):
    return rounded(I.exact_log_z(models(spark, d)[0]), "log_z")


@query("exact_logz_codegen", f"WITH {MODELS}{EXACT} SELECT lz.model_id, round(log_z, 6) AS log_z, var_id, round(prob, 6) AS prob FROM lz JOIN em USING (model_id) WHERE lz.model_id = 100")
def exact_codegen(spark, d):
    return rounded(I.exact_large(models(spark, d)[0], 100), "log_z", "prob")


@query("exact_marginals", f"WITH {MODELS}{EXACT} SELECT model_id, var_id, round(prob, 6) AS prob FROM em")
def exact_marginals(spark, d):
    return rounded(I.exact_marginals(models(spark, d)[0]), "prob")


@query("exact_pair_marginals", f"""WITH {MODELS}{EXACT} SELECT e.model_id, e.src, e.dst, round(sum(CASE WHEN a.v > 0 AND b.v > 0 THEN exp(e.e) ELSE 0 END) / sum(exp(e.e)), 6) AS p11
FROM (SELECT edges.*, ew.s, ew.e FROM edges JOIN ew USING (model_id)) e JOIN sv a ON a.model_id = e.model_id AND a.s = e.s AND a.var_id = e.src
JOIN sv b ON b.model_id = e.model_id AND b.s = e.s AND b.var_id = e.dst GROUP BY 1, 2, 3""")  # fmt: skip
def exact_pairs(spark, d):
    return rounded(I.exact_pair_marginals(models(spark, d)[0]), "p11")


def _run(spark, d, name: str, **options):
    m = models(spark, d)[0]
    return m, I.cluster_mean_field(m, W.fixed_partition(m.node_params, name), tol=1e-13, max_sweeps=500, **options)


for _name, _part, _options in (("naive_mf", "single", {}), ("cmf", "pair", {}), ("cmf_jacobi", "pair", {"schedule": "jacobi"}), ("cmf_sql", "pair", {"executor": "sql", "schedule": "jacobi", "max": 1e-9}), ("cmf_arrow_colour", "pair", {"executor": "arrow", "schedule": "colour", "max": 1e-9})):
    _group = SINGLE_GROUP if _part == "single" else PAIR_GROUP
    _o = dict(_options)
    _tol = _o.pop("max", 1e-13)

    def _marginals(spark, d, part=_part, o=_o, tol=_tol):
        m = models(spark, d)[0]
        return rounded(I.cluster_mean_field(m, W.fixed_partition(m.node_params, part), tol=tol, max_sweeps=500, **o).marginals.select("model_id", "var_id", "prob"), "prob")

    query(f"{_name}_marginals", f"WITH RECURSIVE {MODELS}{mean_field_sql(_group)} SELECT model_id, var_id, round((mean + 1) / 2, 6) AS prob FROM fin")(_marginals)


@query("naive_mf_bound", f"WITH RECURSIVE {MODELS}{mean_field_sql(SINGLE_GROUP)} SELECT model_id, round(bound, 6) AS bound FROM fb")
def naive_bound(spark, d):
    return rounded(_run(spark, d, "single")[1].diagnostics.select("model_id", "bound"), "bound")


@query("cmf_cluster_tables", f"WITH RECURSIVE {MODELS}{mean_field_sql(PAIR_GROUP)} SELECT model_id, cluster, s AS state, round(q, 6) AS q FROM fq")
def cmf_tables(spark, d):
    return rounded(_run(spark, d, "pair")[1].tables, "q")


@query("logz_bound", f"WITH RECURSIVE {MODELS}{mean_field_sql(PAIR_GROUP)} SELECT model_id, round(bound, 6) AS bound FROM fb")
def logz_bound(spark, d):
    return rounded(_run(spark, d, "pair")[1].diagnostics.select("model_id", "bound"), "bound")


@query("kl_divergence", f"WITH RECURSIVE {MODELS}{EXACT}{mean_field_sql(PAIR_GROUP)} SELECT model_id, round(log_z - bound, 6) AS kl FROM fb JOIN lz USING (model_id)")
def kl(spark, d):
    m, r = _run(spark, d, "pair")
    return rounded(I.kl_divergence(r.diagnostics, I.exact_log_z(m)), "kl")


@query("bound_ratio", f"WITH RECURSIVE {MODELS}{EXACT}{mean_field_sql(PAIR_GROUP)} SELECT model_id, round(bound / log_z, 6) AS ratio, round(log_z - bound, 6) AS gap FROM fb JOIN lz USING (model_id)")
def ratio(spark, d):
    m, r = _run(spark, d, "pair")
    return rounded(I.bound_ratio(r.diagnostics, I.exact_log_z(m)), "ratio", "gap")


@query("l1_error", f"""WITH RECURSIVE {MODELS}{EXACT}{mean_field_sql(PAIR_GROUP)} SELECT model_id, round(avg(abs((mean + 1) / 2 - prob)), 6) AS l1 FROM fin JOIN em USING (model_id, var_id) GROUP BY 1""")
def l1(spark, d):
    m, r = _run(spark, d, "pair")
    return rounded(I.l1_error(r.marginals, I.exact_marginals(m)), "l1")


@query("scheme_rank", f"""WITH RECURSIVE {MODELS}{EXACT}{mean_field_sql(ALL_GROUPS)}, l AS (
  SELECT grp AS partition, model_id, round(avg(abs((mean + 1) / 2 - prob)), 6) AS l1 FROM fin JOIN em USING (model_id, var_id) GROUP BY 1, 2)
SELECT partition, model_id, l1, rank() OVER (PARTITION BY model_id ORDER BY l1)::INT AS rnk FROM l""")  # fmt: skip
def scheme_rank(spark, d):
    from pyspark.sql import Window

    m = models(spark, d)[0]
    truth = I.exact_marginals(m)
    out = None
    for name in W.PARTITIONS:
        r = I.cluster_mean_field(m, W.fixed_partition(m.node_params, name), tol=1e-13, max_sweeps=500)
        e = rounded(I.l1_error(r.marginals, truth), "l1").select(F.lit(name).alias("partition"), "model_id", "l1")
        out = e if out is None else out.unionByName(e)
    return out.withColumn("rnk", F.rank().over(Window.partitionBy("model_id").orderBy("l1")))


@query("cluster_tree", f"""WITH RECURSIVE {MODELS}{CROSS}, ce AS (
  SELECT model_id, least(c_src, c_dst) AS a, greatest(c_src, c_dst) AS b, src, dst, theta,
         row_number() OVER (PARTITION BY model_id ORDER BY abs(theta) DESC, src, dst) AS i FROM crossing WHERE c_src <> c_dst
), walk AS (
  SELECT model_id, 0::BIGINT AS i, NULL::BIGINT AS taken, map_from_entries(list((cluster, cluster))) AS root FROM (SELECT DISTINCT model_id, cluster FROM asg) GROUP BY 1
  UNION ALL
  SELECT w.model_id, e.i, CASE WHEN w.root[e.a] <> w.root[e.b] THEN e.i END,
    map_from_entries([(x.key, CASE WHEN x.value = greatest(w.root[e.a], w.root[e.b]) THEN least(w.root[e.a], w.root[e.b]) ELSE x.value END) for x in map_entries(w.root)])
  FROM walk w JOIN ce e ON e.model_id = w.model_id AND e.i = w.i + 1)
SELECT ce.model_id, a AS cluster_a, b AS cluster_b, src, dst, theta FROM walk JOIN ce ON ce.model_id = walk.model_id AND ce.i = walk.taken""")  # fmt: skip
def cluster_tree(spark, d):
    from ..operators.scale import spanning_forest

    m, a = models(spark, d)
    return spanning_forest(m.edges, a)


