"""Registered queries on operators around the methods: JSON, set operations, anti joins, sampling, top-k, sketches."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..hashing import uniform
from ..operators import graph as G
from ..sources import workloads as W
from .queries_core import MODELS, TRADE, models, query, rounded

_CROSSING = "SELECT a.partition, e.model_id, e.src, e.dst FROM edges e JOIN parts a ON a.model_id = e.model_id AND a.var_id = e.src JOIN parts b ON b.model_id = e.model_id AND b.var_id = e.dst AND b.partition = a.partition WHERE a.cluster <> b.cluster"


def _border(m, name: str):
    return G.ends(m.edges, W.fixed_partition(m.node_params, name)).where("c_src <> c_dst").select("model_id", "src", "dst")


@query("borders_intersect", f"WITH {MODELS}, x AS ({_CROSSING}) SELECT model_id, src, dst FROM x WHERE partition = 'pair' INTERSECT SELECT model_id, src, dst FROM x WHERE partition = 'stride'")
def borders_intersect(spark, d):
    m = models(spark, d)[0]
    return _border(m, "pair").intersect(_border(m, "stride"))


@query("borders_except", f"WITH {MODELS}, x AS ({_CROSSING}) SELECT model_id, src, dst FROM x WHERE partition = 'pair' EXCEPT SELECT model_id, src, dst FROM x WHERE partition = 'half'")
def borders_except(spark, d):
    m = models(spark, d)[0]
    return _border(m, "pair").exceptAll(_border(m, "half"))


@query("event_props", """SELECT event_type, count(*) AS n, sum((props->>'k')::BIGINT)::BIGINT AS total, max((props->>'k')::BIGINT) AS top FROM events GROUP BY 1""")
def event_props(spark, d):
    k = F.from_json("props", "k long")["k"]
    return W.table(spark, d, "events").groupBy("event_type").agg(F.count(F.lit(1)).alias("n"), F.sum(k).alias("total"), F.max(k).alias("top"))


@query("unlabelled_documents", "SELECT lang, count(*) AS n FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels WHERE doc_id IS NOT NULL) GROUP BY 1")
def unlabelled(spark, d):
    docs, labels = W.table(spark, d, "documents").select("doc_id", "lang"), W.table(spark, d, "labels").select("doc_id")
    return docs.join(labels, "doc_id", "left_anti").groupBy("lang").agg(F.count(F.lit(1)).alias("n"))


@query("trade_partners_top3", f"""WITH {TRADE}, b AS (SELECT src AS nation, dst AS partner, pairs FROM trade UNION ALL SELECT dst, src, pairs FROM trade)
SELECT nation, partner, pairs, r FROM (SELECT *, row_number() OVER (PARTITION BY nation ORDER BY pairs DESC, partner)::INT AS r FROM b) WHERE r <= 3""")  # fmt: skip
def top_partners(spark, d):
    t = W.trade_graph(spark, d)
    both = t.select(F.col("src").alias("nation"), F.col("dst").alias("partner"), "pairs").unionByName(t.select(F.col("dst").alias("nation"), F.col("src").alias("partner"), "pairs"))
    return both.withColumn("r", F.row_number().over(Window.partitionBy("nation").orderBy(F.desc("pairs"), "partner"))).where("r <= 3")


@query("trade_sparsified", f"""WITH {TRADE}, k AS (SELECT *, percent_rank() OVER (ORDER BY pairs) AS p FROM trade)
SELECT src, dst, pairs FROM k WHERE p >= 0.5 OR concat('0x', substr(md5(concat_ws(':', 9, src, dst)), 1, 8))::UBIGINT::DOUBLE / 4294967296.0 < p""")  # fmt: skip
def sparsified(spark, d):
    """Heavy half of the edges, light ones by a hash with the probability of their rank; the graph has at most 300 edges."""
    t = W.trade_graph(spark, d).withColumn("p", F.percent_rank().over(Window.orderBy("pairs")))
    return t.where((F.col("p") >= 0.5) | (uniform(9, F.col("src"), F.col("dst")) < F.col("p"))).select("src", "dst", "pairs")


@query("label_folds", """SELECT floor(5 * (concat('0x', substr(md5(concat_ws(':', 'fold', doc_id)), 1, 8))::UBIGINT::DOUBLE / 4294967296.0))::INT AS fold, quality, toxic, count(*) AS n FROM labels GROUP BY ALL""")
def label_folds(spark, d):
    fold = F.floor(5 * uniform(F.lit("fold"), F.col("doc_id"))).cast("int").alias("fold")
    return W.table(spark, d, "labels").groupBy(fold, "quality", "toxic").agg(F.count(F.lit(1)).alias("n"))


@query("nation_pivot", """WITH x AS (SELECT n_nationkey AS nation, o_orderstatus AS s, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY ALL)
SELECT nation, max(n) FILTER (WHERE s = 'F') AS F, max(n) FILTER (WHERE s = 'O') AS O, max(n) FILTER (WHERE s = 'P') AS P FROM x GROUP BY 1""")  # fmt: skip
def nation_pivot(spark, d):
    t = lambda n: W.table(spark, d, n)
    rows = t("orders").join(t("customer"), F.col("o_custkey") == F.col("c_custkey")).join(t("nation"), F.col("c_nationkey") == F.col("n_nationkey"))
    return rows.groupBy(F.col("n_nationkey").alias("nation")).pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1)))


@query("users_approx")
def users_approx(spark, d):
    """Distinct users per event type, exact and by sketch."""
    return W.table(spark, d, "events").groupBy("event_type").agg(F.count_distinct("user_id").alias("users"), F.approx_count_distinct("user_id", 0.01).alias("users_sketch"))


@query("affinity_function", f"WITH {MODELS} SELECT model_id, src, dst, round(sqrt(abs(theta)), 6) AS weight FROM edges")
def affinity_function(spark, d):
    return rounded(G.affinity(models(spark, d)[0].edges, lambda t: F.sqrt(F.abs(t))), "weight")


@query("expected_weights_bit", f"WITH {MODELS} SELECT model_id, src, dst, round(abs(theta * exp(theta) / (3 + exp(theta))), 6) AS weight FROM edges")
def expected_bit(spark, d):
    return rounded(G.expected_weights(models(spark, d)[0].edges, "bit"), "weight")
