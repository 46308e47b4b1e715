"""What a clustering does to the cliques of a model: borders, blankets, conditionals, averages and bounds."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..model import Model, TabularModel
from .graph import both_ways, ends


def classify_cliques(cliques: DataFrame, assignment: DataFrame) -> DataFrame:
    """The cliques with touched (cluster ids), k_beta (their number) and is_border."""
    seen = cliques.select("model_id", "clique_id", F.explode("members").alias("var_id")).join(assignment, ["model_id", "var_id"])
    touched = seen.groupBy("model_id", "clique_id").agg(F.array_sort(F.collect_set("cluster")).alias("touched"))
    out = cliques.join(touched, ["model_id", "clique_id"]).withColumn("k_beta", F.size("touched"))
    return out.withColumn("is_border", F.col("k_beta") > 1)


def markov_blanket(cliques: DataFrame, assignment: DataFrame) -> DataFrame:
    """model_id, cluster, blanket_var, blanket_cluster: the outside variables that share a clique with each cluster."""
    member = cliques.select("model_id", "clique_id", F.explode("members").alias("var_id")).join(assignment, ["model_id", "var_id"])
    other = member.select("model_id", "clique_id", F.col("var_id").alias("blanket_var"), F.col("cluster").alias("blanket_cluster"))
    pairs = member.select("model_id", "clique_id", "cluster").distinct().join(other, ["model_id", "clique_id"]).where("cluster <> blanket_cluster")
    return pairs.select("model_id", "cluster", "blanket_var", "blanket_cluster").distinct()


def broken_weight(edges: DataFrame, assignment: DataFrame) -> DataFrame:
    """model_id, w: absolute weight of the crossing potentials."""
    crossing = F.when(F.col("c_src") != F.col("c_dst"), F.abs("theta")).otherwise(0.0)
    return ends(edges, assignment).groupBy("model_id").agg(F.sum(crossing).alias("w"))


def mean_messages(edges: DataFrame, means: DataFrame, assignment: DataFrame) -> DataFrame:
    """model_id, var_id, field: what each node feels of the means across the border; no row for a node without a crossing edge."""
    crossing = ends(edges, assignment).where("c_src <> c_dst").select("model_id", "src", "dst", "theta")
    far = means.select("model_id", F.col("var_id").alias("j"), "mean")
    return both_ways(crossing, "theta").join(far, ["model_id", "j"]).groupBy("model_id", F.col("i").alias("var_id")).agg(F.sum(F.col("theta") * F.col("mean")).alias("field"))


def cluster_rows(model: Model, assignment: DataFrame, budget_states: int = 1 << 16) -> DataFrame:
    """One row per cluster: vars (array, ascending), inner (log-weight of each joint state, bit i for variable i).

    A cluster with more joint states than the budget is an error.
    """
    domain = model.domain
    order = Window.partitionBy("model_id", "cluster").orderBy("var_id")
    nodes = model.node_params.join(assignment, ["model_id", "var_id"]).withColumn("pos", F.row_number().over(order) - 1)
    per = nodes.groupBy("model_id", "cluster").agg(F.array_sort(F.collect_list(F.struct("pos", "var_id", "theta"))).alias("n"))
    a = nodes.select("model_id", F.col("var_id").alias("src"), F.col("cluster").alias("c1"), F.col("pos").alias("p"))
    b = nodes.select("model_id", F.col("var_id").alias("dst"), F.col("cluster").alias("c2"), F.col("pos").alias("r"))
    inside = model.edges.join(a, ["model_id", "src"]).join(b, ["model_id", "dst"]).where("c1 = c2")
    pairs = inside.groupBy("model_id", F.col("c1").alias("cluster")).agg(F.array_sort(F.collect_list(F.struct("p", "r", "theta"))).alias("e"))
    rows = per.join(pairs, ["model_id", "cluster"], "left")
    count = F.pow(F.lit(2.0), F.size("n"))
    states = F.when(count <= budget_states, F.sequence(F.lit(0).cast("long"), count.cast("long") - 1)).otherwise(F.raise_error(F.lit("a cluster has more joint states than the budget")))

    def value(s, i):
        bit = F.pmod(F.floor(s / F.pow(F.lit(2.0), i)), F.lit(2))
        return 2.0 * bit - 1.0 if domain == "spin" else bit.cast("double")

    def weight(s):
        own = F.aggregate("n", F.lit(0.0), lambda acc, x: acc + x["theta"] * value(s, x["pos"]))
        both = F.aggregate("e", F.lit(0.0), lambda acc, x: acc + x["theta"] * value(s, x["p"]) * value(s, x["r"]))
        return own + F.coalesce(both, F.lit(0.0))

    return rows.select("model_id", "cluster", F.transform("n", lambda x: x["var_id"]).alias("vars"), F.transform(states, weight).alias("inner"))


def cluster_conditional(model: Model, assignment: DataFrame, evidence: DataFrame, budget_states: int = 1 << 16) -> DataFrame:
    """model_id, cluster, state, prob: exact conditional of each cluster given the values (model_id, var_id, mean) outside it."""
    from .inference import tables

    field = mean_messages(model.edges, evidence, assignment)
    return tables(cluster_rows(model, assignment, budget_states), field, assignment, model.domain).select("model_id", "cluster", F.posexplode("q").alias("state", "prob")).withColumn("state", F.col("state").cast("long"))


def border_averages(model: TabularModel, assignment: DataFrame, tables: DataFrame) -> DataFrame:
    """model_id, clique_id, cluster, own (array of (var, state)), phi_avg: each border clique's potential averaged over the other clusters.

    ``tables`` has (model_id, cluster, assign: map var -> state, q).  The outside part of a clique inside one cluster is
    averaged under that cluster's joint table; parts in several clusters are independent.
    """
    border = classify_cliques(model.cliques, assignment).where("is_border").select("model_id", "clique_id", "members", "touched")
    rows = border.join(model.potential_rows, ["model_id", "clique_id"])
    cells = rows.select("model_id", "clique_id", "assignment", "phi", "touched", F.posexplode("members").alias("k", "var_id"))
    cells = cells.withColumn("s", F.get("assignment", F.col("k"))).join(assignment, ["model_id", "var_id"])
    part = cells.groupBy("model_id", "clique_id", "assignment", "phi", "cluster").agg(F.array_sort(F.collect_list(F.struct("var_id", "s"))).alias("part"))
    needed = part.select("model_id", "clique_id", "cluster", F.transform("part", lambda x: x["var_id"]).alias("vars")).distinct()
    joint = needed.join(tables, ["model_id", "cluster"])
    joint = joint.withColumn("part", F.transform("vars", lambda v: F.struct(v.alias("var_id"), F.element_at("assign", v).alias("s"))))
    joint = joint.groupBy("model_id", "clique_id", "cluster", "part").agg(F.sum("q").alias("p"))
    weighted = part.join(joint, ["model_id", "clique_id", "cluster", "part"]).select("model_id", "clique_id", "assignment", "phi", F.col("cluster").alias("other"), "p")
    own = part.select("model_id", "clique_id", "assignment", "cluster", F.col("part").alias("own"))
    crossed = own.join(weighted, ["model_id", "clique_id", "assignment"]).where("cluster <> other")
    product = crossed.groupBy("model_id", "clique_id", "cluster", "own", "assignment", "phi").agg(F.product("p").alias("p"))
    return product.groupBy("model_id", "clique_id", "cluster", "own").agg(F.sum(F.col("phi") * F.col("p")).alias("phi_avg"))


def kl_bounds(model: Model, assignment: DataFrame) -> DataFrame:
    """model_id, a_phi, b_phi, a_z, b_z, a, b, w: the constants of the divergence certificate and the broken weight.

    Signs are folded into the potentials, whose extremes follow from the domain; the lower constant is always 0.
    """
    crossing = ends(model.edges, assignment).where("c_src <> c_dst")
    if model.domain == "spin":
        low, high = F.lit(-1.0), F.lit(1.0)
    else:
        low, high = F.when(F.col("theta") > 0, 0.0).otherwise(-1.0), F.when(F.col("theta") > 0, 1.0).otherwise(0.0)
    k = F.lit(2.0)
    per = crossing.select("model_id", F.abs("theta").alias("t"), low.alias("lo"), high.alias("hi"))
    got = per.groupBy("model_id").agg(F.min((k - 1) * F.col("lo")).alias("a_phi"), F.max((k - 1) * F.col("hi")).alias("b_phi"), F.min(k * F.col("lo") - F.col("hi")).alias("a_z"), F.max(k * F.col("hi") - F.col("lo")).alias("b_z"), F.sum("t").alias("w"))
    return got.select("model_id", "a_phi", "b_phi", "a_z", "b_z", F.greatest(F.lit(0.0), F.col("a_phi") - F.col("b_z")).alias("a"), (F.col("b_phi") - F.col("a_z")).alias("b"), "w")


def kl_bound_uniform(model: Model, assignment: DataFrame) -> DataFrame:
    """model_id, upper: number of touched clusters times the potentials' spread times the broken weight."""
    b = kl_bounds(model, assignment)
    crossing = ends(model.edges, assignment).where("c_src <> c_dst")
    if model.domain == "spin":
        spread = crossing.groupBy("model_id").agg(F.lit(2.0).alias("spread"))
    else:
        high = F.max(F.when(F.col("theta") > 0, 1.0).otherwise(0.0))
        low = F.min(F.when(F.col("theta") > 0, 0.0).otherwise(-1.0))
        spread = crossing.groupBy("model_id").agg((high - low).alias("spread"))
    return b.join(spread, "model_id").select("model_id", (2 * F.col("spread") * F.col("w")).alias("upper"))
