"""Weighted graphs as edge relations: affinities, Laplacians, cuts, feasibility and plain partitions."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..hashing import uniform

#: The six schemes: which cut, over which affinity.
SCHEMES = {f"{sense}_{kind}": (sense, kind) for sense in ("min", "max") for kind in ("unit", "coupling", "inverse")}

#: Rows of a table of nodes, some numbers each, that a task may hold in a broadcast.
BROADCAST_NODES = 2_000_000


def few(df: DataFrame, rows: int) -> DataFrame:
    """``df`` to be broadcast where its rows, or a bound of them, are counted to be few, so that edges are not shuffled to meet it."""
    return F.broadcast(df) if rows <= BROADCAST_NODES else df


def affinity(edges: DataFrame, kind: str | Callable[[Column], Column] = "coupling", eps: float = 1e-6, light_quantile: float = 0.5) -> DataFrame:
    """model_id, src, dst, weight: ``unit`` 1, ``coupling`` |theta|, ``inverse`` 1/|theta|, ``large_light`` 1 for light edges
    (up to the quantile of |theta| in their model) and a penalty beyond it, or a function of theta."""
    size = F.abs("theta")
    if kind == "large_light":
        cut = edges.groupBy("model_id").agg(F.percentile(size, F.lit(light_quantile)).alias("cut"), F.max(size).alias("top"))
        weight = F.when(size <= F.col("cut"), F.lit(1.0)).otherwise(-size / F.col("top"))
        return edges.join(cut, "model_id").select("model_id", "src", "dst", weight.alias("weight"))
    weight = kind(F.col("theta")) if callable(kind) else {"unit": F.lit(1.0), "coupling": size, "inverse": 1.0 / F.greatest(size, F.lit(eps))}[kind]
    return edges.select("model_id", "src", "dst", weight.alias("weight"))


def both_ways(edges: DataFrame, value: str = "weight") -> DataFrame:
    """Each edge in both directions: model_id, i, j, and the value."""
    one = edges.select("model_id", F.col("src").alias("i"), F.col("dst").alias("j"), value)
    return one.unionByName(edges.select("model_id", F.col("dst").alias("i"), F.col("src").alias("j"), value))


def degrees(nodes: DataFrame, weighted: DataFrame) -> DataFrame:
    """model_id, i, d for every node, isolated ones with 0."""
    d = both_ways(weighted).groupBy("model_id", "i").agg(F.sum("weight").alias("d"))
    ids = nodes.select("model_id", F.col("var_id").alias("i"))
    return ids.join(d, ["model_id", "i"], "left").select("model_id", "i", F.coalesce("d", F.lit(0.0)).alias("d"))


def affinity_matrix(weighted: DataFrame) -> DataFrame:
    return both_ways(weighted).withColumnRenamed("weight", "a")


def laplacian(nodes: DataFrame, weighted: DataFrame) -> DataFrame:
    """model_id, i, j, l: degrees on the diagonal, minus the affinity off it."""
    diagonal = degrees(nodes, weighted).select("model_id", "i", F.col("i").alias("j"), F.col("d").alias("l"))
    return diagonal.unionByName(both_ways(weighted).select("model_id", "i", "j", (-F.col("weight")).alias("l")))


def ends(edges: DataFrame, assignment: DataFrame) -> DataFrame:
    """The edges with the clusters of their ends, c_src and c_dst."""
    a = assignment.select("model_id", F.col("var_id").alias("src"), F.col("cluster").alias("c_src"))
    b = assignment.select("model_id", F.col("var_id").alias("dst"), F.col("cluster").alias("c_dst"))
    return edges.join(a, ["model_id", "src"]).join(b, ["model_id", "dst"])


def cut_weight(weighted: DataFrame, assignment: DataFrame, form: str = "edges", nodes: DataFrame | None = None) -> DataFrame:
    """model_id, cut: sum of the crossing weights, or half the trace of the indicator's Laplacian form."""
    if form == "edges":
        crossing = F.when(F.col("c_src") != F.col("c_dst"), F.col("weight")).otherwise(0.0)
        return ends(weighted, assignment).groupBy("model_id").agg(F.sum(crossing).alias("cut"))
    return border_weight(weighted, assignment, nodes).groupBy("model_id").agg((F.sum("border") / 2).alias("cut"))


def border_weight(weighted: DataFrame, assignment: DataFrame, nodes: DataFrame | None = None) -> DataFrame:
    """model_id, cluster, border: the Laplacian form of each cluster's indicator, which is the weight on its border."""
    nodes = nodes if nodes is not None else assignment
    l = laplacian(nodes.select("model_id", "var_id").distinct(), weighted).withColumnsRenamed({"i": "src", "j": "dst"})
    return ends(l, assignment).where("c_src = c_dst").groupBy("model_id", F.col("c_src").alias("cluster")).agg(F.sum("l").alias("border"))


def max_cut_identity(nodes: DataFrame, weighted: DataFrame, assignment: DataFrame) -> DataFrame:
    """model_id, lhs, rhs: the trace of the Laplacian form, and total degree minus the trace of the affinity form."""
    lhs = border_weight(weighted, assignment, nodes).groupBy("model_id").agg(F.sum("border").alias("lhs"))
    inside = ends(weighted, assignment).groupBy("model_id").agg((2 * F.sum(F.when(F.col("c_src") == F.col("c_dst"), F.col("weight")).otherwise(0.0))).alias("inside"))
    total = degrees(nodes, weighted).groupBy("model_id").agg(F.sum("d").alias("total"))
    return lhs.join(inside, "model_id").join(total, "model_id").select("model_id", "lhs", (F.col("total") - F.col("inside")).alias("rhs"))


def check_equipartition(nodes: DataFrame, assignment: DataFrame, k: int) -> DataFrame:
    """model_id, ok, n_bad: nodes without exactly one cluster plus clusters whose size is not between floor and ceiling of n / k."""
    hits = nodes.select("model_id", "var_id").join(assignment.groupBy("model_id", "var_id").agg(F.count(F.lit(1)).alias("hits")), ["model_id", "var_id"], "left")
    per_model = hits.groupBy("model_id").agg(F.count(F.lit(1)).alias("n"), F.sum(F.when(F.coalesce("hits", F.lit(0)) == 1, 0).otherwise(1)).alias("bad_nodes"))
    sizes = assignment.groupBy("model_id", "cluster").agg(F.count(F.lit(1)).alias("m"))
    held = sizes.join(per_model, "model_id").groupBy("model_id", "n", "bad_nodes").agg(F.sum(F.when((F.col("m") >= F.floor(F.col("n") / k)) & (F.col("m") <= F.ceil(F.col("n") / k)), 0).otherwise(1)).alias("bad_clusters"), F.count(F.lit(1)).alias("clusters"))
    bad = F.col("bad_nodes") + F.col("bad_clusters") + F.abs(F.col("clusters") - k)
    return held.select("model_id", (bad == 0).alias("ok"), bad.cast("long").alias("n_bad"))


def random_partition(nodes: DataFrame, k: int, seed: int = 1, buckets: int = 64) -> DataFrame:
    """Balanced clusters in the order of a hash of (seed, model, node).

    The order is split into buckets of the hash; a rank is a bucket's offset plus the rank inside it, so no task sorts a whole model.
    """
    u = uniform(seed, F.col("model_id"), F.col("var_id"))
    rows = nodes.select("model_id", "var_id", u.alias("u")).withColumn("bucket", F.floor(F.col("u") * buckets).cast("int"))
    counts = rows.groupBy("model_id", "bucket").agg(F.count(F.lit(1)).alias("n"))
    before = Window.partitionBy("model_id").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.select("model_id", "bucket", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("offset"))
    inside = Window.partitionBy("model_id", "bucket").orderBy("u", "var_id")
    rank = F.col("offset") + F.row_number().over(inside) - 1
    return rows.join(offsets, ["model_id", "bucket"]).select("model_id", "var_id", F.pmod(rank, F.lit(k)).cast("int").alias("cluster"))


def partition_by_column(nodes: DataFrame, column: str) -> DataFrame:
    """Clusters given by hand."""
    return nodes.select("model_id", "var_id", F.col(column).cast("int").alias("cluster"))


def inference_cost(assignment: DataFrame, card: int = 2) -> DataFrame:
    """model_id, sum_states, max_states, imbalance: joint states over all clusters, in the largest, and largest over mean size."""
    sizes = assignment.groupBy("model_id", "cluster").agg(F.count(F.lit(1)).alias("m"))
    states = F.pow(F.lit(float(card)), F.col("m"))
    return sizes.groupBy("model_id").agg(F.sum(states).alias("sum_states"), F.max(states).alias("max_states"), (F.max("m") / F.avg("m")).alias("imbalance"))


def expected_weights(edges: DataFrame, domain: str = "spin", means: DataFrame | None = None) -> DataFrame:
    """Expected-potential weights: from the clique's own local marginal, or from current means (model_id, var_id, mean)."""
    t = F.col("theta")
    if means is None:
        local = F.tanh(t) if domain == "spin" else F.exp(t) / (3 + F.exp(t))
        return edges.select("model_id", "src", "dst", F.abs(t * local).alias("weight"))
    a = means.select("model_id", F.col("var_id").alias("src"), F.col("mean").alias("x"))
    b = means.select("model_id", F.col("var_id").alias("dst"), F.col("mean").alias("y"))
    return edges.join(a, ["model_id", "src"]).join(b, ["model_id", "dst"]).select("model_id", "src", "dst", F.abs(t * F.col("x") * F.col("y")).alias("weight"))
