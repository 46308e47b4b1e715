"""Discrete models as relations: pairwise binary models and models with tabular cliques."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .schema import require_schema


def level(state: Column, domain: str) -> Column:
    """Value of a binary variable's state: -1 and 1 for spins, 0 and 1 for bits."""
    return (2 * state - 1).cast("double") if domain == "spin" else state.cast("double")


@dataclass(frozen=True)
class Model:
    """Pairwise binary models, many at once by ``model_id``: exp(sum of theta_i x_i + sum of theta_ij x_i x_j)."""

    node_params: DataFrame
    edges: DataFrame
    domain: str = "spin"

    @staticmethod
    def pairwise(node_params: DataFrame, edges: DataFrame, domain: str = "spin", merge: str = "sum") -> Model:
        """A validated model: edges point from the smaller id, self-loops, nulls, NaN and zero weights go, ends must exist.

        Repeated or reversed edges are merged by ``merge`` (``sum`` or ``max`` of the absolute value), or are an ``error``.
        """
        if domain not in ("spin", "bit"):
            raise ValueError("domain is spin or bit")
        nodes = require_schema(node_params, "node_params").dropna(subset=["model_id", "var_id"])
        nodes = nodes.groupBy("model_id", "var_id").agg(F.coalesce(F.sum(F.nanvl("theta", F.lit(0.0))), F.lit(0.0)).alias("theta"))
        e = require_schema(edges, "edges").dropna().where("not isnan(theta) and src <> dst")
        e = e.select("model_id", F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"), "theta")
        if merge == "error":
            checked = F.when(F.count(F.lit(1)) == 1, F.first("theta")).otherwise(F.raise_error(F.lit("an edge is given twice")))
            e = e.groupBy("model_id", "src", "dst").agg(checked.alias("theta"))
        else:
            how = {"sum": F.sum("theta"), "max": F.max_by("theta", F.abs("theta"))}[merge]
            e = e.groupBy("model_id", "src", "dst").agg(how.alias("theta"))
        e = e.where("theta <> 0")
        for end in ("src", "dst"):
            e = e.join(nodes.select("model_id", F.col("var_id").alias(end)), ["model_id", end], "left_semi")
        return Model(nodes, e.select("model_id", "src", "dst", "theta"), domain)

    def cliques(self) -> DataFrame:
        """The edges as cliques of two members."""
        return self.edges.select("model_id", F.xxhash64("src", "dst").alias("clique_id"), F.array("src", "dst").alias("members"), "theta")


@dataclass(frozen=True)
class TabularModel:
    """Models whose cliques have any number of members and a table of potentials by assignment."""

    variables: DataFrame
    cliques: DataFrame
    potential_rows: DataFrame

    @staticmethod
    def tabular(variables: DataFrame, cliques: DataFrame, potential_rows: DataFrame) -> TabularModel:
        known = require_schema(cliques, "cliques").where("theta <> 0").withColumn("members", F.array_sort("members"))
        return TabularModel(require_schema(variables, "variables"), known, require_schema(potential_rows, "potential_rows"))


def fold_signs(edges: DataFrame) -> DataFrame:
    """Positive weights, the sign handed to the potential: model_id, src, dst, abs_theta, sgn."""
    return edges.select("model_id", "src", "dst", F.abs("theta").alias("abs_theta"), F.signum("theta").cast("int").alias("sgn"))


def energy(states: DataFrame, model: Model) -> DataFrame:
    """model_id, state_id, energy of assignments given as rows (model_id, state_id, var_id, value)."""
    own = states.join(model.node_params, ["model_id", "var_id"]).select("model_id", "state_id", (F.col("theta") * F.col("value")).alias("e"))
    a = states.select("model_id", "state_id", F.col("var_id").alias("src"), F.col("value").alias("x"))
    b = states.select("model_id", "state_id", F.col("var_id").alias("dst"), F.col("value").alias("y"))
    pair = model.edges.join(a, ["model_id", "src"]).join(b, ["model_id", "state_id", "dst"]).select("model_id", "state_id", (F.col("theta") * F.col("x") * F.col("y")).alias("e"))
    return own.unionByName(pair).groupBy("model_id", "state_id").agg(F.sum("e").alias("energy"))
