"""Equal-size cuts of many graphs at once: one graph is one group of rows, solved by dense kernels in its task.

Graphs beyond ``dense_limit`` nodes go to ``scale.coarse_partition`` in ``cut_any_size``.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..model import Model
from ..shipping import ship
from ..storage import Stored
from . import dense
from .graph import SCHEMES, affinity, cut_weight, expected_weights, random_partition
from .inference import arrays, cluster_mean_field

CUT = "model_id long, var_id long, cluster int, cut double, bound double, ratio double"


def _graphs(nodes: DataFrame, weighted: DataFrame) -> DataFrame:
    """Nodes (isolated ones too) and edges of each graph as one kind of row."""
    n = nodes.select("model_id", F.col("var_id").alias("a"), F.lit(None).cast("long").alias("b"), F.lit(0.0).alias("theta"), F.lit(0).alias("cluster"))
    return n.unionByName(weighted.select("model_id", F.col("src").alias("a"), F.col("dst").alias("b"), F.col("weight").alias("theta"), F.lit(None).cast("int").alias("cluster")))


def _per_graph(nodes: DataFrame, weighted: DataFrame, run: Callable, schema: str) -> DataFrame:
    ship(nodes.sparkSession)
    return _graphs(nodes, weighted).groupBy("model_id").applyInPandas(run, schema)


def equi_cut(nodes: DataFrame, weighted: DataFrame, k: int, sense: str = "min", *, method: str = "kmeans", sizes: list[int] | None = None, level: str = "psd_nonneg", restarts: int = 20, seed: int = 0, dense_limit: int = 512) -> DataFrame:
    """model_id, var_id, cluster, cut, bound, ratio of each graph.

    ``method``: ``kmeans``, ``projection`` (with size repair), ``projection_raw``, ``hyperplane`` and ``hyperplane_raw`` (k = 2),
    ``linearised``, ``spectral``, ``brute``.  ``sizes`` prescribes unequal clusters; else they differ by one at most.  Bound and ratio are
    certified, and null for the raw ways, whose clusters may break the sizes.  A graph above ``dense_limit`` nodes is an error here.
    """

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        ids, _, a, _ = arrays(pdf, dense_limit)
        got = dense.partition(a, k, sense, method, sizes, seed, restarts, level)
        return pd.DataFrame({"model_id": pdf["model_id"].iloc[0], "var_id": ids, "cluster": got["labels"], "cut": got["cut"], "bound": got["bound"], "ratio": got["ratio"]}).astype({"bound": float, "ratio": float})

    return _per_graph(nodes, weighted, run, CUT)


def cut_any_size(nodes: DataFrame, weighted: DataFrame, k: int, sense: str = "min", *, dense_limit: int = 512, **options) -> DataFrame:
    """The columns of ``equi_cut`` for every node of every graph.

    Graphs of up to ``dense_limit`` nodes are solved by ``equi_cut`` with ``options``, larger ones by ``scale.coarse_partition``;
    the cut of those is measured on all their edges, and bound and ratio are null, as no bound is certified.
    """
    from .scale import coarse_partition

    nodes, weighted = Stored(nodes.select("model_id", "var_id")).read(), Stored(weighted.select("model_id", "src", "dst", "weight")).read()
    large = nodes.groupBy("model_id").count().where(F.col("count") > dense_limit).select("model_id")
    if not large.limit(1).count():
        return equi_cut(nodes, weighted, k, sense, dense_limit=dense_limit, **options)
    small = equi_cut(nodes.join(large, "model_id", "left_anti"), weighted.join(large, "model_id", "left_anti"), k, sense, dense_limit=dense_limit, **options)
    edges = weighted.join(large, "model_id", "left_semi")
    found = Stored(coarse_partition(nodes.join(large, "model_id", "left_semi"), edges, k, sense)).read()
    none = F.lit(None).cast("double")
    coarse = found.join(cut_weight(edges, found), "model_id", "left").select("model_id", "var_id", "cluster", F.coalesce("cut", F.lit(0.0)).alias("cut"), none.alias("bound"), none.alias("ratio"))
    return small.unionByName(coarse)


SANDWICH = "model_id long, sense string, sizes string, optimum double, ordered boolean, canonical boolean, feasible boolean"


def size_sandwich(nodes: DataFrame, weighted: DataFrame, cases: tuple[tuple[int, ...], ...], *, dense_limit: int = 12) -> DataFrame:
    """For each graph, sense and prescribed sizes that fit it, the optimum by enumeration, and whether the rest keeps its side of it.

    ``ordered``: spectral, semidefinite and non-negative semidefinite bounds do not pass the optimum, nor the next of them;
    ``canonical``: neither does the generic solver's on equal sizes; ``feasible``: every rounding has the sizes and its cut does not
    pass the optimum.
    """
    ways = ("kmeans", "projection", "linearised", "spectral")

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        ids, _, a, _ = arrays(pdf, dense_limit)
        rows = []
        for case in cases:
            if sum(case) != len(ids):
                continue
            sizes, k = np.array(case), len(case)
            for sense in ("min", "max"):
                sign = 1.0 if sense == "min" else -1.0
                slack = 1e-6 * max(1.0, float(a.sum()))
                best = sign * dense.brute_cut(a, k, sense, sizes)[0]
                equal = len(set(case)) == 1
                bounds = [sign * (dense.relax(a, k, sense, x, 4000, gap=1e-7) if equal else dense.relax_sizes(a, sizes, sense, x, 4000, gap=1e-7))[2] for x in ("eigen", "psd", "psd_nonneg")]
                ordered = bounds[2] <= best + slack and bounds[1] <= bounds[2] + 1e-3 * slack / 1e-6 and bounds[0] <= bounds[1] + 1e-3 * slack / 1e-6
                canonical = True
                if equal:
                    matrices, rhs, cost = dense.canonical_cut(a, k, sense)
                    canonical = dense.solve_sdp(cost, matrices, rhs, trace=len(a))[2] <= best + slack
                feasible = True
                for way in ways:
                    got = dense.partition(a, k, sense, way, list(case))
                    feasible &= sorted(np.bincount(got["labels"]).tolist()) == sorted(case) and sign * got["cut"] >= best - slack and sign * got["bound"] <= sign * got["cut"] + slack
                rows.append((int(pdf["model_id"].iloc[0]), sense, ",".join(map(str, case)), sign * best, bool(ordered), bool(canonical), bool(feasible)))
        return pd.DataFrame(rows, columns=[c.split()[0] for c in SANDWICH.split(", ")])

    return _per_graph(nodes, weighted, run, SANDWICH)


def relax_bounds(nodes: DataFrame, weighted: DataFrame, k: int, sense: str = "min", levels: tuple[str, ...] = ("eigen", "psd", "psd_nonneg")) -> DataFrame:
    """model_id, level, value, bound: the nested relaxations of one objective."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        _, _, a, _ = arrays(pdf)
        rows = [(int(pdf["model_id"].iloc[0]), lev, *dense.relax(a, k, sense, lev)[1:]) for lev in levels]
        return pd.DataFrame(rows, columns=["model_id", "level", "value", "bound"])

    return _per_graph(nodes, weighted, run, "model_id long, level string, value double, bound double")


def gram_points(nodes: DataFrame, weighted: DataFrame, k: int, sense: str = "min", rank: int | None = None) -> DataFrame:
    """model_id, var_id, vec: points whose inner products are the relaxed matrix."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        ids, _, a, _ = arrays(pdf)
        points = dense.factor(dense.relax(a, k, sense)[0], rank)
        return pd.DataFrame({"model_id": pdf["model_id"].iloc[0], "var_id": ids, "vec": [p.tolist() for p in points]})

    return _per_graph(nodes, weighted, run, "model_id long, var_id long, vec array<double>")


def treewidth(nodes: DataFrame, weighted: DataFrame) -> DataFrame:
    """model_id, width: min-fill upper bound."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        _, _, a, _ = arrays(pdf)
        return pd.DataFrame({"model_id": [pdf["model_id"].iloc[0]], "width": [dense.treewidth_minfill(a != 0)]})

    return _per_graph(nodes, weighted, run, "model_id long, width int")


def brute_cut(nodes: DataFrame, weighted: DataFrame, k: int, sense: str = "min") -> DataFrame:
    """model_id, cut, labels of the best equipartition by enumeration in SQL operators; up to 12 nodes.

    Labels grow one node at a time; a label is at most one above the largest before it, so clusters are not renamed.
    Ties go to the smallest label string.
    """
    order = Window.partitionBy("model_id").orderBy("var_id")
    place = nodes.select("model_id", "var_id", F.row_number().over(order).alias("pos"))
    sizes = place.groupBy("model_id").agg(F.count(F.lit(1)).alias("n"))
    grown = sizes.select("model_id", "n", F.array(F.lit(0)).alias("labels"))
    top = 12
    for step in range(1, top):
        more = F.when(F.col("n") > step, F.sequence(F.lit(0), F.lit(k - 1))).otherwise(F.array(F.lit(-1)))
        wider = grown.select("model_id", "n", "labels", F.explode(more).alias("c"))
        room = F.size(F.filter("labels", lambda x: x == F.col("c"))) < F.col("n") / k
        fits = (F.col("c") < 0) | ((F.col("c") <= F.array_max("labels") + 1) & room)
        grown = wider.where(fits).select("model_id", "n", F.when(F.col("c") < 0, F.col("labels")).otherwise(F.concat("labels", F.array("c"))).alias("labels"))
    a = place.select("model_id", F.col("var_id").alias("src"), F.col("pos").alias("p"))
    b = place.select("model_id", F.col("var_id").alias("dst"), F.col("pos").alias("r"))
    edges = weighted.join(a, ["model_id", "src"]).join(b, ["model_id", "dst"])
    packed = edges.groupBy("model_id").agg(F.array_sort(F.collect_list(F.struct("p", "r", "weight"))).alias("e"))
    crossing = F.aggregate("e", F.lit(0.0), lambda acc, x: acc + F.when(F.get("labels", x["p"] - 1) != F.get("labels", x["r"] - 1), x["weight"]).otherwise(0.0))
    scored = grown.join(packed, "model_id").select("model_id", F.round(crossing, 6).alias("cut"), F.array_join("labels", "").alias("labels"))
    sign = 1.0 if sense == "min" else -1.0
    best = scored.groupBy("model_id").agg(F.min(F.struct((sign * F.col("cut")).alias("c"), "labels")).alias("r"))
    return best.select("model_id", (sign * F.col("r.c")).alias("cut"), "r.labels")


def partition(model: Model, scheme: str, k: int, **options) -> DataFrame:
    """Clusters by one of the six schemes: a cut's sense over an affinity."""
    sense, kind = SCHEMES[scheme]
    return equi_cut(model.node_params, affinity(model.edges, kind), k, sense, **options)


def compare_schemes(model: Model, k: int, schemes: tuple[str, ...] = tuple(SCHEMES), seed: int = 1, **options) -> DataFrame:
    """scheme, model_id, bound, w, kl_upper for each scheme, a random partition and naive mean field."""
    out = None
    plans = [(s, partition(model, s, k).select("model_id", "var_id", "cluster")) for s in schemes]
    plans.append(("random", random_partition(model.node_params, k, seed)))
    plans.append(("naive", model.node_params.select("model_id", "var_id", F.col("var_id").cast("int").alias("cluster"))))
    for name, assignment in plans:
        d = cluster_mean_field(model, assignment, **options).diagnostics.select(F.lit(name).alias("scheme"), "*")
        out = d if out is None else out.unionByName(d)
    return out


def alternate(model: Model, k: int, rounds: int = 10) -> DataFrame:
    """round, model_id, bound, w, best: expected-potential weights, cut, inference, and again with the means just found.

    It ends when the partitions of all models repeat, or after ``rounds``; ``best`` marks each model's first round with the highest bound.
    """
    out, means, before = None, None, None
    for r in range(rounds):
        weights = expected_weights(model.edges, model.domain, means)
        found = Stored(equi_cut(model.node_params, weights, k).select("model_id", "var_id", "cluster")).read()  # clusters are named by their smallest node
        if before is not None and not found.join(before, ["model_id", "var_id", "cluster"], "left_anti").limit(1).count():
            break
        result = cluster_mean_field(model, found)
        row = result.diagnostics.select(F.lit(r).alias("round"), "model_id", "bound", "w")
        out = row if out is None else out.unionByName(row)
        means, before = Stored(result.marginals.select("model_id", "var_id", "mean")).read(), found
    first = F.row_number().over(Window.partitionBy("model_id").orderBy(F.round("bound", 9).desc(), "round")) == 1
    return out.withColumn("best", first)


def infer(model: Model, *, budget_states: int = 1 << 16, k: int | None = None, schemes: tuple[str, ...] = ("min_coupling", "min_unit"), tree: bool = True) -> DataFrame:
    """Marginals with their certificate, without choices by hand: model_id, var_id, prob, cluster, scheme, k, bound, kl_upper.

    k is the least number of equal clusters whose joint states, together, stay within the budget; of the candidates (the
    schemes, and tree-linked clusters of the first) each model keeps the one with the best bound.
    """
    ship(model.edges.sparkSession)
    domain = model.domain

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        ids, h, w, _ = arrays(pdf)
        n = len(ids)
        kk = k or next((x for x in range(1, n + 1) if sum(2.0**m for m in dense.cluster_sizes(n, x)) <= budget_states), None)
        if kk is None:
            raise ValueError(f"{n} variables have more states than the budget of {budget_states} even one by one")
        best = None
        for name in schemes:
            sense, kind = SCHEMES[name]
            size = np.abs(w)
            a = np.where(w != 0, {"unit": np.ones_like(w), "coupling": size, "inverse": 1 / np.maximum(size, 1e-6)}[kind], 0.0)
            labels = dense.partition(a, kk, sense)["labels"]
            kinds = [(name, dense.ClusterField)] + ([(name + "_tree", dense.TreeField)] if tree and name == schemes[0] and 1 < kk < n else [])
            for label, make in kinds:
                field = make(h, w, labels, domain, budget_states)
                field.run()
                if best is None or field.bound() > best[1].bound() + 1e-12:
                    best = (label, field, labels)
        name, field, labels = best
        return pd.DataFrame({"model_id": pdf["model_id"].iloc[0], "var_id": ids, "prob": field.prob(), "cluster": labels, "scheme": name, "k": kk, "bound": field.bound(), "kl_upper": field.kl_upper()})

    nodes = model.node_params.select("model_id", F.col("var_id").alias("a"), F.lit(None).cast("long").alias("b"), "theta", F.lit(0).alias("cluster"))
    edges = model.edges.select("model_id", F.col("src").alias("a"), F.col("dst").alias("b"), "theta", F.lit(None).cast("int").alias("cluster"))
    return nodes.unionByName(edges).groupBy("model_id").applyInPandas(run, "model_id long, var_id long, prob double, cluster int, scheme string, k int, bound double, kl_upper double")
