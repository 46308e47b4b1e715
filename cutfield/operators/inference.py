"""Exact inference and cluster mean field on DataFrames.

Executors of the cluster mean field: ``local`` runs whole models, one in a task, for batches of small models; ``sql``
keeps every cluster as a row with its joint table in an array, so a sweep shuffles only the means on the border
and never the tables; ``arrow`` does the same with numpy updates.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..model import Model, level
from ..shipping import ship
from ..storage import Stored
from . import dense
from .graph import ends
from .structure import cluster_rows, mean_messages

# --- exact ------------------------------------------------------------------------------------------------------------------


def exact_states(model: Model, max_states: int = 1 << 20) -> DataFrame:
    """model_id, vars, weights (log-weight of each joint state) of each model, in JVM arrays; for models of up to about 20 variables."""
    whole = model.node_params.select("model_id", "var_id", F.lit(0).alias("cluster"))
    return cluster_rows(model, whole, max_states).select("model_id", "vars", F.col("inner").alias("weights"))


def _normalised(weights: Column) -> Column:
    """(top, z, p) of log-weights, computed once each."""
    top = F.array_max(weights)
    return F.struct(top.alias("top"), F.transform(weights, lambda x: F.exp(x - top)).alias("p"))


def exact_inference(model: Model, max_states: int = 1 << 20) -> DataFrame:
    """model_id, log_z, vars, p (unnormalised, top taken off), z."""
    rows = exact_states(model, max_states).select("model_id", "vars", F.explode(F.array(_normalised(F.col("weights")))).alias("s"))
    z = F.aggregate("s.p", F.lit(0.0), lambda a, x: a + x)
    return rows.select("model_id", "vars", F.col("s.p").alias("p"), F.col("s.top").alias("top"), F.explode(F.array(z)).alias("z")).withColumn("log_z", F.col("top") + F.log("z"))


def _bit(s: Column, i: Column) -> Column:
    return F.pmod(F.floor(s / F.pow(F.lit(2.0), i)), F.lit(2))


def exact_log_z(model: Model, max_states: int = 1 << 20) -> DataFrame:
    return exact_inference(model, max_states).select("model_id", "log_z")


def exact_marginals(model: Model, max_states: int = 1 << 20) -> DataFrame:
    """model_id, var_id, prob: probability of each variable's upper state."""
    rows = exact_inference(model, max_states).select("model_id", "p", "z", F.posexplode("vars").alias("pos", "var_id"))
    up = F.aggregate(F.transform("p", lambda x, s: x * _bit(s, F.col("pos"))), F.lit(0.0), lambda a, x: a + x)
    return rows.select("model_id", "var_id", (up / F.col("z")).alias("prob"))


def exact_pair_marginals(model: Model, max_states: int = 1 << 20) -> DataFrame:
    """model_id, src, dst, p11: probability that both ends of an edge are in their upper state."""
    rows = exact_inference(model, max_states).select("model_id", "vars", "p", "z").join(model.edges, "model_id")
    at = lambda end: F.array_position("vars", F.col(end)).cast("int") - 1
    both = F.aggregate(F.transform("p", lambda x, s: x * _bit(s, at("src")) * _bit(s, at("dst"))), F.lit(0.0), lambda a, x: a + x)
    return rows.select("model_id", "src", "dst", (both / F.col("z")).alias("p11"))


def exact_large(model: Model, model_id: int, max_states: int = 1 << 26) -> DataFrame:
    """model_id, log_z, var_id, prob of one model by enumeration in generated code.

    The parameters of the one model (at most 26 variables) come to the driver and become one energy expression, so the
    scan of all states is a single code-generated stage with one row out of each task.
    """
    nodes = [(r["var_id"], r["theta"]) for r in model.node_params.where(F.col("model_id") == model_id).orderBy("var_id").limit(64).collect()]
    n = len(nodes)
    if 1 << n > max_states:
        raise ValueError(f"2**{n} states exceed the limit")
    place = {v: i for i, (v, _) in enumerate(nodes)}
    edges = [(place[r["src"]], place[r["dst"]], r["theta"]) for r in model.edges.where(F.col("model_id") == model_id).collect()]
    spark = model.edges.sparkSession
    cores = spark.sparkContext.defaultParallelism
    bits = [level(F.shiftright("id", i).bitwiseAND(F.lit(1)), model.domain).alias(f"x{i}") for i in range(n)]
    states = spark.range(0, 1 << n, 1, 4 * cores).select(*bits)
    e = F.lit(0.0)
    for i, (_, t) in enumerate(nodes):
        around = F.lit(float(t))
        for a, b, w in edges:
            if b == i:
                around = around + F.lit(float(w)) * F.col(f"x{a}")
        e = e + F.col(f"x{i}") * around
    shift = sum(abs(t) for _, t in nodes) + sum(abs(w) for *_, w in edges)
    weighed = states.withColumn("w", F.exp(e - F.lit(shift)))
    up = [F.sum(F.when(F.col(f"x{i}") > 0, F.col("w")).otherwise(0.0)).alias(f"u{i}") for i in range(n)]
    total = weighed.agg(F.sum("w").alias("z"), *up)
    rows = F.array(*[F.struct(F.lit(v).alias("var_id"), (F.col(f"u{i}") / F.col("z")).alias("prob")) for i, (v, _) in enumerate(nodes)])
    return total.select((F.log("z") + shift).alias("log_z"), F.explode(rows).alias("r")).select(F.lit(model_id).cast("long").alias("model_id"), "log_z", "r.var_id", "r.prob")


# --- cluster mean field -------------------------------------------------------------------------------------------------------


@dataclass
class Result:
    """Node marginals, cluster tables, one diagnostics row per model, and the trace of its sweeps."""

    marginals: DataFrame
    tables: DataFrame
    diagnostics: DataFrame
    trace: DataFrame


PACKED = "model_id long, kind string, a long, b long, i int, x double, y double, z double"


def _packed(model: Model, assignment: DataFrame) -> DataFrame:
    """Nodes with their clusters, and edges, of each model as one kind of row."""
    nodes = model.node_params.join(assignment, ["model_id", "var_id"]).select("model_id", F.col("var_id").alias("a"), F.lit(None).cast("long").alias("b"), "theta", "cluster")
    edges = model.edges.select("model_id", F.col("src").alias("a"), F.col("dst").alias("b"), "theta", F.lit(None).cast("int").alias("cluster"))
    return nodes.unionByName(edges)


def arrays(pdf: pd.DataFrame, limit: int = 2048) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Ids, node weights, dense couplings and labels of one model's packed rows; above ``limit`` nodes an error, before anything is allocated."""
    nodes = pdf[pdf["b"].isna()].sort_values("a")
    if len(nodes) > limit:
        raise ValueError(f"a model of {len(nodes)} nodes is beyond the dense limit of {limit}; use the sql or arrow executor, or coarse_partition")
    ids = nodes["a"].to_numpy(np.int64)
    edges = pdf[pdf["b"].notna()]
    w = np.zeros((len(ids), len(ids)))
    i, j = np.searchsorted(ids, edges["a"].to_numpy(np.int64)), np.searchsorted(ids, edges["b"].to_numpy(np.int64))
    w[i, j] = w[j, i] = edges["theta"].to_numpy()
    return ids, nodes["theta"].to_numpy(), w, nodes["cluster"].fillna(0).to_numpy(int)


def _local(domain: str, schedule: str, tol: float, sweeps: int, damping: float, restarts: int, tree: bool, budget: int) -> Callable:
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        model_id = int(pdf["model_id"].iloc[0])
        ids, h, w, labels = arrays(pdf)
        if tree:
            field = dense.TreeField(h, w, labels, domain, budget)
            trace = field.run(tol=tol, sweeps=sweeps)
        else:
            start = pdf[pdf["b"].isna()].sort_values("a")["mean"]
            field, trace = dense.best_restart(h, w, labels, domain, restarts, budget=budget, init=start.to_numpy(float) if start.notna().all() else None, schedule=schedule, tol=tol, sweeps=sweeps, damping=damping)
        rows: list[tuple] = []
        for v, p, m in zip(ids, field.prob(), field.mean):
            rows.append((model_id, "marginal", int(v), None, None, float(p), float(m), None))
        for c, q in zip(np.unique(labels), field.q):
            rows += [(model_id, "state", s, None, int(c), float(x), None, None) for s, x in enumerate(q)]
        rows.append((model_id, "diagnostics", None, None, None, field.bound(), field.broken(), field.kl_upper()))
        rows += [(model_id, "trace", None, None, s, d, f, None) for s, d, f in trace]
        return pd.DataFrame(rows, columns=["model_id", "kind", "a", "b", "i", "x", "y", "z"]).astype({"a": "Int64", "b": "Int64", "i": "Int32"})

    return run


def _result(packed: DataFrame) -> Result:
    of = lambda kind: packed.where(F.col("kind") == kind)
    return Result(
        of("marginal").select("model_id", F.col("a").alias("var_id"), F.col("x").alias("prob"), F.col("y").alias("mean")),
        of("state").select("model_id", F.col("i").alias("cluster"), F.col("a").alias("state"), F.col("x").alias("q")),
        of("diagnostics").select("model_id", F.col("x").alias("bound"), F.col("y").alias("w"), F.col("z").alias("kl_upper")),
        of("trace").select("model_id", F.col("i").alias("sweep"), F.col("x").alias("delta"), F.col("y").alias("bound")),
    )


def tables(rows: DataFrame, field: DataFrame, assignment: DataFrame, domain: str) -> DataFrame:
    """Cluster rows with q (table), log_z, means (in the order of vars) and feel (the field), given each node's field."""
    per = field.join(assignment, ["model_id", "var_id"]).groupBy("model_id", "cluster").agg(F.map_from_entries(F.collect_list(F.struct("var_id", "field"))).alias("f"))
    joined = rows.join(per, ["model_id", "cluster"], "left")
    feel = F.transform("vars", lambda v: F.coalesce(F.try_element_at("f", v), F.lit(0.0)))
    joined = joined.select("model_id", "cluster", "vars", "inner", F.explode(F.array(feel)).alias("feel"))

    def value(s, i):
        return 2.0 * _bit(s, i) - 1.0 if domain == "spin" else _bit(s, i).cast("double")

    weights = F.transform("inner", lambda e, s: e + F.aggregate(F.transform("feel", lambda f, i: f * value(s, i)), F.lit(0.0), lambda a, x: a + x))
    joined = joined.select("*", F.explode(F.array(weights)).alias("lw"))
    joined = joined.select("*", F.explode(F.array(_normalised(F.col("lw")))).alias("n")).drop("lw")
    joined = joined.select("*", F.explode(F.array(F.aggregate("n.p", F.lit(0.0), lambda a, x: a + x))).alias("zz"))
    joined = joined.select("model_id", "cluster", "vars", "inner", "feel", (F.col("n.top") + F.log("zz")).alias("log_z"), F.explode(F.array(F.transform("n.p", lambda p: p / F.col("zz")))).alias("q"))
    mean = F.transform("vars", lambda _, i: F.aggregate(F.transform("q", lambda p, s: p * value(s, i)), F.lit(0.0), lambda a, x: a + x))
    return joined.select("*", F.explode(F.array(mean)).alias("means"))


def _tables_arrow(domain: str) -> Callable:
    """The same update in numpy: one cluster after the other, a batch at a time."""

    def run(batches):
        for pdf in batches:
            out = []
            for inner, feel in zip(pdf["inner"], pdf["feel"]):
                s = dense.states_of(len(feel), domain)
                q, log_z = dense._softmax(np.asarray(inner) + s @ np.asarray(feel))
                out.append((log_z, q.tolist(), (q @ s).tolist()))
            pdf = pdf[["model_id", "cluster", "vars", "inner", "feel"]].copy()
            for k, name in enumerate(("log_z", "q", "means")):
                pdf[name] = [o[k] for o in out]
            yield pdf

    return run


def _spread(state: DataFrame) -> DataFrame:
    return state.select("model_id", F.explode(F.arrays_zip("vars", "means")).alias("m")).select("model_id", F.col("m.vars").alias("var_id"), F.col("m.means").alias("mean"))


def _entropy(state: DataFrame) -> Column:
    return F.aggregate("q", F.lit(0.0), lambda a, p: a - F.when(p > 0, p * F.log(p)).otherwise(0.0))


def bound_of(state: DataFrame, edges: DataFrame, assignment: DataFrame) -> DataFrame:
    """model_id, bound: entropy plus inner energy of the tables plus expected crossing potentials."""
    inside = F.aggregate(F.transform("q", lambda p, s: p * F.get("inner", s.cast("int"))), F.lit(0.0), lambda a, x: a + x)
    own = state.select("model_id", (_entropy(state) + inside).alias("f"))
    means = _spread(state)
    crossing = ends(edges, assignment).where("c_src <> c_dst")
    a = means.select("model_id", F.col("var_id").alias("src"), F.col("mean").alias("x"))
    b = means.select("model_id", F.col("var_id").alias("dst"), F.col("mean").alias("y"))
    across = crossing.join(a, ["model_id", "src"]).join(b, ["model_id", "dst"]).select("model_id", (F.col("theta") * F.col("x") * F.col("y")).alias("f"))
    return own.unionByName(across).groupBy("model_id").agg(F.sum("f").alias("bound"))


def cluster_colours(edges: DataFrame, assignment: DataFrame, max_colours: int = 64) -> DataFrame:
    """model_id, cluster, colour: clusters of one colour share no crossing edge.

    Rounds: among the clusters without a colour, those whose hash beats all such neighbours take the next colour.
    """
    crossing = ends(edges, assignment).where("c_src <> c_dst").select("model_id", F.col("c_src").alias("a"), F.col("c_dst").alias("b"))
    near = Stored(crossing.union(crossing.select("model_id", F.col("b").alias("a"), F.col("a").alias("b"))).distinct())
    left = Stored(assignment.select("model_id", "cluster").distinct())
    done = None
    for colour in range(max_colours):
        now = left.read()
        rank = lambda c: F.struct(F.xxhash64(F.lit(colour), "model_id", c), F.col(c))
        live = near.read().join(now.withColumnRenamed("cluster", "a"), ["model_id", "a"], "left_semi").join(now.withColumnRenamed("cluster", "b"), ["model_id", "b"], "left_semi")
        beaten = live.where(rank("a") > rank("b")).select("model_id", F.col("a").alias("cluster")).distinct()
        chosen = Stored(now.join(beaten, ["model_id", "cluster"], "left_anti").withColumn("colour", F.lit(colour)))
        done = chosen.read() if done is None else done.unionByName(chosen.read())
        left = Stored(now.join(beaten, ["model_id", "cluster"], "left_semi"))
        if not left.read().limit(1).count():
            return done
    raise RuntimeError("more colours than allowed")


def cluster_mean_field(model: Model, assignment: DataFrame, *, tol: float = 1e-8, max_sweeps: int = 200, schedule: str | None = None, damping: float = 0.0, restarts: int = 1, executor: str = "local", tree: bool = False, budget_states: int = 1 << 16, init: DataFrame | None = None) -> Result:
    """Cluster mean field to its fixed point.

    ``executor`` is ``local`` (a model a task), ``sql`` or ``arrow``; ``schedule`` is ``sequential`` (local only, its default), ``colour``
    (the default of the others) or ``jacobi``.  ``colour`` updates clusters that do not touch together, which equals one after
    the other in the order of colours.  ``init`` warm-starts from means (model_id, var_id, mean) of all variables.  ``restarts`` and
    ``tree`` are for the local executor.  A cluster above ``budget_states`` joint states, and an option that the chosen way does not have,
    are errors.
    """
    schedule = schedule or ("sequential" if executor == "local" else "colour")
    if executor not in ("local", "sql", "arrow") or schedule not in (("sequential", "colour", "jacobi") if executor == "local" else ("colour", "jacobi")):
        raise ValueError(f"no schedule {schedule} in the executor {executor}")
    if tree and (executor != "local" or schedule != "sequential" or damping or restarts != 1 or init is not None):
        raise ValueError("tree-linked clusters run in the local executor, one after the other, from the uniform start, undamped")
    if executor == "local":
        ship(model.edges.sparkSession)
        run = _local(model.domain, schedule, tol, max_sweeps, damping, restarts, tree, budget_states)
        mean = F.lit(None).cast("double").alias("mean")
        packed = _packed(model, assignment)
        if init is None:
            packed = packed.select("*", mean)
        else:
            packed = packed.join(init.select("model_id", F.col("var_id").alias("a"), F.col("mean")), ["model_id", "a"], "left").select("model_id", "a", "b", "theta", "cluster", F.when(F.col("b").isNull(), F.col("mean")).alias("mean"))
        return _result(packed.groupBy("model_id").applyInPandas(run, PACKED))
    if restarts != 1:
        raise ValueError("restarts are for the local executor")
    rows = Stored(cluster_rows(model, assignment, budget_states))
    start = 0.0 if model.domain == "spin" else 0.5
    means = init if init is not None else model.node_params.select("model_id", "var_id", F.lit(start).alias("mean"))
    nodes = assignment.select("model_id", "var_id", "cluster")
    colours = cluster_colours(model.edges, assignment) if schedule == "colour" else None
    classes = [r[0] for r in colours.select("colour").distinct().orderBy("colour").collect()] if colours is not None else [None]
    held = Stored(means.withColumn("old", F.col("mean")))
    trace = None
    for sweep in range(max_sweeps):
        for step, c in enumerate(classes):
            now = held.read()
            part = rows.read() if c is None else rows.read().join(colours.where(F.col("colour") == c), ["model_id", "cluster"], "left_semi")
            new = _spread(_updated(model, part, now, nodes, executor)).withColumnRenamed("mean", "new")
            mixed = F.coalesce((1 - damping) * F.col("new") + damping * F.col("mean"), F.col("mean"))
            start_of_sweep = F.col("mean") if step == 0 else F.col("old")
            held = Stored(now.join(new, ["model_id", "var_id"], "left").select("model_id", "var_id", mixed.alias("mean"), start_of_sweep.alias("old")))
        deltas = held.read().groupBy("model_id").agg(F.max(F.abs(F.col("mean") - F.col("old"))).alias("delta"))
        row = deltas.select("model_id", F.lit(sweep).alias("sweep"), "delta", F.lit(None).cast("double").alias("bound"))
        trace = row if trace is None else trace.unionByName(row)
        if (deltas.agg(F.max("delta")).first()[0] or 0.0) < tol:
            break
    final = Stored(_updated(model, rows.read(), held.read(), nodes, executor)).read()
    out = _spread(final)
    low, high = (-1.0, 1.0) if model.domain == "spin" else (0.0, 1.0)
    marginals = out.select("model_id", "var_id", ((F.col("mean") - low) / (high - low)).alias("prob"), "mean")
    from .structure import broken_weight, kl_bounds

    diag = bound_of(final, model.edges, assignment).join(broken_weight(model.edges, assignment), "model_id", "left")
    kl = kl_bounds(model, assignment).select("model_id", (F.col("b") * F.col("w")).alias("kl_upper"))
    diag = diag.join(kl, "model_id", "left").select("model_id", "bound", F.coalesce("w", F.lit(0.0)).alias("w"), F.coalesce("kl_upper", F.lit(0.0)).alias("kl_upper"))
    states = final.select("model_id", "cluster", F.posexplode("q").alias("state", "q")).withColumn("state", F.col("state").cast("long"))
    return Result(marginals, states, diag, trace)


def _updated(model: Model, rows: DataFrame, means: DataFrame, nodes: DataFrame, executor: str) -> DataFrame:
    field = mean_messages(model.edges, means, nodes)
    if executor == "sql":
        return tables(rows, field, nodes, model.domain)
    ship(model.edges.sparkSession)
    per = field.join(nodes, ["model_id", "var_id"]).groupBy("model_id", "cluster").agg(F.map_from_entries(F.collect_list(F.struct("var_id", "field"))).alias("f"))
    feel = F.transform("vars", lambda v: F.coalesce(F.try_element_at("f", v), F.lit(0.0)))
    felt = rows.join(per, ["model_id", "cluster"], "left").select("model_id", "cluster", "vars", "inner", feel.alias("feel"))
    return felt.mapInPandas(_tables_arrow(model.domain), "model_id long, cluster int, vars array<long>, inner array<double>, feel array<double>, log_z double, q array<double>, means array<double>")


def naive_mean_field(model: Model, **options) -> Result:
    """Every variable its own cluster."""
    single = model.node_params.select("model_id", "var_id", F.col("var_id").cast("int").alias("cluster"))
    return cluster_mean_field(model, single, **options)


def kl_divergence(diagnostics: DataFrame, log_z: DataFrame) -> DataFrame:
    """model_id, kl: how far the bound is below the log-normaliser, which is the divergence of q from p."""
    return diagnostics.join(log_z, "model_id").select("model_id", (F.col("log_z") - F.col("bound")).alias("kl"))


def kl_border_sum(model: Model, assignment: DataFrame, result: Result, log_z: DataFrame) -> DataFrame:
    """model_id, kl: the divergence at a fixed point as a sum over the cliques that clusters share.

    Every broken potential stands once in each of its two clusters' averages, so one expectation of it is taken back; the
    normaliser of the product is that of the clusters, read from the state in which all variables are low.
    """
    low, high = (-1.0, 1.0) if model.domain == "spin" else (0.0, 1.0)
    means = result.marginals.select("model_id", "var_id", (low + (high - low) * F.col("prob")).alias("mean"))
    nodes = assignment.select("model_id", "var_id", "cluster")
    a = means.select("model_id", F.col("var_id").alias("src"), F.col("mean").alias("x"))
    b = means.select("model_id", F.col("var_id").alias("dst"), F.col("mean").alias("y"))
    met = ends(model.edges, nodes)
    border = met.where("c_src <> c_dst").join(a, ["model_id", "src"]).join(b, ["model_id", "dst"]).select("model_id", (F.col("theta") * F.col("x") * F.col("y")).alias("v"))
    field = mean_messages(model.edges, means, nodes).select("model_id", F.lit(low).alias("at"), "field").select("model_id", (-F.col("at") * F.col("field")).alias("v"))
    alone = model.node_params.select("model_id", (-F.lit(low) * F.col("theta")).alias("v"))
    inside = met.where("c_src = c_dst").select("model_id", (-F.lit(low * low) * F.col("theta")).alias("v"))
    tables = result.tables.where("state = 0").select("model_id", F.log("q").alias("v"))  # minus the energy of that state gives minus the cluster's normaliser
    total = border.unionByName(field).unionByName(alone).unionByName(inside).unionByName(tables).groupBy("model_id").agg(F.sum("v").alias("v"))
    return total.join(log_z, "model_id").select("model_id", (F.col("v") + F.col("log_z")).alias("kl"))


def l1_error(approx: DataFrame, exact: DataFrame, norm: str = "mean") -> DataFrame:
    """model_id, l1: absolute error of binary marginals: ``mean`` over nodes and states, ``node``: summed over states, ``sum``: over all."""
    gap = F.abs(F.col("prob") - F.col("truth"))
    joined = approx.select("model_id", "var_id", "prob").join(exact.select("model_id", "var_id", F.col("prob").alias("truth")), ["model_id", "var_id"])
    value = {"mean": F.avg(gap), "node": 2 * F.avg(gap), "sum": 2 * F.sum(gap)}[norm]
    return joined.groupBy("model_id").agg(value.alias("l1"))


def bound_ratio(diagnostics: DataFrame, log_z: DataFrame) -> DataFrame:
    """model_id, ratio (null unless the log-normaliser is positive), gap."""
    j = diagnostics.join(log_z, "model_id")
    return j.select("model_id", F.when(F.col("log_z") > 0, F.col("bound") / F.col("log_z")).alias("ratio"), (F.col("log_z") - F.col("bound")).alias("gap"))
