"""Models with tabular cliques of any size and variables of any number of states."""

from __future__ import annotations

from collections.abc import Iterable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import TabularModel
from ..shipping import ship
from .structure import classify_cliques


def joint_states(model: TabularModel, max_states: int = 1 << 20) -> DataFrame:
    """model_id, s (state number), digits (array of states in the order of variables): mixed radix, the first variable fastest."""
    cards = model.variables.groupBy("model_id").agg(F.array_sort(F.collect_list(F.struct("var_id", "card"))).alias("v"))
    total = F.aggregate("v", F.lit(1).cast("long"), lambda a, x: a * x["card"])
    states = F.when(total <= max_states, F.sequence(F.lit(0).cast("long"), total - 1)).otherwise(F.raise_error(F.lit("more joint states than the limit")))
    rows = cards.select("model_id", "v", F.explode(states).alias("s"))
    start = F.struct(F.col("s").alias("rest"), F.array().cast("array<int>").alias("digits"))

    def step(acc, x):
        return F.struct(F.floor(acc["rest"] / x["card"]).alias("rest"), F.concat(acc["digits"], F.array(F.pmod(acc["rest"], x["card"].cast("long")).cast("int"))).alias("digits"))

    return rows.select("model_id", "s", F.transform("v", lambda x: x["var_id"]).alias("vars"), F.aggregate("v", start, step, lambda acc: acc["digits"]).alias("digits"))


def log_weights(model: TabularModel, max_states: int = 1 << 20) -> DataFrame:
    """model_id, s, vars, digits, e: log-weight of every joint state, by joining each clique's table on its part of the state."""
    states = joint_states(model, max_states)
    parts = states.join(model.cliques, "model_id").select("model_id", "s", "clique_id", "theta", F.transform("members", lambda m: F.element_at(F.map_from_arrays("vars", "digits"), m)).alias("assignment"))
    e = parts.join(model.potential_rows, ["model_id", "clique_id", "assignment"]).groupBy("model_id", "s").agg(F.sum(F.col("theta") * F.col("phi")).alias("e"))
    return states.join(e, ["model_id", "s"])


def exact(model: TabularModel, max_states: int = 1 << 20) -> tuple[DataFrame, DataFrame]:
    """(model_id, log_z) and (model_id, var_id, state, prob), by log-sum-exp over all states."""
    w = log_weights(model, max_states)
    top = w.groupBy("model_id").agg(F.max("e").alias("top"))
    w = w.join(F.broadcast(top), "model_id").withColumn("p", F.exp(F.col("e") - F.col("top")))  # one row per model
    z = w.groupBy("model_id", "top").agg(F.sum("p").alias("z"))
    log_z = z.select("model_id", (F.col("top") + F.log("z")).alias("log_z"))
    cells = w.select("model_id", "p", F.explode(F.arrays_zip("vars", "digits")).alias("c")).groupBy("model_id", F.col("c.vars").alias("var_id"), F.col("c.digits").alias("state")).agg(F.sum("p").alias("m"))
    return log_z, cells.join(z.select("model_id", "z"), "model_id").select("model_id", "var_id", "state", (F.col("m") / F.col("z")).alias("prob"))


def uniform_tables(model: TabularModel, assignment: DataFrame) -> DataFrame:
    """model_id, cluster, assign (map of variable to state), q: uniform joint tables of clusters."""
    cards = model.variables.join(assignment, ["model_id", "var_id"]).groupBy("model_id", "cluster").agg(F.array_sort(F.collect_list(F.struct("var_id", "card"))).alias("v"))
    total = F.aggregate("v", F.lit(1).cast("long"), lambda a, x: a * x["card"])
    rows = cards.select("model_id", "cluster", "v", F.explode(F.sequence(F.lit(0).cast("long"), total - 1)).alias("s"), total.alias("n"))
    start = F.struct(F.col("s").alias("rest"), F.array().cast("array<int>").alias("digits"))

    def step(acc, x):
        return F.struct(F.floor(acc["rest"] / x["card"]).alias("rest"), F.concat(acc["digits"], F.array(F.pmod(acc["rest"], x["card"].cast("long")).cast("int"))).alias("digits"))

    digits = F.aggregate("v", start, step, lambda acc: acc["digits"])
    return rows.select("model_id", "cluster", F.map_from_arrays(F.transform("v", lambda x: x["var_id"]), digits).alias("assign"), (F.lit(1.0) / F.col("n")).alias("q"))


class TabularField:
    """Cluster mean field of one tabular model in dense arrays: the general averages, joint inside every cluster."""

    def __init__(self, cards: dict[int, int], cliques: Iterable[tuple[tuple[int, ...], float, np.ndarray]], labels: dict[int, int]):
        self.members = {c: sorted(v for v in labels if labels[v] == c) for c in sorted(set(labels.values()))}
        self.cards, self.labels = cards, labels
        self.cliques = [(m, t, p) for m, t, p in cliques]
        self.q = {c: np.full([cards[v] for v in vs], 1 / np.prod([cards[v] for v in vs])) for c, vs in self.members.items()}
        self.inner = {c: np.zeros([cards[v] for v in vs]) for c, vs in self.members.items()}
        self.border = []
        for m, t, p in self.cliques:
            touched = sorted({labels[v] for v in m})
            if len(touched) == 1:
                self.inner[touched[0]] += self._lift(touched[0], m, t * p)
            else:
                self.border.append((m, t, p, touched))

    def _lift(self, c: int, own: tuple[int, ...], table: np.ndarray) -> np.ndarray:
        """A table over some members of a cluster, broadcast to all of them."""
        vs = self.members[c]
        order = sorted(range(len(own)), key=lambda i: vs.index(own[i]))
        shape = [self.cards[v] if v in own else 1 for v in vs]
        return table.transpose(order).reshape(shape)

    def _marginal(self, c: int, keep: list[int]) -> np.ndarray:
        vs = self.members[c]
        out = self.q[c].sum(axis=tuple(i for i, v in enumerate(vs) if v not in keep))
        order = [sorted(keep, key=vs.index).index(v) for v in keep]
        return out.transpose(order)

    def average(self, m: tuple[int, ...], p: np.ndarray, c: int, touched: list[int]) -> tuple[tuple[int, ...], np.ndarray]:
        """The potential averaged over every touched cluster but ``c``."""
        left, table = list(m), p
        for other in touched:
            if other == c:
                continue
            part = [v for v in left if self.labels[v] == other]
            axes = [left.index(v) for v in part]
            table = np.tensordot(table, self._marginal(other, part), axes=(axes, range(len(part))))
            left = [v for v in left if v not in part]
        return tuple(left), table

    def run(self, tol: float = 1e-12, sweeps: int = 500) -> int:
        for sweep in range(sweeps):
            move = 0.0
            for c in self.members:
                e = self.inner[c].copy()
                for m, t, p, touched in self.border:
                    if c in touched:
                        own, avg = self.average(m, p, c, touched)
                        e = e + t * self._lift(c, own, avg)
                e = np.exp(e - e.max())
                e /= e.sum()
                move = max(move, float(np.abs(e - self.q[c]).max()))
                self.q[c] = e
            if move < tol:
                return sweep + 1
        return sweeps

    def bound(self) -> float:
        total = 0.0
        for c, q in self.q.items():
            total += float((q * self.inner[c]).sum() - (q[q > 0] * np.log(q[q > 0])).sum())
        for m, t, p, touched in self.border:
            own, avg = self.average(m, p, touched[0], touched)
            total += t * float((avg * self._marginal(touched[0], list(own))).sum())
        return total


def mean_field(model: TabularModel, assignment: DataFrame, tol: float = 1e-12) -> tuple[DataFrame, DataFrame]:
    """(model_id, var_id, state, prob) and (model_id, bound): one model in a task, any arity, any number of states."""
    ship(model.cliques.sparkSession)
    tables = model.potential_rows.groupBy("model_id", "clique_id").agg(F.collect_list(F.struct("assignment", "phi")).alias("rows"))
    cliques = model.cliques.join(tables, ["model_id", "clique_id"]).groupBy("model_id").agg(F.array_sort(F.collect_list(F.struct("clique_id", "members", "theta", "rows"))).alias("cliques"))
    variables = model.variables.join(assignment, ["model_id", "var_id"]).groupBy("model_id").agg(F.collect_list(F.struct("var_id", "card", "cluster")).alias("variables"))

    def run(batches):
        for pdf in batches:
            for r in pdf.itertuples(index=False):
                cards = {int(v["var_id"]): int(v["card"]) for v in r.variables}
                labels = {int(v["var_id"]): int(v["cluster"]) for v in r.variables}
                found = []
                for c in r.cliques:
                    m = tuple(int(x) for x in c["members"])
                    p = np.zeros([cards[v] for v in m])
                    for row in c["rows"]:
                        p[tuple(row["assignment"])] = row["phi"]
                    found.append((m, float(c["theta"]), p))
                field = TabularField(cards, found, labels)
                field.run(tol)
                rows = [(int(r.model_id), v, s, float(x), None) for v in sorted(cards) for s, x in enumerate(field._marginal(labels[v], [v]))]
                rows.append((int(r.model_id), None, None, None, field.bound()))
                out = pd.DataFrame(rows, columns=["model_id", "var_id", "state", "prob", "bound"])
                yield out.astype({"var_id": "Int64", "state": "Int32"})

    both = variables.join(cliques, "model_id").mapInPandas(run, "model_id long, var_id long, state int, prob double, bound double")
    return both.where("var_id is not null").drop("bound"), both.where("bound is not null").select("model_id", "bound")


def kl_bounds(model: TabularModel, assignment: DataFrame) -> DataFrame:
    """model_id, a_phi, b_phi, a_z, b_z, a, b, w of the general certificate: cliques may touch any number of clusters."""
    border = classify_cliques(model.cliques, assignment).where("is_border")
    extremes = model.potential_rows.groupBy("model_id", "clique_id").agg(F.min("phi").alias("p0"), F.max("phi").alias("p1"))
    b = border.join(extremes, ["model_id", "clique_id"])
    low = F.when(F.col("theta") > 0, F.col("p0")).otherwise(-F.col("p1"))
    high = F.when(F.col("theta") > 0, F.col("p1")).otherwise(-F.col("p0"))
    k = F.col("k_beta")
    got = b.groupBy("model_id").agg(F.min((k - 1) * low).alias("a_phi"), F.max((k - 1) * high).alias("b_phi"), F.min((k - 1) * low + low - high).alias("a_z"), F.max((k - 1) * high + high - low).alias("b_z"), F.sum(F.abs("theta")).alias("w"))
    return got.select("model_id", "a_phi", "b_phi", "a_z", "b_z", F.greatest(F.lit(0.0), F.col("a_phi") - F.col("b_z")).alias("a"), (F.col("b_phi") - F.col("a_z")).alias("b"), "w")
