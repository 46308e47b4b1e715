"""Functions for SQL: numeric UDFs, an aggregate, and table functions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import Row

from ..hashing import uniform_value
from ..operators import dense
from ..shipping import ship


def _softmax(x: pd.Series) -> pd.Series:
    return x.map(lambda v: dense._softmax(np.asarray(v, float))[0].tolist() if v is not None and len(v) else None)


def _entropy(x: pd.Series) -> pd.Series:
    def one(v):
        p = np.asarray(v, float)
        p = p[p > 0]
        return float(-(p * np.log(p)).sum())

    return x.map(one)


def _kl(p: pd.Series, q: pd.Series) -> pd.Series:
    def one(a, b):
        a, b = np.asarray(a, float), np.asarray(b, float)
        on = a > 0
        return float((a[on] * np.log(a[on] / b[on])).sum()) if (b[on] > 0).all() else float("inf")

    return pd.Series([one(a, b) for a, b in zip(p, q)])


def _cosine(a: pd.Series, b: pd.Series) -> pd.Series:
    return pd.Series([float(np.dot(x, y) / (np.linalg.norm(x) * np.linalg.norm(y))) for x, y in zip(a, b)])


def _log_sum_exp(x: pd.Series) -> float:
    v = x.dropna().to_numpy(float)
    return float(v.max() + np.log(np.exp(v - v.max()).sum())) if len(v) else float("-inf")


class EnumerateStates:
    """All joint states of n binary variables."""

    def eval(self, n: int, domain: str) -> Iterator[tuple]:
        if n > 20:
            raise ValueError("at most 20 variables")
        for s, row in enumerate(dense.states_of(n, domain)):
            yield s, row.tolist()


class HashedRandomGraph:
    """Edges of a hashed random graph."""

    def eval(self, seed: int, trial: int, n: int, p: float) -> Iterator[tuple]:
        for i in range(n):
            for j in range(i + 1, n):
                if uniform_value(seed, trial, i, j) < p:
                    yield i, j


class PartitionGraph:
    """Cuts the graph of each partition of an input table (model_id, src, dst, weight) into k equal clusters."""

    def __init__(self) -> None:
        self.rows: list[tuple[int, int, float]] = []
        self.k, self.model_id = 2, None

    def eval(self, row: Row, k: int) -> None:
        self.k, self.model_id = k, row["model_id"]
        self.rows.append((row["src"], row["dst"], row["weight"]))

    def terminate(self) -> Iterator[tuple]:
        if self.rows:
            ids = sorted({x for r in self.rows for x in r[:2]})
            place = {v: i for i, v in enumerate(ids)}
            a = np.zeros((len(ids), len(ids)))
            for s, d, w in self.rows:
                a[place[s], place[d]] = a[place[d], place[s]] = w
            for v, c in zip(ids, dense.partition(a, self.k)["labels"]):
                yield self.model_id, v, int(c)


def register(spark: SparkSession) -> None:
    """softmax, entropy, kl_divergence, cosine; log_sum_exp; enumerate_states, hashed_random_graph, partition_graph."""
    ship(spark)
    spark.udf.register("softmax", F.pandas_udf(_softmax, "array<double>"))
    spark.udf.register("entropy", F.pandas_udf(_entropy, "double"))
    spark.udf.register("kl_divergence", F.pandas_udf(_kl, "double"))
    spark.udf.register("cosine", F.pandas_udf(_cosine, "double"))
    spark.udf.register("log_sum_exp", F.pandas_udf(_log_sum_exp, "double", F.PandasUDFType.GROUPED_AGG))
    spark.udtf.register("enumerate_states", F.udtf(EnumerateStates, returnType="state int, x array<double>"))
    spark.udtf.register("hashed_random_graph", F.udtf(HashedRandomGraph, returnType="src int, dst int"))
    spark.udtf.register("partition_graph", F.udtf(PartitionGraph, returnType="model_id long, var_id long, cluster int"))
