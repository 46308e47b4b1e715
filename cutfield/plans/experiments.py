"""The published experiments on hashed random graphs: cut quality, marginal error, bound tightness, theorem check.

A trial is a row; one task solves a trial with dense kernels, and Spark aggregates.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..hashing import uniform_value
from ..operators import dense
from ..operators.graph import SCHEMES
from ..shipping import ship
from ..storage import Stored


def random_graph(trial: int, n: int, p: float, seed: int = 1) -> np.ndarray:
    """The same graphs as the relation ``random_graphs``."""
    a = np.zeros((n, n))
    for i in range(n):
        for j in range(i + 1, n):
            if uniform_value(seed, trial, i, j) < p:
                a[i, j] = a[j, i] = 1.0
    return a


def random_model(trial: int, n: int, p: float, coupling: str, w_obs: float, w_coup: float) -> tuple[np.ndarray, np.ndarray]:
    """Node weights uniform in (-w_obs, w_obs), couplings in the range of their kind."""
    a = random_graph(trial, n, p)
    low, high = {"repulsive": (-w_coup, 0.0), "mixed": (-w_coup, w_coup), "attractive": (0.0, w_coup)}[coupling]
    h = np.array([-w_obs + 2 * w_obs * uniform_value(3, trial, i) for i in range(n)])
    w = np.zeros((n, n))
    for i, j in zip(*np.nonzero(np.triu(a, 1))):
        w[i, j] = w[j, i] = low + (high - low) * uniform_value(2, trial, i, j)
    return h, w


def _cells(spark: SparkSession, cells: list[tuple], ddl: str, tasks: int = 0) -> DataFrame:
    df = spark.createDataFrame(cells, ddl)
    n = tasks or min(len(cells), 4 * spark.sparkContext.defaultParallelism)
    return df.repartition(n)


def trade_trials(spark: SparkSession, sf_dir: str, trials: int, n: int = 24) -> DataFrame:
    """trial, pairs: for each share of the orders, the lines between two of the first n nations (supplier's and customer's, either way), counted.

    A trial is the orders whose key has its remainder modulo ``trials``; all lines belong to one.
    """
    t = lambda name: spark.read.parquet(f"{sf_dir}/{name}.parquet")
    lines = t("lineitem").select("l_orderkey", F.col("l_suppkey").alias("s_suppkey")).join(t("supplier").select("s_suppkey", "s_nationkey"), "s_suppkey")
    buyers = t("orders").select(F.col("o_orderkey").alias("l_orderkey"), F.col("o_custkey").alias("c_custkey")).join(t("customer").select("c_custkey", "c_nationkey"), "c_custkey")
    both = lines.join(buyers, "l_orderkey").where(f"s_nationkey <> c_nationkey and s_nationkey < {n} and c_nationkey < {n}")
    counted = both.groupBy(F.pmod("l_orderkey", F.lit(trials)).cast("int").alias("trial"), F.least("s_nationkey", "c_nationkey").alias("a"), F.greatest("s_nationkey", "c_nationkey").alias("b")).agg(F.count(F.lit(1)).alias("lines"))
    pairs = counted.groupBy("trial").agg(F.collect_list(F.struct("a", "b", "lines")).alias("pairs"))  # n (n - 1) / 2 at most
    return spark.range(trials).select(F.col("id").cast("int").alias("trial")).join(pairs, "trial", "left")


def trade_matrix(pairs, trial: int, n: int, p: float, weighted: bool) -> np.ndarray:
    """The share p of the pairs of nations that have most lines (ties by a hash): one each, or their lines over the most lines of a pair."""
    lines = np.zeros((n, n))
    for row in pairs if pairs is not None else []:
        lines[row["a"], row["b"]] = row["lines"]
    order = sorted(((-lines[i, j], uniform_value(1, trial, i, j), i, j) for i in range(n) for j in range(i + 1, n)))
    a = np.zeros((n, n))
    for less, _, i, j in order[: round(p * len(order))]:
        a[i, j] = a[j, i] = (1 - less) / (1 + lines.max()) if weighted else 1.0
    return a


QUALITY = "p double, k int, sense string, trial int, rounding string, bound double, cut double, ratio double"


def quality_trials(spark: SparkSession, trials: int = 100, n: int = 24, densities: tuple[float, ...] = (0.3, 0.5), ks: tuple[int, ...] = (3, 4, 6, 8), weighted: bool = False, sf_dir: str | None = None) -> DataFrame:
    """One row per trial, sense, k and rounding: certified bound, feasible cut, and their ratio.

    The graphs are hashed random ones, or with ``sf_dir`` those of trade between nations in shares of the given orders.

    Roundings: K-means, one balanced draw of random directions, the best of twenty, and one draw whose sizes are not repaired.
    """
    ship(spark)
    cells = _cells(spark, [(p, t) for p in densities for t in range(trials)], "p double, trial int")
    if sf_dir:
        held = Stored(trade_trials(spark, sf_dir, trials, n)).read()
        cells = held.select(F.explode(F.array(*map(F.lit, densities))).alias("p"), "trial", "pairs")
        cells = cells.repartition(min(trials * len(densities), 4 * spark.sparkContext.defaultParallelism))

    def run(batches):
        for pdf in batches:
            rows = []
            for at, (p, trial) in enumerate(zip(pdf["p"], pdf["trial"])):
                if sf_dir:
                    a = trade_matrix(pdf["pairs"].iloc[at], int(trial), n, float(p), weighted)
                else:
                    a = random_graph(int(trial), n, float(p)) if not weighted else np.abs(random_model(int(trial), n, float(p), "attractive", 1.0, 1.0)[1])
                for k in ks:
                    for sense in ("min", "max"):
                        y, _, bound = dense.relax(a, k, sense)
                        points, sizes = dense.factor(y), dense.cluster_sizes(n, k)
                        kinds = {
                            "kmeans": dense.round_kmeans(points, a, sizes, sense),
                            "projection": dense.round_projection(points, a, sizes, sense),
                            "projection_20": dense.round_projection(points, a, sizes, sense, 20),
                            "projection_raw": dense.round_projection(points, a, sizes, sense, 1, False),
                        }
                        for name, labels in kinds.items():
                            cut = dense.cut_value(a, labels)
                            held = name != "projection_raw"  # its clusters may break the sizes, so the bound is not its own
                            rows.append((float(p), k, sense, int(trial), name, bound if held else None, cut, cut / bound if held else None))
            yield pd.DataFrame(rows, columns=["p", "k", "sense", "trial", "rounding", "bound", "cut", "ratio"])

    return cells.mapInPandas(run, QUALITY)


def table_quality(spark: SparkSession, trials: int = 100, **options) -> DataFrame:
    """Means and spread of bound, cut and ratio, and the share of trials within 5 % and 10 % of the bound."""
    off = F.abs(F.col("ratio") - 1)
    rows = quality_trials(spark, trials, **options).groupBy("p", "sense", "k", "rounding")
    return rows.agg(F.round(F.avg("bound"), 2).alias("bound"), F.round(F.avg("cut"), 2).alias("cut"), F.round(F.avg("ratio"), 4).alias("ratio"), F.round(F.stddev_samp("ratio"), 4).alias("ratio_sd"), F.round(F.avg((off <= 0.05).cast("int")), 3).alias("within_5"), F.round(F.avg((off <= 0.10).cast("int")), 3).alias("within_10"), F.count(F.lit(1)).alias("trials"))


FIGURE = "p double, coupling string, w_obs double, w_coup double, trial int, k int, clustering string, l1 double, ratio double, gap double, w double, kl double, kl_upper double, sweeps int, width int"


def figure_trials(spark: SparkSession, trials: int = 20, n: int = 24, p: float = 0.3, couplings: tuple[str, ...] = ("repulsive", "mixed", "attractive"), strengths: tuple[tuple[float, float], ...] = ((1.0, 1.0), (1.0, 2.0), (1.0, 4.0), (0.25, 1.0)), ks: tuple[int, ...] = (2, 3, 4, 6, 8, 12), domain: str = "spin", restarts: int = 3, extra: bool = False) -> DataFrame:
    """One row per model, k and clustering (six schemes, random, naive): error of marginals, bound over log-normaliser, broken weight."""
    ship(spark)
    cells = [(c, t) for c in couplings for t in range(trials)]

    def run(batches):
        for pdf in batches:
            rows = []
            for coupling, trial in pdf.itertuples(index=False):
                cuts: dict = {}  # the strength scales all couplings alike, and with them every affinity, so each cut is searched once
                for w_obs, w_coup in strengths:
                    h, w = random_model(int(trial), n, p, coupling, w_obs, w_coup)
                    log_z, truth = dense.exact(h, w, domain)
                    on, size = w != 0, np.abs(w)
                    width = dense.treewidth_minfill(on)
                    kinds = {"unit": on.astype(float), "coupling": size, "inverse": np.where(on, 1 / np.maximum(size, 1e-6), 0.0)}

                    def add(k, name, labels, make=None):
                        if make:
                            field = make(h, w, labels, domain)
                            steps = field.run()
                        else:
                            field, steps = dense.best_restart(h, w, labels, domain, restarts)
                        kl = log_z - field.bound()
                        rows.append((p, coupling, w_obs, w_coup, int(trial), k, name, float(np.abs(field.prob() - truth).mean()), field.bound() / log_z if log_z > 0 else None, kl, field.broken(), kl, field.kl_upper(), len(steps), width))

                    add(n, "naive", np.arange(n))
                    for k in ks:
                        rng = np.array([uniform_value(4, trial, k, i) for i in range(n)])
                        random = np.empty(n, int)
                        random[np.argsort(rng)] = np.arange(n) % k
                        add(k, "random", random)
                        for scheme, (sense, kind) in SCHEMES.items():
                            if (k, scheme) not in cuts:
                                cuts[k, scheme] = dense.partition(kinds[kind], k, sense)["labels"]
                            labels = cuts[k, scheme]
                            add(k, scheme, labels)
                            if extra and scheme == "min_coupling":
                                add(k, "min_coupling_tree", labels, dense.TreeField)
            yield pd.DataFrame(rows, columns=[c.split()[0] for c in FIGURE.split(", ")])

    return _cells(spark, cells, "coupling string, trial int", len(cells)).mapInPandas(run, FIGURE)


_GRIDS: dict[tuple, Stored] = {}


def stored_trials(spark: SparkSession, **options) -> DataFrame:
    """``figure_trials`` written once for each application and choice of options; all figures read that table."""
    trials = figure_trials(spark, **options)
    if spark is None:  # no application to store in
        return trials
    key = (spark.sparkContext.applicationId, *sorted(options.items()))
    if key not in _GRIDS:
        _GRIDS[key] = Stored(trials)
    return _GRIDS[key].read()


def panels(trials: DataFrame, middle: int) -> DataFrame:
    """One row per panel (coupling, strengths), clustering and k, over the graphs whose treewidth is ``middle`` give or take one, and over all.

    ``l1_rank`` and ``bound_rank`` order the clusterings of a panel and k, best first.
    """
    from pyspark.sql import Window

    near = F.abs(F.col("width") - middle) <= 1
    both = trials.withColumn("graphs", F.lit("all")).unionByName(trials.where(near).withColumn("graphs", F.lit("of the width")))
    naive = both.where("clustering = 'naive'").drop("k").join(both.where("clustering <> 'naive'").select("k").distinct())  # a handful of k
    cells = both.where("clustering <> 'naive'").unionByName(naive.select(both.columns)).groupBy("graphs", "coupling", "w_obs", "w_coup", "k", "clustering")
    out = cells.agg(F.avg("l1").alias("l1"), F.stddev_samp("l1").alias("l1_sd"), F.avg("ratio").alias("ratio"), F.avg("gap").alias("gap"), F.avg("w").alias("w"), F.avg("width").alias("width"), F.count(F.lit(1)).alias("n"))
    per = Window.partitionBy("graphs", "coupling", "w_obs", "w_coup", "k")
    out = out.withColumns({"l1_rank": F.rank().over(per.orderBy("l1")), "bound_rank": F.rank().over(per.orderBy("gap"))})
    return out.select("graphs", "coupling", "w_obs", "w_coup", "k", "clustering", *[F.round(c, 5).alias(c) for c in ("l1", "l1_sd", "ratio", "gap", "w", "width")], "n", "l1_rank", "bound_rank")


def figure_marginals(trials: DataFrame) -> DataFrame:
    """Mean and spread of the marginal error; coarser groups by rollup."""
    return trials.rollup("coupling", "clustering", "k").agg(F.round(F.avg("l1"), 5).alias("l1"), F.round(F.stddev_samp("l1"), 5).alias("l1_sd"), F.count(F.lit(1)).alias("n"))


def figure_bounds(trials: DataFrame) -> DataFrame:
    """Mean bound over log-normaliser, gap and broken weight, as a cube."""
    return trials.cube("coupling", "clustering", "k").agg(F.round(F.avg("ratio"), 5).alias("ratio"), F.round(F.avg("gap"), 5).alias("gap"), F.round(F.avg("w"), 4).alias("w"))


def theorem_scatter(trials: DataFrame) -> DataFrame:
    """Divergence against its certificate for each clustering: violations, mean and largest share, rank correlation with the broken weight."""
    from pyspark.sql import Window

    per = Window.partitionBy("coupling", "w_obs", "w_coup", "trial")
    ranked = trials.withColumns({"r_w": F.rank().over(per.orderBy("w")), "r_l1": F.rank().over(per.orderBy("l1")), "r_gap": F.rank().over(per.orderBy("gap"))})
    share = F.when(F.col("kl_upper") > 0, F.col("kl") / F.col("kl_upper"))
    return ranked.groupBy("coupling").agg(F.sum(((F.col("kl") > F.col("kl_upper") + 1e-9) | (F.col("kl") < -1e-9)).cast("int")).alias("violations"), F.round(F.avg(share), 5).alias("mean_share"), F.round(F.max(share), 5).alias("max_share"), F.round(F.corr("r_w", "r_l1"), 4).alias("corr_w_l1"), F.round(F.corr("r_w", "r_gap"), 4).alias("corr_w_gap"), F.round(F.corr("r_l1", "r_gap"), 4).alias("corr_l1_gap"))


def win_rates(trials: DataFrame) -> DataFrame:
    """Share of cells in which each clustering beats naive mean field and a random one of the same k, by marginal error."""
    keys = ["coupling", "w_obs", "w_coup", "trial"]
    naive = trials.where("clustering = 'naive'").select(*keys, F.col("l1").alias("naive_l1"))
    random = trials.where("clustering = 'random'").select(*keys, "k", F.col("l1").alias("random_l1"))
    j = trials.where("clustering <> 'naive'").join(naive, keys).join(random, [*keys, "k"])
    beats = lambda c: F.round(F.avg((F.col("l1") < F.col(c)).cast("int")), 4)
    return j.groupBy("clustering").agg(F.round(F.avg("l1"), 5).alias("l1"), beats("naive_l1").alias("beats_naive"), beats("random_l1").alias("beats_random"))
