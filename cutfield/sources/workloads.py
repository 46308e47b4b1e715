"""Graphs and models built from the given tables."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..hashing import uniform
from ..model import Model, TabularModel


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def trade_graph(spark: SparkSession, sf_dir: str) -> DataFrame:
    """src, dst, pairs, revenue: nations that trade, by lines between a supplier's and a customer's nation."""
    t = lambda name: table(spark, sf_dir, name)
    money = F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4).cast("decimal(38,4)")
    lines = t("lineitem").select("l_orderkey", "l_suppkey", money.alias("money"))
    buyers = t("orders").select("o_orderkey", "o_custkey").join(t("customer").select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
    sold = lines.join(t("supplier").select("s_suppkey", "s_nationkey"), F.col("l_suppkey") == F.col("s_suppkey"))
    both = sold.join(buyers, F.col("l_orderkey") == F.col("o_orderkey")).where("s_nationkey <> c_nationkey")
    grouped = both.groupBy(F.least("s_nationkey", "c_nationkey").cast("long").alias("src"), F.greatest("s_nationkey", "c_nationkey").cast("long").alias("dst"))
    return grouped.agg(F.count(F.lit(1)).alias("pairs"), F.sum("money").cast("double").alias("revenue"))


def trade24(spark: SparkSession, sf_dir: str) -> DataFrame:
    return trade_graph(spark, sf_dir).where("src < 24 and dst < 24")


def trade_threshold(spark: SparkSession, sf_dir: str, quantiles: tuple[float, ...] = (0.7, 0.5)) -> DataFrame:
    """q, src, dst: pairs of the 24 nations whose count reaches the quantile of all counts."""
    g = trade24(spark, sf_dir)
    cuts = g.agg(*[F.percentile("pairs", F.lit(q)).alias(f"q{i}") for i, q in enumerate(quantiles)])
    rows = F.array(*[F.struct(F.lit(q).alias("q"), F.col(f"q{i}").alias("least")) for i, q in enumerate(quantiles)])
    cuts = cuts.select(F.explode(rows).alias("c")).select("c.q", "c.least")  # one row per quantile
    return g.join(F.broadcast(cuts), F.col("pairs") >= F.col("least")).select("q", "src", "dst")


def nation_nodes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """model_id, var_id: five regional models (0 to 4), and the first eight nations as model 100."""
    n = table(spark, sf_dir, "nation")
    regional = n.select(F.col("n_regionkey").cast("long").alias("model_id"), F.col("n_nationkey").cast("long").alias("var_id"))
    first = n.where("n_nationkey < 8").select(F.lit(100).cast("long").alias("model_id"), F.col("n_nationkey").cast("long").alias("var_id"))
    return regional.unionByName(first)


def nation_models(spark: SparkSession, sf_dir: str, coupling: float = 0.06, field: float = 0.2, domain: str = "spin") -> Model:
    """Weakly coupled models: standardised log counts of trade between and of nations."""
    nodes, trade = nation_nodes(spark, sf_dir), trade_graph(spark, sf_dir)
    a = nodes.select("model_id", F.col("var_id").alias("src"))
    b = nodes.select("model_id", F.col("var_id").alias("dst"))
    pairs = a.join(b, "model_id").where("src < dst").join(trade.select("src", "dst", "pairs"), ["src", "dst"], "left")
    per = Window.partitionBy("model_id")

    def standard(x: Column, c: float) -> Column:
        return F.round(F.lit(c) * (x - F.avg(x).over(per)) / F.greatest(F.stddev_pop(x).over(per), F.lit(1e-9)), 6)

    edges = pairs.withColumn("x", F.log(F.coalesce("pairs", F.lit(0)) + F.lit(1.0))).select("model_id", "src", "dst", standard(F.col("x"), coupling).alias("theta"))
    total = trade.select(F.col("src").alias("var_id"), "pairs").unionByName(trade.select(F.col("dst").alias("var_id"), "pairs")).groupBy("var_id").agg(F.sum("pairs").alias("t"))
    own = nodes.join(total, "var_id", "left").withColumn("x", F.log(F.coalesce("t", F.lit(0)) + F.lit(1.0))).select("model_id", "var_id", standard(F.col("x"), field).alias("theta"))
    return Model.pairwise(own, edges, domain)


def positions(nodes: DataFrame) -> DataFrame:
    order = Window.partitionBy("model_id").orderBy("var_id")
    return nodes.select("model_id", "var_id", (F.row_number().over(order) - 1).alias("pos"))


#: Fixed partitions by a node's place in its model.
PARTITIONS = {"pair": "pos div 2", "half": "pos div 4", "stride": "pos % 2", "single": "pos", "whole": "0"}


def fixed_partition(nodes: DataFrame, name: str = "pair") -> DataFrame:
    return positions(nodes).select("model_id", "var_id", F.expr(PARTITIONS[name]).cast("int").alias("cluster"))


def fixed_partitions(nodes: DataFrame) -> DataFrame:
    """All of them, with the name in ``partition``."""
    rows = F.array(*[F.struct(F.lit(n).alias("partition"), F.expr(e).cast("int").alias("cluster")) for n, e in PARTITIONS.items()])
    return positions(nodes).select("model_id", "var_id", F.explode(rows).alias("p")).select("p.partition", "model_id", "var_id", "p.cluster")


def random_graphs(spark: SparkSession, trials: int = 20, n: int = 24, p: float = 0.3, seed: int = 1) -> DataFrame:
    """trial, src, dst: each pair of nodes is an edge with probability p, by hash."""
    pairs = spark.range(trials).withColumnRenamed("id", "trial").select("trial", F.explode(F.sequence(F.lit(0), F.lit(n - 2))).alias("src"))
    pairs = pairs.select("trial", F.col("src").cast("long"), F.explode(F.sequence(F.col("src") + 1, F.lit(n - 1))).alias("dst"))
    pairs = pairs.select("trial", "src", F.col("dst").cast("long"))
    return pairs.where(uniform(seed, F.col("trial"), F.col("src"), F.col("dst")) < p)


def order_members(spark: SparkSession, sf_dir: str) -> DataFrame:
    """trial, var_id: the suppliers of each order, the order as the trial."""
    return table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").cast("long").alias("trial"), F.col("l_suppkey").cast("long").alias("var_id")).distinct()


def order_graphs(spark: SparkSession, sf_dir: str, p: float = 0.3, seed: int = 1) -> DataFrame:
    """trial, src, dst: a random graph over the suppliers of each order; each pair is an edge with probability p, by hash."""
    members = order_members(spark, sf_dir).groupBy("trial").agg(F.array_sort(F.collect_list("var_id")).alias("items"))
    pairs = members.select("trial", "items", F.posexplode("items").alias("i", "src"))
    pairs = pairs.select("trial", "src", F.explode(F.slice("items", F.col("i") + 2, F.size("items"))).alias("dst"))
    return pairs.where(uniform(seed, F.col("trial"), F.col("src"), F.col("dst")) < p)


def couplings(edges: DataFrame, kind: str, strength: float, seed: int = 2) -> DataFrame:
    """trial, src, dst, theta: uniform couplings, ``repulsive`` in (-w, 0), ``mixed`` in (-w, w), ``attractive`` in (0, w)."""
    low, high = {"repulsive": (-strength, 0.0), "mixed": (-strength, strength), "attractive": (0.0, strength)}[kind]
    return edges.select("trial", "src", "dst", F.round(F.lit(low) + F.lit(high - low) * uniform(seed, F.col("trial"), F.col("src"), F.col("dst")), 6).alias("theta"))


def copurchase_graph(spark: SparkSession, sf_dir: str, column: str = "l_partkey", max_basket: int | None = None) -> DataFrame:
    """src, dst, n: pairs of parts (or suppliers) by the orders that have both; baskets beyond ``max_basket`` may be left out on request."""
    # lines meet by order once, for both the distinct items and the baskets
    items = table(spark, sf_dir, "lineitem").select("l_orderkey", F.col(column).alias("item")).repartition("l_orderkey").distinct()
    baskets = items.groupBy("l_orderkey").agg(F.array_sort(F.collect_list("item")).alias("items")).where("size(items) > 1")
    if max_basket:
        baskets = baskets.where(F.size("items") <= max_basket)
    pairs = baskets.select("items", F.posexplode("items").alias("i", "src")).select("src", F.explode(F.slice("items", F.col("i") + 2, F.size("items"))).alias("dst"))
    return pairs.groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n"))


def user_days(spark: SparkSession, sf_dir: str) -> DataFrame:
    """user_id, day, and one 0/1 column per event type."""
    e = table(spark, sf_dir, "events")
    types = ("click", "error", "purchase", "signup", "view")
    return e.groupBy("user_id", F.to_date("ts").alias("day")).agg(*[F.max((F.col("event_type") == t).cast("int")).alias(t) for t in types])


def event_pair_graph(spark: SparkSession, sf_dir: str, per_user: bool = False) -> DataFrame:
    """type_a, type_b, n11, n10, n01, n00, theta: smoothed log-odds of two event types on a user's day, over all or per user."""
    days = user_days(spark, sf_dir)
    types = ("click", "error", "purchase", "signup", "view")
    pairs = F.array(*[F.struct(F.lit(a).alias("type_a"), F.lit(b).alias("type_b"), F.col(a).alias("x"), F.col(b).alias("y")) for i, a in enumerate(types) for b in types[i + 1 :]])
    rows = days.select("user_id", F.explode(pairs).alias("p")).select("user_id", "p.*")
    count = lambda x, y: F.sum(F.when((F.col("x") == x) & (F.col("y") == y), 1).otherwise(0)).alias(f"n{x}{y}")
    keys = ["user_id"] * per_user + ["type_a", "type_b"]
    got = rows.groupBy(*keys).agg(count(1, 1), count(1, 0), count(0, 1), count(0, 0))
    odds = F.log((F.col("n11") + 0.5) * (F.col("n00") + 0.5) / ((F.col("n10") + 0.5) * (F.col("n01") + 0.5)))
    return got.select(*keys, "n11", "n10", "n01", "n00", F.round(odds, 6).alias("theta"))


def user_models(spark: SparkSession, sf_dir: str) -> Model:
    """One five-variable bit model per user; a fifth of the log-odds as couplings."""
    pairs = event_pair_graph(spark, sf_dir, per_user=True)
    number = lambda c: F.array_position(F.array(*[F.lit(t) for t in ("click", "error", "purchase", "signup", "view")]), F.col(c)) - 1
    edges = pairs.select(F.col("user_id").alias("model_id"), number("type_a").alias("src"), number("type_b").alias("dst"), (F.col("theta") / 5).alias("theta"))
    nodes = pairs.select(F.col("user_id").alias("model_id")).distinct().select("model_id", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(4).cast("long"))).alias("var_id"), F.lit(0.0).alias("theta"))
    return Model.pairwise(nodes, edges, "bit")


def near_copy_graph(spark: SparkSession, sf_dir: str, shingle: int = 5, least: float = 0.8) -> DataFrame:
    """src, dst, jaccard: documents that share at least ``least`` of their five-word shingles, in representatives.

    Texts with the same set of shingles are one class under its smallest id, so copies are never expanded into pairs; each
    class is linked by prefix filtering: two sets that similar share one of their rarest shingles.
    """
    from ..plans.similarity import similar_sets

    return similar_sets(table(spark, sf_dir, "documents"), shingle, least).links


def knn_vectors(spark: SparkSession, sf_dir: str, k: int = 10) -> DataFrame:
    """vec_id, nbr, cos: exact nearest vectors of every vector whose id is divisible by 50, against all others.

    The queries are compared in blocks: a block of 256 is one row that travels to all vectors.
    """
    v = table(spark, sf_dir, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("e"))
    queries = v.where("vec_id % 50 = 0").select((F.col("vec_id") / 50 / 256).cast("int").alias("block"), F.struct(F.col("vec_id").alias("q"), F.col("e").alias("x")).alias("row"))
    blocks = queries.groupBy("block").agg(F.collect_list("row").alias("rows"))
    seen = v.join(blocks, F.lit(True)).select("vec_id", "e", F.explode("rows").alias("r")).where("vec_id <> r.q")
    cos = F.round(F.aggregate(F.zip_with("e", "r.x", lambda a, b: a * b), F.lit(0.0), lambda s, x: s + x), 6)
    scored = seen.select(F.col("r.q").alias("vec_id"), F.col("vec_id").alias("nbr"), cos.alias("cos"))
    best = Window.partitionBy("vec_id").orderBy(F.desc("cos"), "nbr")
    return scored.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).drop("rank")


def host_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """src, dst, n: links between hosts, from a page's host to the hosts of its anchors; a path alone stays on its host."""
    host = r"^https?://([^/?#\"'\s]+)"
    pages = table(spark, sf_dir, "pages").select(F.regexp_extract("url", host, 1).alias("src"), F.explode(F.regexp_extract_all("html", F.lit(r"href=[\"']([^\"']+)"), F.lit(1))).alias("href"))
    dst = F.when(F.col("href").startswith("/"), F.col("src")).otherwise(F.regexp_extract("href", host, 1))
    return pages.select("src", dst.alias("dst")).where("src <> '' and dst <> ''").groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n"))


def role_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """src, dst, n: which role follows which inside a conversation."""
    order = Window.partitionBy("conv_id").orderBy("turn", "role", "text")
    c = table(spark, sf_dir, "conversations").select(F.col("role").alias("src"), F.lead("role").over(order).alias("dst"))
    return c.where("src is not null and dst is not null").groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n"))


#: Categorical variables of the tabular workload, in the order of their ids, and the cliques over them.
TABLE6 = ("o_orderstatus", "o_orderpriority", "c_mktsegment", "l_returnflag", "l_linestatus", "r_name")
TABLE6_CLIQUES = ((0, 1), (1, 2), (3, 4), (2, 5), (0, 3, 4), (1, 2, 5))


def table6_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row per line item with the six variables as state numbers x0 to x5, by rank of their values."""
    t = lambda name: table(spark, sf_dir, name)
    rows = t("lineitem").join(t("orders"), F.col("l_orderkey") == F.col("o_orderkey")).join(t("customer"), F.col("o_custkey") == F.col("c_custkey"))
    rows = rows.join(F.broadcast(t("nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(t("region")), F.col("n_regionkey") == F.col("r_regionkey"))
    counted = rows.groupBy(*TABLE6).agg(F.count(F.lit(1)).alias("n"))  # at most 2,250 combinations
    for i, name in enumerate(TABLE6):
        counted = counted.withColumn(f"x{i}", F.dense_rank().over(Window.orderBy(name)) - 1)
    return counted.select(*[f"x{i}" for i in range(6)], "n")


def table6(spark: SparkSession, sf_dir: str, strength: float = 0.2) -> TabularModel:
    """Tabular cliques of two and three members: log of observed over expected counts, rounded."""
    counts = table6_rows(spark, sf_dir)
    tall = counts.select("n", F.posexplode(F.array(*[f"x{i}" for i in range(6)])).alias("var_id", "s"))
    cards = tall.groupBy("var_id").agg((F.max("s") + 1).alias("card"))
    variables = cards.select(F.lit(0).cast("long").alias("model_id"), F.col("var_id").cast("long"), "card")
    potentials = None
    for c, members in enumerate(TABLE6_CLIQUES):
        keys = [f"x{m}" for m in members]
        joint = counts.groupBy(*keys).agg(F.sum("n").alias("n"))
        grid = None
        for m in members:
            card = cards.where(F.col("var_id") == m).select(F.explode(F.sequence(F.lit(0), F.col("card") - 1)).alias(f"x{m}"))
            grid = card if grid is None else grid.crossJoin(card)  # a few states
        full = grid.join(joint, keys, "left").withColumn("n", F.coalesce("n", F.lit(0)))
        everything = Window.partitionBy(F.lit(0))
        expected = F.sum("n").over(everything) / F.count(F.lit(1)).over(everything)
        phi = F.round(F.log((F.col("n") + 1) / (expected + 1)), 6)
        rows = full.select(F.lit(0).cast("long").alias("model_id"), F.lit(c).cast("long").alias("clique_id"), F.array(*keys).cast("array<int>").alias("assignment"), phi.alias("phi"))
        potentials = rows if potentials is None else potentials.unionByName(rows)
    cliques = spark.createDataFrame([(0, c, list(m), strength) for c, m in enumerate(TABLE6_CLIQUES)], "model_id long, clique_id long, members array<long>, theta double")
    return TabularModel.tabular(variables, cliques, potentials)


#: Clusters of the tabular workload's variables.
TABLE6_CLUSTERS = {0: 0, 1: 0, 2: 1, 3: 2, 4: 2, 5: 1}
