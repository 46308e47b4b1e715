"""Graphs beyond dense kernels: components, spanning forests, coarsening, label propagation, spectral iteration, refinement."""

from __future__ import annotations

import itertools

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..storage import Stored
from . import blocks
from .graph import both_ways, ends, few

#: Groups of a coarsened graph beyond which matching goes on; at most twice as many are cut densely.
DENSE_NODES = 1000


def ranked(df: DataFrame, keys: list[str], order: list[Column], name: str) -> DataFrame:
    """``df`` with ``name``: the place of each row, from 1, among those of its keys, by an order without ties.

    Rows are dealt to ranges of keys and order, numbered inside their range, and moved on by what the ranges before hold,
    so no task sees all rows of a key.  The ranges are written once, because their borders come from a sample.
    """
    held = Stored(df.repartitionByRange(*keys, *order).withColumn("_part", F.spark_partition_id())).read()
    counts = held.groupBy(*keys, "_part").agg(F.count(F.lit(1)).alias("_n"))
    earlier = Window.partitionBy(*keys).orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)  # a row a range
    before = counts.select(*keys, "_part", F.coalesce(F.sum("_n").over(earlier), F.lit(0)).alias("_before"))
    inside = F.row_number().over(Window.partitionBy(*keys, "_part").orderBy(*order))
    out = held.withColumn("_in", inside).join(before, [*keys, "_part"])
    return out.withColumn(name, F.col("_before") + F.col("_in")).drop("_part", "_before", "_in")


def components(nodes: DataFrame, edges: DataFrame, max_rounds: int = 64) -> DataFrame:
    """model_id, var_id, component: the smallest node that edges reach.  Labels hook to the smallest around and jump; rounds are logarithmic."""
    pairs = Stored(both_ways(edges.select("model_id", "src", "dst", F.lit(0).alias("w")), "w").select("model_id", "i", "j").distinct())
    now = Stored(nodes.select("model_id", "var_id", F.col("var_id").alias("root")))
    for _ in range(max_rounds):
        label, near = now.read(), pairs.read()
        around = near.join(label.select("model_id", F.col("var_id").alias("j"), "root"), ["model_id", "j"]).groupBy("model_id", F.col("i").alias("var_id")).agg(F.min("root").alias("near"))
        hooked = label.join(around, ["model_id", "var_id"], "left").select("model_id", "var_id", F.col("root").alias("old"), F.least("root", F.coalesce("near", "root")).alias("root"))
        jumped = hooked.join(label.select("model_id", F.col("var_id").alias("root"), F.col("root").alias("up")), ["model_id", "root"]).select("model_id", "var_id", "old", F.least("root", "up").alias("root"))
        after = Stored(jumped)
        changed = after.read().where("root <> old").limit(1).count()
        now = Stored(after.read().select("model_id", "var_id", "root"))
        if not changed:
            return now.read().select("model_id", "var_id", F.col("root").alias("component"))
    raise RuntimeError("components did not settle")


def spanning_forest(edges: DataFrame, assignment: DataFrame, max_rounds: int = 32) -> DataFrame:
    """model_id, cluster_a, cluster_b, src, dst, theta: a maximum spanning forest of the cluster graph, in Boruvka rounds.

    Each round every group of clusters takes its heaviest outgoing edge (ties: smallest ends); groups then merge.
    """
    crossing = ends(edges, assignment).where("c_src <> c_dst")
    order = F.struct(-F.abs("theta"), "src", "dst")
    best = crossing.groupBy("model_id", F.least("c_src", "c_dst").alias("a"), F.greatest("c_src", "c_dst").alias("b")).agg(F.min_by(F.struct("src", "dst", "theta"), order).alias("e"))
    links = Stored(best.select("model_id", "a", "b", "e.src", "e.dst", "e.theta"))
    group = Stored(assignment.select("model_id", F.col("cluster").alias("c"), F.col("cluster").alias("g")).distinct())
    taken = None
    for _ in range(max_rounds):
        g = group.read()
        open_ = links.read().join(g.select("model_id", F.col("c").alias("a"), F.col("g").alias("ga")), ["model_id", "a"]).join(g.select("model_id", F.col("c").alias("b"), F.col("g").alias("gb")), ["model_id", "b"]).where("ga <> gb")
        both = open_.select("model_id", F.col("ga").alias("g"), "a", "b", "src", "dst", "theta").unionByName(open_.select("model_id", F.col("gb").alias("g"), "a", "b", "src", "dst", "theta"))
        picked = Stored(both.groupBy("model_id", "g").agg(F.min_by(F.struct("a", "b", "src", "dst", "theta"), order).alias("e")).select("model_id", "e.*").distinct())
        if not picked.read().limit(1).count():
            break
        taken = picked.read() if taken is None else taken.unionByName(picked.read())
        nodes = g.select("model_id", F.col("c").cast("long").alias("var_id"))
        joined = taken.select("model_id", F.col("a").cast("long").alias("src"), F.col("b").cast("long").alias("dst"))
        merged = components(nodes, joined)
        group = Stored(merged.select("model_id", F.col("var_id").cast("int").alias("c"), F.col("component").cast("int").alias("g")))
    if taken is None:
        taken = links.read().limit(0)
    return taken.select("model_id", F.col("a").alias("cluster_a"), F.col("b").alias("cluster_b"), "src", "dst", "theta")


def heavy_matching(nodes: DataFrame, weighted: DataFrame, cap: float, rounds: int = 12, stop_at: int = 0, at_most: int = 0) -> DataFrame:
    """model_id, var_id, group, mass: nodes merged along heavy edges while a group's mass stays within ``cap``.

    ``nodes`` may have a ``mass`` column (1 if not).  Each round every group proposes to the heaviest neighbour that it fits
    with (ties by a hash of the round); mutual proposals merge.  Rounds end early at ``stop_at`` groups or when none merges,
    and go on while a model has more than ``at_most`` groups, where that is given.

    Where nodes are counted to be few, the rounds run over arrays in blocks of edges (``blocks``), else over tables alone.
    """
    mass = F.col("mass") if "mass" in nodes.columns else F.lit(1.0)
    held = Stored(nodes.select("model_id", "var_id", mass.cast("double").alias("mass"))).read()
    places = blocks.collected(held, held.count())
    first = blocks.adjacency(places, weighted, cap) if places else None
    if first is None:
        return _matched_tables(held, weighted, cap, rounds, stop_at, at_most)
    found = blocks.grouped(held, places, blocks.matched(places, first, cap, rounds, stop_at, at_most))
    first.drop()
    return found


def _matched_tables(nodes: DataFrame, weighted: DataFrame, cap: float, rounds: int, stop_at: int, at_most: int) -> DataFrame:
    """``heavy_matching`` by joins, for any number of nodes."""
    group = Stored(nodes.select("model_id", "var_id", F.col("var_id").alias("group"), F.col("mass").alias("own")))
    masses = Stored(group.read().select("model_id", "group", F.col("own").alias("mass")))
    n = group.read().count()

    def fitting(pairs: DataFrame) -> DataFrame:
        """The pairs that fit together, with their masses, by ranges of src.  Masses only grow, so what does not fit never will."""
        m = lambda end, name: few(masses.read().select("model_id", F.col("group").alias(end), F.col("mass").alias(name)), n)
        return pairs.join(m("src", "m1"), ["model_id", "src"]).join(m("dst", "m2"), ["model_id", "dst"]).where(F.col("m1") + F.col("m2") <= cap).repartitionByRange("model_id", "src")

    coarse = Stored(fitting(weighted.select("model_id", F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"), "weight")))
    largest = 0
    for r in itertools.count():
        if r >= rounds and (not at_most or largest <= at_most):
            break
        # weight for each pair of members, so that large groups do not draw every wish
        fits = coarse.read().select("model_id", "src", "dst", (F.col("weight") / (F.col("m1") * F.col("m2"))).alias("weight"), F.xxhash64(F.lit(r), "src", "dst").alias("h"))
        wishes = fits.select("model_id", F.col("src").alias("i"), F.col("dst").alias("j"), "weight", "h").unionByName(fits.select("model_id", F.col("dst").alias("i"), F.col("src").alias("j"), "weight", "h"))
        # the heaviest first, then the hash among those: numbers alone, which are aggregated without a sort
        top = Stored(wishes.groupBy("model_id", "i").agg(F.max("weight").alias("top")))
        heaviest = wishes.join(few(top.read(), n), ["model_id", "i"]).where(F.col("weight").eqNullSafe(F.col("top")))
        wish = Stored(heaviest.groupBy("model_id", "i").agg(F.max_by("j", "h").alias("j"))).read()
        back = wish.select("model_id", F.col("i").alias("j"), F.col("j").alias("i"))
        matched = Stored(wish.join(back, ["model_id", "i", "j"]).where("i < j").select("model_id", F.col("j").alias("group"), F.col("i").alias("into"))).read()
        if not matched.limit(1).count():
            break
        group = Stored(group.read().join(few(matched, n), ["model_id", "group"], "left").select("model_id", "var_id", F.coalesce("into", "group").alias("group"), "own"))
        masses = Stored(masses.read().join(few(matched, n), ["model_id", "group"], "left").groupBy("model_id", F.coalesce("into", "group").alias("group")).agg(F.sum("mass").alias("mass")))
        if stop_at or at_most:
            largest = masses.read().groupBy("model_id").count().agg(F.max("count")).first()[0]
        if stop_at and largest <= stop_at:
            break
        # the contracted graph takes the place of the last one, so the input is read once
        a, b = (few(matched.select("model_id", F.col("group").alias(e), F.col("into").alias(f"{e}_into")), n) for e in ("src", "dst"))
        ends_now = coarse.read().join(a, ["model_id", "src"], "left").join(b, ["model_id", "dst"], "left").select("model_id", F.coalesce("src_into", "src").alias("x"), F.coalesce("dst_into", "dst").alias("y"), "weight")
        merged = fitting(ends_now.where("x <> y").select("model_id", F.least("x", "y").alias("src"), F.greatest("x", "y").alias("dst"), "weight"))
        last, coarse = coarse, Stored(merged.groupBy("model_id", "src", "dst").agg(F.sum("weight").alias("weight"), F.max("m1").alias("m1"), F.max("m2").alias("m2")))
        last.drop()
    coarse.drop()
    return group.read().select("model_id", "var_id", "group", F.col("own").alias("mass"))


def bounded(group: DataFrame, at_most: int) -> DataFrame:
    """The groups of ``heavy_matching``, at most twice ``at_most`` in a model: those of less than a share of the mass are packed by rank."""
    mass = Stored(group.groupBy("model_id", "group").agg(F.sum("mass").alias("m")))
    total = mass.read().groupBy("model_id").agg(F.count(F.lit(1)).alias("n"), F.sum("m").alias("all")).where(F.col("n") > at_most)
    light = mass.read().join(total, "model_id").where(F.col("m") * at_most <= F.col("all")).select("model_id", "group", "m")
    placed = Stored(ranked(light, ["model_id"], [F.col("m"), F.col("group")], "r"))
    into = placed.read().select("model_id", "group", F.pmod("r", F.lit(at_most)).alias("bin"))
    named = into.groupBy("model_id", "bin").agg(F.min("group").alias("into"))
    return group.join(into.join(named, ["model_id", "bin"]).drop("bin"), ["model_id", "group"], "left").select("model_id", "var_id", F.coalesce("into", "group").alias("group"), "mass")


def merged_clusters(nodes: DataFrame, weighted: DataFrame, cap: float, balance: str = "nodes", rounds: int = 12) -> DataFrame:
    """model_id, var_id, cluster: clusters of any number whose cost stays within a cap, grown along heavy edges.

    ``balance``: ``nodes`` caps their number, ``states`` the joint states (nodes may have ``card``), ``edges`` half the degrees inside.
    """
    if balance == "states":
        import math

        card = F.col("card") if "card" in nodes.columns else F.lit(2)
        nodes, cap = nodes.withColumn("mass", F.log2(card.cast("double"))), math.log2(cap)
    elif balance == "edges":
        d = both_ways(weighted).groupBy("model_id", F.col("i").alias("var_id")).agg((F.count(F.lit(1)) / 2.0).alias("mass"))
        nodes = nodes.select("model_id", "var_id").join(d, ["model_id", "var_id"], "left").fillna(0.0, ["mass"])
    found = heavy_matching(nodes, weighted, cap, rounds)
    found = Stored(found).read()
    named = ranked(found.select("model_id", "group").distinct(), ["model_id"], [F.col("group")], "r")
    return found.join(named, ["model_id", "group"]).select("model_id", "var_id", (F.col("r") - 1).cast("int").alias("cluster"))


def rebalance(nodes: DataFrame, weighted: DataFrame, assignment: DataFrame, k: int, held: tuple[blocks.Nodes, blocks.Adjacency] | None = None) -> DataFrame:
    """The assignment with sizes that differ by one at most: nodes least tied to an overfull cluster move to free places.

    Places are matched by rank, so sizes come out exact in one pass.  ``held``: the graph in blocks, where it is.
    """
    assignment = Stored(assignment).read()
    tie = blocks.ties(held[1], held[0], blocks.labels(assignment, held[0], "cluster")) if held else _ties(weighted, assignment)
    return _rebalanced(assignment, tie, k)


def _ties(weighted: DataFrame, assignment: DataFrame) -> DataFrame:
    n = assignment.count()
    inside = both_ways(weighted).join(few(assignment.select("model_id", F.col("var_id").alias("i"), F.col("cluster").alias("ci")), n), ["model_id", "i"]).join(few(assignment.select("model_id", F.col("var_id").alias("j"), F.col("cluster").alias("cj")), n), ["model_id", "j"])
    return inside.groupBy("model_id", F.col("i").alias("var_id")).agg(F.sum(F.when(F.col("ci") == F.col("cj"), F.col("weight")).otherwise(0.0)).alias("tie"))


def _rebalanced(assignment: DataFrame, tie: DataFrame, k: int) -> DataFrame:
    total = assignment.groupBy("model_id").agg(F.count(F.lit(1)).alias("n"))
    all_clusters = total.select("model_id", "n", F.explode(F.sequence(F.lit(0), F.lit(k - 1))).alias("cluster"))
    sizes = assignment.groupBy("model_id", "cluster").agg(F.count(F.lit(1)).alias("m"))
    by_size = Window.partitionBy("model_id").orderBy(F.desc("m"), "cluster")
    room = all_clusters.join(sizes, ["model_id", "cluster"], "left").fillna(0, ["m"]).withColumn("r", F.row_number().over(by_size))
    room = room.select("model_id", "cluster", "m", (F.floor(F.col("n") / k) + (F.col("r") <= F.col("n") % k).cast("int")).alias("cap"))
    placed = ranked(assignment.join(tie, ["model_id", "var_id"], "left").fillna(0.0, ["tie"]), ["model_id", "cluster"], [F.desc("tie"), F.col("var_id")], "r").join(room, ["model_id", "cluster"])
    free = room.where("m < cap").select("model_id", F.col("cluster").alias("to"), F.explode(F.sequence(F.lit(1), (F.col("cap") - F.col("m")).cast("int"))).alias("s"))
    free = ranked(free, ["model_id"], [F.col("to"), F.col("s")], "slot")
    out = ranked(placed.where("r > cap").select("model_id", "var_id", "cluster", "r"), ["model_id"], [F.col("cluster"), F.col("r")], "slot").select("model_id", "var_id", "slot")
    moved = out.join(free, ["model_id", "slot"]).select("model_id", "var_id", F.col("to").cast("int").alias("cluster"))
    return placed.where("r <= cap").select("model_id", "var_id", F.col("cluster").cast("int").alias("cluster")).unionByName(moved)


def _moves(weighted: DataFrame, a: DataFrame, n: int, sign: float, r: int) -> DataFrame:
    pull = both_ways(weighted).join(few(a.select("model_id", F.col("var_id").alias("j"), F.col("cluster").alias("c")), n), ["model_id", "j"]).groupBy("model_id", F.col("i").alias("var_id"), "c").agg(F.sum("weight").alias("w"))
    pull = Stored(pull).read()  # read twice
    own = a.join(pull.withColumnRenamed("c", "cluster"), ["model_id", "var_id", "cluster"], "left").fillna(0.0, ["w"]).withColumnRenamed("w", "own")
    wish = own.join(pull, ["model_id", "var_id"]).where("c <> cluster").withColumn("gain", F.lit(sign) * (F.col("w") - F.col("own")))
    return wish.where(F.pmod(F.xxhash64(F.lit(r), "var_id"), F.lit(2)) == 0).groupBy("model_id", "var_id", "cluster").agg(F.max_by(F.struct("c", "gain"), F.struct("gain", -F.col("c"))).alias("b")).select("model_id", "var_id", "cluster", F.col("b.c").alias("to"), "b.gain")


def refine(weighted: DataFrame, assignment: DataFrame, sense: str = "min", rounds: int = 4, held: tuple[blocks.Nodes, blocks.Adjacency] | None = None) -> DataFrame:
    """Pair swaps between clusters in rounds, sizes unchanged.

    Each node names the cluster that it would gain most from; for every pair of clusters, wishes in either direction are ranked
    by gain and swapped by equal rank where the sum is positive.  Half of the nodes, by a hash of the round, may move.
    ``held``: the graph in blocks, where it is.
    """
    sign = 1.0 if sense == "min" else -1.0
    now = Stored(assignment.select("model_id", "var_id", F.col("cluster").cast("int").alias("cluster")))
    n = now.read().count()
    for r in range(rounds):
        a = now.read()
        wish = blocks.moves(held[1], held[0], blocks.labels(a, held[0], "cluster"), sign, r) if held else _moves(weighted, a, n, sign, r)
        wish = Stored(wish).read()  # read twice
        wishes = wish.withColumn("r", F.row_number().over(Window.partitionBy("model_id", "cluster", "to").orderBy(F.desc("gain"), "var_id")))
        other = wishes.select("model_id", F.col("cluster").alias("to"), F.col("to").alias("cluster"), "r", F.col("gain").alias("gain2"))
        swaps = Stored(wishes.join(other, ["model_id", "cluster", "to", "r"]).where(F.col("gain") + F.col("gain2") > 1e-9).select("model_id", "var_id", F.col("to").alias("new")))
        if not swaps.read().limit(1).count():
            break
        now = Stored(a.join(swaps.read(), ["model_id", "var_id"], "left").select("model_id", "var_id", F.coalesce("new", "cluster").cast("int").alias("cluster")))
    return now.read()


def _between(weighted: DataFrame, group: DataFrame, n: int) -> DataFrame:
    """model_id, a, b, theta: summed weights between groups."""
    a = few(group.select("model_id", F.col("var_id").alias("src"), F.col("group").alias("ga")), n)
    b = few(group.select("model_id", F.col("var_id").alias("dst"), F.col("group").alias("gb")), n)
    return weighted.join(a, ["model_id", "src"]).join(b, ["model_id", "dst"]).where("ga <> gb").groupBy("model_id", F.least("ga", "gb").alias("a"), F.greatest("ga", "gb").alias("b")).agg(F.sum("weight").alias("theta"))


def coarse_partition(nodes: DataFrame, weighted: DataFrame, k: int, sense: str = "min", coarse_nodes: int = 200, rounds: int = 4) -> DataFrame:
    """model_id, var_id, cluster of large graphs: coarsen by heavy matching, cut the coarse graph densely, project, balance, refine.

    For ``max`` the graph is not coarsened along edges: a balanced hash partition is refined instead.
    """
    import numpy as np
    import pandas as pd

    from ..shipping import ship
    from . import dense
    from .graph import random_partition
    from .inference import arrays

    nodes = Stored(nodes.select("model_id", "var_id")).read()
    n = nodes.count()
    largest = nodes.groupBy("model_id").count().agg(F.max("count")).first()[0] if n else 0
    cap = max(1.0, largest / k / 2)
    ones = nodes.withColumn("mass", F.lit(1.0))
    places = blocks.collected(ones, n)
    # built once, for the matching, the places of the balance and every round of swaps
    first = blocks.adjacency(places, weighted, cap) if places else None
    held = (places, first) if first else None
    if not held:
        weighted = Stored(weighted.repartitionByRange("model_id", "src")).read()
    if sense == "max":
        return refine(weighted, random_partition(nodes, k), "max", rounds, held)
    ship(nodes.sparkSession)
    # the dense kernel takes the square of the groups, so their number is bounded, however large or scattered the graph is
    if held:
        found = blocks.grouped(ones, places, blocks.matched(places, first, cap, 24, coarse_nodes, DENSE_NODES))
    else:
        found = _matched_tables(ones, weighted, cap, 24, coarse_nodes, DENSE_NODES)
    group = Stored(bounded(Stored(found).read(), DENSE_NODES)).read()
    edges = blocks.between(first, places, places.finder()(places.model, blocks.labels(group, places, "group", long=True))) if held else _between(weighted, group, n)
    masses = group.groupBy("model_id", "group").agg(F.sum("mass").alias("theta"))
    packed = masses.select("model_id", F.col("group").alias("a"), F.lit(None).cast("long").alias("b"), "theta", F.lit(0).alias("cluster")).unionByName(edges.select("model_id", "a", "b", "theta", F.lit(None).cast("int").alias("cluster")))

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        ids, mass, w, _ = arrays(pdf)
        points = dense.spectral_points(w, min(k, len(ids)), "min") if len(ids) > k else np.eye(len(ids))
        rng = np.random.default_rng(0)
        best = None
        for _ in range(10):
            centre = points[rng.choice(len(ids), min(k, len(ids)), replace=False)]
            for _ in range(20):
                far = ((points[:, None] - centre[None]) ** 2).sum(2)
                labels, room = np.full(len(ids), -1), np.full(k, mass.sum() / k * 1.05 + mass.max() / 2)
                for i in np.argsort(-mass, kind="stable"):
                    order = np.argsort(far[i], kind="stable")
                    c = next((x for x in order if room[x] >= mass[i]), int(room.argmax()))
                    labels[i] = c
                    room[c] -= mass[i]
                centre = np.stack([points[labels == c].mean(0) if (labels == c).any() else centre[c] for c in range(len(centre))])
            cut = dense.cut_value(w, labels)
            if best is None or cut < best[0]:
                best = (cut, labels)
        return pd.DataFrame({"model_id": pdf["model_id"].iloc[0], "group": ids, "cluster": best[1]})

    coarse = packed.groupBy("model_id").applyInPandas(run, "model_id long, group long, cluster int")
    start = Stored(group.join(coarse, ["model_id", "group"]).select("model_id", "var_id", "cluster")).read()
    balanced = Stored(rebalance(nodes, weighted, start, k, held)).read()
    return refine(weighted, balanced, "min", rounds, held)


def label_propagation(nodes: DataFrame, weighted: DataFrame, k: int, rounds: int = 5, seed: int = 1) -> DataFrame:
    """Size-capped label propagation from a balanced hash partition: a node takes the label that weighs most around it where its rank fits."""
    from .graph import random_partition

    nodes, weighted = Stored(nodes.select("model_id", "var_id")).read(), Stored(weighted).read()
    start = Stored(random_partition(nodes, k, seed))
    for _ in range(rounds):
        a = start.read()
        pull = both_ways(weighted).join(a.select("model_id", F.col("var_id").alias("j"), "cluster"), ["model_id", "j"]).groupBy("model_id", F.col("i").alias("var_id"), "cluster").agg(F.sum("weight").alias("w"))
        best = pull.groupBy("model_id", "var_id").agg(F.max_by(F.struct("cluster", "w"), F.struct("w", -F.col("cluster"))).alias("b"))
        wish = a.join(best, ["model_id", "var_id"], "left").select("model_id", "var_id", F.col("cluster").alias("old"), F.coalesce("b.cluster", "cluster").alias("cluster"), F.coalesce("b.w", F.lit(0.0)).alias("w"))
        size = nodes.groupBy("model_id").agg(F.ceil(F.count(F.lit(1)) / k * 1.1).alias("cap"))
        placed = ranked(wish, ["model_id", "cluster"], [F.desc("w"), F.col("var_id")], "r").join(size, "model_id")
        start = Stored(placed.select("model_id", "var_id", F.when(F.col("r") <= F.col("cap"), F.col("cluster")).otherwise(F.col("old")).alias("cluster")))
    return rebalance(nodes, weighted, start.read(), k)


def spectral_bisection(nodes: DataFrame, weighted: DataFrame, sense: str = "min", rounds: int = 30, tol: float = 1e-4) -> DataFrame:
    """Two equal halves by an extreme eigenvector of the Laplacian, found by power iteration; a product is one join and one sum,
    with the vector broadcast where its nodes are counted to be few.

    It ends when three products move the unit vector by less than ``tol`` in every model, or after ``rounds`` products.

    ``min`` iterates on (2 d_max - L), which brings out the second smallest eigenvector; ``max`` on L itself.
    """
    from ..hashing import uniform

    nodes = Stored(nodes.select("model_id", "var_id")).read()
    size = nodes.count()
    # by ranges of i, so that a product's sums are nearly done before they are shuffled
    pairs = Stored(both_ways(weighted).repartitionByRange("model_id", "i")).read()
    found = pairs.groupBy("model_id", F.col("i").alias("var_id")).agg(F.sum("weight").alias("d"))
    deg = Stored(nodes.join(found, ["model_id", "var_id"], "left").fillna(0.0, ["d"]))
    top = Stored(deg.read().groupBy("model_id").agg((2 * F.max("d")).alias("shift"), F.count(F.lit(1)).alias("n"))).read()
    # a row a model: broadcast where they are counted to be few, so that the nodes of a large model do not meet in one task
    models = top.count()
    x = Stored(nodes.select("model_id", "var_id", (uniform(11, F.col("var_id")) - 0.5).alias("x")))
    # the constant vector and the norm are taken out once for three products
    for step in range(-(-rounds // 3)):
        now = x.read().select("model_id", "var_id", "x", F.col("x").alias("was"))
        for _ in range(min(3, rounds - 3 * step)):
            ax = pairs.join(few(now.select("model_id", F.col("var_id").alias("j"), "x"), size), ["model_id", "j"]).groupBy("model_id", F.col("i").alias("var_id")).agg(F.sum(F.col("weight") * F.col("x")).alias("ax"))
            lx = now.join(deg.read(), ["model_id", "var_id"]).join(ax, ["model_id", "var_id"], "left").join(few(top, models), "model_id").withColumn("lx", F.col("d") * F.col("x") - F.coalesce("ax", F.lit(0.0)))
            part = F.col("x") - F.col("lx") / F.col("shift") if sense == "min" else F.col("lx") / F.col("shift")
            now = Stored(lx.select("model_id", "var_id", F.when(F.col("shift") > 0, part).otherwise(F.col("x")).alias("x"), "was")).read()
        y = now.withColumnRenamed("x", "y")
        stats = y.groupBy("model_id").agg(F.avg("y").alias("mean"), F.sqrt(F.greatest(F.sum(F.col("y") * F.col("y")) - F.count(F.lit(1)) * F.pow(F.avg("y"), 2), F.lit(1e-300))).alias("norm"))
        x = Stored(y.join(few(stats, models), "model_id").select("model_id", "var_id", ((F.col("y") - F.col("mean")) / F.col("norm")).alias("x"), "was"))
        # both operators have no negative eigenvalue here, so the sign stays
        moved = x.read().groupBy("model_id").agg(F.sum(F.pow(F.col("x") - F.col("was"), 2)).alias("m")).agg(F.max("m")).first()[0] or 0.0
        if moved < tol * tol:
            break
    placed = ranked(x.read().select("model_id", "var_id", "x"), ["model_id"], [F.col("x"), F.col("var_id")], "r").join(few(top, models), "model_id")
    return placed.select("model_id", "var_id", (2 * F.col("r") > F.col("n") + 1).cast("int").alias("cluster"))
