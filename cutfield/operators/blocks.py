"""Graphs whose nodes are counted to be few: edges as numpy arrays in blocks, arrays over the nodes broadcast.

Every edge is held in both directions, by the place of its first node; a block has all edges of its nodes, so what a node wishes
or is tied to is found inside one task.  Edges, whose number is not bounded, stay distributed; the driver holds some numbers a node.
"""

from __future__ import annotations

import itertools
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..shipping import ship
from ..storage import Stored
from .graph import BROADCAST_NODES

#: Edges, in one direction, that a block holds on average.
BLOCK_EDGES = 1_500_000

#: At most so many blocks: their numbers are sorted as 16-bit integers.
MOST_BLOCKS = 30_000

EDGES = "block int, i binary, j binary, w binary"
#: The edges of a block, or what its nodes wish: the nodes, the best neighbour of each, and the number of edges.
STATE = "i binary, j binary, w binary, who binary, best binary, edges long"


@dataclass
class Nodes:
    """Nodes in the order of model and id; the place of a node stands for it."""

    model: np.ndarray
    ids: np.ndarray
    mass: np.ndarray

    def finder(self) -> Finder:
        return Finder(self.model, self.ids)


class Finder:
    """Places of nodes by model and id, -1 for what is not a node."""

    def __init__(self, model: np.ndarray, ids: np.ndarray):
        self.models, at_model = np.unique(model, return_inverse=True)
        self.ids = np.unique(ids)
        self.low = int(self.ids[0]) if len(self.ids) else 0
        span = int(self.ids[-1]) - self.low + 1 if len(self.ids) else 0
        self.slot = None
        if span <= 4 * len(self.ids):
            self.slot = np.full(span, -1, np.int32)
            self.slot[self.ids - self.low] = np.arange(len(self.ids), dtype=np.int32)
        # with one model, the place among the ids is the place among the nodes
        self.keys = None if len(self.models) == 1 else at_model * len(self.ids) + self._id(ids)

    def _id(self, ids: np.ndarray) -> np.ndarray:
        if self.slot is not None:
            inside = (ids >= self.low) & (ids <= self.low + (len(self.slot) - 1))
            return np.where(inside, self.slot[np.where(inside, ids - self.low, 0)], -1)
        at = np.minimum(np.searchsorted(self.ids, ids), len(self.ids) - 1)
        return np.where(self.ids[at] == ids, at, -1)

    def __call__(self, model: np.ndarray, ids: np.ndarray) -> np.ndarray:
        if not len(self.ids):
            return np.full(len(ids), -1, np.int32)
        m = np.minimum(np.searchsorted(self.models, model), len(self.models) - 1)
        at = np.where(self.models[m] == model, self._id(ids), -1)
        if self.keys is not None:
            key = m * len(self.ids) + at
            place = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
            at = np.where((at >= 0) & (self.keys[place] == key), place, -1)
        return at.astype(np.int32)


def hashed(seed: int, *longs: np.ndarray) -> np.ndarray:
    """Spark's ``xxhash64`` of an integer and of columns of longs."""
    p1, p2, p3, p4, p5 = (np.uint64(x) for x in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))
    turn = lambda x, by: (x << np.uint64(by)) | (x >> np.uint64(64 - by))

    def mix(h):
        h = (h ^ (h >> np.uint64(33))) * p2
        h = (h ^ (h >> np.uint64(29))) * p3
        return h ^ (h >> np.uint64(32))

    with np.errstate(over="ignore"):
        h = np.full(1, 42, np.uint64) + p5 + np.uint64(4)
        h = mix(turn(h ^ (np.uint64(seed & 0xFFFFFFFF) * p1), 23) * p2 + p3)
        for x in longs:
            k = turn(x.astype(np.int64).view(np.uint64) * p2, 31) * p1
            h = mix(turn((h + p5 + np.uint64(8)) ^ k, 27) * p1 + p4)
    return h.view(np.int64)


def _packed(w: np.ndarray) -> bytes:
    """Weights in half the bytes where nothing is lost."""
    half = w.astype(np.float32)
    return half.tobytes() if (half == w).all() else w.tobytes()


def _read(i: bytes, j: bytes, w: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    return np.frombuffer(i, np.int32), np.frombuffer(j, np.int32), np.frombuffer(w, np.float32 if len(w) == len(i) else np.float64).astype(np.float64)


def _rows(batch: pa.RecordBatch) -> Iterator[tuple]:
    for k in range(batch.num_rows):
        yield tuple(batch.column(c)[k].as_py() for c in range(batch.num_columns))


def _dealt(i: np.ndarray, j: np.ndarray, w: np.ndarray, blocks: int) -> Iterator[pa.RecordBatch]:
    """The edges by the block of their first node."""
    owner = (i % blocks).astype(np.int16)
    half = w.astype(np.float32)
    order = np.argsort(owner, kind="stable")
    i, j, w = i[order], j[order], (half if (half == w).all() else w)[order]
    ends = np.cumsum(np.bincount(owner, minlength=blocks))
    parts = [(b, int(s), int(e)) for b, (s, e) in enumerate(zip(np.r_[0, ends[:-1]], ends)) if e > s]
    if parts:
        columns = [pa.array([b for b, _, _ in parts], pa.int32())]
        columns += [pa.array([x[s:e].tobytes() for _, s, e in parts], pa.binary()) for x in (i, j, w)]
        yield pa.RecordBatch.from_arrays(columns, ["block", "i", "j", "w"])


def _split(finder, blocks: int) -> Callable:
    """Rows of model, src, dst and weight to blocks of edges in both directions; an edge needs both nodes, and two of them."""

    def run(batches):
        find, held, n = finder.value, [], 0
        for batch in batches:
            model, src, dst, w = (batch.column(c).to_numpy(zero_copy_only=False) for c in range(4))
            x, y = find(model, src), find(model, dst)
            ok = (x >= 0) & (y >= 0) & (x != y)
            held.append((x[ok], y[ok], w[ok]))
            n += len(x)
            if n * 2 >= BLOCK_EDGES:
                x, y, w = (np.concatenate(p) for p in zip(*held))
                yield from _dealt(np.r_[x, y], np.r_[y, x], np.r_[w, w], blocks)
                held, n = [], 0
        if held:
            x, y, w = (np.concatenate(p) for p in zip(*held))
            yield from _dealt(np.r_[x, y], np.r_[y, x], np.r_[w, w], blocks)

    return run


def _moved(arrays, cap: float | None, blocks: int) -> Callable:
    """Edges between what their nodes have gone into; those that do not fit are left out."""

    def run(batches):
        _, mass, into = arrays.value
        for batch in batches:
            for row in _rows(batch):
                i, j, w = _read(*row)
                i, j = into[i], into[j]
                ok = i != j
                if cap is not None:
                    ok &= mass[i] + mass[j] <= cap
                yield from _dealt(i[ok], j[ok], w[ok], blocks)

    return run


def _order(key: np.ndarray, most: int) -> np.ndarray:
    """The places of the keys in order; keys below ``most`` are sorted with their places in one number, where both have room."""
    bits = len(key).bit_length()
    if most >> (62 - bits):
        return np.argsort(key)
    return np.sort((key << bits) | np.arange(len(key))) & ((1 << bits) - 1)


def _gathered(arrays, blocks: int, cap: float | None, r: int, merge: bool) -> Callable:
    """The edges of a block in order, parallel ones summed where ``merge``, and the wishes of its nodes where there is a cap."""

    def run(batches):
        ids, mass, _ = arrays.value
        parts = [_read(*row[1:]) for batch in batches for row in _rows(batch)]
        if not parts:
            return
        i, j, w = (np.concatenate(p) for p in zip(*parts))
        del parts
        key = (i // blocks).astype(np.int64) * len(ids) + j
        home = int(i[0]) % blocks
        # sums of fractions depend on their order, which is then that of the weights, alike seen from either end
        whole = not merge or (w == np.rint(w)).all()
        order = _order(key, (len(ids) // blocks + 1) * len(ids)) if whole else np.lexsort((w, key))
        key, w = key[order], w[order]
        if merge:
            starts = np.flatnonzero(np.r_[True, key[1:] != key[:-1]])
            key, w = key[starts], np.add.reduceat(w, starts)
        del order
        i = key // len(ids)
        j = (key - i * len(ids)).astype(np.int32)
        i = (i * blocks + home).astype(np.int32)
        del key
        who, best = _wishes(i, j, w, ids, mass, cap, r) if cap is not None else (i[:0], j[:0])
        none = [None]
        yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in ((none, pa.binary()), (none, pa.binary()), (none, pa.binary()), ([who.tobytes()], pa.binary()), ([best.tobytes()], pa.binary()), ([len(i)], pa.int64()))], ["i", "j", "w", "who", "best", "edges"])
        yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in (([i.tobytes()], pa.binary()), ([j.tobytes()], pa.binary()), ([_packed(w)], pa.binary()), (none, pa.binary()), (none, pa.binary()), (none, pa.int64()))], ["i", "j", "w", "who", "best", "edges"])

    return run


def _wishes(i, j, w, ids, mass, cap: float, r: int) -> tuple[np.ndarray, np.ndarray]:
    """Of each node with an edge that fits, the neighbour of most weight for each pair of members, ties by a hash of the round."""
    a, b = mass[i], mass[j]
    fits = a + b <= cap
    if not fits.all():
        i, j, w, a, b = i[fits], j[fits], w[fits], a[fits], b[fits]
    if not len(i):
        return i, j

    def ties() -> np.ndarray:
        out, step = np.empty(len(i), np.int64), 1 << 14  # what is computed on the way stays in the cache
        for at in range(0, len(i), step):
            x, y = ids[i[at : at + step]], ids[j[at : at + step]]
            out[at : at + step] = hashed(r, np.minimum(x, y), np.maximum(x, y))
        return out

    for value in (lambda: w / (a * b), ties):
        v = value()
        starts = np.flatnonzero(np.r_[True, i[1:] != i[:-1]])
        top = np.repeat(np.maximum.reduceat(v, starts), np.diff(np.r_[starts, len(i)]))
        keep = v == top
        i, j = i[keep], j[keep]
    first = np.flatnonzero(np.r_[True, i[1:] != i[:-1]])  # parallel edges have the same hash
    return i[first], j[first]


class Adjacency:
    """Edges in blocks, and for each node the neighbour that it wishes to merge with, or -1."""

    def __init__(self, spark: SparkSession, dealt: DataFrame, blocks: int, arrays, cap: float | None, r: int, merge: bool):
        self.spark = spark
        self.table = Stored(dealt.repartitionById(blocks, F.col("block")).mapInArrow(_gathered(arrays, blocks, cap, r, merge), STATE))
        self.best = np.full(len(arrays.value[0]), -1, np.int32)
        self.edges = 0
        for who, best, edges in _rows_of(self.table.read().where("edges is not null").select("who", "best", "edges")):
            self.best[np.frombuffer(who, np.int32)] = np.frombuffer(best, np.int32)
            self.edges += edges

    def read(self) -> DataFrame:
        return self.table.read().where("edges is null").select("i", "j", "w")

    def moved(self, nodes: Nodes, mass: np.ndarray, into: np.ndarray, cap: float | None, r: int) -> Adjacency:
        """The contracted graph."""
        arrays = self.spark.sparkContext.broadcast((nodes.ids, mass, into))
        blocks = _blocks(self.edges)
        out = Adjacency(self.spark, self.read().mapInArrow(_moved(arrays, cap, blocks), EDGES), blocks, arrays, cap, r, True)
        arrays.unpersist()
        if self.edges > BLOCK_EDGES:
            self.spark.sparkContext._jvm.System.gc()  # Spark removes a round's shuffle files once its plan is collected
        return out

    def drop(self) -> None:
        self.table.drop()


def _rows_of(df: DataFrame) -> Iterator[tuple]:
    for batch in df.toArrow().to_batches():
        yield from _rows(batch)


def _blocks(edges: int) -> int:
    return min(MOST_BLOCKS, max(1, -(-edges // BLOCK_EDGES)))


def collected(nodes: DataFrame, n: int) -> Nodes | None:
    """The nodes (model_id, var_id, mass), where they are counted to be few, are all different and have a mass."""
    if not 0 < n <= BROADCAST_NODES:
        return None
    got = nodes.select(F.col("model_id").cast("long"), F.col("var_id").cast("long"), F.col("mass").cast("double")).toArrow()
    if any(c.null_count for c in got.columns):
        return None
    model, ids, mass = (c.to_numpy() for c in got.columns)
    order = np.lexsort((ids, model))
    model, ids, mass = model[order], ids[order], mass[order]
    same = (model[1:] == model[:-1]) & (ids[1:] == ids[:-1])
    return None if same.any() or not (mass > 0).all() else Nodes(model, ids, mass)


def adjacency(nodes: Nodes, weighted: DataFrame, cap: float | None) -> Adjacency | None:
    """The edges in blocks, with the wishes of round 0; None where a weight is missing or not a number."""
    spark = weighted.sparkSession
    weighted = weighted.select(*[F.col(c).cast("long") for c in ("model_id", "src", "dst")], F.col("weight").cast("double"))
    odd = F.col("weight").isNull() | F.isnan("weight") | F.col("model_id").isNull() | F.col("src").isNull() | F.col("dst").isNull()
    count, bad = weighted.agg(F.count(F.lit(1)), F.count(F.when(odd, 1))).first()
    if bad:
        return None
    ship(spark)
    blocks = _blocks(2 * count)
    finder = spark.sparkContext.broadcast(nodes.finder())
    arrays = spark.sparkContext.broadcast((nodes.ids, nodes.mass, None))
    out = Adjacency(spark, weighted.mapInArrow(_split(finder, blocks), EDGES), blocks, arrays, cap, 0, False)
    finder.unpersist()
    arrays.unpersist()
    return out


def matched(nodes: Nodes, first: Adjacency, cap: float, rounds: int, stop_at: int, at_most: int) -> np.ndarray:
    """For each node the place that stands for its group, by the rounds of ``scale.heavy_matching``; ``first`` is left."""
    n = len(nodes.ids)
    group, mass, alive, now, largest = np.arange(n, dtype=np.int32), nodes.mass, np.ones(n, bool), first, 0
    model = np.unique(nodes.model, return_inverse=True)[1]
    for r in itertools.count(1):
        i = np.flatnonzero(now.best >= 0)
        i = i[(now.best[now.best[i]] == i) & (i < now.best[i])]
        if r > rounds and (not at_most or largest <= at_most) or not len(i):
            break
        into = np.arange(n, dtype=np.int32)
        into[now.best[i]] = i
        alive[now.best[i]] = False
        group, mass = into[group], np.bincount(into, mass, n)
        largest = int(np.bincount(model[alive]).max())
        if stop_at and largest <= stop_at or r >= rounds and (not at_most or largest <= at_most):
            break
        last, now = now, now.moved(nodes, mass, into, cap, r)
        if last is not first:
            last.drop()
    if now is not first:
        now.drop()
    return group


def _with_finder(df: DataFrame, nodes: Nodes, values: np.ndarray, run: Callable, schema: str) -> DataFrame:
    context = df.sparkSession.sparkContext
    ship(df.sparkSession)
    return df.mapInArrow(run(context.broadcast((nodes.finder(), nodes.ids, values))), schema)


def grouped(df: DataFrame, nodes: Nodes, group: np.ndarray) -> DataFrame:
    """model_id, var_id, group, mass of the nodes of ``df``."""

    def run(held):
        def each(batches):
            find, ids, values = held.value
            for b in batches:
                at = find(b.column(0).to_numpy(), b.column(1).to_numpy())
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(ids[values[at]]), b.column(2)], ["model_id", "var_id", "group", "mass"])

        return each

    df = df.select(F.col("model_id").cast("long"), F.col("var_id").cast("long"), F.col("mass").cast("double"))
    return _with_finder(df, nodes, group, run, "model_id long, var_id long, group long, mass double")


def labels(df: DataFrame, nodes: Nodes, column: str, long: bool = False) -> np.ndarray:
    """A column of a table of nodes, as an array by their places."""
    got = df.select(F.col("model_id").cast("long"), F.col("var_id").cast("long"), F.col(column).cast("long")).toArrow()
    model, ids, value = (c.to_numpy() for c in got.columns)
    out = np.zeros(len(nodes.ids), np.int64)
    out[nodes.finder()(model, ids)] = value
    return out if long else out.astype(np.int32)


def between(first: Adjacency, nodes: Nodes, group: np.ndarray) -> DataFrame:
    """model_id, a, b, theta: summed weights between groups, each pair once; ``group`` by places."""
    moved = first.moved(nodes, nodes.mass, group, None, 0)
    held = first.spark.sparkContext.broadcast((nodes.model, nodes.ids))

    def run(batches):
        model, ids = held.value
        for batch in batches:
            for row in _rows(batch):
                i, j, w = _read(*row)
                once = i < j
                i, j, w = i[once], j[once], w[once]
                yield pa.RecordBatch.from_arrays([pa.array(x) for x in (model[i], ids[i], ids[j], w)], ["model_id", "a", "b", "theta"])

    return moved.read().mapInArrow(run, "model_id long, a long, b long, theta double")


def _sums(i, j, w, cluster: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Nodes of a block, the weight of each to every cluster, and whether there is an edge to it."""
    starts = np.flatnonzero(np.r_[True, i[1:] != i[:-1]])
    at = np.repeat(np.arange(len(starts)), np.diff(np.r_[starts, len(i)])) * k + cluster[j]
    size = len(starts) * k
    return i[starts], np.bincount(at, w, size).reshape(-1, k), (np.bincount(at, minlength=size) > 0).reshape(-1, k)


def ties(first: Adjacency, nodes: Nodes, cluster: np.ndarray) -> DataFrame:
    """model_id, var_id, tie: the weight of each node to its own cluster, for nodes with edges."""
    k, held = int(cluster.max()) + 1, first.spark.sparkContext.broadcast((nodes.model, nodes.ids, cluster))

    def run(batches):
        model, ids, cluster = held.value
        for batch in batches:
            for row in _rows(batch):
                who, w, _ = _sums(*_read(*row), cluster, k)
                yield pa.RecordBatch.from_arrays([pa.array(x) for x in (model[who], ids[who], w[np.arange(len(who)), cluster[who]])], ["model_id", "var_id", "tie"])

    return first.read().mapInArrow(run, "model_id long, var_id long, tie double")


def moves(first: Adjacency, nodes: Nodes, cluster: np.ndarray, sign: float, r: int) -> DataFrame:
    """model_id, var_id, cluster, to, gain: the cluster around it that a node would gain most from (ties: the smallest), for the half
    of the nodes that may move in this round."""
    k, held = int(cluster.max()) + 1, first.spark.sparkContext.broadcast((nodes.model, nodes.ids, cluster))

    def run(batches):
        model, ids, cluster = held.value
        for batch in batches:
            for row in _rows(batch):
                i, j, w = _read(*row)
                may = (hashed(r, ids[i]) & 1) == 0
                i, j, w = i[may], j[may], w[may]
                if not len(i):
                    continue
                who, w, near = _sums(i, j, w, cluster, k)
                each, own = np.arange(len(who)), cluster[who]
                near[each, own] = False
                gain = np.where(near, sign * (w - w[each, own][:, None]), -np.inf)
                to = gain.argmax(1)
                ok = near.any(1)
                who, own, to, gain = who[ok], own[ok], to[ok].astype(np.int32), gain[each, to][ok]
                yield pa.RecordBatch.from_arrays([pa.array(x) for x in (model[who], ids[who], own.astype(np.int32), to, gain)], ["model_id", "var_id", "cluster", "to", "gain"])

    return first.read().mapInArrow(run, "model_id long, var_id long, cluster int, to int, gain double")
