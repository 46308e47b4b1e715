"""Exact similarity join of documents by their sets of word shingles."""

from __future__ import annotations

import hashlib
import math
from contextlib import contextmanager
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..shipping import ship
from ..storage import Stored

SIGNS = "doc_id long, key binary, n int, h array<long>, f array<long>"
MET = "key long, src long, dst long, times long, need long"
#: Texts that are read at once, and texts and shingles among which often seen shingles are counted at once.
ROWS, OFTEN_ROWS, OFTEN_GRAMS = 1024, 10_000, 4 << 20
#: Members of a shingle up to which one task pairs them; those of more are dealt over blocks of as many.
BLOCK = 1024
#: Ids that a task may hold in a broadcast.
BROADCAST_ROWS = 500_000


@dataclass
class SimilarSets:
    """``members``: doc_id, class_id (smallest id with the same set); ``links``: src, dst, jaccard between classes."""

    members: DataFrame
    links: DataFrame


def grams(text: bytes, shingle: int) -> np.ndarray:
    """Ascending distinct 64-bit hashes of the shingles of a text; a text of fewer words is one shingle, one without words has none."""
    words = text.split()  # of bytes: at space and 0x09-0x0D
    if not words:
        return np.empty(0, np.uint64)
    k = min(shingle, len(words))
    values = np.fromiter(map(xxhash.xxh64_intdigest, words), np.uint64, len(words))
    out = np.full(len(words) - k + 1, k, np.uint64)
    for i in range(k):
        out = (out ^ values[i : len(words) - k + 1 + i]) * np.uint64(0x9E3779B97F4A7C15)
        out ^= out >> np.uint64(29)
        out *= np.uint64(0xBF58476D1CE4E5B9)
        out ^= out >> np.uint64(32)
    return np.unique(out)


def _sets(batches, shingle: int):
    """Slices of the batches, each with the sets of its texts."""
    for batch in batches:
        for at in range(0, batch.num_rows, ROWS):
            part = batch.slice(at, ROWS)
            yield part, [grams(t.as_py(), shingle) for t in part.column("body").cast(pa.binary())]


def _signs(shingle: int):
    """A row of doc_id, key, n for each text; rows of h, f alone: shingles that a 4096th of a part's texts have, and how many."""

    def often(held, rows):
        every = np.sort(np.concatenate(held))
        cut = np.flatnonzero(np.concatenate(([True], every[1:] != every[:-1], [True])))
        hot = np.diff(cut) >= max(3, rows // 4096)
        return every[cut[:-1][hot]].view(np.int64), np.diff(cut)[hot]

    def run(batches):
        held, rows, size = [], 0, 0
        for part, sets in _sets(batches, shingle):
            m = len(sets)
            keys = [hashlib.blake2b(g.tobytes(), digest_size=16).digest() for g in sets]
            none = pa.nulls(m, pa.list_(pa.int64()))
            yield pa.record_batch([part.column("doc_id"), pa.array(keys, pa.binary()), pa.array([len(g) for g in sets], pa.int32()), none, none], names=["doc_id", "key", "n", "h", "f"])
            held, rows, size = held + sets, rows + m, size + sum(map(len, sets))
            if rows >= OFTEN_ROWS or size >= OFTEN_GRAMS:
                yield one(*often(held, rows))
                held, rows, size = [], 0, 0
        if held:
            yield one(*often(held, rows))

    def one(h, f):
        return pa.record_batch([pa.nulls(1, pa.int64()), pa.nulls(1, pa.binary()), pa.nulls(1, pa.int32()), pa.array([h], pa.list_(pa.int64())), pa.array([f], pa.list_(pa.int64()))], names=["doc_id", "key", "n", "h", "f"])

    return run


def _prefixes(shingle: int, least: float, often):
    """doc_id, n, keys: the first n - ceil(least n) + 1 shingles of each text, often seen ones behind all others."""

    def run(batches):
        h, place = often.value
        for part, sets in _sets(batches, shingle):
            keys = []
            for g in sets:
                keep = len(g) - math.ceil(least * len(g) - 1e-9) + 1 if len(g) else 0
                if len(h) and len(g):
                    at = np.minimum(np.searchsorted(h, g), len(h) - 1)
                    g = g[np.argsort(np.where(h[at] == g, place[at], 0), kind="stable")]
                keys.append(g[:keep].view(np.int64))
            offsets = np.concatenate(([0], np.cumsum([len(k) for k in keys]))).astype(np.int32)
            flat = pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.concatenate(keys)))
            yield pa.record_batch([part.column("doc_id"), pa.array([len(g) for g in sets], pa.int32()), flat], names=["doc_id", "n", "keys"])

    return run


def _whole(shingle: int):
    def run(batches):
        for part, sets in _sets(batches, shingle):
            yield pa.record_batch([part.column("doc_id"), pa.array([g.tobytes() for g in sets], pa.binary())], names=["doc_id", "s"])

    return run


def _runs(batches):
    """The columns of each run of two rows and more from rows sorted by the first column."""
    held = None
    for batch in batches:
        cols = [batch.column(i).to_numpy(zero_copy_only=False) for i in range(batch.num_columns)]
        if held is not None:
            cols = [np.concatenate(c) for c in zip(held, cols)]
        if not len(cols[0]):
            continue
        cut = np.concatenate(([0], np.flatnonzero(np.diff(cols[0])) + 1))
        held = [c[cut[-1] :] for c in cols]
        for i in np.flatnonzero(np.diff(cut) > 1).tolist():
            yield [c[cut[i] : cut[i + 1]] for c in cols]
    if held is not None and len(held[0]) > 1:
        yield held


def _meetings(least: float):
    """key, src, dst, times, need: pairs that meet at a shingle (key null), or members (src, and need its size) of a shingle of many.

    The sets of a pair share at most the shingles in both prefixes and, beyond the prefix that ends first, as many as that
    set has left; so it must meet ``need`` times to be similar enough.
    """

    def pairs(ids, n, block, lo, hi):
        ids, at = np.unique(ids, return_index=True)
        n, block = n[at], block[at]
        for s in range(0, len(ids), 256):
            x = slice(s, s + 256)
            fits = np.minimum(n[x, None], n[None]) >= least * np.maximum(n[x, None], n[None]) - 1e-9
            i, j = np.nonzero(fits & (ids[x, None] < ids[None]) & ((block[x, None] != block[None]) | (lo == hi)))
            if len(i):
                i = i + s
                left = np.ceil(least * n - 1e-9) - 1
                shared = np.ceil(least / (1 + least) * (n[i].astype(float) + n[j]) - 1e-6)
                yield ids[i], ids[j], np.maximum(1, shared - np.maximum(left[i], left[j])).astype(np.int64)

    def found(batches):
        for cols in _runs(batches):
            if len(cols) > 3:  # cells of two blocks
                for out in pairs(*cols[1:4], cols[4][0], cols[5][0]):
                    yield False, out
            elif len(cols[0]) > BLOCK:
                yield True, (cols[0], cols[1], cols[2].astype(np.int64))
            else:
                for out in pairs(cols[1], cols[2], np.zeros(len(cols[0]), np.int64), 0, 0):
                    yield False, out

    def packed(hot, rows):
        cols, times = np.unique(np.stack([np.concatenate(c) for c in zip(*rows)], 1), axis=0, return_counts=True)
        a, b, need = (pa.array(c) for c in cols.T.copy())
        none = pa.nulls(len(cols), pa.int64())
        return pa.record_batch([a if hot else none, b if hot else a, none if hot else b, pa.array(times.astype(np.int64)), need], names=["key", "src", "dst", "times", "need"])

    def run(batches):
        held, size = {True: [], False: []}, 0
        for hot, cols in found(batches):
            held[hot].append(cols)
            size += len(cols[0])
            if size >= 1 << 16:
                yield from (packed(k, rows) for k, rows in held.items() if rows)
                held, size = {True: [], False: []}, 0
        yield from (packed(k, rows) for k, rows in held.items() if rows)

    return run


def _scores(least: float):
    def run(batches):
        for batch in batches:
            rows = []
            for src, dst, x, y in zip(batch.column("src").to_pylist(), batch.column("dst").to_pylist(), batch.column("x"), batch.column("y")):
                x, y = (np.frombuffer(v.as_buffer() or b"", np.uint64) for v in (x, y))
                both = len(np.intersect1d(x, y, assume_unique=True))
                if both / (len(x) + len(y) - both) >= least:
                    rows.append((src, dst, both / (len(x) + len(y) - both)))
            cols = list(zip(*rows)) or [(), (), ()]
            yield pa.record_batch([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int64(), pa.float64()))], names=["src", "dst", "jaccard"])

    return run


@contextmanager
def _rows_at_once(spark: SparkSession, most: int):
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    was = spark.conf.get(key)
    spark.conf.set(key, str(most))
    try:
        yield
    finally:
        spark.conf.set(key, was)


def similar_sets(docs: DataFrame, shingle: int = 5, least: float = 0.8) -> SimilarSets:
    """Classes of equal sets, and every pair of classes whose Jaccard similarity is at least ``least``.

    Two such sets share one of the first n - ceil(least n) + 1 shingles in any one order; often seen ones come last in it.
    Pairs that meet there as often as they must are verified on the whole sets.  Only prefixes and the sets of such pairs
    are shuffled; sets are made anew from the texts where they are needed.  Empty sets form a class without links.
    """
    spark = docs.sparkSession
    ship(spark)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("body"))
    with _rows_at_once(spark, 4 * ROWS):
        signs = Stored(rows.mapInArrow(_signs(shingle), SIGNS)).read()
        sets = signs.where("key is not null").select("doc_id", "key")
        classes = sets.groupBy("key").agg(F.min("doc_id").alias("class_id"))
        members = Stored(sets.join(classes, "key").select("doc_id", "class_id")).read()
        seen = signs.where("h is not null").select(F.explode(F.arrays_zip("h", "f")).alias("o")).groupBy("o.h").agg(F.sum("o.f").alias("f"))
        seen = seen.where(F.col("f") >= max(8, members.count() // 4096)).toArrow()  # at most 4096 times the mean number of shingles of a text
        h, f = (seen[c].to_numpy() for c in ("h", "f"))
        h, place = h.view(np.uint64), np.empty(len(h), np.int64)
        place[np.lexsort((h, f))] = np.arange(1, len(h) + 1)
        often = spark.sparkContext.broadcast((np.sort(h), place[np.argsort(h)]))

        reps = members.where("doc_id = class_id").select("doc_id").distinct()
        keys = rows.mapInArrow(_prefixes(shingle, least, often), "doc_id long, n int, keys array<long>").join(reps, "doc_id")
        keys = keys.select(F.explode("keys").alias("key"), "doc_id", "n").repartition("key").sortWithinPartitions("key")
        met = Stored(keys.mapInArrow(_meetings(least), MET)).read()
        hot = met.where("key is not null").select("key", F.col("src").alias("id"), F.col("need").alias("n"))
        blocks = hot.groupBy("key").agg(F.ceil(F.count(F.lit(1)) / BLOCK).alias("blocks"))
        cells = hot.join(blocks, "key").withColumn("block", F.pmod(F.xxhash64("id"), "blocks")).withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)))
        cells = cells.withColumns({"lo": F.least("block", "other"), "hi": F.greatest("block", "other")})
        cells = cells.select(F.xxhash64("key", "lo", "hi").alias("cell"), "id", "n", "block", "lo", "hi").repartition("cell").sortWithinPartitions("cell")
        pairs = met.where("key is null").unionByName(cells.mapInArrow(_meetings(least), MET))
        near = pairs.groupBy("src", "dst").agg(F.sum("times").alias("times"), F.min("need").alias("need")).where("times >= need")
        near = Stored(near.select("src", "dst")).read()

        ids = Stored(near.select(F.col("src").alias("doc_id")).union(near.select("dst")).distinct()).read()
        few = ids.count() <= BROADCAST_ROWS  # so that other texts are not read as sets, and no text is shuffled
        whole = (rows.join(F.broadcast(ids), "doc_id", "left_semi") if few else rows).mapInArrow(_whole(shingle), "doc_id long, s binary")
        pool = Stored(whole if few else whole.join(ids, "doc_id", "left_semi")).read()
    full = near.join(pool.select(F.col("doc_id").alias("src"), F.col("s").alias("x")), "src").join(pool.select(F.col("doc_id").alias("dst"), F.col("s").alias("y")), "dst")
    with _rows_at_once(spark, ROWS // 2):
        links = Stored(full.select("src", "dst", "x", "y").mapInArrow(_scores(least), "src long, dst long, jaccard double").dropDuplicates(["src", "dst"])).read()
    return SimilarSets(members, links.select("src", "dst", F.round("jaccard", 6).alias("jaccard")))
