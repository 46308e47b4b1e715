"""Near-duplicate groups by SimHash fingerprints and meet-in-the-middle ball hashing.

Two fingerprints within ``radius`` bits differ in at most ``radius // 2`` bits on each side of a midpoint.  For
an odd radius the odd bit is taken up by a mask: the 64 bits are cut into ``masks`` blocks, at least one of which
holds a differing bit, and with that block hidden ``radius - 1`` bits are left.  So every distinct fingerprint
emits, for each hidden block, all variants within half the radius of what is left; fingerprints that meet at
a variant are verified bit by bit.

``near_dedup`` removes documents by five-word similarity: ball hashing over fingerprints of weighted words, which move little
when few words change, proposes one comparison a document, and what it leaves open is completed by prefixes of the shingle sets.

Copies share one fingerprint, so hot groups of copies shrink to one row before anything is emitted.  A group of many
distinct fingerprints at one variant is linked through a spanning forest, never through all its pairs.
"""

from __future__ import annotations

import hashlib
import math
from collections import Counter
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..shipping import ship
from .common import SharedTable, released, rows_at_once, sliced

FINGERPRINTS = "doc_id long, fp long"
EDGES = "a long, b long"
#: Groups up to this size compare all members at once, in one small matrix; larger ones are searched through sub-blocks.
DENSE = 1024


def fingerprint(text: bytes, shingle: int = 3, seed: int = 42) -> int:
    """64-bit SimHash: a bit is 1 if it is set in over half of the shingles' XXH64 values; zero for no words."""
    words = text.lower().split()  # of bytes: A-Z alone; separators are space and 0x09-0x0D
    if not words:
        return 0
    k = min(shingle, len(words))
    digest = xxhash.xxh64_intdigest
    join = b" ".join
    values = np.fromiter((digest(s, seed) for s in map(join, zip(*(words[i:] for i in range(k))))), np.uint64, len(words) - k + 1)
    ones = np.zeros(64, np.int64)
    for i in range(0, len(values), 1 << 16):  # bounded memory for very long texts
        ones += np.unpackbits(values[i : i + (1 << 16)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * ones > len(values), bitorder="little").view(np.uint64)[0])


def _fingerprints(shingle: int, seed: int):
    def run(batches):
        for batch in batches:
            texts = batch.column("body").cast(pa.binary()).to_pylist()
            fps = np.fromiter((fingerprint(t, shingle, seed) for t in texts), np.uint64, len(texts)).view(np.int64)
            yield pa.record_batch([batch.column("doc_id"), pa.array(fps)], names=["doc_id", "fp"])

    return run


def fingerprints(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", shingle: int = 3, seed: int = 42) -> DataFrame:
    """doc_id, fp (64 bits as a long) of each row; null texts have no words and the fingerprint zero."""
    ship(docs.sparkSession)
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("body"))
    return rows.mapInArrow(_fingerprints(shingle, seed), FINGERPRINTS)


def _blocks(masks: int) -> list[list[int]]:
    cut = [64 * i // masks for i in range(masks + 1)]
    return [list(range(a, b)) for a, b in zip(cut, cut[1:])]


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def variants(fp: Column, radius: int, masks: int) -> Column:
    """Array of (mask, key): all variants within half the radius of the fingerprint under each hidden block."""
    half = radius // 2
    hidden = _blocks(masks) if radius % 2 else [[]]
    flips: list[tuple[int, int, int]] = []
    for m, block in enumerate(hidden):
        keep = [b for b in range(64) if b not in set(block)]
        mask = _signed(sum(1 << b for b in keep))
        flips += [(m, mask, _signed(sum(1 << b for b in bits))) for k in range(half + 1) for bits in combinations(keep, k)]
    table = F.array(*(F.struct(F.lit(m).alias("m"), F.lit(mask).alias("k"), F.lit(x).alias("x")) for m, mask, x in flips))
    return F.transform(table, lambda t: F.struct(t["m"].cast("byte").alias("mask"), fp.bitwiseAND(t["k"]).bitwiseXOR(t["x"]).alias("key")))


def _distance(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.bitwise_count(a ^ b)


def _forest(fps: np.ndarray, radius: int) -> list[tuple[int, int]]:
    """Edges between members within the radius, enough to connect all that the full set of such edges connects."""
    parent = np.arange(len(fps))

    def root(i: int) -> int:
        while parent[i] != i:
            parent[i] = parent[parent[i]]
            i = parent[i]
        return i

    out = []

    def link(i: int, j: int) -> None:
        a, b = root(i), root(j)
        if a != b:
            parent[max(a, b)] = min(a, b)
            out.append((int(fps[i]), int(fps[j])))

    def dense(at: np.ndarray) -> None:
        for s in range(0, len(at), DENSE):
            for t in range(s, len(at), DENSE):
                x, y = at[s : s + DENSE], at[t : t + DENSE]
                i, j = np.nonzero(_distance(fps[x][:, None], fps[y][None, :]) <= radius)
                for p, q in zip(x[i].tolist(), y[j].tolist()):
                    if p < q or s != t:
                        link(p, q)

    if len(fps) <= DENSE:
        dense(np.arange(len(fps)))
        return out
    # one of radius + 1 blocks is equal in any pair within the radius
    for block in _blocks(radius + 1):
        key = fps & np.uint64(sum(1 << b for b in block))
        order = np.argsort(key, kind="stable")
        cut = np.flatnonzero(np.diff(key[order])) + 1
        for part in np.split(order, cut):
            if len(part) > 1:
                dense(np.sort(part))
    return out


def _verify(radius: int):
    def runs(batches):
        """Members of each (mask, key) from rows sorted by it; a run may span batches."""
        last, held = None, []
        for batch in batches:
            mask, key, fp = (batch.column(i).to_numpy(zero_copy_only=False) for i in range(3))
            cut = np.concatenate(([0], np.flatnonzero((np.diff(key) != 0) | (np.diff(mask) != 0)) + 1, [len(key)]))
            head = (mask[0], key[0]) if len(key) else None
            if held and head != last:
                yield np.concatenate(held)
                held = []
            for i, j in zip(cut[:-1], cut[1:]):
                if j == len(key):
                    held.append(fp[i:j])
                    last = (mask[i], key[i])
                elif held:
                    held.append(fp[i:j])
                    yield np.concatenate(held)
                    held = []
                elif j - i > 1:
                    yield fp[i:j]
        if held:
            yield np.concatenate(held)

    def run(batches):
        a: list[int] = []
        b: list[int] = []
        for members in runs(batches):
            if len(members) > 1:
                for x, y in _forest(np.unique(members.view(np.uint64)), radius):
                    a.append(x)
                    b.append(y)
            if len(a) > 1 << 16:
                yield pa.record_batch([pa.array(np.array(v, np.uint64).view(np.int64)) for v in (a, b)], names=["a", "b"])
                a, b = [], []
        if a:
            yield pa.record_batch([pa.array(np.array(v, np.uint64).view(np.int64)) for v in (a, b)], names=["a", "b"])

    return run


def links(distinct: DataFrame, *, radius: int = 3, masks: int = 3) -> DataFrame:
    """a, b: verified links between the distinct fingerprints of column ``fp``, enough to connect each component."""
    ship(distinct.sparkSession)
    tasks = int(distinct.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    distinct = distinct.select("fp").repartition(tasks, F.xxhash64("fp"))  # few bytes in, many variants out: not to be coalesced
    met = distinct.select("fp", F.explode(variants(F.col("fp"), radius, masks)).alias("v")).select("v.mask", "v.key", "fp")
    met = met.repartition("mask", "key").sortWithinPartitions("mask", "key")
    return met.mapInArrow(_verify(radius), EDGES).distinct()


def components(edges: DataFrame, *, max_rounds: int = 64) -> DataFrame:
    """node, root: the smallest node of each component of ``edges`` (a, b), for every node that has an edge.

    Each round hooks every node onto the smallest label around it and then jumps to that label's own label, so
    paths halve; labels go to the shared folder after each round, and the driver sees one count.
    """
    both = SharedTable(edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), "links")
    pairs = both.read()
    now = SharedTable(pairs.groupBy(F.col("a").alias("node")).agg(F.least(F.min("b"), F.first("a")).alias("root")), "labels")
    for _ in range(max_rounds):
        label = now.read()
        near = pairs.join(label.select(F.col("node").alias("b"), "root"), "b").groupBy(F.col("a").alias("node")).agg(F.min("root").alias("near"))
        hooked = label.join(near, "node").select("node", F.col("root").alias("old"), F.least("root", "near").alias("root"))
        target = label.select(F.col("node").alias("root"), F.col("root").alias("up"))
        jumped = hooked.join(target, "root", "left").select("node", "old", F.least("root", F.coalesce("up", "root")).alias("root"))
        after = SharedTable(jumped, "labels")
        changed = after.read().where("root <> old").limit(1).count()
        now.drop()
        now = after
        if not changed:
            break
    else:
        raise RuntimeError("components did not settle")
    both.drop()
    return now.read().select("node", "root")


def simhash_groups(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", shingle: int = 3, seed: int = 42, radius: int = 3, masks: int = 3) -> DataFrame:
    """``doc_id, fingerprint, component_id`` of each row: 16 hex digits, and the smallest id that links reach.

    Fingerprints link at ``radius`` or fewer differing bits; equal ones always do.  Null and empty texts, and texts of
    separators alone, have no words: fingerprint zero, linked like any other.  Repeated rows share a component; a null id
    never names one unless all its ids are null.  Other columns are ignored.  An empty input gives an empty result.
    """
    held = SharedTable(fingerprints(docs, id_col=id_col, text_col=text_col, shingle=shingle, seed=seed), "fingerprints")
    marks = held.read()
    distinct = marks.groupBy("fp").agg(F.min("doc_id").alias("least"))
    roots = components(links(distinct.select("fp"), radius=radius, masks=masks))
    named = distinct.join(roots.withColumnRenamed("node", "fp"), "fp", "left").select("fp", F.coalesce("root", "fp").alias("root"), "least")
    ids = named.groupBy("root").agg(F.min("least").alias("component_id"))
    by_fp = named.join(ids, "root").select("fp", "component_id")
    return marks.join(by_fp, "fp").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def simhash_dedup(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """The rows of ``docs`` whose id is the smallest of its group, all columns unchanged; rows that repeat that id stay with it."""
    groups = simhash_groups(docs, id_col=id_col, text_col=text_col, **options)
    stay = groups.where(F.col("doc_id").eqNullSafe(F.col("component_id"))).select(F.col("doc_id").alias("_stay")).distinct()
    names = docs.columns
    plain = docs.toDF(*[f"c{i}" for i in range(len(names))])  # clashing names stay apart
    mine = F.col(f"c{names.index(id_col)}").cast("long")
    return plain.join(stay, mine.eqNullSafe(F.col("_stay")), "left_semi").toDF(*names)


# --- near duplicates by similarity --------------------------------------------------------------------------------------------------

MARKS = "doc_id long, fp long, class binary, n int, grams binary"
#: Up to this many members that share a shingle are compared as pairs of rows; larger groups are compared in packed blocks.
PAIRWISE = 128
#: Members, and bytes of shingles, in one packed block.
BLOCK, BLOCK_BYTES = 512, 4 << 20
#: Texts, and their shingles, that are counted at once.
OFTEN_ROWS, OFTEN_GRAMS = 10_000, 4 << 20
#: Shingles that came so many times are often seen; of these at most so many, the most often seen, have a place in the order.
OFTEN_LEAST, OFTEN = 2, 4 << 20
#: Rows that a task hands to Python at once where each holds two sets of shingles, or two packed blocks.
PAIR_ROWS, BLOCK_ROWS = 512, 1
#: Texts, or sets of shingles, that a task hands to Python at once.
TEXT_ROWS = 1024
#: Rows of a class, its number and its smallest id that a task may hold in a broadcast.
BROADCAST_ROWS = 500_000


def weighted_fingerprint(words: list[bytes], seed: int = 42) -> int:
    """64-bit SimHash of the words, each weighted by one and the logarithm of its count; zero for no words."""
    if not words:
        return 0
    count = Counter(words)
    weight = {n: round(64 * (1 + math.log(n))) for n in set(count.values())}  # whole numbers, so that sums do not depend on the order
    weights = np.fromiter((weight[n] for n in count.values()), np.int64, len(count))
    values = np.fromiter((xxhash.xxh64_intdigest(w, seed) for w in count), np.uint64, len(count))
    ones = np.zeros(64, np.int64)
    for i in range(0, len(values), 1 << 14):  # bounded memory for very long texts
        bits = np.unpackbits(values[i : i + (1 << 14)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        ones += weights[i : i + (1 << 14)] @ bits
    return int(np.packbits(2 * ones > weights.sum(), bitorder="little").view(np.uint64)[0])


def grams(words: list[bytes], size: int) -> np.ndarray:
    """Ascending distinct 64-bit hashes of the word shingles; fewer words than ``size`` are one shingle, none are none."""
    if not words:
        return np.empty(0, np.uint64)
    k = min(size, len(words))
    return np.unique(np.fromiter(map(xxhash.xxh64_intdigest, map(b" ".join, zip(*(words[i:] for i in range(k))))), np.uint64, len(words) - k + 1))


def _class(words: list[bytes]) -> bytes:
    return hashlib.blake2b(b" ".join(words), digest_size=16).digest()


def _marks(size: int):
    def run(batches):
        for part in sliced(batches):
            out = []
            for text in part.column("body").cast(pa.binary()):
                words = text.as_py().lower().split()
                g = grams(words, size)
                out.append((weighted_fingerprint(words), _class(words), len(g), g.tobytes()))
            fp, own, n, g = zip(*out)
            yield pa.record_batch([part.column("doc_id"), pa.array(np.array(fp, np.uint64).view(np.int64)), pa.array(own, pa.binary()), pa.array(n, pa.int32()), pa.array(g, pa.binary())], names=["doc_id", "fp", "class", "n", "grams"])

    return run


def _lead(radius: int):
    """a, b: for each fingerprint of a run of equal (mask, key), the one of the smallest id in it, where that is within the radius."""

    def run(batches):
        for _, fp, least in _runs(batches):
            first = int(least.argmin())
            near = (_distance(fp.view(np.uint64), fp.view(np.uint64)[first]) <= radius) & (fp != fp[first])
            if near.any():
                yield fp[near], np.full(int(near.sum()), fp[first])

    return lambda batches: _batched(run(batches), ("a", "b"))


def _runs(batches):
    """(key columns of the first row, further columns ...) of the runs of two rows and more from rows sorted by the first column."""
    held = None
    for batch in batches:
        cols = [batch.column(i).to_numpy(zero_copy_only=False) for i in range(batch.num_columns)]
        if held is not None:
            cols = [np.concatenate(c) for c in zip(held, cols)]
        if not len(cols[0]):
            continue
        cut = np.concatenate(([0], np.flatnonzero(np.diff(cols[0]) != 0) + 1))
        held = [c[cut[-1] :] for c in cols]
        for i in np.flatnonzero(np.diff(cut) > 1).tolist():
            yield (cols[0][cut[i]], *(c[cut[i] : cut[i + 1]] for c in cols[1:]))
    if held is not None and len(held[0]) > 1:
        yield (held[0][0], *held[1:])


def _batched(found, names, rows: int = 1 << 16):
    """Record batches of distinct rows from tuples of columns, with ``times``: how often each came."""

    def pack():
        kept, times = np.unique(np.stack([np.concatenate(c) for c in zip(*held)], 1), axis=0, return_counts=True)
        return pa.record_batch([pa.array(kept[:, i]) for i in range(len(names))] + [pa.array(times.astype(np.int64))], names=[*names, "times"])

    held, n = [], 0
    for cols in found:
        held.append(cols)
        n += len(cols[0])
        if n >= rows:
            yield pack()
            held, n = [], 0
    if held:
        yield pack()


def _sets(column: pa.Array) -> list[np.ndarray]:
    """The sets of a binary column, as views of its buffer."""
    return [np.frombuffer(x.as_buffer() or b"", np.uint64) for x in column]


def _cell(g: np.ndarray) -> np.ndarray:
    """The upper half of each hash; it only orders the shingles."""
    return (g >> np.uint64(32)).astype(np.uint32)


def _sums(cells: np.ndarray, times: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Ascending distinct cells, and the sum of ``times`` of each, or how often it came."""
    if times is None:
        return np.unique(cells, return_counts=True)
    order = np.argsort(cells, kind="stable")
    cells = cells[order]
    cut = np.flatnonzero(np.concatenate(([True], cells[1:] != cells[:-1])))
    return cells[cut], np.add.reduceat(times[order].astype(np.int64), cut)


def _cells(similarity: float, bins: int):
    """bin, cells, times: how often cells came, packed and dealt over ``bins`` by cell.

    In a text its shingles of the least hashes count, half as many again as its prefix has; of its others those that a 4096th of a
    part's texts have (three at least).  A part is ``OFTEN_ROWS`` texts, or fewer that have ``OFTEN_GRAMS`` shingles together.
    """

    def run(batches):
        def count():
            first, rest = (np.concatenate(x) for x in zip(*held))
            held.clear()
            (cells, times), (late, f) = _sums(first), _sums(rest)
            hot = f >= max(3, rows // 4096)
            cells, times = np.concatenate((cells, late[hot])), np.concatenate((times, f[hot]))
            own = cells % np.uint32(bins)
            order = np.argsort(own, kind="stable")
            at = np.searchsorted(own[order], np.arange(bins + 1))
            packed = [[x[order[i:j]].astype(np.uint32).tobytes() for i, j in zip(at[:-1], at[1:])] for x in (cells, times)]
            return pa.record_batch([pa.array(np.arange(bins, dtype=np.int32)), *(pa.array(x, pa.binary()) for x in packed)], names=["bin", "cells", "times"])

        held, rows, size = [], 0, 0
        for batch in batches:
            for g in _sets(batch.column("grams")):
                cells, least = _cell(g), _kept(len(g), similarity) * 3 // 2
                held.append((cells[:least], cells[least:]))
                rows, size = rows + 1, size + len(g)
                if rows >= OFTEN_ROWS or size >= OFTEN_GRAMS:
                    if size:
                        yield count()
                    held, rows, size = [], 0, 0
        if size:
            yield count()

    return run


def _often(least: int):
    """cell, f: cells that came ``least`` times or more, and how often, from rows of ``_cells`` sorted by bin."""

    def run(batches):
        def count():
            cells, f = _sums(*(np.concatenate([np.frombuffer(x, np.uint32) for x in side]) for side in zip(*held)))
            hot = f >= least
            return pa.record_batch([pa.array(cells[hot].view(np.int32)), pa.array(f[hot])], names=["cell", "f"])

        held, last = [], None
        for batch in batches:
            for own, cells, times in zip(*(batch.column(c).to_pylist() for c in ("bin", "cells", "times"))):
                if held and own != last:
                    yield count()
                    held = []
                held.append((cells, times))
                last = own
        if held:
            yield count()

    return run


def _kept(n: int, similarity: float) -> int:
    """How many shingles the prefix of a set of ``n`` has."""
    return n - math.ceil(similarity * n - 1e-9) + 1


def _order(marks: DataFrame, similarity: float) -> tuple[np.ndarray, np.ndarray]:
    """Ascending cells of often seen shingles, ``OFTEN`` at most, and their places: the more often, the later.

    Counts are taken over the whole table, not in its parts, where a shingle of few texts is seen once.
    """
    spark = marks.sparkSession
    tasks = int(spark.conf.get("spark.sql.shuffle.partitions"))
    dealt = marks.select("grams").mapInArrow(released(_cells(similarity, tasks)), "bin int, cells binary, times binary")
    dealt = dealt.where("length(cells) > 0").repartition(tasks, "bin").sortWithinPartitions("bin")
    with rows_at_once(spark, TEXT_ROWS):
        seen = SharedTable(dealt.mapInArrow(released(_often(OFTEN_LEAST)), "cell int, f long"), "often").read()
    many = {x["bits"]: x["m"] for x in seen.groupBy(F.length(F.bin("f")).alias("bits")).agg(F.count(F.lit(1)).alias("m")).collect()}
    bits = OFTEN_LEAST.bit_length()
    while sum(m for b, m in many.items() if b >= bits) > OFTEN:
        bits += 1
    seen = seen.where(F.length(F.bin("f")) >= bits).toArrow()
    cell, f = seen["cell"].to_numpy().view(np.uint32), seen["f"].to_numpy()
    place = np.empty(len(cell), np.int32)
    place[np.lexsort((cell, f))] = np.arange(1, len(cell) + 1)
    at = np.argsort(cell)
    return cell[at], place[at]


def prefix(g: np.ndarray, often: np.ndarray, place: np.ndarray, similarity: float) -> np.ndarray:
    """The first n - ceil(similarity n) + 1 shingles, often seen ones behind all others: sets that are similar enough share one."""
    keep = _kept(len(g), similarity)
    if len(often):
        cells = _cell(g)
        at = np.minimum(np.searchsorted(often, cells), len(often) - 1)
        late = np.where(often[at] == cells, place[at], 0)
        g = g[np.argsort(late, kind="stable")]
    return g[:keep]


def _prefixes(often, similarity: float):
    def run(batches):
        h, place = often.value
        for batch in batches:
            keys = [prefix(np.frombuffer(g, np.uint64), h, place, similarity).view(np.int64) if g else np.empty(0, np.int64) for g in batch.column("grams").to_pylist()]
            offsets = np.concatenate(([0], np.cumsum([len(k) for k in keys]))).astype(np.int32)
            flat = np.concatenate(keys) if keys else np.empty(0, np.int64)
            yield pa.record_batch([batch.column(c) for c in ("doc_id", "class", "n")] + [pa.ListArray.from_arrays(pa.array(offsets), pa.array(flat))], names=["doc_id", "class", "n", "keys"])

    return run


def _meetings(similarity: float):
    """hot, a, b, need: pairs (later, earlier) of the runs of few members; key and member of the runs of many.

    The sets of a pair share at most the shingles in both prefixes and, beyond the prefix that ends first, as many as that
    set has left; so it must meet in ``need`` runs to be similar enough, or in one of many members.
    """

    def run(batches):
        for key, num, least, n, open_ in _runs(batches):
            num, at = np.unique(num, return_index=True)
            least, n, open_ = least[at], n[at], open_[at].astype(bool)
            if len(num) < 2 or not open_[least > least.min()].any():
                continue
            if len(num) > PAIRWISE:
                yield np.ones(len(num), np.int64), np.full(len(num), key), num, np.ones(len(num), np.int64)
                continue
            fits = np.minimum(n[:, None], n[None]) >= similarity * np.maximum(n[:, None], n[None]) - 1e-9
            i, j = np.nonzero(fits & (least[:, None] > least[None]) & open_[:, None])
            if len(i):
                left = np.ceil(similarity * n.astype(float) - 1e-9) - 1
                least_shared = np.ceil(similarity / (1 + similarity) * (n[i].astype(float) + n[j]) - 1e-6)
                yield np.zeros(len(i), np.int64), num[i], num[j], np.maximum(1, least_shared - np.maximum(left[i], left[j])).astype(np.int64)

    return lambda batches: _batched(run(batches), ("hot", "a", "b", "need"))


def _similar(similarity: float):
    def run(batches):
        for batch in batches:
            gone = []
            for own, a, b in zip(batch.column("x").to_pylist(), _sets(batch.column("mine")), _sets(batch.column("theirs"))):
                if min(len(a), len(b)) >= similarity * max(len(a), len(b)) - 1e-9:
                    both = len(np.intersect1d(a, b, assume_unique=True))
                    if both >= similarity * (len(a) + len(b) - both):
                        gone.append(own)
            yield pa.record_batch([pa.array(gone, pa.int64())], names=["num"])

    return run


def shared(xs: list[np.ndarray], ys: list[np.ndarray], width: int = 4096) -> np.ndarray:
    """Matrix of the numbers of shingles that each of ``xs`` shares with each of ``ys``, by products of indicator matrices."""
    out = np.zeros((len(xs), len(ys)), np.float32)
    x, y = np.concatenate(xs), np.concatenate(ys)
    both = np.intersect1d(x, y)

    def cells(values, sets):
        row = np.repeat(np.arange(len(sets)), [len(s) for s in sets])
        at = np.minimum(np.searchsorted(both, values), len(both) - 1)
        held = both[at] == values
        return row[held], at[held]

    if len(both):
        (rx, cx), (ry, cy) = cells(x, xs), cells(y, ys)
        for s in range(0, len(both), width):
            a, b = np.zeros((len(xs), width), np.float32), np.zeros((len(ys), width), np.float32)
            for m, r, c in ((a, rx, cx), (b, ry, cy)):
                inside = (c >= s) & (c < s + width)
                m[r[inside], c[inside] - s] = 1
            out += a @ b.T
    return out


def _blocks_similar(similarity: float):
    def run(batches):
        for batch in batches:
            gone = []
            for i in range(batch.num_rows):
                mine, theirs = batch.column("mine")[i].values, batch.column("theirs")[i].values
                xs, ys = (_sets(side.field("grams")) for side in (mine, theirs))
                nx, ny = (np.array([len(s) for s in side], np.int64) for side in (xs, ys))
                both = shared(xs, ys).astype(np.int64)
                later = mine.field("least").to_numpy()[:, None] > theirs.field("least").to_numpy()[None]
                hit = later & (both >= similarity * (nx[:, None] + ny[None] - both))
                gone += mine.field("num").to_numpy()[hit.any(1)].tolist()
            yield pa.record_batch([pa.array(gone, pa.int64())], names=["num"])

    return run


def _verified(pairs: DataFrame, marks: DataFrame, classes: DataFrame, similarity: float) -> DataFrame:
    """num: the ``x`` of the pairs (x, y) whose shingles are similar enough."""
    pairs = SharedTable(pairs.distinct(), "pairs").read()
    pool = _pool(pairs.select(F.col("x").alias("num")).union(pairs.select("y")).distinct(), marks, classes).select("num", "grams")
    pool = SharedTable(pool, "pool").read()
    # earlier members of over a thousandth of all pairs, fewer than a thousand, are dealt over as many parts as they have thousandths
    often = pairs.groupBy("y").agg(F.count(F.lit(1)).alias("m"))
    share = max(1000, (often.agg(F.sum("m")).first()[0] or 0) // 1000)
    parts = often.where(F.col("m") > share).select("y", F.ceil(F.col("m") / share).cast("int").alias("parts"))
    parts = SharedTable(parts, "parts").read()
    dealt = pairs.join(F.broadcast(parts), "y", "left").select("x", "y", F.pmod(F.xxhash64("x"), F.coalesce("parts", F.lit(1))).cast("int").alias("part"))
    ys = pool.select(F.col("num").alias("y"), F.col("grams").alias("theirs")).join(F.broadcast(parts), "y", "left")
    ys = ys.select("y", "theirs", F.explode(F.sequence(F.lit(0), F.coalesce("parts", F.lit(1)) - 1)).alias("part"))
    met = dealt.join(ys, ["y", "part"]).join(pool.select(F.col("num").alias("x"), F.col("grams").alias("mine")), "x")
    with rows_at_once(pairs.sparkSession, PAIR_ROWS):
        return SharedTable(met.select("x", "mine", "theirs").mapInArrow(released(_similar(similarity)), "num long").distinct(), "gone").read()


def _pool(nums: DataFrame, marks: DataFrame, classes: DataFrame) -> DataFrame:
    """num, least, open, n, grams of the classes with these numbers."""
    named = SharedTable(classes.join(nums, "num", "left_semi").select("num", "class", "least", "open"), "named").read()
    few = F.broadcast if named.count() <= BROADCAST_ROWS else lambda df: df  # so that the sets of all others are not shuffled
    rows = marks.select("doc_id", "class", "n", "grams").join(few(named), "class").where("doc_id = least")
    return rows.select("num", "least", "open", "n", "grams").dropDuplicates(["num"])


def _hot(members: DataFrame, marks: DataFrame, classes: DataFrame, similarity: float) -> DataFrame:
    """num: members of large groups (key, num) with a similar earlier one; keys that share a member are one group, so that a member travels once."""
    one = members.groupBy("num").agg(F.min("key").alias("first"))
    edges = members.join(one, "num").where("key <> first").select(F.col("first").alias("a"), F.col("key").alias("b")).distinct()
    roots = components(edges).select(F.col("node").alias("first"), "root")
    group = one.join(roots, "first", "left").select("num", F.coalesce("root", "first").alias("root"))
    pool = SharedTable(_pool(one.select("num"), marks, classes).join(group, "num"), "pool").read()

    def packed(rows: DataFrame, name: str) -> DataFrame:
        size = rows.groupBy("root").agg(F.greatest(F.ceil(F.count(F.lit(1)) / BLOCK), F.ceil(F.sum(F.col("n").cast("long") * 8) / BLOCK_BYTES)).alias("blocks"))
        dealt = rows.join(size, "root").withColumn("block", F.pmod(F.xxhash64("num"), F.col("blocks")))
        return SharedTable(dealt.groupBy("root", "block").agg(F.collect_list(F.struct("num", "least", "grams")).alias(name)), "blocks").read()

    mine, theirs = packed(pool.where("open"), "mine"), packed(pool, "theirs").withColumnRenamed("block", "other")
    tasks = int(pool.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    met = mine.join(theirs, "root").repartition(tasks, F.xxhash64("root", "block", "other"))
    with rows_at_once(pool.sparkSession, BLOCK_ROWS):
        return SharedTable(met.select("mine", "theirs").mapInArrow(released(_blocks_similar(similarity)), "num long").distinct(), "gone").read()


def near_dedup(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", words: int = 5, similarity: float = 0.8, radius: int = 3, masks: int = 3) -> DataFrame:
    """The rows of ``docs`` without near duplicates, all columns unchanged.

    Texts are compared by their words, A-Z lowered.  Of rows with the same words the smallest id stays.  A document goes when
    one with a smaller id has ``words``-word shingles that are similar by ``similarity`` or more (shared over all distinct shingles,
    by 64-bit hashes), and only then.  First each document is compared with the smallest id that ball hashing of weighted
    fingerprints shows within ``radius`` bits.  Those that stay open meet all others with which they share one of the first
    n - ceil(similarity n) + 1 shingles in one order of all shingles, so that no pair is lost; often seen shingles come
    last in it.  Meetings of up to ``PAIRWISE`` are pairs of rows; larger ones are packed in blocks and compared by matrix products.

    Null and empty texts have the same (no) words.  A row without an id has no place in the order and stays; rows that share an
    id stay or go together.  An empty input gives an empty result.
    """
    spark = docs.sparkSession
    ship(spark)
    names = docs.columns
    plain = docs.toDF(*[f"c{i}" for i in range(len(names))])  # clashing names stay apart
    mine = F.col(f"c{names.index(id_col)}").cast("long")
    body = F.coalesce(F.col(f"c{names.index(text_col)}").cast("string"), F.lit(""))
    rows = plain.select(mine.alias("doc_id"), body.alias("body")).where("doc_id is not null")
    with rows_at_once(spark, TEXT_ROWS):
        marks = SharedTable(rows.mapInArrow(released(_marks(words)), MARKS), "marks").read()
    classes = marks.groupBy("class").agg(F.min("doc_id").alias("least"), F.min("fp").alias("fp"))
    classes = SharedTable(classes.withColumn("num", F.monotonically_increasing_id()), "classes").read()

    # one comparison for each class: the smallest id within the radius
    tasks = int(spark.conf.get("spark.sql.shuffle.partitions"))
    firsts = SharedTable(classes.groupBy("fp").agg(F.min(F.struct("least", "num")).alias("one")).select("fp", "one.*"), "firsts").read()
    met = firsts.select("fp", "least").repartition(tasks, F.xxhash64("fp")).select("fp", "least", F.explode(variants(F.col("fp"), radius, masks)).alias("v"))
    met = met.select(F.xxhash64("v.mask", "v.key").alias("k"), "fp", "least").repartition("k").sortWithinPartitions("k")
    leads = SharedTable(met.mapInArrow(_lead(radius), EDGES + ", times long"), "leads").read()
    near = leads.join(firsts.withColumnRenamed("fp", "b"), "b").groupBy(F.col("a").alias("fp")).agg(F.min(F.struct("least", "num")).alias("far"))
    best = firsts.join(near, "fp", "left").select("fp", F.least(F.struct("least", "num"), "far").alias("lead"))
    first = classes.join(best, "fp").where("lead.least < least").select(F.col("num").alias("x"), F.col("lead.num").alias("y"))
    gone = _verified(first, marks, classes.withColumn("open", F.lit(True)), similarity)

    # whatever is open meets all that it may be similar to
    classes = classes.join(gone.withColumn("_gone", F.lit(True)), "num", "left").select("class", "least", "num", F.col("_gone").isNull().alias("open"))
    classes = SharedTable(classes, "classes").read()
    often = spark.sparkContext.broadcast(_order(marks, similarity))
    keys = marks.select("doc_id", "class", "n", "grams").where("n > 0").mapInArrow(released(_prefixes(often, similarity)), "doc_id long, class binary, n int, keys array<long>")
    keys = keys.join(classes, "class").where("doc_id = least").select("num", "least", "n", "open", F.explode("keys").alias("key"))
    keys = keys.select("key", "num", "least", "n", F.col("open").cast("byte").alias("open")).repartition("key").sortWithinPartitions("key")
    meetings = keys.mapInArrow(_meetings(similarity), "hot long, a long, b long, need long, times long")
    meetings = meetings.groupBy("hot", "a", "b", "need").agg(F.sum("times").alias("times")).where("times >= need")
    with rows_at_once(spark, 4 * TEXT_ROWS):
        meetings = SharedTable(meetings, "meetings").read()
    gone = gone.unionAll(_verified(meetings.where("hot = 0").select(F.col("a").alias("x"), F.col("b").alias("y")), marks, classes, similarity))
    gone = gone.unionAll(_hot(meetings.where("hot = 1").select(F.col("a").alias("key"), F.col("b").alias("num")), marks, classes, similarity))
    stay = classes.join(gone, "num", "left_anti").select(F.col("least").alias("_stay")).distinct()
    kept = plain.join(stay, mine == F.col("_stay"), "left_semi")
    return kept.unionAll(plain.where(mine.isNull())).toDF(*names)
