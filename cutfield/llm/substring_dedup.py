"""Substring deduplication by fixed-block anchors.

A repeat of ``window`` words holds, in either copy, one whole aligned block of ``block = (window + 1) // 2``
words.  So the blocks that start at multiples of ``block`` words are indexed, every rolling window of
``block`` words probes the index, and only windows of ``window`` words around a hit are compared; runs of
those are the maximal exact repeats.

Documents are dealt by a hash of id and text into chunks of bounded bytes.  A chunk sends each distinct hash once,
so a passage that a third of all documents share is one row a chunk, and every hash meets its equals in a bucket.
Chunks grow with the square root of the input up to a bound, so that the rows between chunks and buckets stay in
proportion to it.

1. probe:  chunk -> (bucket, sorted 27-bit hashes, flags: is a block, repeats here)
2. match:  bucket -> (chunk, hashes of blocks that some other window equals)
3. extend: chunk + hits -> (bucket, 96-bit hashes of the windows around hits, smallest id here)
4. order:  bucket -> (chunk, hashes that start earlier elsewhere and where; hashes that start here first but repeat)
5. cut:    chunk + verdicts -> documents without the covered words
6. runs, check: each distinct run that 5 cuts goes, with its words, to the document that it is said to start in,
   and must stand there word by word; repeats inside a chunk are compared word by word at once

A false hit in 1-2 only adds a window to 3.  Words are hashed eight bytes at a time, each step mixed by a bijection, long
words by BLAKE2b; should two word sequences ever share 96 bits, 6 fails the job instead of returning a wrong row, and
another ``seed`` gives other hashes.
"""

from __future__ import annotations

import hashlib
import math
from itertools import compress

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..shipping import ship
from .common import text_bytes

U64 = np.uint64
#: Odd bases of the polynomials that join the hashes of a window's words.
BASES = (U64(0x9E3779B97F4A7C15), U64(0xC2B2AE3D27D4EB4F))
#: Bits of a hash inside its bucket, and bytes above which a word is hashed by BLAKE2b.
BITS, LONG = 27, 256
#: Order of rows without an id: behind all others.
LAST = np.iinfo(np.int64).max
_SPACE = np.zeros(256, bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
_MASKS = np.array([(1 << 8 * k) - 1 for k in range(9)], U64)


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> U64(30))) * U64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> U64(27))) * U64(0x94D049BB133111EB)
    return x ^ (x >> U64(31))


def word_hashes(raw: bytes, start: np.ndarray, length: np.ndarray, seed: int, hashes: int) -> list[np.ndarray]:
    """64-bit hashes of each word; words of up to eight bytes and equal length never share one."""
    lanes = np.ndarray(len(raw), "<u8", raw + b"\0" * 8, strides=(1,))
    out = []
    with np.errstate(over="ignore"):
        for k in range(hashes):
            out.append(_mix(length.astype(U64) + U64(((2 * seed + k) * 0x9E3779B97F4A7C15 + 0x632BE59BD9B4E019) & (2**64 - 1))))
        at, here, size = slice(None), start, np.where(length <= LONG, length, 0)
        k = 0
        while len(here):
            lane = lanes[here] & _MASKS[np.minimum(8, size)]
            for j, h in enumerate(out):
                h[at] = _mix((h[at] ^ lane) * BASES[j] + U64(k + 1))
            more = np.flatnonzero(size > 8)
            at = more if isinstance(at, slice) else at[more]
            here, size = here[more] + 8, size[more] - 8
            k += 1
    for i in np.flatnonzero(length > LONG).tolist():
        digest = hashlib.blake2b(raw[start[i] : start[i] + length[i]], digest_size=16, key=seed.to_bytes(8, "little")).digest()
        for j, h in enumerate(out):
            h[i] = int.from_bytes(digest[8 * j : 8 * j + 8], "little")
    return out


class Chunk:
    """The words of several texts: their hashes, and the documents they stand in."""

    def __init__(self, texts: list[bytes], seed: int, hashes: int = 2):
        self.texts = texts
        self.raw = b" ".join(texts)
        raw = np.frombuffer(self.raw, np.uint8)
        solid = ~_SPACE[raw]
        edge = np.flatnonzero(np.diff(np.concatenate(([False], solid, [False])).view(np.int8)))
        self.start, self.length = edge[::2], np.diff(edge)[::2]
        begins = np.concatenate(([0], np.cumsum(np.fromiter((len(t) + 1 for t in texts), np.int64, len(texts)))))
        self.first = np.searchsorted(self.start, begins)  # word at which each text begins; the last is the total
        self.n = len(self.start)
        self.hashes = word_hashes(self.raw, self.start, self.length, seed, hashes) if self.n else [np.empty(0, U64)] * hashes

    def words(self, a: int, b: int) -> list[bytes]:
        """Some consecutive words of one text."""
        return self.raw[self.start[a] : self.start[b - 1] + self.length[b - 1]].split() if b > a else []

    def numbers(self, at: np.ndarray) -> np.ndarray:
        """A number for each of some words, equal for equal words alone."""
        seen: dict[bytes, int] = {}
        return np.fromiter((seen.setdefault(self.raw[a : a + n], len(seen)) for a, n in zip(self.start[at].tolist(), self.length[at].tolist())), np.int64, len(at))

    def windows(self, size: int, which: int) -> tuple[np.ndarray, np.ndarray]:
        """First word of each window of ``size`` words inside one text, and the window's 64-bit hash."""
        reach = np.repeat(self.first[1:], np.diff(self.first))  # end of each word's text
        at = np.flatnonzero(np.arange(self.n) + size <= reach)
        w = self.hashes[which]
        if not len(at):
            return at, np.empty(0, U64)
        part, width, power = self.hashes[which], 1, BASES[which]  # hashes of ``width`` words, joined from shorter ones
        out, done = None, 0
        with np.errstate(over="ignore"):
            while True:
                if size & width:
                    if out is None:
                        out = part
                    else:  # what is there already goes behind
                        n = self.n - done - width + 1
                        out = part[:n] * raised + out[width : width + n]
                    raised = power if done == 0 else raised * power
                    done += width
                if done == size:
                    return at, _mix(out[at])
                n = self.n - 2 * width + 1
                part = part[:n] * power + part[width : width + n]
                width, power = 2 * width, power * power

    def keys(self, window: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """First word, hash and second hash of each window."""
        at, h = self.windows(window, 0)
        return at, h, (self.windows(window, 1)[1] >> U64(32)).astype(np.uint32)

    def place(self, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Text and place in it of each word."""
        text = np.searchsorted(self.first, at, side="right") - 1
        return text, at - self.first[text]


def _pack(sorted_values: np.ndarray) -> bytes:
    """Ascending numbers below 2**32 as gaps: of two bytes, where 65535 means go on, or of four; whatever is shorter."""
    gaps = np.diff(sorted_values, prepend=sorted_values[:0].dtype.type(0))
    more = gaps // 65535
    if int(more.sum()) < len(gaps):
        out = np.full(len(gaps) + int(more.sum()), 65535, "<u2")
        out[np.arange(len(gaps)) + np.cumsum(more)] = gaps % 65535
        return b"\x02" + out.tobytes()
    return b"\x04" + gaps.astype("<u4").tobytes()


def _unpack(blob: bytes) -> np.ndarray:
    if blob[0] == 4:
        return np.cumsum(np.frombuffer(blob, "<u4", offset=1), dtype=np.int64)
    gaps = np.frombuffer(blob, "<u2", offset=1)
    return np.cumsum(gaps, dtype=np.int64)[gaps != 65535]


def _steps(ascending: np.ndarray) -> bytes:
    """Ascending longs as differences, whose zero bytes the shuffle's compression takes away."""
    return np.diff(ascending.astype("<i8"), prepend=np.int64(0)).astype("<i8").tobytes()


def _from_steps(blob: bytes) -> np.ndarray:
    return np.cumsum(np.frombuffer(blob, "<i8"), dtype=np.int64)


def _split(bucket: np.ndarray, n: int) -> np.ndarray:
    """Bounds of each bucket's run in an ascending array of buckets."""
    return np.searchsorted(bucket, np.arange(n + 1))


def _key(h: np.ndarray, buckets: int) -> np.ndarray:
    """Bucket and BITS bits of it, as one number."""
    return ((h >> U64(32)) % U64(buckets)).astype(np.int64) << BITS | (h & U64((1 << BITS) - 1)).astype(np.int64)


def _texts(table: pa.Table) -> tuple[np.ndarray, np.ndarray, list[bytes]]:
    """Ids (LAST for none), whether there is one, and texts of a chunk, in the order of ids."""
    texts = table["body"].cast(pa.binary()).to_pylist()
    ids, there = table["doc_id"].fill_null(LAST).to_numpy(), table["doc_id"].is_valid().to_numpy()
    order = np.argsort(ids, kind="stable")
    return ids[order], there[order], [texts[i] for i in order]


def _table(rows: list[tuple], schema: pa.Schema) -> pa.Table:
    return pa.table(dict(zip(schema.names, map(list, zip(*rows)))), schema) if rows else schema.empty_table()


PROBE = pa.schema([("bucket", pa.int32()), ("chunk", pa.int32()), ("hashes", pa.binary()), ("blocks", pa.binary()), ("again", pa.binary())])
HITS = pa.schema([("chunk", pa.int32()), ("bucket", pa.int32()), ("hashes", pa.binary())])


def _probe(buckets: int, block: int, seed: int):
    def run(table: pa.Table) -> pa.Table:
        chunk = Chunk(_texts(table)[2], seed, 1)
        at, h = chunk.windows(block, 0)
        aligned = chunk.place(at)[1] % block == 0
        both = np.sort(_key(h, buckets) << 1 | aligned)  # blocks stand last among their equals
        new = np.flatnonzero(np.concatenate((np.ones(min(1, len(both)), bool), both[1:] >> 1 != both[:-1] >> 1)))
        end = np.append(new[1:], len(both))[: len(new)]
        found, count, flag = both[new] >> 1, end - new, (both[end - 1] & 1).astype(bool)
        bounds = _split(found >> BITS, buckets)
        me, low = table["chunk"][0].as_py(), (1 << BITS) - 1
        return _table([(b, me, _pack(found[i:j] & low), np.packbits(flag[i:j]).tobytes(), np.packbits(count[i:j] > 1).tobytes()) for b, (i, j) in enumerate(zip(bounds[:-1], bounds[1:])) if j > i], PROBE)

    return run


def _match(table: pa.Table) -> pa.Table:
    hashes = [_unpack(x) for x in table["hashes"].to_pylist()]
    bits = lambda name: np.concatenate([np.unpackbits(np.frombuffer(x, np.uint8), count=len(h)) for x, h in zip(table[name].to_pylist(), hashes)]) > 0
    every = np.concatenate(hashes)
    block, again = np.unique(every[bits("blocks")]), every[bits("again")]
    every = np.sort(every)
    many = np.union1d(every[1:][every[1:] == every[:-1]], again)
    hit = np.intersect1d(block, many, assume_unique=True)
    if not len(hit):
        return HITS.empty_table()
    rows = []
    for c, b, h in zip(table["chunk"].to_pylist(), table["bucket"].to_pylist(), hashes):
        mine = h[hit[np.minimum(np.searchsorted(hit, h), len(hit) - 1)] == h]
        if len(mine):
            rows.append((c, b, _pack(mine)))
    return _table(rows, HITS)


PAIR = np.dtype([("h", "<u8"), ("m", "<u4")])
CANDIDATES = pa.schema([("bucket", pa.int32()), ("chunk", pa.int32()), ("hashes", pa.binary()), ("more", pa.binary()), ("ids", pa.binary()), ("again", pa.binary())])
VERDICTS = pa.schema([("chunk", pa.int32()), ("elsewhere", pa.binary()), ("chunks", pa.binary()), ("owners", pa.binary()), ("here", pa.binary())])


def _fold(h: np.ndarray, more: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Order by (hash, second hash), the start of each group of equals in it, and the group of each entry."""
    order = np.argsort(h)
    a, b = h[order], more[order]
    new = np.ones(len(a), bool)
    new[1:] = a[1:] != a[:-1]
    if (~new[1:] & (b[1:] != b[:-1])).any():  # a first hash alone may collide
        order = np.lexsort((more, h))
        a, b = h[order], more[order]
        new[1:] = (a[1:] != a[:-1]) | (b[1:] != b[:-1])
    group = np.empty(len(a), np.int64)
    group[order] = np.cumsum(new) - 1
    return order, np.flatnonzero(new), group


def _extend(buckets: int, block: int, window: int, seed: int):
    def run(docs: pa.Table, hits: pa.Table) -> pa.Table:
        if not docs.num_rows or not hits.num_rows:
            return CANDIDATES.empty_table()
        ids, _, texts = _texts(docs)
        chunk = Chunk(texts, seed)
        at, h = chunk.windows(block, 0)
        wanted = np.sort(np.concatenate([_unpack(x) | b << BITS for x, b in zip(hits["hashes"].to_pylist(), hits["bucket"].to_pylist())]))
        key = _key(h, buckets)
        near = np.searchsorted(wanted, key)
        hit = np.zeros(chunk.n + window + 1, np.int32)
        hit[at] = wanted[np.minimum(near, len(wanted) - 1)] == key
        total = np.concatenate(([0], np.cumsum(hit)))
        at, h, more = chunk.keys(window)
        around = total[at + window - block + 1] > total[at]
        at, h, more = at[around], h[around], more[around]
        if not len(at):
            return CANDIDATES.empty_table()
        by_hash, start, _ = _fold(h, more)
        first = np.minimum.reduceat(by_hash, start)  # texts stand in the order of ids, so the first is the smallest
        h, more, owner, many = h[first], more[first], ids[chunk.place(at[first])[0]], np.diff(np.append(start, len(h))) > 1
        bucket = ((h >> U64(40)) % U64(buckets)).astype(np.int64)
        order = np.lexsort((owner, bucket))
        h, more, owner, many = h[order], more[order], owner[order], many[order]
        bounds = _split(bucket[order], buckets)
        me = docs["chunk"][0].as_py()
        return _table([(b, me, h[i:j].tobytes(), more[i:j].tobytes(), _steps(owner[i:j]), np.packbits(many[i:j]).tobytes()) for b, (i, j) in enumerate(zip(bounds[:-1], bounds[1:])) if j > i], CANDIDATES)

    return run


def _order(table: pa.Table) -> pa.Table:
    hashes = [np.frombuffer(x, U64) for x in table["hashes"].to_pylist()]
    sizes = list(map(len, hashes))
    h = np.concatenate(hashes)
    more = np.concatenate([np.frombuffer(x, np.uint32) for x in table["more"].to_pylist()])
    owner = np.concatenate([_from_steps(x) for x in table["ids"].to_pylist()])
    many = np.concatenate([np.unpackbits(np.frombuffer(x, np.uint8), count=n) for x, n in zip(table["again"].to_pylist(), sizes)]) > 0
    names = table["chunk"].to_numpy().astype(np.int64)
    chunk = np.repeat(names, sizes)
    order, start, group = _fold(h, more)
    least = np.minimum.reduceat(owner[order], start)[group]  # smallest id, and of its chunks the smallest
    where = np.minimum.reduceat(np.where(owner == least, chunk, LAST)[order], start)[group]
    later = owner > least  # rows that share an id never stand before each other
    rows, i = [], 0
    for me, n in zip(names.tolist(), sizes):
        s = np.arange(i, i + n)
        i += n
        away, here = s[later[s]], s[many[s] & ~later[s]]
        if len(away) or len(here):
            away = away[np.lexsort((least[away], where[away]))]
            both = lambda at: np.rec.fromarrays((h[at], more[at]), dtype=PAIR).tobytes()
            rows.append((me, both(away), _steps(where[away]), np.diff(least[away], prepend=np.int64(0)).astype("<i8").tobytes(), both(here)))
    return _table(rows, VERDICTS)


RESULT = pa.schema([("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_removed", pa.int64()), ("kept_sha256", pa.string()), ("text", pa.string())])
RUNS = pa.schema([("chunk", pa.int32()), ("owner", pa.int64()), ("body", pa.binary())])


def spread(at: np.ndarray, size: int, n: int) -> np.ndarray:
    """Which of ``n`` words the windows of ``size`` words that begin at ``at`` cover."""
    return np.cumsum(np.bincount(at, minlength=n + 1) - np.bincount(at + size, minlength=n + 1))[:n] > 0


class Verdicts:
    """Which windows of a chunk start earlier, and where those of other chunks do."""

    def __init__(self, chunk: Chunk, ids: np.ndarray, verdicts: pa.Table, window: int, compare: bool):
        at, h, more = chunk.keys(window)
        away, here = (np.concatenate([np.frombuffer(x, PAIR) for x in verdicts[name].to_pylist()]) for name in ("elsewhere", "here"))
        named = np.concatenate((away, here))
        sieve, low = np.zeros(1 << 22, bool), U64((1 << 22) - 1)
        sieve[named["h"] & low] = True
        near = np.flatnonzero(sieve[h & low])
        order, start, group = _fold(np.concatenate((h[near], named["h"])), np.concatenate((more[near], named["m"])))
        n, e = len(near), len(near) + len(away)
        source = np.full(len(start), -1)  # line of ``away`` that says where a window starts first
        source[group[n:e]] = np.arange(e - n)
        home = np.zeros(len(start), bool)
        home[group[e:]] = True
        hit = (source >= 0) | home
        near, group = near[hit[group[:n]]], group[:n][hit[group[:n]]]
        self.at, self.line, n = at[near], source[group], len(near)
        self.away = self.line >= 0
        local = np.flatnonzero(home[group])
        row = chunk.place(self.at[local])[0]
        mine = group[local]
        least = np.full(len(start), n)
        np.minimum.at(least, mine, local)  # rows stand in the order of ids
        smallest = ids[chunk.place(self.at[np.minimum(least, max(0, n - 1))])[0]] if n else np.empty(0, np.int64)
        _, first, back = np.unique(mine * len(chunk.texts) + row, return_index=True, return_inverse=True)
        earlier = local[first][back]  # first of the same words in the same row
        lead = np.where(ids[row] > smallest[mine], least[mine], earlier) if len(local) else local
        self.drop = self.away.copy()
        self.drop[local] = lead != local
        later = local[lead != local]
        if compare and len(later):
            spot = np.unique(np.concatenate((later, lead[lead != local])))
            number = np.full(chunk.n, -1)
            inside = np.flatnonzero(spread(self.at[spot], window, chunk.n))
            number[inside] = chunk.numbers(inside)
            x, y = self.at[later], self.at[lead[lead != local]]
            if any((number[x + k] != number[y + k]).any() for k in range(window)):
                raise ValueError(COLLISION)
        self.chunks = np.concatenate([_from_steps(x) for x in verdicts["chunks"].to_pylist()])
        self.owners = np.concatenate([np.cumsum(np.frombuffer(x, "<i8"), dtype=np.int64) for x in verdicts["owners"].to_pylist()])


COLLISION = "two different word sequences share a hash of 96 bits; give another seed"


def _cut(window: int, seed: int, with_text: bool):
    def run(docs: pa.Table, verdicts: pa.Table) -> pa.Table:
        if not docs.num_rows:
            return RESULT.empty_table()
        ids, there, texts = _texts(docs)
        covered = None
        if verdicts.num_rows:
            chunk = Chunk(texts, seed)
            found = Verdicts(chunk, ids, verdicts, window, True)
            covered = spread(found.at[found.drop], window, chunk.n)
        out = []
        for k, text in enumerate(texts):
            words = text.split()
            n, gone = len(words), 0
            if covered is not None:
                mask = covered[chunk.first[k] : chunk.first[k + 1]]
                gone = int(mask.sum())
                if gone:
                    words = compress(words, (~mask).tolist())
            kept = b" ".join(words)
            out.append((int(ids[k]) if there[k] else None, n, gone, hashlib.sha256(kept).hexdigest(), kept.decode() if with_text else None))
        return _table(out, RESULT)

    return run


def _runs(window: int, seed: int):
    """Distinct stretches that are cut because they start in another chunk, with the document where they are said to start."""

    def run(docs: pa.Table, verdicts: pa.Table) -> pa.Table:
        if not docs.num_rows or not verdicts.num_rows:
            return RUNS.empty_table()
        ids, _, texts = _texts(docs)
        chunk = Chunk(texts, seed)
        found = Verdicts(chunk, ids, verdicts, window, False)
        at = found.at[found.away]
        if not len(at):
            return RUNS.empty_table()
        line = found.line[found.away]
        row = chunk.place(at)[0]
        where, owner = found.chunks[line], found.owners[line]
        new = np.ones(len(at), bool)
        new[1:] = (np.diff(at) != 1) | (np.diff(row) != 0) | (np.diff(where) != 0) | (np.diff(owner) != 0)
        start = np.flatnonzero(new)
        end = np.append(start[1:], len(at)) - 1
        out = set()
        for c, o, a, b in zip(where[start].tolist(), owner[start].tolist(), at[start].tolist(), (at[end] + window).tolist()):
            out.add((c, o, b" ".join(chunk.words(a, b))))
        return _table(list(out), RUNS)

    return run


def _check(window: int):
    def run(docs: pa.Table, runs: pa.Table) -> pa.Table:
        if not runs.num_rows:
            return RESULT.empty_table()
        wanted = set(runs["owner"].to_pylist())
        held: dict[int, list[bytes]] = {}
        for doc, text in zip(docs["doc_id"].to_pylist(), docs["body"].cast(pa.binary()).to_pylist()):
            if doc in wanted:
                held.setdefault(doc, []).append(b" " + b" ".join(text.split()) + b" ")
        for doc, body in zip(runs["owner"].to_pylist(), runs["body"].to_pylist()):
            texts = held.get(doc, [])
            if any(b" " + body + b" " in t for t in texts):
                continue
            words = body.split(b" ")  # parts of the run may stand at different places
            if not all(any(b" " + b" ".join(words[i : i + window]) + b" " in t for t in texts) for i in range(len(words) - window + 1)):
                raise ValueError(COLLISION)
        return RESULT.empty_table()

    return run


def _ddl(schema: pa.Schema) -> str:
    kinds = {"int32": "int", "int64": "long", "string": "string", "binary": "binary"}
    return ", ".join(f"{f.name} {kinds[str(f.type)]}" for f in schema)


def deal(total: int, chunk_bytes: int, bucket_bytes: int, most: int = 32 << 20) -> tuple[int, int]:
    """Chunks and buckets for so many bytes of text; chunks grow with the root of the input, up to ``most`` bytes."""
    size = min(max(most, chunk_bytes), max(chunk_bytes, int(chunk_bytes * math.sqrt(total / (1 << 30)))))
    return max(1, -(-total // size)), max(1, -(-total // bucket_bytes))


def substring_dedup(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", window: int = 20, chunk_bytes: int = 4 << 20, bucket_bytes: int = 8 << 20, seed: int = 0, with_text: bool = True) -> DataFrame:
    """``doc_id, n_words, n_removed, kept_sha256, text``: documents without the words of later repeats.

    Words are maximal runs of bytes other than space and 0x09-0x0D, unchanged.  A word goes when a window of
    ``window`` consecutive words of its document covers it and the same words also start earlier: in a smaller id, or
    earlier in the same document.  Windows are judged on the input.  ``text`` has the kept words joined by one space.

    Null texts have no words.  Rows that share an id are documents of their own, none before the other, so repeated rows get
    equal rows.  Rows with a null id stand behind all others, none before the other, and the null is passed on.  Other
    columns are ignored.  An empty input gives an empty result.
    """
    ship(docs.sparkSession)
    block = (window + 1) // 2
    body = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), body.alias("body"))
    chunks, buckets = deal(text_bytes(docs, text_col), chunk_bytes, bucket_bytes)
    rows = rows.withColumn("chunk", F.pmod(F.xxhash64("doc_id", "body"), F.lit(chunks)).cast("int"))
    probes = rows.groupBy("chunk").applyInArrow(_probe(buckets, block, seed), _ddl(PROBE))
    hits = probes.groupBy("bucket").applyInArrow(_match, _ddl(HITS))
    near = rows.groupBy("chunk").cogroup(hits.groupBy("chunk")).applyInArrow(_extend(buckets, block, window, seed), _ddl(CANDIDATES))
    verdicts = near.groupBy("bucket").applyInArrow(_order, _ddl(VERDICTS)).groupBy("chunk")
    cut = rows.groupBy("chunk").cogroup(verdicts).applyInArrow(_cut(window, seed, with_text), _ddl(RESULT))
    runs = rows.groupBy("chunk").cogroup(verdicts).applyInArrow(_runs(window, seed), _ddl(RUNS)).distinct()  # combined before the shuffle
    checked = rows.groupBy("chunk").cogroup(runs.groupBy("chunk")).applyInArrow(_check(window), _ddl(RESULT))  # no rows, or an error
    return cut.unionAll(checked)
