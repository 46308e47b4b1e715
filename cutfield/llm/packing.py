"""Packing of tokenised documents into fixed windows by non-negative least squares over length combinations.

1. Tokenise once into a shared table; every row knows its task and its rank among that task's rows of equal rest
   length, so no row is ever gathered to be numbered.
2. Whole windows of long documents are sequences of their own; what is left of each document has a rest length below
   the window, and the histogram of those lengths is all the driver sees (fewer rows than the window has places).
3. All combinations of up to three lengths that fill a window, or a part of it by a power of two, exactly are
   enumerated; non-negative least squares finds how often to use each so that the histogram is met best; the
   counts are rounded, and the method is run again on what is left until no combination fits any more.
4. Parts of windows stand in falling sizes, so they fill windows together.  Rests that no combination takes are packed
   greedily behind them, longest first, cut where a window ends.  The last window's remainder is cut at powers of
   two, which need no padding.

Every place follows from (length, rank) by a table bounded by the window, so assignment is one narrow pass.
"""

from __future__ import annotations

import json
import unicodedata
import zlib
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..shipping import ship
from .common import SharedTable, released, rows_at_once, sliced

TOKENS = "part int, doc_id long, ids binary, n int, rest int, rank long, full_rank long"
#: Distinct words that a worker remembers before it starts anew, and the longest one that it remembers.
REMEMBERED, LONGEST = 500_000, 48
#: Texts that a task hands to Python at once.
TEXT_ROWS = 1024


#: Last letter of the Latin blocks, where lower case is the same everywhere.
LATIN = "\u024f"
_PRINTED = {*range(33, 127), *range(161, 173), *range(174, 256)}
#: Characters that stand for bytes in byte-level vocabularies: printed ones for themselves, the others from 256 on, in order.
_BYTE_CHARS = {b: 256 + i for i, b in enumerate(sorted(set(range(256)) - _PRINTED))}


#: Normaliser and splitter that the quick way by words rests on (fixed values); other files are read text by text.
_NORMAL = [{"type": "NFC"}, {"type": "Replace", "pattern": {"Regex": r"\s+"}, "content": " "}, {"type": "Lowercase"}]
_WORDS = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"


def _by_words(spec: dict) -> bool:
    """Whether a tokenizer file lower-cases, cuts at white space and merges bytes inside words, so that words may be coded apart."""
    normal, split, model = spec.get("normalizer") or {}, spec.get("pre_tokenizer") or {}, spec.get("model") or {}
    parts = split.get("pretokenizers") or [{}]
    return (
        normal.get("normalizers") == _NORMAL
        and len(parts) == 2
        and parts[0].get("pattern") == {"Regex": _WORDS}
        and parts[0].get("behavior") == "Removed"
        and parts[0].get("invert") is True
        and parts[1].get("type") == "ByteLevel"
        and not parts[1].get("add_prefix_space")
        and not parts[1].get("use_regex")
        and model.get("type") == "BPE"
        and not model.get("dropout")
    )


class WordCoder(dict):
    """Ids of each word, packed; words are split at ASCII white space, over which such a tokenizer never merges."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        super().__init__()
        self.tokenizer = Tokenizer.from_file(path)
        with open(path, encoding="utf-8") as file:
            self.by_words = _by_words(json.load(file))
        self.tokenizer.no_truncation()
        self.tokenizer.no_padding()
        self.model = self.tokenizer.model
        self.kind = "<u2" if self.tokenizer.get_vocab_size() <= 1 << 16 else "<u4"
        self.special = [t.content.encode() for t in self.tokenizer.get_added_tokens_decoder().values()]

    def raw(self, text: bytes) -> bytes:
        return np.array(self.tokenizer.encode(text.decode(), add_special_tokens=False).ids, self.kind).tobytes()

    def fresh(self, word: bytes) -> bytes:
        """Ids of a word, A-Z lowered already; Latin letters go to the merge model at once, with marks behind them apart, as the tokenizer would cut."""
        core = word.rstrip(b".,;:!?")
        if core.isascii():
            if not core.isalpha():
                return self.raw(word)
            letters = core.decode()
        else:
            text = unicodedata.normalize("NFC", core.decode())
            if not text.isalpha() or max(text) > LATIN or "\u0130" in text:
                return self.raw(word)
            letters = text.lower().encode().decode("latin-1").translate(_BYTE_CHARS)
        if len(core) < len(word):
            return self[core] + self[word[len(core) :]]
        return np.array([t.id for t in self.model.tokenize(letters)], self.kind).tobytes()

    def __missing__(self, word: bytes) -> bytes:
        out = self.fresh(word)
        if len(word) <= LONGEST:
            if len(self) >= REMEMBERED:
                self.clear()
            self[word] = out
        return out

    def ids(self, text: bytes) -> bytes:
        if not self.by_words or any(s in text for s in self.special):
            return self.raw(text)
        return b"".join(map(self.__getitem__, text.lower().split()))  # of bytes: A-Z alone, which the tokenizer lowers too


@lru_cache(maxsize=2)
def word_coder(path: str) -> WordCoder:
    import os

    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    return WordCoder(path)


def _tokenise(path: str, end_id: int, window: int):
    def run(batches):
        from pyspark import TaskContext

        code = word_coder(path)
        width = np.dtype(code.kind).itemsize
        end = np.array([end_id], code.kind).tobytes()
        part = TaskContext.get().partitionId()
        seen = np.zeros(window, np.int64)
        full = 0
        for batch in sliced(batches):
            docs, texts = batch.column("doc_id"), batch.column("body").cast(pa.binary()).to_pylist()
            at = 0
            while at < len(texts):  # slices of bounded size, whatever the batch
                rows, size, first = [], 0, at
                while at < len(texts) and size < 4 << 20:
                    ids = code.ids(texts[at] or b"") + end
                    n = len(ids) // width
                    rest = n % window
                    rows.append((ids, n, rest, int(seen[rest]), full))
                    seen[rest] += 1
                    full += n // window
                    size += len(ids)
                    at += 1
                ids, n, rest, rank, fulls = zip(*rows)
                yield pa.record_batch([pa.array([part] * len(rows), pa.int32()), docs.slice(first, len(rows)), pa.array(ids, pa.binary()), pa.array(n, pa.int32()), pa.array(rest, pa.int32()), pa.array(rank, pa.int64()), pa.array(fulls, pa.int64())], names=["part", "doc_id", "ids", "n", "rest", "rank", "full_rank"])

    return run


def combinations_of(lengths: np.ndarray, counts: np.ndarray, window: int) -> np.ndarray:
    """Rows of three falling lengths (zero: none) that sum to the window, none used more often than it is there; all of them."""
    stock = np.zeros(window + 1, np.int64)
    inside = lengths <= window
    stock[lengths[inside]] = counts[inside]
    there = stock > 0
    out = [np.array([[window, 0, 0]])] if there[window] else []
    for a in np.flatnonzero(there[:window])[::-1]:
        left = window - a
        if left > 2 * a:
            break
        b = np.arange(-(-left // 2), min(a, left) + 1)
        c = left - b
        b, c = (x[there[b] & ((c == 0) | there[c])] for x in (b, c))
        out.append(np.stack((np.full(len(b), a), b, c), 1))
    rows = np.concatenate(out).astype(np.int32) if out else np.zeros((0, 3), np.int32)
    return rows[fits(rows, stock)]


def fits(rows: np.ndarray, stock: np.ndarray) -> np.ndarray:
    """Rows that the stock of each length can fill once."""
    a, b, c = rows.T
    pairs = 1 + (a == b) + (b == c) * (a == b)  # most frequent length of a row: a, unless only b and c are equal
    low = 1 + (b == c) * (c > 0)
    return (stock[a] >= pairs) & ((b == 0) | (stock[b] >= np.where(a == b, pairs, low))) & ((c == 0) | (stock[c] >= np.where(b == c, np.where(a == b, pairs, low), 1)))


def _meet(rows: np.ndarray, x: np.ndarray, places: int) -> np.ndarray:
    """How often each length is used."""
    out = np.zeros(places)
    for k in range(rows.shape[1]):
        out += np.bincount(rows[:, k], x, minlength=places)
    out[0] = 0.0
    return out


def _least_squares(rows: np.ndarray, goal: np.ndarray, x: np.ndarray, rounds: int = 30) -> np.ndarray:
    """Unbounded least squares over a few combinations, by conjugate gradients from ``x``."""
    pull = lambda r: r[rows].sum(1)  # noqa: E731  # transpose; place 0 of r is 0
    r = goal - _meet(rows, x, len(goal))
    r[0] = 0.0
    g = pull(r)
    d, size = g.copy(), g @ g
    enough = 1e-12 * max(1.0, size)
    for _ in range(rounds):
        if size <= enough:
            break
        step = _meet(rows, d, len(goal))
        bend = step @ step
        if bend <= 0:
            break
        x = x + size / bend * d
        r = r - size / bend * step
        g = pull(r)
        size, before = g @ g, size
        d = g + size / before * d
    return x


def _inward(rows: np.ndarray, goal: np.ndarray, x: np.ndarray, inside: np.ndarray) -> np.ndarray:
    """Least squares over the columns inside, stepping back to the border and putting out what lies on it until none is negative."""
    while True:
        on = np.flatnonzero(inside)
        z = _least_squares(rows[on], goal, x[on], 4 * len(goal))
        low = z <= 0
        if not low.any():
            x[:] = 0.0
            x[on] = z
            return x
        part = float((x[on][low] / np.maximum(x[on][low] - z[low], 1e-300)).min())
        x[on] = np.maximum(0.0, x[on] + part * (z - x[on]))
        inside[on[low & (x[on] <= 1e-12)]] = False


def nonnegative_least_squares(rows: np.ndarray, target: np.ndarray, *, rounds: int = 1000, tolerance: float = 1e-3, gain: float | None = None) -> np.ndarray:
    """x >= 0 that minimises |A x - target|, where column j of A counts the lengths of ``rows[j]``; by active sets.

    Each round lets in the columns of steepest descent that share no length, solves over the columns that are in, and puts
    those out that turn negative; few columns end up in use.  Where such a block gains nothing, one column enters at a time.
    It ends when no column outside descends by more than ``tolerance`` of the target's size, or, with ``gain``, when a round
    lowers the distance by less than that share.
    """
    x = np.zeros(len(rows))
    if not len(rows):
        return x
    goal = target.astype(float).copy()
    goal[0] = 0.0
    places, scale = len(goal), max(1e-12, float(np.sqrt(goal @ goal)))
    first, second, third = (np.ascontiguousarray(c) for c in rows.T)
    short = np.sqrt(((rows > 0).sum(1) + 2 * ((first == second) * (second > 0) + (second == third) * (third > 0) + (first == third))).astype(float))  # length of a column
    left = lambda x: goal - _meet(rows[x > 0], x[x > 0], places)
    error, single = scale, False
    for _ in range(rounds):
        r = left(x)
        slope = (r[first] + r[second] + r[third]) / short
        inside = x > 0
        slope[inside] = -np.inf
        if single:
            top = np.array([int(np.argmax(slope))])
        else:
            top = np.argpartition(-slope, 4 * places)[: 4 * places] if len(slope) > 4 * places else np.arange(len(slope))
        top = top[slope[top] > tolerance * scale / np.sqrt(places)]
        if not len(top):
            break
        taken = bytearray(places)
        top = top[np.argsort(-slope[top], kind="stable")]
        for j, (a, b, c) in zip(top.tolist(), rows[top].tolist()):
            if not (taken[a] or taken[b] or taken[c]):
                taken[a] = taken[b] = taken[c] = 1
                taken[0] = 0
                inside[j] = True
        if single:
            new = _inward(rows, goal, x.copy(), inside)
        else:
            new = x.copy()
            for _ in range(20):
                on = np.flatnonzero(inside)
                z = _least_squares(rows[on], goal, new[on])
                new[on] = np.maximum(z, 0.0)
                if (z > 0).all():
                    break
                inside[on[z <= 0]] = False
            new[~inside] = 0.0
        r = left(new)
        now = float(np.sqrt(r @ r))
        gained = now < error * (1 - (gain or 1e-9))
        if now < error:
            x, error = new, now
        if not gained:
            if gain or single:
                break
            single = True
    return x


@dataclass
class Plan:
    """Places of all rests on one line, which windows cut; for each length, the ranks that combinations take, then the others.

    ``low``, ``base`` and ``step`` say where the ranks from ``low`` on stand: at ``base``, one every ``step``.
    """

    window: int
    low: dict[int, np.ndarray]
    base: dict[int, np.ndarray]
    step: dict[int, np.ndarray]
    taken: np.ndarray
    stream: np.ndarray
    total: int

    def cuts(self, start: int, end: int) -> list[tuple[int, int, int]]:
        """(begin, sequence, offset) of each part of a stretch of the line."""
        out, tail = [], self.total - self.total % self.window
        while start < end:
            if start < tail:
                k, into = divmod(start, self.window)
                stop = start - into + self.window
            else:  # the remainder, in falling powers of two
                k, base, left = self.total // self.window, tail, self.total - tail
                while True:
                    size = 1 << (left.bit_length() - 1)
                    if start < base + size:
                        break
                    base, left, k = base + size, left - size, k + 1
                into, stop = start - base, base + size
            out.append((start, k, into))
            start = stop
        return out

    def places(self, length: int, rank: int) -> list[tuple[int, int, int, int]]:
        """(start in the rest, length, sequence, offset) of each piece of the rest of that length and rank."""
        if rank < self.taken[length]:
            i = int(np.searchsorted(self.low[length], rank, side="right")) - 1
            start = int(self.base[length][i]) + (rank - int(self.low[length][i])) * int(self.step[length][i])
        else:
            start = int(self.stream[length]) + (rank - int(self.taken[length])) * length
        parts = self.cuts(start, start + length)
        ends = [p[0] for p in parts[1:]] + [start + length]
        return [(b - start, e - b, s, o) for (b, s, o), e in zip(parts, ends)]


def repeats(counts: np.ndarray, window: int, smallest: int = 32) -> list[tuple[int, list[int], int]]:
    """(size, lengths, times) of the combinations in use: least squares, rounded, again on what is left, until none fits.

    Sizes are the window and, where it is a power of two, its halves down to ``smallest``.
    """
    sizes = [window]
    while window & (window - 1) == 0 and sizes[-1] > smallest:
        sizes.append(sizes[-1] // 2)
    left = counts.copy()
    there = np.flatnonzero(left)
    rows = np.concatenate([combinations_of(there, left[there], size) for size in sizes])
    out = []
    while len(rows):
        weight = nonnegative_least_squares(rows, left, tolerance=1e-2, gain=1e-2)
        used = np.flatnonzero(weight > 0)
        before = left.sum()
        for up in (0.5, 1.0 - 1e-6):  # to the nearest; upwards only where that places nothing
            for j in used[np.argsort(-weight[used], kind="stable")].tolist():
                parts = [x for x in rows[j].tolist() if x]
                times = min(int(weight[j] + up), *(int(left[x]) // parts.count(x) for x in parts))
                if times > 0:
                    for x in parts:
                        left[x] -= times
                    out.append((sum(parts), parts, times))
            if left.sum() < before:
                break
        if left.sum() == before:
            break
        rows = rows[fits(rows, left)]
    return out


def plan_windows(histogram: dict[int, int], window: int) -> Plan:
    """A plan for rests with these counts by length (1 to window - 1)."""
    counts = np.zeros(window + 1, np.int64)
    for length, n in histogram.items():
        counts[length] = n
    used = np.zeros(window + 1, np.int64)
    low: dict[int, list[int]] = {}
    base: dict[int, list[int]] = {}
    step: dict[int, list[int]] = {}
    at = 0
    for size, parts, times in sorted(repeats(counts, window), key=lambda x: -x[0]):  # falling sizes, so that none crosses a window's end
        into = 0
        for x in parts:
            low.setdefault(x, []).append(int(used[x]))
            base.setdefault(x, []).append(at + into)
            step.setdefault(x, []).append(size)
            used[x] += times
            into += x
        at += size * times
    stream = np.zeros(window + 1, np.int64)
    order = np.arange(window, 0, -1)  # longest first
    sizes = (counts - used)[order] * order
    stream[order] = at + np.cumsum(sizes) - sizes
    pick = lambda d: {k: np.array(v, np.int64) for k, v in d.items()}
    return Plan(window, pick(low), pick(base), pick(step), used, stream, at + int(sizes.sum()))


PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, ids binary"


def _assign(plan: Plan, kind: str, with_ids: bool):
    names = [c.split()[0] for c in PIECES.split(", ")]
    width = np.dtype(kind).itemsize

    def run(batches):
        w = plan.window
        for batch in sliced(batches):
            out: list[tuple] = []
            cols = [batch.column(i).to_pylist() for i in range(batch.num_columns)]
            for part, doc, raw, n, rest, rank, full_rank, base in zip(*cols):
                ids = np.frombuffer(raw, kind).astype("<u4")
                # whole windows are numbered by task, above all planned sequences
                cut = [(k * w, w, (part + 1 << 40) + full_rank + k, 0) for k in range(n // w)]
                if rest:
                    cut += [(n - rest + s, size, seq, o) for s, size, seq, o in plan.places(rest, base + rank)]
                for s, size, seq, o in cut:
                    out.append((doc, s, size, zlib.crc32(ids[s : s + size]), n, seq, o, raw[s * width : (s + size) * width] if with_ids else None))
                if len(out) >= 20_000:
                    yield _batch(out, names)
                    out = []
            if out:
                yield _batch(out, names)

    return run


def _batch(rows: list[tuple], names: list[str]) -> pa.RecordBatch:
    return pa.record_batch([pa.array(c, pa.binary() if k == len(names) - 1 else pa.int64()) for k, c in enumerate(zip(*rows))], names=names)


def pack(docs: DataFrame, path: str, *, id_col: str = "doc_id", text_col: str = "text", end_id: int = 2, window: int = 4096, with_ids: bool = True) -> DataFrame:
    """One row per piece: ``doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset, ids``.

    A document's ids are those of the tokenizer file at ``path`` without special tokens, then ``end_id``; null and empty
    texts have that one id.  Files of the kind that lower-cases and cuts at white space are read word by word, any other
    file text by text.  Pieces of a sequence lie gapless from offset 0 and end at the window, or at a power of two;
    ``ids`` has a piece's ids as little-endian numbers of two bytes (four for vocabularies over 65,536), or null without
    ``with_ids``.  Sequence ids are unique, not dense.  Repeated rows are packed each for itself; a null id is
    passed on.  Other columns are ignored.  An empty input gives an empty result.
    """
    ship(docs.sparkSession)
    body = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), body.alias("body"))
    with rows_at_once(docs.sparkSession, TEXT_ROWS):
        held = SharedTable(rows.mapInArrow(released(_tokenise(path, end_id, window)), TOKENS), "tokens")
    tokens = held.read()
    counts = tokens.where("rest > 0").groupBy("part", "rest").agg(F.count(F.lit(1)).alias("n"))
    earlier = Window.partitionBy("rest").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    bases = counts.select("part", "rest", F.coalesce(F.sum("n").over(earlier), F.lit(0)).alias("base"))
    plan = plan_windows({r["rest"]: r["n"] for r in counts.groupBy("rest").agg(F.sum("n").alias("n")).collect()}, window)
    placed = tokens.join(bases, ["part", "rest"], "left").select("part", "doc_id", "ids", "n", "rest", "rank", "full_rank", F.coalesce("base", F.lit(0)).alias("base"))
    kind = word_coder(path).kind
    return placed.mapInArrow(released(_assign(plan, kind, with_ids)), PIECES)
