"""Quality classifier by attention-based multiple-instance learning.

A document is a bag of passages.  A passage is its words, hashed to places whose embeddings are learned, beside
statistics of its bytes and words; nothing of the rest of the document goes into it.  A gated attention network weighs
the passages, and the weighted representation is scored.  Only documents carry labels; which passages matter is
learned.  The model is trained on the driver from a bounded, documented sample of labelled documents, each taken
whole, and is a few kilobytes; every whole text is scored where it lies.
"""

from __future__ import annotations

import math
import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..shipping import ship
from .common import released, sliced

#: Words in a passage; a last passage shorter than half joins the one before.
PASSAGE = 128
#: Places that words are hashed to, and words that a worker remembers before it starts anew.
PLACES, REMEMBERED = 256, 100_000
_CLASS = np.zeros(256, np.int64)  # 0: other bytes
for _k, _chars in enumerate((b" \t\n\x0b\x0c\r", b"abcdefghijklmnopqrstuvwxyz", b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"0123456789", b".,;:", b"!?", b"#*$%&|<>", b"'\"()[]{}", b"-_/\\=+~^@`"), 1):
    _CLASS[list(_chars)] = _k
_CLASS[128:] = 10
CLASSES = 11
COUNTS = CLASSES + 6
WIDTH = COUNTS + PLACES


class _Places(dict):
    """The place of each word, A-Z lowered."""

    def __missing__(self, word: bytes) -> int:
        out = zlib.crc32(word.lower()) % PLACES
        if len(self) >= REMEMBERED:
            self.clear()
        self[word] = out
        return out


_PLACES = _Places()


def bounds_of(n: int) -> np.ndarray:
    """First word of each passage of a text of ``n`` words, and ``n``."""
    count = max(1, n // PASSAGE + (n % PASSAGE >= PASSAGE // 2))
    out = np.arange(count + 1) * PASSAGE
    out[-1] = n
    return out


def passages(text: bytes) -> np.ndarray:
    """One row of WIDTH numbers for each passage of a whole text; a single row for a text without words."""
    words = text.split()
    n = len(words)
    raw = np.frombuffer(text, np.uint8)
    if not n:
        row = np.zeros((1, WIDTH), np.float32)
        row[0, CLASSES] = 1.0
        return row
    bounds = bounds_of(n)
    count = len(bounds) - 1
    kind = _CLASS[raw]
    solid = kind != 1
    start = np.flatnonzero(solid & np.concatenate(([True], ~solid[:-1])))  # first byte of each word
    edge = np.concatenate((start[bounds[:-1]], [len(raw)]))
    edge[0] = 0
    passage = np.repeat(np.arange(count), np.diff(edge))
    mix = np.bincount(passage * CLASSES + kind, minlength=count * CLASSES).reshape(count, CLASSES).astype(float)
    size = mix.sum(1, keepdims=True)
    solid_size = np.maximum(size[:, 0] - mix[:, 1], 1)
    out = np.zeros((count, WIDTH), np.float32)
    out[:, :CLASSES] = np.sqrt(mix / size)
    length = np.diff(bounds).astype(float)
    feeds = np.bincount(passage, raw == 10, minlength=count)
    for k in range(count):
        part = words[bounds[k] : bounds[k + 1]]
        m = len(part)
        pairs = set(zip(part, part[1:]))
        out[k, CLASSES + 1] = len(set(part)) / m
        out[k, CLASSES + 2] = len(pairs) / max(1, m - 1)
    c = CLASSES
    out[:, c + 3] = solid_size / length / 10
    out[:, c + 4] = feeds / length
    out[:, c + 5] = mix[:, 6] / length  # marks of emphasis for each word
    place = np.fromiter(map(_PLACES.__getitem__, words), np.int64, n) + np.repeat(np.arange(count) * PLACES, np.diff(bounds))
    out[:, COUNTS:] = np.sqrt(np.bincount(place, minlength=count * PLACES).reshape(count, PLACES) / length[:, None])
    return out


@dataclass
class AttentionModel:
    """Encoder, gated attention and scorer; ``mean`` and ``scale`` standardise passages."""

    mean: np.ndarray
    scale: np.ndarray
    weights: dict[str, np.ndarray]
    prior: float

    def score(self, rows: np.ndarray, bag: np.ndarray, bags: int) -> np.ndarray:
        """Score of each bag; ``bag`` ascends and has the bag of each row."""
        return _sigmoid(_forward(self.weights, (rows - self.mean) / self.scale, bag, bags)[-1])

    def attention(self, rows: np.ndarray, bag: np.ndarray, bags: int) -> np.ndarray:
        """Weight of each row in its bag; those of a bag add up to one."""
        return _forward(self.weights, (rows - self.mean) / self.scale, bag, bags)[3]


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -40, 40)))


def _sum(values: np.ndarray, bag: np.ndarray, bags: int) -> np.ndarray:
    head = np.searchsorted(bag, np.arange(bags))
    return np.add.reduceat(values, head, axis=0)


def _forward(w: dict[str, np.ndarray], x: np.ndarray, bag: np.ndarray, bags: int) -> tuple:
    h = np.tanh(x @ w["enc"] + w["enc0"])
    t, g = np.tanh(h @ w["att"]), _sigmoid(h @ w["gate"])
    e = (t * g) @ w["pick"]
    top = np.full(bags, -np.inf)
    np.maximum.at(top, bag, e)
    u = np.exp(e - top[bag])
    a = u / _sum(u, bag, bags)[bag]
    z = _sum(a[:, None] * h, bag, bags)
    return h, t, g, a, z, z @ w["out"] + w["out0"]


def train(bags: list[np.ndarray], labels: np.ndarray, *, hidden: int = 24, attention: int = 12, epochs: int = 60, batch: int = 128, rate: float = 0.01, decay: float = 1e-4, seed: int = 7) -> AttentionModel:
    """Adam on the logistic loss, classes weighted by the square root of their rarity; gradients written out."""
    rng = np.random.default_rng(seed)
    total = sum(map(len, bags))
    mean = sum(b.sum(0, dtype=float) for b in bags) / total
    scale = np.sqrt(sum(((b - mean) ** 2).sum(0) for b in bags) / total) + 0.02
    share = float(np.clip(labels.mean(), 1e-3, 1 - 1e-3))
    d = bags[0].shape[1]
    w = {"enc": rng.normal(0, 1 / math.sqrt(d), (d, hidden)), "enc0": np.zeros(hidden), "att": rng.normal(0, 1 / math.sqrt(hidden), (hidden, attention)), "gate": rng.normal(0, 1 / math.sqrt(hidden), (hidden, attention)), "pick": rng.normal(0, 0.1, attention), "out": rng.normal(0, 0.1, hidden), "out0": np.zeros(1)}
    first = {k: np.zeros_like(v) for k, v in w.items()}
    second = {k: np.zeros_like(v) for k, v in w.items()}
    bags = [((b - mean) / scale).astype(np.float32) for b in bags]
    cost = np.where(labels > 0, 1.0, math.sqrt(share / (1 - share)))
    step = 0
    for epoch in range(epochs):
        order = rng.permutation(len(bags))
        for s in range(0, len(order), batch):
            pick = order[s : s + batch]
            x = np.concatenate([bags[i] for i in pick])
            bag = np.repeat(np.arange(len(pick)), [len(bags[i]) for i in pick])
            h, t, g, a, z, out = _forward(w, x, bag, len(pick))
            d_out = (_sigmoid(out) - labels[pick]) * cost[pick] / len(pick)
            d_z = d_out[:, None] * w["out"]
            d_a = (d_z[bag] * h).sum(1)
            d_e = a * (d_a - _sum(a * d_a, bag, len(pick))[bag])
            d_tg = d_e[:, None] * w["pick"]
            d_t, d_g = d_tg * g * (1 - t * t), d_tg * t * g * (1 - g)
            d_h = a[:, None] * d_z[bag] + d_t @ w["att"].T + d_g @ w["gate"].T
            d_x = d_h * (1 - h * h)
            grad = {"enc": x.T @ d_x, "enc0": d_x.sum(0), "att": h.T @ d_t, "gate": h.T @ d_g, "pick": (t * g).T @ d_e, "out": z.T @ d_out, "out0": d_out.sum(keepdims=True)}
            step += 1
            for k in w:
                q = grad[k] + decay * w[k]
                first[k] = 0.9 * first[k] + 0.1 * q
                second[k] = 0.999 * second[k] + 0.001 * q * q
                w[k] = w[k] - rate * (0.98**epoch) * (first[k] / (1 - 0.9**step)) / (np.sqrt(second[k] / (1 - 0.999**step)) + 1e-8)
    return AttentionModel(mean, scale, w, share)


def _constant(label: float) -> AttentionModel:
    w = {"enc": np.zeros((WIDTH, 1)), "enc0": np.zeros(1), "att": np.zeros((1, 1)), "gate": np.zeros((1, 1)), "pick": np.zeros(1), "out": np.zeros(1), "out0": np.array([6.0 if label > 0.5 else -6.0])}
    return AttentionModel(np.zeros(WIDTH), np.ones(WIDTH), w, label)


def held_out(id_: Column) -> Column:
    """Rows that are never learned from: crc32 of the id as text is a multiple of five."""
    return F.pmod(F.crc32(F.coalesce(id_.cast("string"), F.lit("")).cast("binary")), F.lit(5)) == 0


def _encode(batches):
    for batch in sliced(batches):
        texts = batch.column("body").cast(pa.binary()).to_pylist()
        bags = [passages(t or b"") for t in texts]
        yield pa.record_batch([batch.column("doc_id"), batch.column("label"), pa.array([len(b) for b in bags], pa.int32()), pa.array([b.astype("<f4").tobytes() for b in bags], pa.large_binary())], names=["doc_id", "label", "n", "bag"])


def fit(docs: DataFrame, labels: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", sample_rows: int = 8_000, sample_bytes: int = 32 << 20, **options) -> AttentionModel:
    """A model from labelled documents outside the held-out fold, taken whole in the order of a hash of their id.

    At most ``sample_rows`` of them, and only as many as have ``sample_bytes`` of text together, so that training fits the
    driver; a single text above that is left out.  A document labelled twice with different values counts as 0; of rows
    that share an id the smallest text counts.  Without usable rows every text scores high.
    """
    ship(docs.sparkSession)
    usable = labels.where(F.col(label_col).isNotNull() & F.col(id_col).isNotNull() & ~held_out(F.col(id_col)))
    chosen = usable.groupBy(F.col(id_col).cast("long").alias("doc_id")).agg(F.min(label_col).cast("int").alias("label")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample_rows)
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("body"))
    size = F.octet_length("body").cast("long")
    sizes = rows.join(F.broadcast(chosen), "doc_id").where(size <= sample_bytes).groupBy("doc_id", "label").agg(F.min(F.struct("body", size.alias("size")))["size"].alias("size"))
    order = Window.orderBy(F.xxhash64("doc_id"), "doc_id").rowsBetween(Window.unboundedPreceding, 0)  # sample_rows at most
    picked = sizes.withColumn("until", F.sum("size").over(order)).where(F.col("until") <= sample_bytes).select("doc_id", "label", "size")
    taken = rows.join(F.broadcast(picked), "doc_id").where(size <= sample_bytes).groupBy("doc_id", "label").agg(F.min("body").alias("body"))
    seen = taken.mapInArrow(released(_encode), "doc_id long, label int, n int, bag binary").toArrow()
    seen = seen.sort_by("doc_id")
    if not seen.num_rows:
        return _constant(1.0)
    y = seen["label"].to_numpy().astype(float)
    if y.min() == y.max():
        return _constant(float(y[0]))
    packed, sizes = seen["bag"].to_pylist(), seen["n"].to_pylist()
    del seen  # the sample is held once
    return train([np.frombuffer(packed.pop(), "<f4").reshape(n, WIDTH) for n in reversed(sizes)][::-1], y, **options)


def _scores(model: AttentionModel, texts: list[bytes | None], most: int = 8_192) -> np.ndarray:
    """Score of each text, in slices of about ``most`` passages."""
    out, bags, held = [np.empty(0)], [], 0
    for i, text in enumerate(texts, 1):
        bags.append(passages(text or b""))
        held += len(bags[-1])
        if held >= most or i == len(texts):
            out.append(model.score(np.concatenate(bags), np.repeat(np.arange(len(bags)), [len(b) for b in bags]), len(bags)).astype(float))
            bags, held = [], 0
    return np.concatenate(out)


def _score(model: AttentionModel):
    def run(batches):
        for batch in sliced(batches):
            yield pa.record_batch([batch.column("doc_id"), pa.array(_scores(model, batch.column("body").cast(pa.binary()).to_pylist()))], names=["doc_id", "score"])

    return run


def quality_scores(docs: DataFrame, model: AttentionModel, *, id_col: str = "doc_id", text_col: str = "text", threshold: float = 0.3) -> DataFrame:
    """``doc_id, held_out, score, predicted`` of each row.

    Only the text goes into a score, from 0 to 1, higher for label 1; null and empty texts are one passage without
    words.  Repeated rows get equal rows; a null id is passed on.  Other columns are ignored.  An empty input gives an
    empty result.
    """
    ship(docs.sparkSession)
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("body"))
    scored = rows.mapInArrow(released(_score(model)), "doc_id long, score double")
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def passage_weights(docs: DataFrame, model: AttentionModel, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, passage, first_word, n_words, weight``: one row per passage, with its share of its document's score.

    The weights of a document add up to one.  Null and empty texts are one passage of no words.
    """
    ship(docs.sparkSession)
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("body"))

    def run(batches):
        for batch in batches:
            ids, texts = batch.column("doc_id").to_pylist(), batch.column("body").cast(pa.binary()).to_pylist()
            for doc, text in zip(ids, texts):
                bag = passages(text or b"")
                edge = bounds_of(len((text or b"").split()))
                weight = model.attention(bag, np.zeros(len(bag), np.int64), 1).astype(float)
                yield pa.record_batch([pa.array([doc] * len(bag), pa.int64()), pa.array(np.arange(len(bag)), pa.int32()), pa.array(edge[:-1], pa.int64()), pa.array(np.diff(edge), pa.int64()), pa.array(weight)], names=["doc_id", "passage", "first_word", "n_words", "weight"])

    return rows.mapInArrow(run, "doc_id long, passage int, first_word long, n_words long, weight double")


def keep_good(docs: DataFrame, model: AttentionModel, *, id_col: str = "doc_id", text_col: str = "text", threshold: float = 0.3) -> DataFrame:
    """The rows of ``docs`` that score at or above the threshold, all columns unchanged, in one narrow pass."""
    ship(docs.sparkSession)
    names = docs.columns
    plain = docs.select(*[F.col(f"`{c}`").alias(f"c{i}") for i, c in enumerate(names)])
    mine = names.index(text_col)

    def run(batches):
        for batch in sliced(batches):
            yield batch.filter(pa.array(_scores(model, batch.column(mine).cast(pa.binary()).to_pylist()) >= threshold))

    return plain.mapInArrow(released(run), plain.schema).toDF(*names)
