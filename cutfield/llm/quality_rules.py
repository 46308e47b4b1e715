"""Learned decision lists over document statistics.  Features and verdicts are DataFrame functions only.

``learn_rules`` reads a bounded sample of labelled statistics and covers the rejected class sequentially: a
rule grows one threshold test at a time by information gain on two thirds of the rows, is pruned from its
end on the other third, and is kept while it stays precise there; rows it covers leave the pool.  The list
becomes one ordered ``CASE WHEN`` expression.
"""

from __future__ import annotations

import math
import zlib
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import SPACE_CLASS, text_or_empty, words

#: Ratios of the base statistics that rules may test.
FEATURES = ("n_words", "word_length", "symbols_per_word", "dup_line_share", "repeat_share", "upper_share", "bang_share", "digit_share", "distinct_share", "words_per_line", "alpha_share")


def statistics(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", carry: tuple[str, ...] = ()) -> DataFrame:
    """doc_id, the carried columns, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words and FEATURES, from whole texts."""
    text = text_or_empty(text_col)
    df = docs.select(F.col(id_col).alias("doc_id"), *carry, text.alias("body")).withColumn("w", words(F.col("body")))
    n = F.size("w")
    # hashes of the 5-word windows, in place order
    window = lambda i: F.xxhash64(*(F.get("w", i + k) for k in range(5)))
    df = df.withColumn("h", F.when(n >= 5, F.transform(F.sequence(F.lit(0), n - 5), window)).otherwise(F.array().cast("array<long>")))
    # sorted (hash, place) rows stand next to their equals; only texts with a repeat get that far
    placed = F.array_sort(F.transform("h", lambda x, i: F.struct(x.alias("x"), i.alias("i"))))
    df = df.withColumn("p", F.when(F.size(F.array_distinct("h")) < F.size("h"), placed))
    same = lambda a, b: F.coalesce(F.get("p", a)["x"] == F.get("p", b)["x"], F.lit(False))
    twice = F.array_sort(F.transform(F.filter("p", lambda _, j: ((j > 0) & same(j, F.greatest(j - 1, F.lit(0)))) | same(j, j + 1)), lambda s: s["i"]))
    df = df.withColumn("q", twice)
    # merged cover of the windows: each adds 5 words, or as many as lie before the next start
    reach = F.aggregate(F.transform("q", lambda s, j: F.least(F.lit(5), F.coalesce(F.get("q", j + 1) - s, F.lit(5)))), F.lit(0), lambda a, x: a + x)
    lines = F.filter(F.split("body", "\n"), lambda x: F.btrim(x, F.lit(" \t\x0b\x0c\r")) != "")
    left = lambda chars: F.char_length("body") - F.char_length(F.translate("body", chars, ""))
    # one struct through a generator: a later filter on a statistic stays above it, instead of being computed again for each test
    counts = F.struct(
        n.cast("long").alias("n_words"),
        F.char_length(F.array_join("w", "")).cast("long").alias("word_chars"),
        left("#*$%&|<>").cast("long").alias("n_symbols"),
        (F.size(lines) - F.size(F.array_distinct(lines))).cast("long").alias("n_dup_lines"),
        F.coalesce(reach, F.lit(0)).cast("long").alias("n_repeat_words"),
        left("ABCDEFGHIJKLMNOPQRSTUVWXYZ").alias("upper"), left("!").alias("bang"), left("0123456789").alias("digits"),
        F.size(F.array_distinct("w")).alias("distinct"), F.size(lines).alias("lines"),
        left("#*$%&|<>!?.,;:()[]{}\"'/\\-_=+~^@0123456789").alias("marks"),
    )
    df = df.select("doc_id", *carry, F.explode(F.array(counts)).alias("s")).select("doc_id", *carry, "s.*")
    per = lambda a, b: F.when(F.col(b) > 0, F.col(a) / F.col(b)).otherwise(F.lit(0.0))
    return df.select(
        "doc_id", *carry, "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words",
        per("word_chars", "n_words").alias("word_length"), per("n_symbols", "n_words").alias("symbols_per_word"),
        per("n_dup_lines", "lines").alias("dup_line_share"), per("n_repeat_words", "n_words").alias("repeat_share"),
        per("upper", "word_chars").alias("upper_share"), per("bang", "n_words").alias("bang_share"),
        per("digits", "word_chars").alias("digit_share"), per("distinct", "n_words").alias("distinct_share"),
        per("n_words", "lines").alias("words_per_line"), (F.lit(1.0) - per("marks", "word_chars")).alias("alpha_share"),
    )


def base_failed() -> Column:
    return (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))


@dataclass(frozen=True)
class Test:
    feature: str
    above: bool
    at: float

    def holds(self, row: dict) -> bool:
        return (row[self.feature] > self.at) == self.above

    def column(self) -> Column:
        return F.col(self.feature) > F.lit(self.at) if self.above else F.col(self.feature) <= F.lit(self.at)

    def __str__(self) -> str:
        return f"{self.feature} {'>' if self.above else '<='} {self.at:.6g}"


@dataclass(frozen=True)
class DecisionList:
    """Ordered conjunctions that reject; a row that none covers is kept."""

    rules: tuple[tuple[Test, ...], ...]

    def verdict(self) -> Column:
        """The ordered conditional expression: true keeps."""
        out = None
        for rule in self.rules:
            test = F.lit(True)
            for t in rule:
                test = test & t.column()
            out = F.when(test, False) if out is None else out.when(test, False)
        return F.lit(True) if out is None else out.otherwise(True)

    def __str__(self) -> str:
        return "\n".join("reject if " + " and ".join(map(str, r)) for r in self.rules) + "\nkeep otherwise"


def _gain(p0: int, n0: int, p1: int, n1: int) -> float:
    if not p1:
        return -1.0
    return p1 * (math.log2(p1 / (p1 + n1)) - math.log2(p0 / (p0 + n0)))


def _best_test(rows: list[dict], features: tuple[str, ...]) -> tuple[float, Test | None]:
    p0 = sum(r["_bad"] for r in rows)
    n0 = len(rows) - p0
    best: tuple[float, Test | None] = (1e-9, None)
    for f in features:
        order = sorted(rows, key=lambda r: r[f])
        p = n = 0
        for i, r in enumerate(order[:-1]):
            p, n = p + r["_bad"], n + (not r["_bad"])
            if order[i + 1][f] > r[f]:
                at = (r[f] + order[i + 1][f]) / 2
                for above, x in ((False, _gain(p0, n0, p, n)), (True, _gain(p0, n0, p0 - p, n0 - n))):
                    if x > best[0]:
                        best = (x, Test(f, above, at))
    return best


def cover(rows: list[dict], features: tuple[str, ...] = FEATURES, *, max_rules: int = 24, max_tests: int = 5, precision: float = 0.8, least: int = 4) -> DecisionList:
    """Sequential covering over labelled statistics; each row has the features, ``_bad`` and ``_fold`` (0: prune, else grow)."""
    rules: list[tuple[Test, ...]] = []
    pool = list(rows)
    while len(rules) < max_rules:
        grow, prune = [r for r in pool if r["_fold"]], [r for r in pool if not r["_fold"]]
        rule: list[Test] = []
        inside = grow
        while len(rule) < max_tests and any(not r["_bad"] for r in inside):
            _, test = _best_test(inside, features)
            if test is None:
                break
            rule.append(test)
            inside = [r for r in inside if test.holds(r)]

        def worth(k: int, rule=rule, prune=prune) -> float:
            hit = [r["_bad"] for r in prune if all(t.holds(r) for t in rule[:k])]
            return (2 * sum(hit) - len(hit)) / max(1, len(hit))

        if not rule:
            break
        rule = rule[: max(range(1, len(rule) + 1), key=lambda k: (worth(k), -k))]
        hit = [r for r in pool if all(t.holds(r) for t in rule)]
        if len(hit) < least or sum(r["_bad"] for r in hit) < precision * len(hit):
            break
        rules.append(tuple(rule))
        pool = [r for r in pool if not all(t.holds(r) for t in rule)]
    return DecisionList(tuple(rules))


def learn_rules(docs: DataFrame, labels: DataFrame, *, sample_rows: int = 12_000, label_col: str = "quality", id_col: str = "doc_id", text_col: str = "text", **options) -> DecisionList:
    """A decision list from at most ``sample_rows`` labelled documents, chosen by a hash of their id.

    Rows without a label, a document or an id are not used; a document labelled twice with different values counts as
    rejected.  No usable rows give the empty list, which keeps everything.
    """
    chosen = labels.where(F.col(label_col).isNotNull() & F.col(id_col).isNotNull()).groupBy(F.col(id_col).alias("doc_id")).agg(F.min(label_col).cast("int").alias("label"))
    chosen = chosen.orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample_rows)  # bounded: broadcast below
    rows = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("body0")).join(F.broadcast(chosen), "doc_id")
    seen = statistics(rows, text_col="body0", carry=("label",)).where(~base_failed()).select("doc_id", "label", *FEATURES).collect()
    table = [r.asDict() | {"_bad": int(r["label"] == 0), "_fold": zlib.crc32(str(r["doc_id"]).encode()) % 3} for r in sorted(seen, key=lambda r: str(r["doc_id"]))]
    return cover(table, **options)


def quality_rules(docs: DataFrame, rules: DecisionList, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, kept`` for each row.

    Null texts have no words and so fail the base rule, like empty ones.  Repeated rows get equal rows; a null
    id is passed on.  Other columns are ignored.  An empty input gives an empty result.
    """
    stats = statistics(docs, id_col=id_col, text_col=text_col)
    failed = base_failed()
    return stats.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", failed.alias("base_failed"), (~failed & rules.verdict()).alias("kept"))
