"""Secret scans: fixed patterns, and a battery of randomness tests on long tokens.  DataFrame functions only.

Every long token gets an inferred encoding: the smallest alphabet that holds it.  The null hypothesis is that its
characters are drawn uniformly from that alphabet, as those of a generated secret are.  Three tests stand against it:
chi-squared uniformity over characters and over classes of characters (the lesser p, doubled), runs about the
alphabet's middle (about vowels, in alphabets of letters), and serial correlation at lag one; Fisher's method combines
them.  Words and paths fail.  The false-discovery control is aware of length: in each band of lengths the
Benjamini-Hochberg procedure, over all tokens of the corpus, rejects the null for the tokens that are not random, at a
level that is higher for short tokens, whose tests are weak; the tokens whose null stands are secrets.  Its cut-offs
come from a histogram of fixed size, so nothing that grows reaches the driver.

Places are running sums over the parts of a marked text, taken in blocks, so that a text with very many matches costs
little more than in proportion to them.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import text_or_empty

#: Kinds in their order, with their patterns (fixed values).
ASSIGN = r"(?i:password|passwd|secret|token|api_?key)[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)"
ACCESS = r"AKIA[A-Z0-9]+"
HEX = r"[0-9a-f]+"
LEAST = {"assign": 6, "access": 20, "hex": 24}
#: Tokens that the battery looks at.
TOKEN = r"[A-Za-z0-9+/_-]{20,}={0,2}"
DIGITS, UPPER, LOWER = "0123456789", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Classes of characters: vowels, frequent consonants and other consonants, small and large, then digits and marks.
CLASSES = ("aeiou", "tnrslhd", "bcfgjkmpqvwxyz", "AEIOU", "TNRSLHD", "BCFGJKMPQVWXYZ", DIGITS, "+/-_")
_SMALL, _LARGE = "".join(CLASSES[:3]), "".join(CLASSES[3:6])
#: Encodings from the smallest alphabet on: name, pattern, alphabet, place at which its upper part begins; the first that holds a token is its own.
ENCODINGS = (
    ("digits", r"^[0-9]+$", DIGITS, 5),
    ("hex", r"^[0-9a-f]+$", DIGITS + "abcdef", 8),
    ("HEX", r"^[0-9A-F]+$", DIGITS + "ABCDEF", 8),
    ("lower", r"^[a-z]+$", _SMALL, 5),
    ("UPPER", r"^[A-Z]+$", _LARGE, 5),
    ("base32", r"^[A-Z2-7]+$", UPPER + "234567", 16),
    ("base36", r"^[0-9a-z]+$", DIGITS + LOWER, 18),
    ("BASE36", r"^[0-9A-Z]+$", DIGITS + UPPER, 18),
    ("letters", r"^[A-Za-z]+$", CLASSES[0] + CLASSES[3] + "".join(CLASSES[1:3]) + "".join(CLASSES[4:6]), 10),
    ("base62", r"^[0-9A-Za-z]+$", DIGITS + UPPER + LOWER, 31),
    ("base64url", r"^[0-9A-Za-z_-]+$", DIGITS + UPPER + LOWER + "-_", 32),
    ("base64", r"^[0-9A-Za-z+/]+$", DIGITS + UPPER + LOWER + "+/", 32),
    ("mixed", r".", DIGITS + UPPER + LOWER + "+/-_", 33),
)
#: Bands of token lengths: the least length of each, and the level of its false-discovery control.
BANDS = ((20, 0.25), (32, 0.15), (48, 0.05))
#: Bins of -log10(p) in the histogram, ten to a unit.
BINS = 400
SPAN = "array<struct<start:int,end:int,body:string>>"


def _safe(text: Column) -> Column:
    """The text with the two marker characters replaced by one that no pattern matches; lengths stay."""
    return F.when(text.contains("\x01") | text.contains("\x02"), F.translate(text, "\x01\x02", "\x03\x03")).otherwise(text)


def _let(value: Column, use) -> Column:
    """``use(value)`` with the value computed once."""
    return F.get(F.transform(F.array(value), use), F.lit(0))


def _running(values: Column, join, block: int = 64) -> Column:
    """Running results of ``join`` (sum or greatest, from 0) over an array of ints, itself included; in blocks, so that few are copied."""
    zero = F.array().cast("array<int>")
    last = lambda xs: F.coalesce(F.try_element_at(xs, F.lit(-1)), F.lit(0))
    grow = lambda xs, x: F.concat(xs, F.array(join(last(xs), x)))

    def scan(v):
        count = F.ceil(F.size(v) / block).cast("int")
        inner = F.transform(F.sequence(F.lit(0), count - 1), lambda j: F.aggregate(F.slice(v, j * block + 1, F.lit(block)), zero, grow))

        def tops(parts):
            whole = F.aggregate(parts, F.array(F.lit(0)), lambda acc, part: grow(acc, last(part)))
            return _let(F.struct(parts.alias("parts"), whole.alias("tops")), lambda s: F.flatten(F.transform(s["parts"], lambda part, j: F.transform(part, lambda x: join(F.get(s["tops"], j), x)))))

        return F.when(F.size(v) <= block, F.aggregate(v, zero, grow)).otherwise(_let(inner, tops))

    return _let(values, scan)


def _found(text: Column, pattern: str) -> Column:
    """Leftmost non-overlapping matches as (start, end, body), in code points: the text is marked, split and measured."""
    parts = F.split(F.regexp_replace(text, pattern, "\x01$0\x02"), "[\x01\x02]", -1)

    def measured(p):
        ends = _running(F.transform(p, lambda x: F.char_length(x)), lambda a, b: a + b)
        inside = lambda s: F.transform(F.sequence(F.lit(1), F.size(s["p"]) - 2, F.lit(2)), lambda i: F.struct(F.get(s["ends"], i - 1).alias("start"), F.get(s["ends"], i).alias("end"), F.get(s["p"], i).alias("body")))
        return _let(F.struct(p.alias("p"), ends.alias("ends")), inside)

    return F.when(text.rlike(pattern), _let(parts, measured)).otherwise(F.array().cast(SPAN))


def _tail(z: Column) -> Column:
    """Upper tail of the standard normal, by its logistic approximation."""
    z = F.greatest(F.lit(-12.0), F.least(F.lit(12.0), z))
    return F.lit(1.0) / (F.lit(1.0) + F.exp(F.lit(1.5976) * z + F.lit(0.07056) * z * z * z))


def _encoding(token: Column) -> Column:
    """Alphabet and cut of the first encoding that holds a token."""
    out = None
    for _, pattern, alphabet, cut in ENCODINGS:
        found = F.struct(F.lit(alphabet).alias("alphabet"), F.lit(cut).alias("cut"))
        out = F.when(token.rlike(pattern), found) if out is None else out.when(token.rlike(pattern), found)
    return out


def _normal(chi: Column, df: Column) -> Column:
    """Upper tail of chi-squared: its cube root over the degrees of freedom is close to normal."""
    return _tail((F.pow(F.greatest(chi, F.lit(0.0)) / df, 1.0 / 3) - (1 - 2 / (9 * df))) / F.sqrt(2 / (9 * df)))


def _sum(values: Column) -> Column:
    return F.aggregate(values, F.lit(0.0), lambda a, x: a + x)


def p_value(token: Column) -> Column:
    """Combined p of a token under uniform draws from its inferred alphabet."""

    # each step names what the next ones use more than once, so that it is computed once
    def named(s, **more):
        return F.struct(*[s[x].alias(x) for x in ("v", "k", "n", "cut", "classes")], *[c.alias(x) for x, c in more.items()])

    def first(s):
        squares = _sum(F.transform(F.array_distinct(s["v"]), lambda x: F.pow(F.size(F.filter(s["v"], lambda y: y == x)).cast("double"), 2.0)))
        return named(s, squares=squares, ones=_sum(F.transform(s["v"], lambda x: (x >= s["cut"]).cast("double"))), m=_sum(s["v"]) / s["n"])

    def second(s):
        steps = F.sequence(F.lit(1), F.size(s["v"]) - 1)
        both = 2 * s["ones"] * (s["n"] - s["ones"])
        runs = F.lit(1.0) + _sum(F.transform(steps, lambda i: ((F.get(s["v"], i) >= s["cut"]) != (F.get(s["v"], i - 1) >= s["cut"])).cast("double")))
        spread = _sum(F.transform(s["v"], lambda x: (x - s["m"]) * (x - s["m"])))
        lagged = _sum(F.transform(steps, lambda i: (F.get(s["v"], i) - s["m"]) * (F.get(s["v"], i - 1) - s["m"])))
        expected = lambda c: s["n"] * c["of"] / s["k"]
        classes = _sum(F.transform(s["classes"], lambda c: F.pow(c["seen"] - expected(c), 2.0) / expected(c)))
        return named(s, fine=s["squares"] * s["k"] / s["n"] - s["n"], coarse=classes, both=both, var=both * (both - s["n"]) / (s["n"] * s["n"] * (s["n"] - 1)), runs=runs, spread=spread, lagged=lagged)

    def third(s):
        degrees = F.size(s["classes"]).cast("double") - 1
        coarse = F.when(degrees > 0, _normal(s["coarse"], degrees)).otherwise(F.lit(1.0))
        p1 = F.least(F.lit(1.0), 2 * F.least(_normal(s["fine"], s["k"] - 1), coarse))
        low = s["cut"] / s["k"]
        alone = F.when(s["both"] == 0, F.pow(low, s["n"]) + F.pow(1 - low, s["n"])).otherwise(F.lit(1.0))  # all on one side
        p2 = F.when(s["var"] > 0, F.least(F.lit(1.0), 2 * _tail(F.abs(s["runs"] - s["both"] / s["n"] - 1) / F.sqrt(F.greatest(s["var"], F.lit(1e-12)))))).otherwise(alone)
        p3 = F.when(s["spread"] > 0, F.least(F.lit(1.0), 2 * _tail(F.abs(s["lagged"] / F.greatest(s["spread"], F.lit(1e-12))) * F.sqrt(s["n"])))).otherwise(F.lit(0.0))
        floor = F.lit(1e-30)
        return -(F.log(F.greatest(p1, floor)) + F.log(F.greatest(p2, floor)) + F.log(F.greatest(p3, floor)))

    left = lambda text, chars: F.char_length(text) - F.char_length(F.translate(text, chars, ""))

    def prepare(s):
        alphabet = s["e"]["alphabet"]
        v = F.transform(F.filter(F.split(s["t"], ""), lambda c: c != ""), lambda c: F.call_function("position", c, alphabet) - 1)
        classes = F.array(*[F.struct(left(alphabet, c).cast("double").alias("of"), left(s["t"], c).cast("double").alias("seen")) for c in CLASSES])
        return F.struct(v.alias("v"), F.char_length(alphabet).cast("double").alias("k"), F.char_length(s["t"]).cast("double").alias("n"), s["e"]["cut"].alias("cut"), F.filter(classes, lambda c: c["of"] > 0).alias("classes"))

    body = F.regexp_replace(token, "=+$", "")
    encoded = _let(body, lambda t: F.struct(t.alias("t"), _encoding(t).alias("e")))
    logs = _let(_let(_let(_let(encoded, prepare), first), second), third)
    return _let(logs, lambda x: F.exp(-x) * (1 + x + x * x / 2))


def _tokens(text: Column) -> Column:
    """Long tokens with their combined p: (start, end, p)."""
    return F.transform(_found(text, TOKEN), lambda m: F.struct(m["start"].alias("start"), m["end"].alias("end"), p_value(m["body"]).alias("p")))


def _band(length: Column) -> Column:
    out = F.lit(0)
    for i, (least, _) in enumerate(BANDS):
        out = F.when(length >= least, i).otherwise(out)
    return out


@dataclass(frozen=True)
class CutOffs:
    """Largest p at which the null is rejected, for each band; -1 for none."""

    by_band: tuple[float, ...]

    def random(self, token: Column) -> Column:
        band, out = _band(token["end"] - token["start"]), F.lit(-1.0)
        for i, cut in enumerate(self.by_band):
            out = F.when(band == i, F.lit(float(cut))).otherwise(out)
        return token["p"] > out


def control(docs: DataFrame, *, text_col: str = "text") -> CutOffs:
    """Benjamini-Hochberg cut-offs for each band over all tokens of the corpus; p is read from tenths of its decimal logarithm, upwards.

    A band without a rejection has the cut-off -1: all its tokens count as random.  A lone token faces its level itself.
    """
    tokens = docs.select(F.explode(_tokens(_safe(text_or_empty(text_col)))).alias("t"))
    bin_ = F.least(F.lit(BINS), F.floor(-F.log10(F.greatest(F.col("t.p"), F.lit(1e-60))) * 10)).cast("int")
    counts = tokens.groupBy(_band(F.col("t.end") - F.col("t.start")).alias("band"), F.greatest(bin_, F.lit(0)).alias("bin")).agg(F.count(F.lit(1)).alias("n"))
    cuts = [-1.0] * len(BANDS)
    rows = counts.collect()  # at most len(BANDS) * (BINS + 1) rows
    for band, (_, level) in enumerate(BANDS):
        mine = sorted((-r["bin"], r["n"]) for r in rows if r["band"] == band)
        total, seen = sum(n for _, n in mine), 0
        for minus, n in mine:
            seen += n
            upper = 10 ** (minus / 10)  # the largest p of the bin
            if upper <= level * seen / total:
                cuts[band] = max(cuts[band], upper)
    return CutOffs(tuple(cuts))


def _blocks(spans: Column, block: int = 128) -> Column:
    """Spans in the order of their starts, in blocks with the stretch that each covers."""
    cut = lambda j: _let(F.slice(spans, j * block + 1, F.lit(block)), lambda part: F.struct(F.get(part, F.lit(0))["start"].alias("low"), F.array_max(F.transform(part, lambda b: b["end"])).alias("high"), part.alias("part")))
    return F.when(F.size(spans) > 0, F.transform(F.sequence(F.lit(0), F.ceil(F.size(spans) / block).cast("int") - 1), cut))


def _apart(token: Column, blocks: Column) -> Column:
    """Whether a token overlaps none of the spans in the blocks."""
    meets = lambda b: (b["start"] < token["end"]) & (token["start"] < b["end"])
    return blocks.isNull() | ~F.exists(blocks, lambda x: (x["low"] < token["end"]) & (token["start"] < x["high"]) & F.exists(x["part"], meets))


def scan(docs: DataFrame, cutoffs: CutOffs | None = None, *, id_col: str = "doc_id", text_col: str = "text", carry: tuple[str, ...] = ()) -> DataFrame:
    """``doc_id``, the carried columns, ``spans`` of each row: array of (start, rank, kind, end) by start, then rank.

    Kinds by rank: assign, access, hex (the fixed patterns) and random (the battery, where no fixed pattern
    overlaps).  Places count code points, the end is exclusive.  Null texts count as empty.  Repeated rows get equal
    rows; a null id is passed on.  Other columns are ignored.  An empty input gives an empty result.
    """
    cutoffs = cutoffs or control(docs, text_col=text_col)
    text = _safe(text_or_empty(text_col))
    value = F.regexp_extract
    rows = docs.select(F.col(id_col).alias("doc_id"), *carry, text.alias("body"))
    rows = rows.withColumns({
        "m0": F.filter(_found(F.col("body"), ASSIGN), lambda m: F.char_length(value(m["body"], ASSIGN, 1)) >= LEAST["assign"]),
        "m1": F.filter(_found(F.col("body"), ACCESS), lambda m: m["end"] - m["start"] >= LEAST["access"]),
        # maximal runs of 24 or more are what is left of all maximal runs
        "m2": _found(F.col("body"), HEX[:-1] + "{%d,}" % LEAST["hex"]),
        "m3": _tokens(F.col("body")),
    })

    def tagged(name: str, rank: int, kind: str) -> Column:
        return F.transform(name, lambda m: F.struct(m["start"].alias("start"), F.lit(rank).alias("rank"), F.lit(kind).alias("kind"), m["end"].alias("end")))

    base = F.array_sort(F.concat(tagged("m0", 0, "assign"), tagged("m1", 1, "access"), tagged("m2", 2, "hex")))
    rows = rows.withColumn("base", base).withColumn("near", _blocks(F.col("base")))
    added = F.transform(F.filter("m3", lambda t: cutoffs.random(t) & _apart(t, F.col("near"))), lambda m: F.struct(m["start"].alias("start"), F.lit(3).alias("rank"), F.lit("random").alias("kind"), m["end"].alias("end")))
    # through a generator, so that a later filter does not compute the spans again
    return rows.select("doc_id", *carry, F.explode(F.array(F.struct(F.array_sort(F.concat("base", added)).alias("spans")))).alias("s")).select("doc_id", *carry, "s.spans")


def listed(spans: Column) -> Column:
    """``kind:start:end``, joined by commas."""
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def redact(docs: DataFrame, cutoffs: CutOffs | None = None, *, text_col: str = "text", mark: str = "[SECRET]") -> DataFrame:
    """All rows and columns of ``docs``, with each secret in the text replaced by ``mark``; null texts stay null."""
    names = docs.columns
    plain = docs.select(*[F.col(f"`{c}`").alias(f"c{i}") for i, c in enumerate(names)])  # clashing names stay apart
    mine = f"c{names.index(text_col)}"
    found = scan(plain, cutoffs, id_col=mine, text_col=mine, carry=tuple(plain.columns))
    body = F.col(mine)

    def pieces(s):
        """What stands between the secrets, each secret that begins outside the ones before it as the mark, and the rest."""
        before = lambda i: F.when(i > 0, F.get(s["until"], i - 1)).otherwise(F.lit(0))
        # many cuts in a long text are taken from its characters, a few from the text itself
        take = lambda a, n: F.when(s["chars"].isNotNull(), F.array_join(F.slice(s["chars"], a + 1, n), "")).otherwise(F.substring(body, a + 1, n))
        cut = lambda x, i: F.when(x["start"] >= before(i), F.concat(take(before(i), x["start"] - before(i)), F.lit(mark))).otherwise(F.lit(""))
        end = F.get(s["until"], F.size("spans") - 1)
        return F.concat(F.array_join(F.transform("spans", cut), ""), F.substring(body, end + 1, F.lit(2**31 - 1)))

    until = _running(F.transform("spans", lambda x: x["end"]), lambda a, b: F.greatest(a, b))
    chars = F.when(F.size("spans") > 64, F.regexp_extract_all(body, F.lit("(?s)."), F.lit(0)))
    clean = _let(F.struct(until.alias("until"), chars.alias("chars")), pieces)
    text = F.when(F.col(mine).isNull() | (F.size("spans") == 0), F.col(mine)).otherwise(clean)
    return found.select(*[(text if c == text_col else F.col(f"c{i}")).alias(c) for i, c in enumerate(names)])
