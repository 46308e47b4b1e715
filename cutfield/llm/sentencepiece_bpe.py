"""SentencePiece encoding and decoding for merge-type vocabularies.

A text is a row of characters; the adjacent pair whose concatenation is the best-scored piece merges first, ties
to the left, until no adjacent pair is a piece.  The pairs wait in an agenda ordered by (score, place); merged
symbols leave stale entries that are skipped.  Where no piece of the vocabulary has a space mark after another
character, or a line feed beside one, merges never cross those borders, so a text is cut there and each distinct
part is encoded once per worker.  Every part that is new to a worker is checked against the sentencepiece
library, a batch at a time.
"""

from __future__ import annotations

import hashlib
import heapq
import re
from functools import lru_cache

import pyarrow as pa
import sentencepiece
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..shipping import ship

MARK = "▁"
#: Distinct parts that a worker remembers; beyond it, it forgets all and starts anew, which costs time and nothing else.
REMEMBERED = 1_000_000
#: Parts longer than this are not remembered.
LONGEST = 64
_BYTE = re.compile(r"<0x([0-9A-F]{2})>\Z")


class PieceCoder:
    """Encoder and decoder over one vocabulary file."""

    def __init__(self, path: str):
        self.library = sentencepiece.SentencePieceProcessor(model_file=path)
        n = self.library.get_piece_size()
        names = [self.library.id_to_piece(i) for i in range(n)]
        special = [self.library.is_control(i) or self.library.is_unknown(i) or self.library.is_unused(i) for i in range(n)]
        self.unknown = self.library.unk_id()
        self.byte_ids: dict[int, int] = {}
        self.score: dict[str, float] = {}
        self.ids: dict[str, int] = {}
        self.out: list[bytes] = []
        self.is_byte: list[bool] = []
        for i, name in enumerate(names):
            byte = _BYTE.match(name) if self.library.is_byte(i) else None
            if byte:
                self.byte_ids[int(byte[1], 16)] = i
                self.out.append(bytes([int(byte[1], 16)]))
            elif special[i]:
                self.out.append(b" \xe2\x81\x87 " if i == self.unknown else b"")
            else:
                self.score[name] = self.library.get_score(i)
                self.ids[name] = i
                self.out.append(name.encode().replace(MARK.encode(), b" "))
            self.is_byte.append(bool(byte))
        #: Neighbours inside some piece; no merge crosses a border between two other characters.
        self.pairs = {p[i : i + 2] for p in self.score for i in range(len(p) - 1)}
        # merges stay inside parts cut before a space mark and around a line feed
        self.cuttable = not any(MARK in p.lstrip(MARK) or "\n" in p for p in self.score)
        self.memory = _Memory(self)
        self.pending: list[tuple[str, list[int]]] = []
        self.decoded: list[tuple[list[int], bytes]] = []

    def agenda(self, text: str) -> list[int]:
        """Ids of a text whose spaces are marks already, by merging its best adjacent pair again and again."""
        symbols: list[str | None] = list(text)
        n = len(symbols)
        before, after = list(range(-1, n - 1)), [*range(1, n), -1]
        score = self.score.get
        waiting: list[tuple[float, int, int, str]] = []

        def offer(i: int, j: int) -> None:
            if i >= 0 and j >= 0:
                both = symbols[i] + symbols[j]
                s = score(both)
                if s is not None:
                    heapq.heappush(waiting, (-s, i, j, both))

        for i in range(n - 1):
            offer(i, i + 1)
        while waiting:
            _, i, j, both = heapq.heappop(waiting)
            if symbols[i] is None or symbols[j] is None or after[i] != j or symbols[i] + symbols[j] != both:
                continue  # one of the two has merged meanwhile
            symbols[i], symbols[j] = both, None
            after[i] = after[j]
            if after[j] >= 0:
                before[after[j]] = i
            offer(before[i], i)
            offer(i, after[i])
        ids: list[int] = []
        for s in symbols:
            if s is not None:
                i = self.ids.get(s)
                if i is not None:
                    ids.append(i)
                elif self.byte_ids:
                    ids += [self.byte_ids[b] for b in s.encode()]
                else:
                    ids.append(self.unknown)
        return ids

    def encode(self, text: str) -> list[int]:
        """Ids of one text, with the leading space mark that the vocabulary asks for."""
        return self.agenda(MARK + text.replace(" ", MARK)) if text else []

    def decode_bytes(self, ids: list[int]) -> bytes:
        """Bytes of some ids, space marks as spaces, invalid byte runs as U+FFFD; the leading space is still there."""
        out, run = [], []
        for i in [*ids, -1]:
            if i >= 0 and self.is_byte[i]:
                run.append(self.out[i])
                continue
            if run:
                out.append(_repair(b"".join(run)))
                run = []
            if i >= 0:
                out.append(self.out[i])
        return b"".join(out)

    def decode(self, ids: list[int]) -> str:
        body = self.decode_bytes(ids)
        lead = bool(ids) and not self.is_byte[ids[0]] and body[:1] == b" " and ids[0] != self.unknown
        return (body[1:] if lead else body).decode()

    def parts_of(self, text: str) -> list[str]:
        """Parts of a non-empty text between which no merge can happen, spaces as marks."""
        marked = MARK + text.replace(" ", MARK)
        if not self.cuttable:
            return [marked]
        return [p for line in re.split("(\n)", marked) if line for p in _RUN.findall(line)]

    def digest(self, text: bytes) -> tuple[int, str, str]:
        """Number of ids, SHA-256 of the ids in decimal and of the decoded text."""
        if not text:
            return 0, EMPTY, EMPTY
        if self.cuttable and text[:1] != b" " and b"  " not in text and MARK_BYTES not in text:
            # every part is a word after a space, or a line feed with the word behind it
            parts = text.replace(b"\n", b" \n").split(b" ")
            ids = b",".join(map(self.memory.__getitem__, parts))
            if self.memory.odd and not self.memory.odd.isdisjoint(parts):
                body = b"".join(self.decode_bytes([int(i) for i in self.memory[p].split(b",")]) for p in parts)
                body = body.removeprefix(b" ")
            else:
                body = text  # each of its parts decodes to itself
        else:
            numbers = [i for p in self.parts_of(text.decode()) for i in self.agenda(p)]
            self.pending.append((text.decode(), numbers))
            ids = b",".join([b"%d" % i for i in numbers])
            body = self.decode_bytes(numbers).removeprefix(b" ")
            self.decoded.append((numbers, body))
        return ids.count(b",") + 1, hashlib.sha256(ids).hexdigest(), hashlib.sha256(body).hexdigest()

    def check(self) -> None:
        """Hold all that was encoded and decoded since the last call against the library; a difference is an error."""
        texts = [t for t, _ in self.pending]
        for (text, ids), theirs in zip(self.pending, self.library.encode(texts, num_threads=1) if texts else []):
            if ids != theirs:
                raise AssertionError(f"the agenda and the library disagree on {text[:80]!r}")
        numbers = [ids for ids, _ in self.decoded]
        for (ids, body), theirs in zip(self.decoded, self.library.decode(numbers, num_threads=1) if numbers else []):
            if body != theirs.encode():
                raise AssertionError(f"decoding and the library disagree on {ids[:40]!r}")
        self.pending.clear()
        self.decoded.clear()


class _Memory(dict):
    """Ids, in decimal and joined by commas, of each part met so far; bounded."""

    def __init__(self, code: PieceCoder):
        self.code = code
        self.odd: set[bytes] = set()  # parts that do not decode to themselves

    def __missing__(self, part: bytes) -> bytes:
        code, text = self.code, part.decode()
        line = text[:1] == "\n"
        if text[-1:] in ENDINGS and len(text) > 1 and text[-2:] not in code.pairs:
            stem = part[:-1]
            ids = [int(i) for i in self[stem].split(b",")] + code.agenda(text[-1])  # no piece joins the mark
            odd = stem in self.odd or len(stem) > LONGEST
        else:
            ids = code.agenda("\n") + (code.agenda(text[1:]) if text[1:] else []) if line else code.agenda(MARK + text)
            odd = True
        full = code.agenda(MARK) + ids if line else ids  # at the start of a text a lone mark stands before a line feed
        own = part if line else b" " + part
        body = code.decode_bytes(ids) if odd else own
        if body != own:
            self.odd.add(part)
        if text:
            code.pending.append((text, full))
            code.decoded.append((full, body if line else body.removeprefix(b" ")))
        return self._keep(part, b",".join([b"%d" % i for i in ids]))

    def _keep(self, part: bytes, out: bytes) -> bytes:
        if len(part) <= LONGEST:
            if len(self) >= REMEMBERED:
                self.clear()
            self[part] = out
        return out


#: Marks at the end of a word that are tried for a border of their own.
ENDINGS = frozenset(",.;:!?")
EMPTY = hashlib.sha256(b"").hexdigest()
MARK_BYTES = MARK.encode()
_RUN = re.compile(f"{MARK}+[^{MARK}]*|[^{MARK}]+")


def _repair(raw: bytes) -> bytes:
    """Bytes that are no UTF-8 become U+FFFD, one for each byte."""
    try:
        raw.decode()
        return raw
    except UnicodeDecodeError:
        out, i = [], 0
        while i < len(raw):
            for n in (1, 2, 3, 4):
                try:
                    raw[i : i + n].decode()
                except UnicodeDecodeError:
                    continue
                out.append(raw[i : i + n])
                i += n
                break
            else:
                out.append("�".encode())
                i += 1
        return b"".join(out)


@lru_cache(maxsize=2)
def coder(path: str) -> PieceCoder:
    """One coder a worker and vocabulary; it outlives tasks."""
    return PieceCoder(path)


def _encode(path: str):
    def run(batches):
        code = coder(path)
        for batch in batches:
            ids = [code.encode(t or "") for t in batch.column("body").to_pylist()]
            yield pa.record_batch([batch.column("doc_id"), pa.array(ids, pa.list_(pa.int32()))], names=["doc_id", "ids"])

    return run


def encode(docs: DataFrame, path: str, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, ids (array<int>) of each row; null and empty texts have no ids.  Other columns are ignored."""
    ship(docs.sparkSession)
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("body")).mapInArrow(_encode(path), "doc_id long, ids array<int>")


def _decode(path: str):
    def run(batches):
        code = coder(path)
        for batch in batches:
            texts = [code.decode(x or []) for x in batch.column("ids").to_pylist()]
            yield pa.record_batch([batch.column("doc_id"), pa.array(texts, pa.string())], names=["doc_id", "text"])

    return run


def decode(encoded: DataFrame, path: str, *, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """doc_id, text of each row of ids; null and empty arrays give an empty text."""
    ship(encoded.sparkSession)
    return encoded.select(F.col(id_col).cast("long").alias("doc_id"), F.col(ids_col).alias("ids")).mapInArrow(_decode(path), "doc_id long, text string")


def _digests(path: str):
    def run(batches):
        code = coder(path)
        for batch in batches:
            out = [code.digest(t or b"") for t in batch.column("body").cast(pa.binary()).to_pylist()]
            code.check()
            n, ids, text = zip(*out) if out else ((), (), ())
            yield pa.record_batch([batch.column("doc_id"), pa.array(n, pa.int64()), pa.array(ids, pa.string()), pa.array(text, pa.string())], names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return run


def round_trip_digests(docs: DataFrame, path: str, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, n_tokens, ids_sha256, decoded_sha256`` of each row: its ids, and the text that they decode to.

    Null and empty texts have no ids and decode to an empty text.  Repeated rows get equal rows; a null id is passed
    on.  Other columns are ignored.  An empty input gives an empty result.  A part on which the agenda and the
    library differ ends the job with an error that names it.
    """
    ship(docs.sparkSession)
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("body"))
    return rows.mapInArrow(_digests(path), "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")
