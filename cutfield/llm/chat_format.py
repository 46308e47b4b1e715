"""Chat formatting by schema fingerprints.

The nested field paths that a record fills, without array positions, are sorted and hashed; the hash selects a
declarative mapping from that layout (prompt and response, instruction with input and output, message lists, share
lists, or one row per turn) to canonical turns.  Each record has a fingerprint of its own, so one table, or one
column of JSON texts, may mix layouts.  Turns are rendered with marks that no escaped text can contain,
and every formatted conversation can be read back exactly, with the characters that carry the loss.
"""

from __future__ import annotations

import hashlib
import json
import re
from collections.abc import Iterable
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..shipping import ship

#: The marks of a turn (fixed values), and the escape character, which stands behind the first character of a control string or of itself.
OPEN, BODY, CLOSE = "<|turn|>", "<|text|>", "<|end|>"
ESCAPE = "\\"
#: Control strings of common templates that must not appear unescaped inside a text either.
CONTROL = ("<|", "|>", "</s>", "<s>", "[INST]", "[/INST]", "<<SYS>>", "<</SYS>>")
#: An escape, or any character at which a control string starts.
_DANGER = re.compile(r"\\|(?=" + "|".join(map(re.escape, CONTROL)) + r").", re.DOTALL)
_ESCAPED = re.compile(r"\\(.)", re.DOTALL)


def escape(text: str) -> str:
    """Break every control string with an escape behind its first character; double escapes."""
    return _DANGER.sub(lambda m: m[0] + ESCAPE, text)


def unescape(text: str) -> str:
    return _ESCAPED.sub(r"\1", text)


def paths(value: object, prefix: str = "") -> set[str]:
    """Nested field paths that a record fills, array positions left out; nulls fill nothing."""
    if isinstance(value, dict):
        return {p for name, x in value.items() for p in paths(x, f"{prefix}.{name}" if prefix else name)}
    if isinstance(value, list):
        return {p for x in value for p in paths(x, prefix + "[]")}
    return set() if value is None else {prefix}


def fingerprint(found: Iterable[str]) -> str:
    """Hash of a layout: its sorted paths."""
    return hashlib.sha256("\n".join(sorted(found)).encode()).hexdigest()[:16]


@dataclass(frozen=True)
class Mapping:
    """How one layout becomes turns: either fixed (role, path) pairs, or a list path with role and text fields."""

    name: str
    fields: tuple[str, ...]
    pairs: tuple[tuple[str, tuple[str, ...]], ...] = ()
    list_path: str = ""
    role_field: str = ""
    text_field: str = ""
    roles: dict[str, str] = field(default_factory=dict)

    @property
    def key(self) -> str:
        return fingerprint(self.fields)


#: Role names of common layouts and their canonical ones (fixed values).
ROLES = {"human": "user", "gpt": "assistant", "prompter": "user", "bot": "assistant", "model": "assistant"}
MAPPINGS = (
    Mapping("prompt_response", ("prompt", "response"), (("user", ("prompt",)), ("assistant", ("response",)))),
    Mapping("prompt_completion", ("prompt", "completion"), (("user", ("prompt",)), ("assistant", ("completion",)))),
    Mapping("system_prompt_response", ("system", "prompt", "response"), (("system", ("system",)), ("user", ("prompt",)), ("assistant", ("response",)))),
    Mapping("system_prompt_completion", ("system", "prompt", "completion"), (("system", ("system",)), ("user", ("prompt",)), ("assistant", ("completion",)))),
    Mapping("instruction", ("instruction", "output"), (("user", ("instruction",)), ("assistant", ("output",)))),
    Mapping("instruction_input", ("instruction", "input", "output"), (("user", ("instruction", "input")), ("assistant", ("output",)))),
    Mapping("question_answer", ("question", "answer"), (("user", ("question",)), ("assistant", ("answer",)))),
    Mapping("messages", ("messages[].role", "messages[].content"), list_path="messages", role_field="role", text_field="content", roles=ROLES),
    Mapping("shares", ("conversations[].from", "conversations[].value"), list_path="conversations", role_field="from", text_field="value", roles=ROLES),
    Mapping("turn_rows", ("turns[].turn", "turns[].role", "turns[].text"), list_path="turns", role_field="role", text_field="text"),
)
BY_KEY = {m.key: m for m in MAPPINGS}
#: Top-level names that a mapping reads; any other column or field is not looked at.
NAMES = frozenset(re.split(r"[.\[]", f)[0] for m in MAPPINGS for f in m.fields)
TURNS = "array<struct<role:string,text:string>>"


class Layouts(dict):
    """The mapping of each set of filled paths, among those whose top-level names a table has."""

    def __init__(self, names: Iterable[str]):
        super().__init__()
        self.open = [m for m in MAPPINGS if all(re.split(r"[.\[]", f)[0] in names for f in m.fields)]

    def __missing__(self, found: frozenset[str]) -> Mapping:
        exact = BY_KEY.get(fingerprint(found))
        over = sorted((m for m in self.open if found <= set(m.fields)), key=lambda m: len(m.fields))
        under = sorted((m for m in self.open if found >= set(m.fields)), key=lambda m: -len(m.fields))
        chosen = exact if exact in self.open else next(iter(over or under), None)
        if chosen is None:
            raise ValueError(f"no mapping for the layout {sorted(found)}")
        self[found] = chosen
        return chosen


def turns_of(record: dict, layouts: Layouts) -> list[tuple[str, str]]:
    """Canonical turns of a record."""
    record = {k: v for k, v in record.items() if k in NAMES}
    mapping = layouts[frozenset(paths(record))]
    text = lambda x: "" if x is None else x if isinstance(x, str) else json.dumps(x, ensure_ascii=False)
    if mapping.list_path:
        out = []
        for x in record.get(mapping.list_path) or []:
            role = text((x or {}).get(mapping.role_field))
            out.append((mapping.roles.get(role, role), text((x or {}).get(mapping.text_field))))
        return out
    return [(role, "\n".join(filter(None, (text(record.get(n)) for n in names)))) for role, names in mapping.pairs]


def _table_of(turns: list[list[tuple[str, str]]]) -> pa.Array:
    return pa.array([[{"role": r, "text": t} for r, t in x] for x in turns], pa.list_(pa.struct([("role", pa.string()), ("text", pa.string())])))


def _records(records: DataFrame, id_col: str) -> tuple[DataFrame, Layouts]:
    """conv_id and the columns that mappings read."""
    names = [c for c in dict.fromkeys(records.columns) if c in NAMES and c != id_col]
    layouts = Layouts(names)
    if not layouts.open:
        raise ValueError(f"no mapping for the layout {sorted(records.columns)}")
    return records.select(F.col(id_col).cast("long").alias("conv_id"), *[F.col(c) for c in names]), layouts


def _canonical(layouts: Layouts):
    def run(batches):
        for batch in batches:
            ids = batch.column("conv_id")
            rows = batch.select([n for n in batch.schema.names if n != "conv_id"]).to_pylist()
            yield pa.record_batch([ids, _table_of([turns_of(x, layouts) for x in rows])], names=["conv_id", "turns"])

    return run


def canonical(records: DataFrame, id_col: str = "conv_id") -> DataFrame:
    """conv_id, turns (array of role, text) of records, each by the mapping that its own filled paths select.

    The fingerprint of the filled paths is looked up first; a record that fills no layout exactly, as where a text is null, gets
    the smallest mapping that has all it fills, else the largest one that it fills.  Columns that no mapping names are not
    looked at.  Null texts and roles are empty; parts of one turn that are null or empty are left out.  A table or record
    without any mapping is an error.
    """
    ship(records.sparkSession)
    rows, layouts = _records(records, id_col)
    return rows.mapInArrow(_canonical(layouts), f"conv_id long, turns {TURNS}")


def canonical_json(records: DataFrame, *, id_col: str = "conv_id", json_col: str = "record") -> DataFrame:
    """conv_id, turns of records that are JSON objects in a text column, layouts mixed at will; a null or empty text has no turns."""
    ship(records.sparkSession)
    layouts = Layouts(NAMES)

    def run(batches):
        for batch in batches:
            turns = [turns_of(json.loads(x), layouts) if x and x.strip() else [] for x in batch.column("body").to_pylist()]
            yield pa.record_batch([batch.column("conv_id"), _table_of(turns)], names=["conv_id", "turns"])

    rows = records.select(F.col(id_col).cast("long").alias("conv_id"), F.col(json_col).cast("string").alias("body"))
    return rows.mapInArrow(run, f"conv_id long, turns {TURNS}")


def from_rows(rows: DataFrame, *, id_col: str = "conv_id", turn_col: str = "turn", role_col: str = "role", text_col: str = "text") -> DataFrame:
    """One record per conversation from one row per turn, turns in order (ties: by role, then text); one conversation fits a row by its nature."""
    turn = F.struct(F.col(turn_col).cast("long").alias("turn"), F.col(role_col).cast("string").alias("role"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    return rows.groupBy(F.col(id_col).cast("long").alias("conv_id")).agg(F.array_sort(F.collect_list(turn)).alias("turns"))


def render(turns: list[tuple[str, str]]) -> str:
    return "".join(f"{OPEN}{escape(role)}{BODY}{escape(text)}{CLOSE}" for role, text in turns)


def loss_spans(formatted: str) -> list[tuple[int, int]]:
    """Stretches of a formatted conversation under the loss mask: the texts of assistant turns, still escaped."""
    out, at = [], 0
    while at < len(formatted):
        body = formatted.index(BODY, at)
        end = formatted.index(CLOSE, body)
        if unescape(formatted[at + len(OPEN) : body]) == "assistant":
            out.append((body + len(BODY), end))
        at = end + len(CLOSE)
    return out


def read_back(formatted: str) -> list[tuple[str, str]]:
    out, at = [], 0
    while at < len(formatted):
        body = formatted.index(BODY, at)
        end = formatted.index(CLOSE, body)
        out.append((unescape(formatted[at + len(OPEN) : body]), unescape(formatted[body + len(BODY) : end])))
        at = end + len(CLOSE)
    return out


FORMATTED = "conv_id long, formatted string, loss array<struct<start:int,end:int>>"
DIGESTS = "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long"


def _formatted(ids: pa.Array, turns: list[list[tuple[str, str]]]) -> pa.RecordBatch:
    texts = [render(x) for x in turns]
    loss = [[{"start": a, "end": b} for a, b in loss_spans(x)] for x in texts]
    return pa.record_batch([ids, pa.array(texts, pa.string()), pa.array(loss, pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32())])))], names=["conv_id", "formatted", "loss"])


def format_turns(conversations: DataFrame) -> DataFrame:
    """``conv_id, formatted, loss`` of canonical turns (``conv_id, turns``)."""
    ship(conversations.sparkSession)

    def run(batches):
        for batch in batches:
            yield _formatted(batch.column("conv_id"), [[(t["role"] or "", t["text"] or "") for t in x or []] for x in batch.column("turns").to_pylist()])

    return conversations.select("conv_id", "turns").mapInArrow(run, FORMATTED)


def format_chats(records: DataFrame, id_col: str = "conv_id") -> DataFrame:
    """``conv_id, formatted, loss`` of each record, by its own layout; ``loss`` has code point stretches, ends exclusive."""
    ship(records.sparkSession)
    rows, layouts = _records(records, id_col)

    def run(batches):
        for batch in batches:
            found = batch.select([n for n in batch.schema.names if n != "conv_id"]).to_pylist()
            yield _formatted(batch.column("conv_id"), [turns_of(x, layouts) for x in found])

    return rows.mapInArrow(run, FORMATTED)


def _digest(batches):
    names = [c.split()[0] for c in DIGESTS.split(", ")]
    for batch in batches:
        out = []
        for conv, text, loss in zip(*(batch.column(i).to_pylist() for i in range(3))):
            turns = read_back(text)
            said = "".join(unescape(text[s["start"] : s["end"]]) for s in loss)
            whole = "".join(f"{role}\n{body}\n" for role, body in turns)
            out.append((conv, len(turns), hashlib.sha256(whole.encode()).hexdigest(), len(said), hashlib.sha256(said.encode()).hexdigest(), len(text)))
        cols = list(zip(*out)) if out else [()] * len(names)
        kinds = (pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64())
        yield pa.record_batch([pa.array(c, k) for c, k in zip(cols, kinds)], names=names)


def digests(formatted: DataFrame) -> DataFrame:
    """``conv_id, n_turns, turns_sha256, loss_chars, loss_sha256, formatted_chars``, read back from the formatted text.

    Null and empty roles read back as empty, any other as it stands.  Repeated turn rows are turns of their own; rows with a null conversation id form one conversation; an empty input gives
    an empty result.
    """
    return formatted.mapInArrow(_digest, DIGESTS)
