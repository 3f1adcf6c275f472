"""Secret scans: base patterns, and assignment-aware lexing of source and configuration syntax.

The lexer reads name-literal pairs (name = "x", name: x, "name" => 'x', export NAME=x, name: type = "x"), in literals of
any quotes with escapes, over several lines too, and in indented blocks. It collects the constants of a document, follows
references to them wherever they are defined (name = OTHER, ${OTHER}, "${OTHER}"), and scores each literal by the words of the
names that it reaches and by its own look. A literal scored at least THRESHOLD is reported where it is written, as kind "literal".
"""

from __future__ import annotations

import hashlib
import heapq
import math
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from runloom.llm.common import texts

#: The base patterns. Lower limits on length are part of them where that gives the same matches.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.A | re.I)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{24,}")
ASSIGN_NAMES = ("password", "passwd", "secret", "token", "api")
KINDS = ("assign", "access", "hex", "literal")

#: One name-literal pair. Names, types, literals and bare values are possessive: the lexer stays linear.
PAIR = re.compile(
    r"""(?<![A-Za-z0-9_.-])(?P<name>[A-Za-z_][A-Za-z0-9_.-]*+)["'\]]{0,2}
    (?:[ \t]*+:[ \t]*+(?P<type>[A-Za-z_&*?](?:[A-Za-z0-9_.&*?\[\]<>|,' \t]|::)*+)(?==(?![=>])))?
    [ \t]*(?::=|=>|==?|:)[ \t]*
    (?:[rRbBuUfFL@$]{0,2}(?:(?P<long>\"{3}|'{3})(?P<in_long>(?:\\.|(?!(?P=long)).)*+)(?P=long)
        |"(?P<in_double>(?:[^"\\\n]|\\.)*+)"|'(?P<in_single>(?:[^'\\\n]|\\.)*+)'|`(?P<in_tick>(?:[^`\\]|\\.)*+)`|(?P<open>["']))
    |(?P<block>[|>][+-]?[1-9]?[+-]?[ \t]*\n)|\$?\{?(?P<bare>[A-Za-z0-9_+/.~!@%^&*=-]++)\}?)""",
    re.X | re.S,
)
QUOTED = ("in_long", "in_double", "in_single", "in_tick")
#: Literals of plain quotes that end on a later line.
LATER = {q: re.compile(rf"(?:[^{q}\\]|\\.)*+(?={q})", re.S) for q in "\"'"}
#: References inside a quoted literal.
INSIDE = re.compile(r"\$\{?([A-Za-z_][A-Za-z0-9_.-]*+)(?:\})?|\{\{?[ \t]*([A-Za-z_][A-Za-z0-9_.-]*+)[ \t]*\}|%\(([A-Za-z_][A-Za-z0-9_.-]*+)\)s|#\{([A-Za-z_][A-Za-z0-9_.-]*+)\}")
WHOLE = re.compile(rf"(?:{INSIDE.pattern})\}}?\Z")
NAME_WORD = re.compile(r"[A-Z]+(?![a-z])|[A-Z]?[a-z]+|[0-9]+")
#: How much a word of a target name tells of a secret; the last group speaks against one.
SENSITIVE = {
    "password": 1.0, "passwd": 1.0, "pwd": 1.0, "passphrase": 1.0, "pass": 0.8, "secret": 1.0, "token": 0.9, "credential": 0.9, "credentials": 0.9,
    "apikey": 1.0, "auth": 0.6, "key": 0.55, "private": 0.4, "access": 0.3, "api": 0.35, "signing": 0.4, "encryption": 0.4, "bearer": 0.7, "salt": 0.5,
    "id": -0.3, "name": -0.5, "path": -0.6, "file": -0.5, "url": -0.5, "count": -0.8, "length": -0.8, "size": -0.8, "type": -0.6, "public": -0.6, "max": -0.6,
}
PLACEHOLDER = re.compile(r"(?i)(?:true|false|null|none|undefined|changeme|example|placeholder|x+|\*+|your.*|todo|test|\d{1,5})\Z")
THRESHOLD = 0.75
MIN_LITERAL = 6


def name_score(name: str) -> float:
    """0 to 1: how sensitive the words of a target name are."""
    return max(0.0, min(1.0, sum(SENSITIVE.get(w.lower(), 0.0) for w in dict.fromkeys(NAME_WORD.findall(name)))))


def literal_score(value: str) -> float:
    """0 to 1: bits per character of the literal against 4, longer ones count in full."""
    if len(value) < MIN_LITERAL or PLACEHOLDER.match(value):
        return 0.0
    bits = -sum((n := value.count(c) / len(value)) * math.log2(n) for c in set(value))
    return min(1.0, bits / 4) * min(1.0, 0.5 + len(value) / 24)


def _block(text: str, key: int, at: int) -> tuple[int, int]:
    """Start and end of the lines from at on that stand deeper than the line of key."""
    line = text.rfind("\n", 0, key) + 1
    indent = len(text[line:key]) - len(text[line:key].lstrip(" \t"))
    start = end = -1
    while at < len(text):
        stop = text.find("\n", at)
        stop = len(text) if stop < 0 else stop
        body = at
        while body < stop and text[body] in " \t":
            body += 1
        if body < stop:
            if body - at <= indent:
                break
            start, end = body if start < 0 else start, stop
        at = stop + 1
    return start, end


def pairs(text: str) -> Iterator[tuple[str, int, int, bool]]:
    """Name, start and end of its value, and whether the value is bare, in order."""
    at = 0
    while m := PAIR.search(text, at):
        at = m.end()
        if m["type"] and len(kind := m["type"].strip()) >= MIN_LITERAL and any(c.isdigit() for c in kind):  # no type, or it may be a value
            yield m["name"], m.start("type"), m.start("type") + len(kind), True
        if m["bare"] is not None:
            yield m["name"], m.start("bare"), m.end("bare"), True
        elif m["open"]:  # what stands inside is read again: the quote may be none
            if later := LATER[m["open"]].match(text, m.end()):
                yield m["name"], later.start(), later.end(), False
        elif m["block"]:
            start, end = _block(text, m.start("name"), m.end())
            if start >= 0:
                yield m["name"], start, end, False
        else:
            group = next(g for g in QUOTED if m[g] is not None)
            yield m["name"], m.start(group), m.end(group), False


def lexed(text: str) -> list[tuple[int, int, float]]:
    """Start, end and score of the literals that sensitive names reach."""
    defined: dict[str, list[tuple[int, int, bool]]] = {}
    for name, start, end, bare in pairs(text):
        defined.setdefault(name, []).append((start, end, bare))
    found: dict[tuple[int, int], float] = {}
    asked = [(-x, name) for name in defined if (x := name_score(name)) > 0]
    heapq.heapify(asked)
    done: set[str] = set()
    while asked:  # the most sensitive first: every name is followed once, by the best that leads to it
        by_name, name = heapq.heappop(asked)
        if name in done:
            continue
        done.add(name)
        for start, end, bare in defined[name]:
            value = text[start:end]
            others = {value} if bare else {x for m in INSIDE.finditer(value) for x in m.groups() if x}
            others = {x for x in others if x in defined and x != name}
            for other in others - done:
                heapq.heappush(asked, (by_name, other))
            if others and (bare or WHOLE.match(value)):
                continue
            look = literal_score(value)
            score = 0.6 * -by_name + 0.4 * look
            if score >= THRESHOLD and look > 0:
                found[start, end] = max(score, found.get((start, end), 0.0))
    return sorted((s, e, x) for (s, e), x in found.items())


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind number, end) of the base kinds, in order."""
    out = []
    low = text.lower()
    if any(x in low for x in ASSIGN_NAMES):
        out += [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if len(m[2]) >= 6]
    if "AKIA" in text:
        out += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text) if m.end() - m.start() >= 20]
    out += [(m.start(), 2, m.end()) for m in HEX.finditer(text)]
    return sorted(out)


def joined(spans: list[tuple[int, int, int]], kinds: tuple[str, ...]) -> str:
    return ",".join(f"{kinds[k]}:{s}:{e}" for s, k, e in spans)


SCHEMA = "doc_id {id_type}, n_assign long, n_access long, n_hex long, n_literal long, base_sha256 string, spans string, top_score double"


def _scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        column, out = texts(batch.column(1)), []
        for text in map(pa.StringScalar.as_py, column):
            base = base_spans(text)
            more = lexed(text) if "=" in text or ":" in text else []
            spans = sorted(base + [(s, 3, e) for s, e, _ in more])
            counts = [sum(k == n for _, k, _ in spans) for n in range(4)]
            out.append((*counts, hashlib.sha256(joined(base, KINDS).encode()).hexdigest(), joined(spans, KINDS), max((x for *_, x in more), default=0.0)))
        types = [pa.int64()] * 4 + [pa.string()] * 2 + [pa.float64()]
        yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array([r[j] for r in out], t) for j, t in enumerate(types))], ["doc_id", "n_assign", "n_access", "n_hex", "n_literal", "base_sha256", "spans", "top_score"])


def scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: counts by base kind, n_literal, digest of the base spans, all spans, highest literal score.

    Map only: no shuffle. Null text counts as empty, without spans; repeated rows give repeated rows; an empty table gives
    none; other columns are not read. Offsets are code points, ends exclusive.
    """
    kind = docs.select(id_col).schema[0].dataType.simpleString()
    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(_scan, SCHEMA.format(id_type=kind))


def redacted(docs: DataFrame) -> DataFrame:
    """doc_id and text with every span replaced by [SECRET]."""

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for text in batch.column(1).to_pylist():
                marks = [] if text is None else base_spans(text) + [(s, 3, e) for s, e, _ in lexed(text)]
                at, parts = 0, []
                for s, _, e in sorted(marks):
                    if s >= at:
                        parts += [text[at:s], "[SECRET]"]
                    at = max(at, e)
                out.append(None if text is None else "".join(parts) + text[at:])
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.string())], ["doc_id", "text"])

    kind = docs.select("doc_id").schema[0].dataType.simpleString()
    return docs.select("doc_id", "text").mapInArrow(cut, f"doc_id {kind}, text string")
