"""Secret scans by assignment-aware lexing.

Base kinds are fixed patterns (leftmost, not overlapping within a kind, then a
length test). On top, lines that look like code or configuration are lexed into
name-literal pairs; values that are names are resolved through earlier
assignments of the same text (constant propagation, joined by ``+`` or ``.``),
and a literal is reported if the most sensitive name that it reaches scores
high enough together with the literal's own look. The rest of a line after
``name =`` or ``name:`` (.env, INI, YAML, properties) is a literal without
quotes, unless it is a call or a subscript, or reads a name that an earlier
assignment holds. Literals may stand in one or three quotes or in back quotes;
targets may be subscripts; the text of an element belongs to its name. Values
that are plain words apart from spaces are prose and not reported. Block scalars and values continued on further lines are not
joined.

Edge cases: a null text is empty and has no spans; an empty table gives an
empty result; repeated rows are scanned alike; other columns are dropped.
"""

from __future__ import annotations

import hashlib
import math
import re
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import plain_documents, slices, small_batches

# The base patterns and the least lengths.
ASSIGN = r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]+"
HEX = r"[0-9a-f]+"
LEAST_ASSIGN, LEAST_ACCESS, LEAST_HEX = 6, 20, 24

KINDS = ("assign", "access", "hex", "flow")
_ASSIGN = re.compile(ASSIGN, re.I | re.A)
_ACCESS = re.compile(ACCESS)
_HEX = re.compile(r"[0-9a-f]{%d,}" % LEAST_HEX)
_KEYWORD = re.compile(r"(?:passw|secret|token|api_?key)", re.I | re.A)

#: Parts of names that stand for a secret, with their weight.
SENSITIVE = {"password": 3, "passwd": 3, "passphrase": 3, "pwd": 3, "secret": 3, "token": 2, "apikey": 3, "credential": 3, "credentials": 3, "private": 2, "auth": 1, "bearer": 2, "access": 1, "key": 1, "salt": 1, "signature": 1, "cert": 1, "session": 1, "api": 1}
#: Parts of names that say the value is about something else.
HARMLESS = {"public": -3, "name": -2, "id": -1, "path": -2, "file": -2, "url": -2, "length": -3, "size": -3, "count": -3, "type": -2, "max": -2, "min": -2, "ttl": -3, "timeout": -3, "expiry": -3, "header": -1, "field": -2, "label": -2, "hint": -2, "prompt": -3}
#: Literals that stand for "nothing here yet".
PLACEHOLDERS = re.compile(r"(?i)^(?:change_?me|your[_-].*|example.*|placeholder|dummy|none|null|true|false|todo|test|x+|\*+|<.*>|\$\{.*\}|%\(.*\)s|\{\{.*\}\})$")

#: Quoted by three marks (over lines), one mark, or a back quote.
_LITERAL = r"""(?:\"{3}(?:[^"\\]|\\.|"(?!""))*+"{3}|'{3}(?:[^'\\]|\\.|'(?!''))*+'{3}|"(?:[^"\\\n]|\\.)*+"|'(?:[^'\\\n]|\\.)*+'|`(?:[^`\\\n]|\\.)*+`)"""
_NAME = r"[A-Za-z_][A-Za-z0-9_.\-]*"
#: A name that is read: no dot at its end, which would be a join, and perhaps a sigil.
_READ = r"[A-Za-z_][A-Za-z0-9_\-]*(?:\.[A-Za-z0-9_\-]+)*"
_TERM = rf"(?:{_LITERAL}|\$?{_READ})"
_OPERATOR = r"[\x20\t]*(?::=|=>|->|=(?!=)|:(?!:))[\x20\t]*"
#: name (= | : | :=| => | ->) term ((+ | .) term)*; the name may be quoted, as in JSON, and be a subscript.
_PAIR = re.compile(rf"""(?<![A-Za-z0-9_.\-])(?P<q>["']?)(?P<name>{_NAME})(?P=q)\]?{_OPERATOR}(?P<value>{_TERM}(?:[\x20\t]*[+.][\x20\t]*{_TERM})*)""")
_TERMS = re.compile(rf"(?P<literal>{_LITERAL})|(?P<name>{_READ})")
_MAYBE_PAIR = re.compile(r"""[A-Za-z0-9_.\-"'\]][\x20\t]*(?::=|=>|->|=|:)[\x20\t]*\S|</""")
#: An element whose text is its value.
_ELEMENT = re.compile(rf"<(?P<name>{_NAME})(?:\s[^<>]*+)?>[\x20\t]*+(?P<value>[^<>\s](?:[^<>\n]*[^<>\s])?)[\x20\t]*</(?P=name)\s*>")
#: Words and nothing else.
_PROSE = re.compile(r"[A-Za-z',.!?]+(?:\x20[A-Za-z',.!?]+)+")
#: A line of configuration syntax: the name stands first, the value is the rest.
_LINE = re.compile(rf"""^[\x20\t]*+(?:(?:export|set|-)[\x20\t]++)?(?P<q>["']?)(?P<name>{_NAME})(?P=q){_OPERATOR}(?P<value>[^\s"'\[{{|>&][^\n]*+)""", re.M)
_COMMENT = re.compile(r"[\x20\t][#;]")
#: A call or a subscript as a whole value is code.
_CODE = re.compile(rf"(?:(?:await|new)\x20)?\$?{_READ}\s?(?:\(.*\)|\[.*\])")
_CAMEL = re.compile(r"[A-Z]+(?![a-z])|[A-Z]?[a-z]+|\d+")


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind number, end) of the fixed patterns, unordered."""
    found = []
    if _KEYWORD.search(text):
        found += [(m.start(), 0, m.end()) for m in _ASSIGN.finditer(text) if m.end(2) - m.start(2) >= LEAST_ASSIGN]
    if "AKIA" in text:
        found += [(m.start(), 1, m.end()) for m in _ACCESS.finditer(text) if m.end() - m.start() >= LEAST_ACCESS]
    found += [(m.start(), 2, m.end()) for m in _HEX.finditer(text)]
    return found


def name_score(name: str) -> int:
    """How sensitive a target name is: sum over its parts, the last part counting most."""
    parts = [p.lower() for p in _CAMEL.findall(name)]
    joined = "".join(parts[-2:])
    score = SENSITIVE.get(joined, 0) if len(parts) > 1 else 0
    score += sum(SENSITIVE.get(p, 0) for p in parts)
    return score + sum(HARMLESS.get(p, 0) for p in parts[-1:])


def literal_score(value: str) -> float:
    """Looks of a literal: length, mixture and entropy; below 0 for placeholders and prose."""
    n = len(value)
    if n < 6 or PLACEHOLDERS.match(value) or value.count(" ") > 1 or _PROSE.fullmatch(value):
        return -9.0
    counts = Counter(value)
    entropy = -sum(c / n * math.log2(c / n) for c in counts.values())
    classes = any(c.isdigit() for c in value) + any(c.islower() for c in value) + any(c.isupper() for c in value) + any(not c.isalnum() for c in value)
    return min(entropy, 4.5) - 2.0 + 0.5 * (classes - 1)


def scalar(text: str, start: int, end: int) -> tuple[str, int, int] | None:
    """A value without quotes (value, start, end), or None if it is code."""
    comment = _COMMENT.search(text, start, end)
    value = text[start : comment.start() if comment else end].rstrip(" \t\r,;")
    return (value, start, start + len(value)) if value and not _CODE.fullmatch(value) else None


def lex(text: str) -> list[tuple[str, list[tuple[str, int, int]], list[str], tuple[str, int, int] | None]]:
    """Assignments in order: target name, literals (value, start, end without quotes), names read, the value as it stands without quotes."""
    bare = {m.start("name"): (m["name"], scalar(text, m.start("value"), m.end("value"))) for m in _LINE.finditer(text)}
    out = []
    for m in _PAIR.finditer(text):
        literals, names = [], []
        for t in _TERMS.finditer(text, m.start("value"), m.end("value")):
            if t["literal"] is not None:
                k = 3 if t["literal"][:3] in ('"""', "'''") and len(t["literal"]) >= 6 else 1
                literals.append((t["literal"][k:-k], t.start() + k, t.end() - k))
            else:
                names.append(t["name"])
        out.append((m.start("name"), m["name"], literals, names, bare.pop(m.start("name"), (None, None))[1]))
    out += [(at, name, [], [], value) for at, (name, value) in bare.items()]
    out += [(m.start(), m["name"], [(m["value"], m.start("value"), m.end("value"))], [], None) for m in _ELEMENT.finditer(text)]
    return [x[1:] for x in sorted(out, key=lambda x: x[0])]


def flow_spans(text: str, least: float = 3.0) -> list[tuple[int, int, int]]:
    """Spans of literals that reach a sensitive name, directly or through other names."""
    if not _MAYBE_PAIR.search(text):
        return []
    pairs = lex(text)
    holds: dict[str, list[tuple[str, int, int]]] = {}
    best: dict[tuple[int, int], tuple[float, str]] = {}
    for name, literals, names, bare in pairs:
        reached = literals + [x for other in names for x in holds.get(other, ())]
        if not reached and bare:
            reached = [bare]
        if not reached:
            continue
        reached = list(dict.fromkeys(reached))
        holds[name] = reached
        score = name_score(name)
        if score < 2:
            continue
        whole = "".join(v for v, _, _ in reached)
        looks = literal_score(whole)
        for value, start, end in reached:
            if end > start:
                found = score + max(looks, literal_score(value))
                if found > best.get((start, end), (0.0, ""))[0]:
                    best[start, end] = (found, name)
    return [(start, 3, end) for (start, end), (found, _) in best.items() if found >= least]


def all_spans(text: str) -> tuple[list[tuple[int, int, int]], list[tuple[int, int, int]]]:
    """Base spans and all spans, each by start, then kind as listed."""
    base = sorted(base_spans(text))
    covered = [(s, e) for s, _, e in base]
    extra = [x for x in flow_spans(text) if not any(s <= x[0] and x[2] <= e for s, e in covered)] if text else []
    return base, sorted(base + extra)


def _join(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{s}:{e}" for s, k, e in spans)


SCHEMA = "doc_id long, n_assign long, n_access long, n_hex long, n_flow long, base_sha256 string, spans string"


def scan(docs: DataFrame) -> DataFrame:
    """Per document the counts of the base kinds, a digest of the base spans, and all spans."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "text"):
            counts: tuple[list, ...] = ([], [], [], [])
            digests, joined = [], []
            for text in batch.column(1).to_pylist():
                base, spans = all_spans(text or "")
                kinds = [k for _, k, _ in spans]
                for k in range(4):
                    counts[k].append(kinds.count(k))
                digests.append(hashlib.sha256(_join(base).encode()).hexdigest())
                joined.append(_join(spans))
            yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), *(pa.array(c, pa.int64()) for c in counts), pa.array(digests, pa.string()), pa.array(joined, pa.string())], names=["doc_id", "n_assign", "n_access", "n_hex", "n_flow", "base_sha256", "spans"])

    return plain_documents(docs).mapInArrow(run, SCHEMA)


def redact_text(text: str, mask: str = "[SECRET]") -> str:
    """The text with every span (overlapping ones merged) replaced."""
    _, spans = all_spans(text)
    if not spans:
        return text
    out, at = [], 0
    for start, _, end in spans:
        if end <= at:
            continue
        if start >= at:
            out += [text[at:start], mask]
        at = end
    return "".join([*out, text[at:]])


def redact(docs: DataFrame, mask: str = "[SECRET]") -> DataFrame:
    """All columns as they are, secrets in ``text`` masked; a null text stays null; n_chars, if there, is renewed."""
    fields = docs.schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "text"):
            at = batch.schema.get_field_index("text")
            columns = list(batch.columns)
            columns[at] = pa.array([None if t is None else redact_text(t, mask) for t in batch.column(at).to_pylist()], batch.schema.field(at).type)
            yield pa.RecordBatch.from_arrays(columns, schema=batch.schema)

    out = small_batches(docs).mapInArrow(run, fields)
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(F.col("text").isNull(), F.col("n_chars")).otherwise(F.length("text")).cast(fields["n_chars"].dataType))
    return out
