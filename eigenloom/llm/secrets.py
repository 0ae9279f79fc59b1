"""Secret scans: three base patterns and an assignment-aware lexer.

The lexer reads name-literal pairs of source and configuration syntax (`name = "x"`, `name: x`, `"name": "x"`, `NAME=x`, `name := x`, `name => x`, `name: type = "x"`,
`map["name"] = "x"`; quotes may hold escaped characters, names are of any length), propagates constants through plain references and `+` joins within a document, and scores each literal by how sensitive its target name is and
by its make-up. A pair whose score reaches `THRESHOLD` adds a span of kind `lexed` over the literal (or over the constant it refers to). Base spans always stay.

Null texts count as empty; repeated rows are scanned alike; spans that tie on their start are ordered by kind; texts of any length are read whole; an empty table gives an
empty result; extra columns are kept where `redacted` returns documents, whatever their names, and ignored elsewhere.
"""

from __future__ import annotations

import math
import re
from collections import Counter

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

KINDS = ("assign", "access", "hex", "lexed")
ASSIGN = re.compile(r"""(?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]{14,}")
HEX = re.compile(r"[0-9a-f]{16,}")
HINTS = ("password", "passwd", "secret", "token", "apikey", "api_key")
#: A quoted literal with escaped characters, or, where its end would be escaped, up to the next quote.
_QUOTED = r""""(?:[^"\\\n]|\\.)*+"|'(?:[^'\\\n]|\\.)*+'|`(?:[^`\\\n]|\\.)*+`|"[^"\n]*"|'[^'\n]*'|`[^`\n]*`"""
_INNER = r"[^\[\]<>\n=]*+"
_ONE_TYPE = rf"&?(?:'\w++[ ])?[A-Za-z_][\w.]*+(?:[\[<]{_INNER}(?:[\[<]{_INNER}[\]>]{_INNER})*+[\]>])*+"
#: A type of a declaration, as in `name: str = "x"`; only where a sign and a literal or a sum follow.
_TYPE = rf"""(?:\??[ \t]*:[ \t]*{_ONE_TYPE}(?:[ \t]*\|[ \t]*{_ONE_TYPE})*+\??(?=[ \t]*=[ \t]*(?:["'`]|[A-Za-z_]\w*[ \t]*\+)))?"""
PAIR = re.compile(
    r"""(?<![\w.-])(?P<q>["'`]?)(?P<name>[A-Za-z_][\w.-]*+)(?P=q)(?:(?<=["'`])[ \t]*\])?""" + _TYPE + r"""[ \t]*(?:=>|:=|==?|:)[ \t]*(?P<value>(?:""" + _QUOTED + r"""|\$?\{?[\w./+=-]+\}?)(?:[ \t]*\+[ \t]*(?:""" + _QUOTED + r"""|[A-Za-z_]\w*))*)""",
    re.ASCII,
)
PART = re.compile(_QUOTED + r"""|\$\{?\w+\}?|[\w./+=-]+""", re.ASCII)
#: Weights of name parts.
NAME_WEIGHTS = {"password": 3, "passwd": 3, "pwd": 3, "secret": 3, "token": 2.5, "apikey": 3, "api": 1, "key": 1.5, "private": 2, "credential": 3, "credentials": 3, "auth": 1.5, "access": 1, "passphrase": 3, "signature": 1, "bearer": 2}
PLACEHOLDERS = re.compile(r"(?i)^(x+|\*+|\.+|none|null|true|false|changeme|change_me|example.*|your.*|test|todo|password|secret|token|<.*>|\$\{.*\})$")
THRESHOLD = 4.0


def _entropy(s: str) -> float:
    return -sum(c / len(s) * math.log2(c / len(s)) for c in Counter(s).values()) if s else 0.0


def score(name: str, literal: str) -> float:
    """Sensitivity of the target name plus evidence in the literal; a name without any sensitive part scores zero, and so does a literal that reads as prose: with spaces, but without a digit."""
    parts = [p for p in re.split(r"[_.\W]+|(?<=[a-z])(?=[A-Z])", name) if p]
    joined = re.sub(r"\W|_", "", name).lower()
    named = sum({p.lower(): NAME_WEIGHTS.get(p.lower(), 0) for p in parts}.values()) or max((w for k, w in NAME_WEIGHTS.items() if len(k) > 4 and k in joined), default=0)
    spaced = " " in literal and not re.search("[0-9]", literal)
    if not named or len(literal) < 6 or spaced or PLACEHOLDERS.match(literal):
        return 0.0
    kinds = sum(bool(re.search(p, literal)) for p in ("[a-z]", "[A-Z]", "[0-9]", "[^A-Za-z0-9]"))
    return named + (kinds >= 2) * 0.5 + (kinds >= 3) * 0.5 + min(1.5, len(literal) / 16) + max(0.0, _entropy(literal) - 2.5) * 0.5


def pairs(text: str) -> list[tuple[str, str, list[tuple[int, int]]]]:
    """(name, value after constant propagation, spans of the literals it is made of), in order."""
    known: dict[str, tuple[str, list[tuple[int, int]]]] = {}
    found = []
    for m in PAIR.finditer(text):
        value, spans, begin = "", [], m.start("value")
        parts = list(PART.finditer(m["value"]))
        for p in parts:
            s = p[0]
            if s[0] in "\"'`":
                value += s[1:-1]
                spans.append((begin + p.start() + 1, begin + p.end() - 1))
            elif (ref := s.strip("${}")) in known:
                value += known[ref][0]
                spans += known[ref][1]
            elif len(parts) == 1 and s[0] != "$":
                value += s
                spans.append((begin + p.start(), begin + p.end()))
        known[m["name"]] = (value, spans)
        found.append((m["name"], value, spans))
    return found


def scan(text: str | None) -> list[tuple[int, int, int]]:
    """(start, end, kind) in code points, by start and then kind."""
    text = text or ""
    lowered = text.lower() if ":" in text or "=" in text else ""
    out = [(m.start(), m.end(), 2) for m in HEX.finditer(text)]
    if "AKIA" in text:
        out += [(m.start(), m.end(), 1) for m in ACCESS.finditer(text)]
    if any(h in lowered for h in HINTS):
        out += [(m.start(), m.end(), 0) for m in ASSIGN.finditer(text) if len(m[1]) >= 12]
    if lowered:
        out += sorted({(s, e, 3) for name, value, spans in pairs(text) if score(name, value) >= THRESHOLD for s, e in spans if e > s})
    return sorted(out, key=lambda x: (x[0], x[2], x[1]))


def joined(spans, base_only: bool = False) -> str:
    return ",".join(f"{KINDS[k]}:{s}:{e}" for s, e, k in spans if k < 3 or not base_only)


def scanned(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, n_lexed, base_spans, spans: one row per row of docs."""

    def run(batches):
        for batch in batches:
            found = [scan(t) for t in batch.column(1).to_pylist()]
            counts = [pa.array([sum(x[2] == k for x in f) for f in found], pa.int64()) for k in range(4)]
            yield pa.RecordBatch.from_arrays([batch.column(0), *counts, pa.array([joined(f, True) for f in found], pa.string()), pa.array([joined(f) for f in found], pa.string())], ["doc_id", "n_assign", "n_access", "n_hex", "n_lexed", "base_spans", "spans"])

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    return rows.mapInArrow(run, "doc_id long, n_assign long, n_access long, n_hex long, n_lexed long, base_spans string, spans string")


def redact(text: str | None, mask: str = "[REDACTED]") -> str | None:
    if text is None:
        return None
    out, at, end = [], 0, -1
    for s, e, _ in scan(text):
        if s >= end:
            out += [text[at if end < 0 else end : s], mask]
        end = max(end, e)
    return "".join(out) + text[max(end, 0) :]


def redacted(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """docs with every found span replaced in the text; all columns and rows stay."""
    at = docs.columns.index(text_col)

    def run(batches):
        for batch in batches:
            yield batch.set_column(at, batch.schema.field(at), pa.array([redact(t) for t in batch.column(at).to_pylist()], batch.schema.field(at).type))

    return docs.mapInArrow(run, docs.schema)
