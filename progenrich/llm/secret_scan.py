"""Secret scans by assignment-aware lexing.

Two layers. The base layer finds three fixed forms. The lexing layer reads the text as source or
configuration: a small lexer yields assignments of a name to literals, to other names or to a chain of
both; constants are propagated through names (the last assignment before the use counts, so one pass in
text order suffices); each literal is scored by how sensitive the name is that it reaches, and by its
own shape. Literals of a sufficient score become spans of kind ``literal``.
"""

from __future__ import annotations

import hashlib
import math
import re
from collections import Counter
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame

from .common import bound_batches, map_slices, texts_of

# Fixed forms of the base layer and their least lengths.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{32,}")
KEYWORDS = re.compile(r"(?:passw(?:or)?d|secret|token|api_?key)[\"' :=]", re.IGNORECASE | re.ASCII)
KINDS = ("assign", "access", "hex", "literal")

# no name gives characters back: none of its characters can begin what follows it
_NAME = r"[A-Za-z_][A-Za-z0-9_.\-]{0,127}+"
_QUOTED = r"\"\"\"(?:[^\\]|\\[\s\S])*?\"\"\"|'''(?:[^\\]|\\[\s\S])*?'''|\"(?:[^\"\\\n]|\\.)*\"|'(?:[^'\\\n]|\\.)*'|`(?:[^`\\]|\\[\s\S])*`"
#: name, operator, first operand; further operands follow by "+".
_START = re.compile(rf"""["']?({_NAME})["']?[ \t]*(:=|=>|=(?!=)|:(?!:))[ \t]*(?=["'`A-Za-z0-9_/+])""", re.ASCII)
#: What follows the type's first name in a typed assignment.
_TYPED = re.compile(r"""(?:[\[<][^\n=]{0,200}[\]>])?(?:[ \t]*\|[ \t]*[A-Za-z_][A-Za-z0-9_.]*){0,20}\??[ \t]*=(?![=>])[ \t]*(?=["'`A-Za-z0-9_/+])""", re.ASCII)
_OPERAND = re.compile(rf"({_QUOTED})|([A-Za-z0-9+/_.=\-]+)", re.ASCII)
_PLUS = re.compile(r"[ \t]*\+[ \t]*(?=[\"'`A-Za-z_])")
_QUOTES = ('"', "'", "`")
#: Most characters of a name.
NAME_SIZE = 128
_PARTS = re.compile(r"[A-Z]+(?![a-z])|[A-Z]?[a-z]+|[0-9]+")

# Sensitive parts of names and their weights (fixed values).
STRONG = frozenset("password passwd passwd pwd passphrase secret token apikey credential credentials".split())
WEAK = frozenset("auth key private access bearer signature salt session cookie".split())
HARMLESS = frozenset("public example sample name id type length size file path url count index".split())


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind number, end) of the base layer, leftmost and non-overlapping per kind."""
    out = []
    if KEYWORDS.search(text):
        out += [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if len(m[2]) >= 8]
    if "AKIA" in text:
        out += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text) if m.end() - m.start() >= 16]
    out += [(m.start(), 2, m.end()) for m in HEX.finditer(text)]
    return sorted(out)


def name_weight(name: str) -> float:
    """How sensitive a target name is, 0 to 1."""
    parts = [p.lower() for p in _PARTS.findall(name.replace("_", " ").replace("-", " ").replace(".", " "))]
    joined = "".join(parts)
    if any(p in STRONG for p in parts) or any(s in joined for s in ("apikey", "password", "passwd", "secretkey", "accesskey", "privatekey", "authtoken")):
        w = 1.0
    elif sum(p in WEAK for p in parts) >= 2:
        w = 0.8
    elif any(p in WEAK for p in parts):
        w = 0.4
    else:
        return 0.0
    return w * (0.5 if parts[-1:] and parts[-1] in HARMLESS or "public" in parts else 1.0)


def literal_weight(value: str) -> float:
    """How much a literal looks like a secret, 0 to 1: length, entropy by character, classes."""
    n = len(value)
    if n < 8 or any(c.isspace() for c in value) or re.search(r"\$\{|\{\{|<[a-z_]+>|%\(|^\*+$|^x+$|example|changeme|placeholder", value, re.IGNORECASE):
        return 0.0
    counts = Counter(value)
    bits = -sum(c / n * math.log2(c / n) for c in counts.values())
    kinds = sum(bool(re.search(p, value)) for p in ("[a-z]", "[A-Z]", "[0-9]", "[^A-Za-z0-9]"))
    return min(1.0, bits / 3.5) * min(1.0, 0.4 + 0.2 * kinds) * min(1.0, 0.6 + n / 40)


@dataclass
class Assignment:
    """One assignment: its literals, and the earlier assignments whose values it takes over."""

    name: str
    literals: set[tuple[int, int]] = field(default_factory=set)
    sources: set[int] = field(default_factory=set)


def _unquoted(text: str, a: int, b: int, known: dict[str, int]) -> tuple[set[tuple[int, int]], set[int], int]:
    """Literals and assignments that an unquoted token stands for, and where it ends.

    A token is a name only as a whole, or as names chained by "+"; any other token is one literal, whatever
    its length. A "+" at its end chains when a string follows, or when the rest is known names.
    """
    if b - a <= NAME_SIZE and (whole := known.get(text[a:b])) is not None:
        return set(), {whole}, b
    plus = text.find("+", a, b)
    if plus < 0:
        return {(a, b)}, set(), b
    last = b - 1 if text[b - 1] == "+" else b
    names = [known.get(x) for x in text[a:last].split("+")] if text[a:plus] in known else [None]
    chained = all(x is not None for x in names)
    if last < b and last > a and (chained or text[b : b + 1] in _QUOTES):
        b = last
    # names within a token that is no chain count beside the literal, as either reading may hold
    return set() if chained else {(a, b)}, {x for x in names if x is not None}, b


def _inside(text: str, a: int, b: int) -> tuple[int, int]:
    """The span within the quotes; space at the ends of strings of several lines is not part of it."""
    size = 3 if b - a >= 6 and text[a : a + 3] in ('"""', "'''") else 1
    a, b = a + size, b - size
    if size == 3 or text[a - 1] == "`":
        body = text[a:b]
        a, b = a + len(body) - len(body.lstrip()), b - len(body) + len(body.rstrip())
    return a, max(a, b)


def assignments(text: str) -> list[Assignment]:
    """Assignments in text order; a name stands for the last one to it before the use."""
    out: list[Assignment] = []
    known: dict[str, int] = {}
    run = (0, 0)  # the last unquoted token: assignments inside of it end with it
    for m in _START.finditer(text):
        made, at = Assignment(m[1]), m.end()
        while True:
            if run[0] <= at < run[1]:
                end, quoted = run[1], False
            else:
                o = _OPERAND.match(text, at)
                if not o:
                    break
                end, quoted = o.end(), o[1] is not None
            if quoted:
                made.literals.add(_inside(text, at, end))
            else:
                run = (at, end) if end > run[1] else run
                # the token may be a type, whose value follows; it counts as well, as it may be a value
                typed = at == m.end() and m[2] == ":"
                if typed and text[end - 1] == "=" and text[end : end + 1] in _QUOTES:
                    at = end
                    continue
                literals, sources, end = _unquoted(text, at, end, known)
                made.literals |= literals
                made.sources |= sources
                if typed and (after := _TYPED.match(text, end)):
                    at = after.end()
                    continue
            plus = _PLUS.match(text, end)
            if not plus:
                break
            at = plus.end()
        known[made.name] = len(out)
        out.append(made)
    return out


def pairs(text: str) -> list[tuple[str, str, int, int]]:
    """(name, literal, start, end) with constants propagated: a literal appears once under every name it reaches.

    The list is as long as names times literals; ``literal_spans`` needs no such list.
    """
    found, reach = assignments(text), []
    for made in found:
        reach.append(made.literals.union(*(reach[i] for i in made.sources)))
    return [(made.name, text[a:b], a, b) for made, spans in zip(found, reach) for a, b in sorted(spans)]


def literal_spans(text: str, least: float = 0.5) -> list[tuple[int, int, int]]:
    """Literals of a sufficient score, in one pass backwards: an assignment hands the greatest weight of the names that
    its value reaches down to its sources, so the work is linear in operands however constants are chained."""
    if "=" not in text and ":" not in text:
        return []
    found = assignments(text)
    weight = [0.0] * len(found)
    best: dict[tuple[int, int], float] = {}
    for i in range(len(found) - 1, -1, -1):
        made = found[i]
        w = max(weight[i], name_weight(made.name))
        if not w:
            continue
        for j in made.sources:
            weight[j] = max(weight[j], w)
        for span in made.literals:
            best[span] = max(best.get(span, 0.0), w)
    return [(a, 3, b) for (a, b), w in best.items() if b > a and w * literal_weight(text[a:b]) >= least]


def spans_of(text: str, least: float = 0.5) -> list[tuple[int, int, int]]:
    """All spans by start, then kind."""
    return sorted(base_spans(text) + literal_spans(text, least))


def joined(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{a}:{b}" for a, k, b in spans)


def redact(text: str, spans: list[tuple[int, int, int]], mark: str = "[SECRET]") -> str:
    out, at = [], 0
    for a, _, b in spans:
        if b <= at:
            continue
        out += [text[at : max(a, at)], mark if a >= at else ""]
        at = b
    return "".join([*out, text[at:]])


SCHEMA = "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string"


def scan(docs: DataFrame, least: float = 0.5, key: str = "doc_id", text: str = "text") -> DataFrame:
    """``doc_id``, counts of the base kinds, digest of the base spans, all spans.

    Null texts count as empty (no spans); repeated rows and null keys pass through; an empty table gives
    no rows; other columns are not read. Offsets are code points, ends exclusive.
    """

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        cols: list[list] = [[], [], [], [], []]
        for t in batch["text"].to_pylist():
            base = base_spans(t)
            kinds = Counter(k for _, k, _ in base)
            every = sorted(base + literal_spans(t, least))
            for c, v in zip(cols, (kinds[0], kinds[1], kinds[2], hashlib.sha256(joined(base).encode()).hexdigest(), joined(every))):
                c.append(v)
        types = (pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.string())
        return pa.RecordBatch.from_arrays([batch["doc_id"], *(pa.array(c, k) for c, k in zip(cols, types))], names=["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans"])

    return map_slices(texts_of(docs, key, text), run, SCHEMA)


def redact_documents(docs: DataFrame, least: float = 0.5, mark: str = "[SECRET]", text: str = "text", size: str = "n_chars") -> DataFrame:
    """The same rows and columns with every span of the text replaced; ``size`` follows the new text.

    Rows without spans, and null texts, are unchanged.
    """
    names = docs.columns

    def run(batches):
        for b in batches:
            for at in range(0, b.num_rows, 256):
                part = b.slice(at, 256)
                new, changed = [], False
                for t in part[text].to_pylist():
                    found = spans_of(t, least) if t else []
                    changed |= bool(found)
                    new.append(redact(t, found, mark) if found else t)
                if changed:
                    cols = {c: part[c] for c in names}
                    cols[text] = pa.array(new, part.schema.field(text).type)
                    if size in cols:
                        old = part[size].to_pylist()
                        cols[size] = pa.array([len(n) if n != o else k for n, o, k in zip(new, part[text].to_pylist(), old)], part.schema.field(size).type)
                    part = pa.RecordBatch.from_arrays([cols[c] for c in names], schema=part.schema)
                yield part

    bound_batches(docs.sparkSession)
    return docs.mapInArrow(run, docs.schema)
