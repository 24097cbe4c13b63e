"""Boolean expressions over tags: a parser, a normal form, and match probabilities as Columns."""

from __future__ import annotations

import itertools
import re
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

WORLDS = 4096


@dataclass(frozen=True)
class Pred:
    type: str
    tag: object
    op: str = "="


@dataclass(frozen=True)
class And:
    parts: tuple


@dataclass(frozen=True)
class Or:
    parts: tuple


_TOKEN = re.compile(r"\s*(?:(\()|(\))|(,)|(!=|<>|=)|'((?:[^']|'')*)'|(-?\d+(?:\.\d+)?)|([A-Za-z_]\w*))")


def _tokens(text: str) -> list[tuple[str, object]]:
    out, at = [], 0
    text = text.rstrip()
    while at < len(text):
        m = _TOKEN.match(text, at)
        if not m:
            raise ValueError(f"cannot read {text[at:]!r}")
        at = m.end()
        if m[4]:
            out.append(("op", "!=" if m[4] == "<>" else m[4]))
        elif m[5] is not None:
            out.append(("value", m[5].replace("''", "'")))
        elif m[6]:
            out.append(("value", float(m[6]) if "." in m[6] else int(m[6])))
        elif m[7]:
            out.append(("word", m[7]))
        else:
            out.append(("punct", m[1] or m[2] or m[3]))
    return out


def parse_tag_expr(text: str):
    """Read ``Type = 'tag'``, ``!=``, ``IN (...)``, AND, OR, NOT and parentheses; NOT ends up in the predicates."""
    tokens, i = _tokens(text), 0

    def word(w: str) -> bool:
        return i < len(tokens) and tokens[i][0] == "word" and tokens[i][1].upper() == w

    def take(kind: str, value=None):
        nonlocal i
        if i >= len(tokens) or tokens[i][0] != kind or (value is not None and tokens[i][1] != value):
            raise ValueError(f"expected {value or kind} at token {i} of {text!r}")
        i += 1
        return tokens[i - 1][1]

    def any_of():
        nonlocal i
        parts = [all_of()]
        while word("OR"):
            i += 1
            parts.append(all_of())
        return parts[0] if len(parts) == 1 else Or(tuple(parts))

    def all_of():
        nonlocal i
        parts = [one()]
        while word("AND"):
            i += 1
            parts.append(one())
        return parts[0] if len(parts) == 1 else And(tuple(parts))

    def one():
        nonlocal i
        if word("NOT"):
            i += 1
            return negate(one())
        if i < len(tokens) and tokens[i] == ("punct", "("):
            i += 1
            e = any_of()
            take("punct", ")")
            return e
        name = take("word")
        if word("IN"):
            i += 1
            take("punct", "(")
            tags = [take("value")]
            while i < len(tokens) and tokens[i] == ("punct", ","):
                i += 1
                tags.append(take("value"))
            take("punct", ")")
            return Pred(name, tags[0]) if len(tags) == 1 else Or(tuple(Pred(name, t) for t in tags))
        op = take("op")
        return Pred(name, take("value"), op)

    e = any_of()
    if i != len(tokens):
        raise ValueError(f"text after the expression: {tokens[i:]}")
    return normalize(e)


def negate(e):
    if isinstance(e, Pred):
        return Pred(e.type, e.tag, "=" if e.op == "!=" else "!=")
    return (Or if isinstance(e, And) else And)(tuple(negate(p) for p in e.parts))


def normalize(e):
    """Flatten nested And/Or and drop repeated parts."""
    if isinstance(e, Pred):
        return e
    parts = []
    for p in map(normalize, e.parts):
        for q in p.parts if isinstance(p, type(e)) else (p,):
            if q not in parts:
                parts.append(q)
    return parts[0] if len(parts) == 1 else type(e)(tuple(parts))


def predicates(e) -> list[Pred]:
    """Distinct predicates in order of appearance; their numbers are those of the state columns."""
    out: list[Pred] = []

    def walk(x):
        if isinstance(x, Pred):
            if x not in out:
                out.append(x)
        else:
            for p in x.parts:
                walk(p)

    walk(e)
    return out


def holds(e, tags: dict) -> bool:
    """Truth of the expression for known tags."""
    if isinstance(e, Pred):
        return (tags.get(e.type) == e.tag) == (e.op == "=")
    return (all if isinstance(e, And) else any)(holds(p, tags) for p in e.parts)


def holds_column(e, truth: dict[str, str]) -> Column:
    """The same as a Column over hidden truth columns."""
    if isinstance(e, Pred):
        c = F.col(truth[e.type]) == F.lit(e.tag)
        return c if e.op == "=" else ~c
    cols = [holds_column(p, truth) for p in e.parts]
    out = cols[0]
    for c in cols[1:]:
        out = out & c if isinstance(e, And) else out | c
    return out


def _types(e) -> set[str]:
    return {p.type for p in predicates(e)}


def _read_once(e) -> bool:
    """Each type in one place only, and every group of one type plain ``=`` predicates."""
    if isinstance(e, Pred):
        return True
    same = [p for p in e.parts if isinstance(p, Pred)]
    deep = [p for p in e.parts if not isinstance(p, Pred)]
    sets = [_types(p) for p in deep] + [{t} for t in {p.type for p in same}]
    if sum(map(len, sets)) != len(set().union(*sets)):
        return False
    for t in {p.type for p in same}:
        group = [p for p in same if p.type == t]
        if len(group) > 1 and any(p.op != "=" for p in group):
            return False
    return all(map(_read_once, deep))


def match_probability(e, probs: dict[Pred, Column], method: str = "auto") -> Column:
    """Probability that the expression holds, types being independent.

    ``structural``: product over And, complement product over Or; within a type the tags exclude each
    other (Or adds, And of two tags is impossible). ``worlds``: a sum over assignments of the mentioned
    tags and one for all others, right for any nesting. ``auto`` takes the first where it is exact.
    """
    if method == "auto":
        method = "structural" if _read_once(e) else "worlds"
    if method == "structural":
        return _structural(e, probs)
    return _worlds(e, probs)


def _structural(e, probs) -> Column:
    if isinstance(e, Pred):
        return probs[e]
    groups: dict[str, list] = {}
    terms = []
    for p in e.parts:
        if isinstance(p, Pred):
            groups.setdefault(p.type, []).append(p)
        else:
            terms.append(_structural(p, probs))
    firsts = []
    for group in groups.values():
        if len(group) == 1:
            firsts.append(probs[group[0]])
        elif isinstance(e, And):
            firsts.append(F.lit(0.0))
        else:
            firsts.append(F.least(F.lit(1.0), sum((probs[p] for p in group[1:]), probs[group[0]])))
    out = None
    for t in firsts + terms:
        if isinstance(e, And):
            out = t if out is None else out * t
        else:
            out = 1 - t if out is None else out * (1 - t)
    return out if isinstance(e, And) else 1 - out


def _worlds(e, probs) -> Column:
    tags: dict[str, list] = {}
    for p in predicates(e):
        if p.tag not in tags.setdefault(p.type, []):
            tags[p.type].append(p.tag)
    size = 1
    for ts in tags.values():
        size *= len(ts) + 1
    if size > WORLDS:
        raise ValueError(f"{size} assignments; at most {WORLDS} are compiled")
    mass: dict[tuple, Column] = {}
    for t, ts in tags.items():
        total = F.lit(0.0)
        for tag in ts:
            eq, ne = Pred(t, tag), Pred(t, tag, "!=")
            mass[t, tag] = probs[eq] if eq in probs else 1 - probs[ne]
            total = total + mass[t, tag]
        mass[t, None] = F.greatest(F.lit(0.0), 1 - total)
    out = F.lit(0.0)
    for world in itertools.product(*[[(t, tag) for tag in [*ts, None]] for t, ts in tags.items()]):
        if holds(e, dict(world)):
            term = F.lit(1.0)
            for key in world:
                term = term * mass[key]
            out = out + term
    return out


def split_predicates(parts: list) -> tuple[list, list]:
    """Exact conditions (Columns or SQL strings) and tag expressions of a mixed conjunction."""
    exact, tags = [], []
    for p in parts:
        if isinstance(p, str) and p.startswith("tag:"):
            tags.append(parse_tag_expr(p[4:]))
        else:
            (exact if isinstance(p, (Column, str)) else tags).append(p)
    return exact, tags
