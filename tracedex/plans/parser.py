"""Text dialect of queries (Q12).

    find view -> click+ -> error* -> !signup -> purchase|refund
    in shop where time(1,5) <= 2h and gap(1,2) >= 3
    between 2024-01-02 00:00:00 and 2024-01-05 00:00:00
    groups {1..3,8} {5..7} all explain 4h 2h 1h

Only `find` is mandatory. Durations carry us, ms, s, min, h or d; activities with other characters stand in quotes."""

from __future__ import annotations

import re
from datetime import UTC, datetime

from tracedex.model import Elem, PatternQuery

UNITS = {"us": 1, "ms": 1_000, "s": 1_000_000, "min": 60_000_000, "h": 3_600_000_000, "d": 86_400_000_000}
_NAME = r'(?:"[^"]+"|[\w:/.-]+?)'
_CLAUSES = re.compile(r"\b(find|in|where|between|groups|all|explain)\b(?=(?:[^\"]*\"[^\"]*\")*[^\"]*$)")


def duration(text: str) -> int:
    m = re.fullmatch(r"(\d+(?:\.\d+)?)\s*(us|ms|s|min|h|d)", text.strip())
    if not m:
        raise ValueError(f"not a duration: {text}")
    return round(float(m[1]) * UNITS[m[2]])


def instant(text: str) -> int:
    t = datetime.fromisoformat(text.strip())
    return round((t if t.tzinfo else t.replace(tzinfo=UTC)).timestamp() * 1_000_000)


def element(text: str) -> Elem:
    text, op = text.strip(), "one"
    if text.startswith("!"):
        text, op = text[1:], "neg"
    elif text.endswith(("+", "*")):
        text, op = text[:-1], {"+": "plus", "*": "star"}[text[-1]]
    if not re.fullmatch(rf"{_NAME}(?:\s*\|\s*{_NAME})*", text):
        raise ValueError(f"not an element: {text}")
    return Elem(tuple(x.strip().strip('"') for x in text.split("|")), op)


def parse_groups(text: str) -> list[list[tuple[int, int]]]:
    """'{1..3,8} {5..7}' -> [[(1, 3), (8, 8)], [(5, 7)]]: inclusive ranges of each group (Q8)."""
    if not re.fullmatch(r"\s*(\{[^{}]*\}\s*)+", text):
        raise ValueError(f"not groups: {text}")
    out = []
    for body in re.findall(r"\{([^{}]*)\}", text):
        ranges = []
        for part in body.split(","):
            a, _, b = part.strip().partition("..")
            ranges.append((int(a), int(b or a)))
            if ranges[-1][0] > ranges[-1][1]:
                raise ValueError(f"empty range: {part}")
        out.append(ranges)
    return out


def parse_query(text: str) -> PatternQuery:
    parts = _CLAUSES.split(text)
    if parts[0].strip() or len(parts) < 3 or parts[1] != "find":
        raise ValueError("a query starts with find")
    clauses = dict(zip(parts[1::2], (x.strip() for x in parts[2::2]), strict=True))
    q = PatternQuery(tuple(element(x) for x in clauses["find"].split("->")))
    if "in" in clauses:
        q = PatternQuery(q.elems, log=clauses["in"])
    for one in re.split(r"\s+and\s+", clauses["where"]) if "where" in clauses else []:
        m = re.fullmatch(r"(time|gap)\s*\(\s*(\d+)\s*,\s*(\d+)\s*\)\s*(<=|>=)\s*(.+)", one.strip())
        if not m:
            raise ValueError(f"not a constraint: {one}")
        q = q._and(m[1], "within" if m[4] == "<=" else "atleast", int(m[2]), int(m[3]), duration(m[5]) if m[1] == "time" else int(m[5]))
    if "between" in clauses:
        a, b = re.split(r"\s+and\s+", clauses["between"])
        q = q.between(instant(a), instant(b))
    if "groups" in clauses:
        parse_groups(clauses["groups"])
        q = q.groups(clauses["groups"])
    if "all" in clauses:
        q = q.all_matches()
    if "explain" in clauses:
        k, u, s = clauses["explain"].split()
        q = q.explain(duration(k), duration(u), duration(s))
    return q.check()
