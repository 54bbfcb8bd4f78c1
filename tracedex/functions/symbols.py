"""Patterns as regular expressions over symbol strings (V2): one character for each event type that matters."""

from __future__ import annotations

from itertools import pairwise

from pyspark.sql import Column
from pyspark.sql import functions as F

from tracedex.model import PatternQuery

FIRST = 0xE000  # a private range: no letter of it means anything to a regular expression


def alphabet(q: PatternQuery) -> dict[str, str]:
    """Characters of the types that required or negated elements name; starred ones are looked up afterwards."""
    types = sorted({t for e in q.elems if e.op != "star" for t in e.types})
    return {t: chr(FIRST + i) for i, t in enumerate(types)}


def symbol(q: PatternQuery) -> Column:
    letters = alphabet(q)
    return F.create_map(*[F.lit(x) for kv in letters.items() for x in kv])[F.col("activity")]


def between(q: PatternQuery) -> list[list[str]]:
    """Negated types before the first required element, between neighbours, and after the last."""
    spots = [-1, *q.required, len(q.elems)]
    return [sorted({t for e in q.elems[a + 1 : b] if e.op == "neg" for t in e.types}) for a, b in pairwise(spots)]


def expression(q: PatternQuery) -> str:
    """Group 1: what lies before an occurrence; group k + 1: up to and with the k-th required element.

    Every skip excludes the element that it waits for and all that is negated in the span, so it never backtracks over a choice."""
    letters, negated = alphabet(q), between(q)
    out = []
    for k, place in enumerate(q.required):
        wanted = "".join(letters[t] for t in q.elems[place].types)
        if k == 0:
            out.append(f"([{wanted}])")
        elif q.policy == "strict":
            out.append(f"([{wanted}])")
        else:
            out.append(f"([^{wanted}{''.join(letters[t] for t in negated[k])}]*+[{wanted}])")
    return "(?s)(.*?)" + "".join(out)
