"""Which pairs a query needs (P2-P5), with the corrections G3, G4, G9, G10."""

from __future__ import annotations

from collections import Counter
from dataclasses import dataclass
from itertools import pairwise, product

from tracedex.model import Elem, PatternQuery

Pair = tuple[str, str]


#: Or-free patterns beyond which a query is planned place by place.
MOST_ALTERNATIVES = 64


@dataclass(frozen=True)
class PairPlan:
    alternatives: tuple[tuple[Pair, ...], ...]  # consecutive pairs of each or-free pattern, in order; none where there are too many of them
    spots: tuple[frozenset[Pair], ...]  # between each two neighbouring required elements: the pairs of which one must occur
    required: frozenset[Pair]  # in every alternative: their absence excludes a trace
    fetched: frozenset[Pair]  # required and helper pairs; helpers never exclude
    types: tuple[str, ...]  # of all elements
    needs_ts: bool

    @property
    def wanted(self) -> list[Pair]:
        """All pairs that some alternative needs."""
        return sorted(frozenset().union(*self.spots))

    def multiplicity(self) -> list[Counter]:
        return [Counter(a) for a in self.alternatives]


def _choices(q: PatternQuery) -> list[list[Elem]]:
    return [[Elem((t,), e.op) for t in dict.fromkeys(e.types)] if e.required else [e] for e in q.elems]


def expand_alternatives(q: PatternQuery, cap: int = MOST_ALTERNATIVES) -> list[tuple[Elem, ...]]:
    """Or-free patterns; none where there are more than `cap`, and the plan's `spots` say what is needed."""
    choices = _choices(q)
    n = 1
    for c in choices:
        n *= len(c)
    return list(product(*choices)) if n <= cap else []


def plan_pairs(q: PatternQuery, cap: int = MOST_ALTERNATIVES) -> PairPlan:
    """Pruning by alternatives keeps traces with all pairs of one or-free pattern; by spots, those with a pair for every two neighbours, whose
    number grows with the sum and not the product of the choices. Neither loses a trace."""
    q.check()
    alternatives = [tuple(pairwise(e.types[0] for e in pattern if e.required)) for pattern in expand_alternatives(q, cap)]
    needed = [dict.fromkeys(q.elems[n].types) for n in q.required]
    spots = tuple(frozenset(product(a, b)) for a, b in pairwise(needed))
    required = frozenset.intersection(*map(frozenset, alternatives)) if alternatives else frozenset(p for s in spots if len(s) == 1 for p in s)
    helpers = {(t, t) for e in q.elems if e.op in ("neg", "star", "plus") for t in e.types}
    for c in q.constraints:  # a too early first or too late second event is replaced by another of its type
        helpers |= {(t, t) for t in q.elems[(c.i if c.side == "within" else c.j) - 1].types}
    return PairPlan(tuple(alternatives), spots, required, frozenset(helpers).union(*spots), tuple(q.types()), any(c.kind == "time" for c in q.constraints) or q.window is not None)
