"""Schemas, index configuration and the query model."""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass, field, replace
from datetime import timedelta

from pyspark.sql import types as T

EVENT_SCHEMA = T.StructType([T.StructField("trace_id", T.LongType()), T.StructField("pos", T.IntegerType()), T.StructField("ts_us", T.LongType()), T.StructField("activity", T.StringType())])
EVENT = ["trace_id", "pos", "ts_us", "activity"]
HOUR = 3_600_000_000
DAY = 24 * HOUR


def micros(value: int | float | timedelta) -> int:
    """A duration in microseconds; bare numbers are microseconds already."""
    return round(value.total_seconds() * 1_000_000) if isinstance(value, timedelta) else int(value)


@dataclass(frozen=True)
class IndexConfig:
    """Fixed at creation (M8)."""

    split_every_days: int = 30
    trace_split: int = 10_000
    lookback_us: int | None = None
    mode: str = "both"  # pos, ts or both (I14)
    compression: str = "snappy"  # snappy, lz4_raw, zstd or none (I15)
    policy: str = "non_overlap"  # or unused_second (I5)
    long_traces: int | None = None  # events a type beyond which a trace is paired by intervals; a store looks at its batches where nothing is given
    layout: str = "segmented"  # or pair_key (I18)
    first_buckets: int = 32
    origin_us: int = 0

    def to_json(self) -> str:
        return json.dumps(asdict(self))

    @staticmethod
    def from_json(text: str) -> IndexConfig:
        return IndexConfig(**json.loads(text))


@dataclass(frozen=True)
class Elem:
    """A pattern element: its types (more than one: alternatives) and its operator."""

    types: tuple[str, ...]
    op: str = "one"  # one, plus, star, neg

    def plus(self) -> Elem:
        return replace(self, op="plus")

    def star(self) -> Elem:
        return replace(self, op="star")

    def neg(self) -> Elem:
        return replace(self, op="neg")

    def or_(self, *types: str) -> Elem:
        return replace(self, types=(*self.types, *types))

    @property
    def required(self) -> bool:
        return self.op in ("one", "plus")


def P(activity: str) -> Elem:
    return Elem((activity,))


@dataclass(frozen=True)
class Constraint:
    """(kind, side, value) between elements i < j of the original pattern, counted from 1."""

    kind: str  # time or gap
    side: str  # within or atleast
    i: int
    j: int
    value: int


@dataclass(frozen=True)
class PatternQuery:
    elems: tuple[Elem, ...]
    constraints: tuple[Constraint, ...] = ()
    log: str = "log"
    window: tuple[int, int] | None = None  # microseconds, both inclusive (S11)
    group_text: str | None = None
    all: bool = False
    explain_with: tuple[int, int, int] | None = None  # k, uncertainty, step
    edge_negation: bool = False
    policy: str = "next_match"  # next_match, any_match or strict

    def _and(self, kind: str, side: str, i: int, j: int, value) -> PatternQuery:
        return replace(self, constraints=(*self.constraints, Constraint(kind, side, i, j, micros(value) if kind == "time" else int(value))))

    def within_time(self, i: int, j: int, value) -> PatternQuery:
        return self._and("time", "within", i, j, value)

    def atleast_time(self, i: int, j: int, value) -> PatternQuery:
        return self._and("time", "atleast", i, j, value)

    def within_gap(self, i: int, j: int, value: int) -> PatternQuery:
        return self._and("gap", "within", i, j, value)

    def atleast_gap(self, i: int, j: int, value: int) -> PatternQuery:
        return self._and("gap", "atleast", i, j, value)

    def max_span(self, value) -> PatternQuery:
        return self.within_time(1, len(self.elems), value)

    def between(self, start_us: int, end_us: int) -> PatternQuery:
        return replace(self, window=(start_us, end_us))

    def groups(self, text: str) -> PatternQuery:
        return replace(self, group_text=text)

    def all_matches(self, on: bool = True) -> PatternQuery:
        return replace(self, all=on)

    def explain(self, k, uncertainty, step) -> PatternQuery:
        return replace(self, explain_with=(micros(k), micros(uncertainty), micros(step)))

    @property
    def required(self) -> list[int]:
        """Places (from 0) of the elements that must be bound."""
        return [n for n, e in enumerate(self.elems) if e.required]

    @property
    def plain(self) -> bool:
        return all(e.op == "one" and len(e.types) == 1 for e in self.elems)

    def types(self) -> list[str]:
        return sorted({t for e in self.elems for t in e.types})

    def check(self) -> PatternQuery:
        """Raises on queries without a meaning."""
        if not self.required:
            raise ValueError("a pattern needs an element that must be bound")
        if any(not e.types for e in self.elems):
            raise ValueError("an element needs a type")
        for c in self.constraints:
            if not 1 <= c.i < c.j <= len(self.elems):
                raise ValueError(f"a constraint needs 1 <= i < j <= {len(self.elems)}: {c}")
            if "neg" in (self.elems[c.i - 1].op, self.elems[c.j - 1].op):
                raise ValueError("a negated element is never bound, so nothing can be asked of it")
        if not self.edge_negation and (self.elems[0].op == "neg" or self.elems[-1].op == "neg"):
            raise ValueError("negation at an edge needs edge_negation=True")
        if self.explain_with and not self.plain:
            raise ValueError("only plain patterns can be explained")
        if self.explain_with and any(c.kind == "gap" for c in self.constraints):
            raise ValueError("gap constraints have no meaning on altered times")
        return self


def seq(*elems: Elem | str, **options) -> PatternQuery:
    """seq(P('A'), P('B').plus(), 'C') and so on."""
    return PatternQuery(tuple(P(e) if isinstance(e, str) else e for e in elems), **options)
