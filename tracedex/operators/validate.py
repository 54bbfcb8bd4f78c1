"""Validation of surviving traces (V1-V4, V6): events (unit_id, trace_id, pos, ts_us, activity) -> bound events.

Without constraints every required element binds the first event that fits after the one before it (S2); a negated event in a
span drops the attempt and the search goes on from the next start (S6). With constraints the smallest position
vector that satisfies them is taken (S8). Starred elements and repetitions bind what lies in their span (S4, S5)."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from tracedex.functions import symbols
from tracedex.model import Constraint, PatternQuery

BOUND = "unit_id long, occ_no int, elem int, trace_id long, pos int, ts_us long, activity string"
COLUMNS = ["unit_id", "occ_no", "elem", "trace_id", "pos", "ts_us", "activity"]


def regex_fits(q: PatternQuery) -> bool:
    """No constraints, no negation at an edge: the expression says all."""
    return not q.constraints and q.policy != "any_match" and q.elems[0].op != "neg" and q.elems[-1].op != "neg"


def validate(events: DataFrame, q: PatternQuery, how: str = "auto") -> DataFrame:
    """V6: the cheapest way that can answer the query."""
    if how == "auto":
        how = "regex" if regex_fits(q) else "join" if q.plain and q.constraints and not q.all and q.policy == "next_match" and len(q.elems) <= 4 else "nfa"
    return {"regex": validate_regex, "linear": validate_linear, "join": validate_join, "nfa": validate_nfa}[how](events, q)


def validate_linear(events: DataFrame, q: PatternQuery) -> DataFrame:
    """V1: plain patterns by one pass over each unit's events in order: a fold that binds the next element to the first event that fits
    and begins anew after the last one. JVM code throughout."""
    if not q.plain or q.constraints or q.policy != "next_match":
        raise ValueError("the linear parser takes plain patterns without constraints")
    n, types = len(q.elems), F.array(*[F.lit(e.types[0]) for e in q.elems])
    relevant = events.filter(F.col("activity").isin(q.types()))
    per_unit = relevant.groupBy("unit_id").agg(F.array_sort(F.collect_list(F.struct("pos", "trace_id", "ts_us", "activity"))).alias("ev"))
    # bound: places of all bound events so far; its size says which element is next
    step = lambda bound, k: F.when(F.element_at("ev", k)["activity"] == F.element_at(types, F.size(bound) % n + 1), F.concat(bound, F.array(k))).otherwise(bound)
    bound = F.aggregate(F.sequence(F.lit(1), F.size("ev")), F.array().cast("array<int>"), step)
    if not q.all:  # the fold of one occurrence stops growing when it is whole
        bound = F.aggregate(F.sequence(F.lit(1), F.size("ev")), F.array().cast("array<int>"), lambda b, k: F.when(F.size(b) < n, step(b, k)).otherwise(b))
    found = per_unit.select("unit_id", "ev", bound.alias("b")).withColumn("b", F.slice("b", 1, F.expr(f"cast(size(b) div {n} * {n} as int)")))
    rows = found.select("unit_id", "ev", F.posexplode("b").alias("k", "at")).withColumn("e", F.element_at("ev", F.col("at")))
    return rows.select("unit_id", F.expr(f"cast(k div {n} + 1 as int)").alias("occ_no"), (F.col("k") % n + 1).alias("elem"), "e.trace_id", "e.pos", "e.ts_us", "e.activity")


def validate_regex(events: DataFrame, q: PatternQuery) -> DataFrame:
    """V2: symbol strings and one expression; positions come from the lengths of its groups. JVM code throughout."""
    if not regex_fits(q):
        raise ValueError("constraints and negation at an edge need another validator")
    event = F.struct("pos", "trace_id", "ts_us", "activity")
    # strict matching looks at every event; otherwise types the expression does not name are left out of the string
    shown = F.coalesce(symbols.symbol(q), F.lit("")) if q.policy == "strict" else symbols.symbol(q)
    per_unit = events.withColumn("s", shown).groupBy("unit_id").agg(F.array_sort(F.collect_list(F.when(F.col("s").isNotNull(), F.struct("pos", "s", "trace_id", "ts_us", "activity")))).alias("ev"), *([F.array_sort(F.collect_list(F.when(F.col("activity").isin([t for e in q.elems if e.op in ("star", "plus") for t in e.types] or [""]), event))).alias("more")] if any(e.op in ("star", "plus") for e in q.elems) else []))
    text = F.array_join(F.transform("ev", lambda e: e["s"]), "")
    rx = F.lit(symbols.expression(q))
    n = len(q.required)
    lengths = [F.transform(F.regexp_extract_all("text", rx, F.lit(k + 1)), F.length) for k in range(n + 1)]
    found = per_unit.withColumn("text", text).filter(F.col("text").rlike(symbols.expression(q)))
    found = found.withColumn("occ", F.arrays_zip(*[x.alias(f"g{k}") for k, x in enumerate(lengths)])).drop("text")
    if not q.all:
        found = found.withColumn("occ", F.slice("occ", 1, 1))
    # running ends of occurrences, one step an occurrence
    total = lambda o: sum((o[f"g{k}"] for k in range(1, n + 1)), o["g0"])
    ends = F.aggregate("occ", F.array(F.lit(0)), lambda acc, o: F.concat(acc, F.array(F.element_at(acc, -1) + total(o))))
    rows = found.withColumn("ends", ends).select("*", F.posexplode("occ").alias("k", "o")).withColumn("base", F.element_at("ends", F.col("k") + 1) + F.col("o.g0"))
    spots, at = [], F.col("base")
    for k in range(1, n + 1):
        at = at + F.col(f"o.g{k}")
        spots.append(F.element_at("ev", at))
    rows = rows.select("unit_id", (F.col("k") + 1).alias("occ_no"), *[s.alias(f"e{k}") for k, s in enumerate(spots)], *(["more"] if "more" in per_unit.columns else []))
    rows = rows.withColumn("before", F.coalesce(F.lag(f"e{n - 1}.pos").over(W.partitionBy("unit_id").orderBy("occ_no")), F.lit(0))) if any(e.op == "star" for e in q.elems[: q.required[0]]) else rows.withColumn("before", F.lit(0))
    parts = F.array(*[F.array(F.struct(F.lit(place + 1).alias("elem"), F.col(f"e{k}.trace_id").alias("trace_id"), F.col(f"e{k}.pos").alias("pos"), F.col(f"e{k}.ts_us").alias("ts_us"), F.col(f"e{k}.activity").alias("activity"))) for k, place in enumerate(q.required)], *_fillers(q))
    return rows.select("unit_id", "occ_no", F.explode(F.flatten(parts)).alias("b")).select("unit_id", F.col("occ_no").cast("int"), "b.elem", "b.trace_id", "b.pos", "b.ts_us", "b.activity")


def _fillers(q: PatternQuery) -> list[Column]:
    """What repeated and starred elements bind inside their spans; a trailing one takes the rest of the trace."""
    out: list[Column] = []
    spots = q.required
    if spots[-1] != len(q.elems) - 1 or q.elems[spots[-1]].op == "plus":
        if q.all and any(e.op in ("star", "plus") for e in q.elems[spots[-1] :]):
            raise ValueError("a trailing repetition takes the rest of the trace: there is no second occurrence to ask for; use the automaton")
    for k in range(-1, len(spots)):
        low = F.col(f"e{k}.pos") if k >= 0 else F.col("before")
        high = F.col(f"e{k + 1}.pos") if k + 1 < len(spots) else F.lit(2**31 - 1)
        span = range((spots[k] if k >= 0 else -1) + 1, spots[k + 1] if k + 1 < len(spots) else len(q.elems))
        fills = ([spots[k]] if k >= 0 and q.elems[spots[k]].op == "plus" else []) + [n for n in span if q.elems[n].op == "star"]
        for n in fills:
            got = _inside(list(q.elems[n].types), low, high)
            out.append(_numbered(got, n + 1))
            low = F.coalesce(F.try_element_at(got, F.lit(-1))["pos"], low) if len(fills) > 1 else low
    return out


def _inside(types: list[str], low: Column, high: Column) -> Column:
    return F.filter("more", lambda e: (e["pos"] > low) & (e["pos"] < high) & e["activity"].isin(types))


def _numbered(events: Column, elem: int) -> Column:
    return F.transform(events, lambda e: F.struct(F.lit(elem).alias("elem"), e["trace_id"].alias("trace_id"), e["pos"].alias("pos"), e["ts_us"].alias("ts_us"), e["activity"].alias("activity")))


def validate_join(events: DataFrame, q: PatternQuery) -> DataFrame:
    """V3: plain patterns with constraints as p - 1 joins inside traces; the first occurrence is the least position vector."""
    if not q.plain or q.all:
        raise ValueError("joins answer the first occurrence of plain patterns")
    window = []
    for n, e in enumerate(q.elems, 1):
        window.append(events.filter(F.col("activity") == e.types[0]).select("unit_id", F.col("pos").alias(f"p{n}"), F.col("ts_us").alias(f"t{n}"), F.col("trace_id").alias(f"r{n}")))
    chain = window[0]
    for n in range(2, len(q.elems) + 1):
        chain = chain.join(window[n - 1], "unit_id").filter(F.col(f"p{n}") > F.col(f"p{n - 1}"))
        for c in q.constraints:
            if c.j == n:
                d = (F.col(f"t{c.j}") - F.col(f"t{c.i}")) if c.kind == "time" else (F.col(f"p{c.j}") - F.col(f"p{c.i}"))
                chain = chain.filter(d <= c.value if c.side == "within" else d >= c.value)
    names = [f"{x}{n}" for x in "ptr" for n in range(1, len(q.elems) + 1)]
    best = chain.groupBy("unit_id").agg(F.min(F.struct(*names)).alias("b"))
    bound = F.array(*[F.struct(F.lit(n).alias("elem"), F.col(f"b.r{n}").alias("trace_id"), F.col(f"b.p{n}").alias("pos"), F.col(f"b.t{n}").alias("ts_us"), F.lit(e.types[0]).alias("activity")) for n, e in enumerate(q.elems, 1)])
    return best.select("unit_id", F.lit(1).alias("occ_no"), F.explode(bound).alias("x")).select("unit_id", "occ_no", "x.elem", "x.trace_id", "x.pos", "x.ts_us", "x.activity")


Event = tuple[int, int, str, int]  # pos, ts_us, activity, trace_id


def holds(c: Constraint, first: Event, second: Event) -> bool:
    d = second[1] - first[1] if c.kind == "time" else second[0] - first[0]
    return d <= c.value if c.side == "within" else d >= c.value


def occurrences(events: list[Event], q: PatternQuery) -> Iterator[list[tuple[int, Event]]]:
    """V4, one unit: occurrences as (element from 1, event) lists, in order and without overlap."""
    required, negated = q.required, symbols.between(q)
    start = 0  # events before it belong to earlier occurrences
    while start < len(events):
        chain = _first_chain(events, q, required, negated, start)
        if chain is None:
            return
        bound = _fill(events, q, required, chain, start)
        yield sorted(((n + 1, events[k]) for n, k in bound), key=lambda x: (x[1][0], x[0]))
        if not q.all:
            return
        start = max(k for _, k in bound) + 1


def _first_chain(events, q, required, negated, start) -> list[int] | None:
    if q.policy == "strict" or not q.constraints:
        for s in range(start, len(events)):
            if events[s][2] in q.elems[required[0]].types and not any(e[2] in negated[0] for e in events[start:s]):
                chain = [s]
                for k, place in enumerate(required[1:], 1):
                    at = None
                    for i in range(chain[-1] + 1, len(events)):
                        if events[i][2] in q.elems[place].types:
                            at = i
                            break
                        if events[i][2] in negated[k] or q.policy == "strict":
                            break
                    if at is None:
                        chain = []
                        break
                    chain.append(at)
                if chain and not any(e[2] in negated[-1] for e in events[chain[-1] + 1 :]) and _satisfied(events, q, required, chain, start):
                    return chain
        return None
    places = {place: k for k, place in enumerate(required)}
    simple = [(c, places[c.i - 1], places[c.j - 1]) for c in q.constraints if c.i - 1 in places and c.j - 1 in places and q.elems[c.i - 1].op == "one"]
    certain = len(simple) == len(q.constraints) and not negated[-1]  # a full chain is an answer then, so that a dead end stays one
    ends = [[(c, i) for c, i, j in simple if j == k] for k in range(len(required))]  # what an element must satisfy
    pending = [[(c, i) for c, i, j in simple if i < k < j or i < k == j] for k in range(len(required) + 1)]  # chosen first events that still matter
    limits = [[(c, i) for c, i in pending[k] if c.side == "within"] for k in range(len(required) + 1)]
    dead: set[tuple] = set()  # (elements bound, next event, first events that still matter) without a way on
    stack: list[tuple[list[int], int]] = [([], start)]
    tried: list[tuple] = []
    while stack:  # depth first over positions in order: the first full chain is the least
        chain, at = stack.pop()
        k = len(chain)
        if at < 0:  # all ways on from here have failed
            dead.add(tried.pop())
            continue
        if k == len(required):
            if not any(e[2] in negated[-1] for e in events[chain[-1] + 1 :]) and _satisfied(events, q, required, chain, start):
                return chain
            continue
        wanted, barred = q.elems[required[k]].types, negated[k]
        while at < len(events):
            e = events[at]
            if any(not holds(c, events[chain[i]], e) for c, i in limits[k]):
                break  # positions and times only grow: nothing later can be near enough
            if e[2] in wanted and all(holds(c, events[chain[i]], e) for c, i in ends[k]):
                if e[2] not in barred:
                    stack.append((chain, at + 1))
                state = (k + 1, at + 1, tuple(chain[i] if i < k else at for _, i in pending[k + 1]))
                if state not in dead:
                    if certain:
                        tried.append(state)
                        stack.append((chain, -1))
                    stack.append(([*chain, at], at + 1))
                break
            if e[2] in barred:
                break
            at += 1
    return None


def _fill(events, q, required, chain, start) -> list[tuple[int, int]]:
    """(element, index) of all bound events: required ones, and what repetitions and stars find in their spans."""
    bound = list(zip(required, chain, strict=True))
    if q.policy == "strict":
        return bound
    for k in range(-1, len(required)):
        low, high = (chain[k] if k >= 0 else start - 1), (chain[k + 1] if k + 1 < len(required) else len(events))
        span = range((required[k] if k >= 0 else -1) + 1, required[k + 1] if k + 1 < len(required) else len(q.elems))
        for n in ([required[k]] if k >= 0 and q.elems[required[k]].op == "plus" else []) + [n for n in span if q.elems[n].op == "star"]:
            got = [i for i in range(low + 1, high) if events[i][2] in q.elems[n].types]
            bound += [(n, i) for i in got]
            low = got[-1] if got else low
    return bound


def _satisfied(events, q, required, chain, start) -> bool:
    """Constraints on the bound events: of a repetition, its last event as i and its first as j; unbound elements ask nothing."""
    if not q.constraints:
        return True
    at: dict[int, list[int]] = {}
    for n, i in _fill(events, q, required, chain, start):
        at.setdefault(n, []).append(i)
    return all(holds(c, events[max(at[c.i - 1])], events[min(at[c.j - 1])]) for c in q.constraints if c.i - 1 in at and c.j - 1 in at)


def validate_nfa(events: DataFrame, q: PatternQuery) -> DataFrame:
    """V4: the reference automaton for every operator and constraint, one unit at a time."""

    def one(unit: pd.DataFrame) -> pd.DataFrame:
        unit = unit.sort_values("pos")
        rows = list(zip(unit["pos"], unit["ts_us"], unit["activity"], unit["trace_id"], strict=True))
        uid, out = unit["unit_id"].iloc[0], []
        for n, bound in enumerate(occurrences(rows, q), 1):
            out += [(uid, n, elem, e[3], e[0], e[1], e[2]) for elem, e in bound]
        return pd.DataFrame(out, columns=COLUMNS)

    return events.select("unit_id", "trace_id", "pos", "ts_us", "activity").groupBy("unit_id").applyInPandas(one, BOUND)
