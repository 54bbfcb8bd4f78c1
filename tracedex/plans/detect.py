"""Detection: plan, prune through the index, fetch, validate."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from tracedex.functions import masks
from tracedex.model import PatternQuery
from tracedex.operators.validate import validate
from tracedex.plans.parser import parse_groups, parse_query
from tracedex.plans.planning import plan_pairs


def _pairs_of(index, wanted: list[tuple[str, str]], q: PatternQuery) -> DataFrame:
    """trace_id and n (place among `wanted`) of entries; bucket and segment filters prune files, the window looks at the second event only."""
    rows = index.pair_rows(wanted, q.window)
    if len(wanted) == 1:
        return rows.select("trace_id", F.lit(0).alias("n"))
    ordinal = F.create_map(*[F.lit(x) for n, (a, b) in enumerate(wanted) for x in (f"{a}\x00{b}", n)])[F.concat(F.col("a_first"), F.lit("\x00"), F.col("a_second"))]
    return rows.select("trace_id", ordinal.alias("n"))


def survivors(index, q: PatternQuery, prune: str = "any_alternative", multiplicity: bool = True) -> DataFrame:
    """trace_id of traces that can hold an occurrence.

    `required`: every pair common to all alternatives is present (P1, P3). `any_alternative`: all pairs of some alternative are (P6); where there
    are too many alternatives, one pair between any two neighbours is. `semijoin`: rarest pair first, each list filtered by the traces left
    (P8). All are one pass over short lists of ids; the aggregate of bit words is one shuffle whatever the pattern's length and the number
    of its pairs. None loses a matching trace within the index's lookback."""
    plan = plan_pairs(q)
    if not plan.spots:
        types = q.elems[q.required[0]].types
        return index.type_rows(list(types), q.window).select("trace_id").distinct()
    if prune == "semijoin" and plan.required:
        need = sorted(plan.required)
        size = {(r["a_first"], r["a_second"]): r["completions"] for r in index.stats().filter(F.concat("a_first", F.lit("\x00"), "a_second").isin([f"{a}\x00{b}" for a, b in need])).collect()}  # a row for each pair of the query
        lists = [index.pair_rows([p], q.window).select("trace_id").distinct() for p in sorted(need, key=lambda p: size.get(p, 0))]
        return reduce(lambda a, b: b.join(a, "trace_id", "left_semi"), lists)
    wanted = plan.wanted
    place, n = {p: k for k, p in enumerate(wanted)}, len(wanted)
    rows = _pairs_of(index, wanted, q)
    if prune == "required" and not plan.required:
        return rows.select("trace_id").distinct()
    counts = plan.multiplicity() if multiplicity and prune != "required" else [{} for _ in plan.alternatives]
    repeated = sorted({p for c in counts for p, k in c.items() if k > 1})
    seen = rows.groupBy("trace_id").agg(*masks.gathered("n", n), *[F.sum((F.col("n") == place[p]).cast("int")).alias(f"m{place[p]}") for p in repeated])
    if prune == "required":
        return seen.filter(masks.holds_all({place[p] for p in plan.required}, n)).select("trace_id")
    if not plan.alternatives:
        return seen.filter(reduce(lambda a, b: a & b, [masks.holds_any({place[p] for p in s}, n) for s in plan.spots])).select("trace_id")
    tests = []
    for pairs, count in zip(plan.alternatives, counts, strict=True):
        t = masks.holds_all({place[p] for p in pairs}, n)
        for p in repeated:
            if count.get(p, 0) > 1:
                t = t & (F.col(f"m{place[p]}") >= count[p])
        tests.append(t)
    return seen.filter(reduce(lambda a, b: a | b, tests)).select("trace_id")


def attach_groups(events: DataFrame, text: str) -> DataFrame:
    """Events of each group in one order by (time, trace, position), renumbered; unit_id is the group's number from 1."""
    spark = events.sparkSession
    ranges = spark.createDataFrame([(g, a, b) for g, body in enumerate(parse_groups(text), 1) for a, b in body], "unit_id long, low long, high long")
    member = events.join(F.broadcast(ranges), (F.col("trace_id") >= F.col("low")) & (F.col("trace_id") <= F.col("high"))).drop("low", "high").distinct()
    order = W.partitionBy("unit_id").orderBy("ts_us", "trace_id", "pos")
    return member.withColumn("pos", F.row_number().over(order).cast("int"))


def groups_with_types(index, q: PatternQuery) -> DataFrame:
    """unit_id of groups whose traces together have all required types."""
    needs = [q.elems[n].types for n in q.required]
    events = attach_groups(index.type_rows(q.types(), q.window), q.group_text)
    found = events.groupBy("unit_id").agg(*masks.met([F.col("activity").isin(list(t)) for t in needs]))
    return found.filter(masks.holds_all(set(range(len(needs))), len(needs))).select("unit_id")


def fetch(index, q: PatternQuery, prune: str = "any_alternative", source: str = "types") -> DataFrame:
    """Events (unit_id, trace_id, pos, ts_us, activity) of what survives.

    `types` reads the type index and is exact; `pairs` takes only events that the fetched pairs name, as the literal method does
    (it may miss single negated events and later occurrences, G4, G6); `traces` reads whole traces."""
    if q.group_text:
        events = attach_groups(index.type_rows(q.types(), q.window), q.group_text)
        return events.join(groups_with_types(index, q), "unit_id", "left_semi")
    left = survivors(index, q, prune)
    if source == "pairs":
        rows = index.pair_rows(sorted(plan_pairs(q).fetched), q.window)
        both = rows.select("trace_id", F.col("pos_a").alias("pos"), F.col("a_first").alias("activity")).union(rows.select("trace_id", "pos_b", "a_second")).distinct()
        events = both.join(index.traces().select("trace_id", "pos", "ts_us"), ["trace_id", "pos"])
        if q.window:
            events = events.filter(F.col("ts_us").between(*q.window))
    elif source == "traces":
        events = index.traces()
        if q.window:
            events = events.filter(F.col("ts_us").between(*q.window))
    else:
        # strict matching must see what lies between, so it reads whole traces
        events = index.type_rows(q.types(), q.window) if q.policy != "strict" else index.traces()
    return events.join(left, "trace_id", "left_semi").select(F.col("trace_id").alias("unit_id"), "trace_id", "pos", "ts_us", "activity")


def detect(index, q: PatternQuery, how: str = "auto", prune: str = "any_alternative", source: str = "types") -> DataFrame:
    """Q1: one row for each bound event."""
    return validate(fetch(index, q.check(), prune, source), q, how)


def matching_traces(index, q: PatternQuery, **options) -> DataFrame:
    """Q1a."""
    return detect(index, q.all_matches(False), **options).select("unit_id").distinct()


def count_matches(index, q: PatternQuery, **options) -> DataFrame:
    """Occurrences of each unit."""
    return detect(index, q.all_matches(), **options).groupBy("unit_id").agg(F.max("occ_no").cast("long").alias("occurrences"))


def collect_occurrences(bound: DataFrame) -> DataFrame:
    """One row an occurrence with its events as a list."""
    return bound.groupBy("unit_id", "occ_no").agg(F.sort_array(F.collect_list(F.struct("pos", "elem", "ts_us", "activity"))).alias("events"))


def register_answer(spark, index, text: str, name: str) -> DataFrame:
    """Q12 for SQL users: the answer of a query in the text dialect as a temporary view."""
    answer = detect(index, parse_query(text))
    answer.createOrReplaceTempView(name)
    return answer
