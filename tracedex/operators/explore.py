"""Statistics (Q2), continuation (Q3) and explanation of missing answers."""

from __future__ import annotations

from dataclasses import replace
from itertools import pairwise

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from tracedex.model import Elem, PatternQuery, seq
from tracedex.operators.validate import validate
from tracedex.plans.detect import attach_groups, detect, fetch, matching_traces, survivors
from tracedex.plans.planning import plan_pairs


def _pair_table(index, pattern: PatternQuery) -> DataFrame:
    """ordinal, a_first, a_second: the pairs between neighbouring required elements, one for each choice of alternatives."""
    rows = [(n, a, b) for n, s in enumerate(plan_pairs(replace(pattern, explain_with=None)).spots, 1) for a, b in sorted(s)]
    return F.broadcast(index.stats().sparkSession.createDataFrame(rows, "ordinal int, a_first string, a_second string"))  # a size of the query


def statistics(index, pattern: PatternQuery) -> DataFrame:
    """Q2: ordinal, a_first, a_second, completions, sum, mean, min and max duration; a pair that never occurs has a zero row, and an element with
    alternatives has a row for each of them."""
    wanted = _pair_table(index, pattern)
    stats = index.stats().join(wanted.select("a_first", "a_second").distinct(), ["a_first", "a_second"], "left_semi")
    joined = wanted.join(stats, ["a_first", "a_second"], "left")
    return joined.select("ordinal", "a_first", "a_second", F.coalesce("completions", F.lit(0)).cast("long").alias("completions"), F.coalesce("sum_dur", F.lit(0)).cast("long").alias("sum_dur"), F.round(F.col("sum_dur") / F.col("completions"), 3).alias("mean_dur"), "min_dur", "max_dur")


def _continued(index, pattern: PatternQuery) -> DataFrame:
    """activity, duration: one row for each occurrence of the pattern extended by the activity, occurrences of one extended pattern apart from each other.

    A unit is a trace beside one activity that it holds; in it that activity's events stand for the new element, so all new activities are
    matched in one pass. Activities that the pattern names itself (as many as the query has) are matched one by one."""
    own, mark = pattern.types(), "\x00next"
    base = replace(pattern.all_matches(), group_text=None)
    rows = index.traces().filter(F.col("ts_us").between(*pattern.window)) if pattern.window else index.traces()
    left = survivors(index, pattern)
    own_rows = fetch(index, base).select("trace_id", "pos", "ts_us", "activity")
    others = rows.filter(~F.col("activity").isin(own)).join(left, "trace_id", "left_semi").select("trace_id", "pos", "ts_us", F.col("activity").alias("next"))
    units = others.select("trace_id", "next").distinct()
    events = own_rows.join(units, "trace_id").unionByName(others.select("trace_id", "pos", "ts_us", F.lit(mark).alias("activity"), "next"))
    # units are long: number them by trace and activity, which a hash does without a shuffle; the activity travels with the events
    events = events.withColumn("unit_id", F.xxhash64("trace_id", "next"))
    names = events.filter(F.col("activity") == mark).select("unit_id", "next").distinct()
    extended = replace(base, elems=(*base.elems, Elem((mark,))))
    found = _ends(validate(events.select("unit_id", "trace_id", "pos", "ts_us", "activity"), extended), extended).join(names, "unit_id").select(F.col("next").alias("activity"), "duration")
    for activity in own:
        extended = replace(base, elems=(*base.elems, Elem((activity,))))
        found = found.unionByName(_ends(detect(index, extended), extended).select(F.lit(activity).alias("activity"), "duration"))
    return found


def _ends(bound: DataFrame, q: PatternQuery) -> DataFrame:
    """unit_id, occ_no, duration between the last event of what comes before the last element and that element."""
    last = len(q.elems)
    return bound.groupBy("unit_id", "occ_no").agg((F.max(F.when(F.col("elem") == last, F.col("ts_us"))) - F.max(F.when(F.col("elem") < last, F.col("ts_us")))).alias("duration"))


def continuation(index, pattern: PatternQuery, how: str = "exact", k: int = 3) -> DataFrame:
    """Q3: activity, completions (of the pattern extended by it), mean_dur from the pattern's end, best first.

    exact: occurrences of each extended pattern that do not overlap. bound: the least number of completions between any two neighbours, of the last
    element and the activity too, from statistics alone: occurrences that do not overlap are no more than pairs that do not overlap, so no
    exact value is above it (as long as the index has no lookback). hybrid: exact for the k activities of the highest bound, the bound for others."""
    if how in ("bound", "hybrid"):
        lasts = list(pattern.elems[pattern.required[-1]].types)
        following = index.stats().filter(F.col("a_first").isin(lasts)).groupBy(F.col("a_second").alias("activity"))
        following = following.agg(F.sum("completions").cast("long").alias("completions"), F.round(F.sum("sum_dur") / F.sum("completions"), 3).alias("mean_dur"))
        if len(pattern.required) > 1:
            least = statistics(index, pattern).groupBy("ordinal").agg(F.sum("completions").alias("n")).agg(F.min("n").alias("least"))
            following = following.crossJoin(F.broadcast(least)).withColumn("completions", F.least("completions", "least")).drop("least")  # one row
        if how == "bound":
            return following.orderBy(F.desc("completions"), "activity")
        top = following.orderBy(F.desc("completions"), "activity").limit(k)
        exact = continuation(index, pattern, "exact").join(F.broadcast(top.select("activity")), "activity", "left_semi").withColumn("exact", F.lit(True))
        rest = following.join(F.broadcast(top.select("activity")), "activity", "left_anti").withColumn("exact", F.lit(False))
        return exact.unionByName(rest).orderBy(F.desc("completions"), "activity")
    ranked = _continued(index, pattern).groupBy("activity").agg(F.count("*").alias("completions"), F.round(F.avg("duration"), 3).alias("mean_dur"))
    return ranked.orderBy(F.desc("completions"), "activity")


def diagnose(index, q: PatternQuery, exact: bool = False) -> DataFrame:
    """Check, subject, ok, detail. Duration checks from indexed pairs only suspect (G7); `exact` measures all event pairs. An element
    with alternatives is checked with all of them: a pair is missing if no choice has it, a constraint fails if no choice can meet it."""
    spark = index.stats().sparkSession
    types = spark.createDataFrame([(t,) for t in q.types()], "activity string")
    known = index.dictionary().select("activity").withColumn("has", F.lit(True))
    rows = types.join(known, "activity", "left").select(F.lit("unknown_type").alias("check"), F.col("activity").alias("subject"), F.coalesce("has", F.lit(False)).alias("ok"), F.lit(None).cast("long").alias("detail"))
    if len(q.required) > 1:
        spots = [("|".join(dict.fromkeys(q.elems[a].types)) + " -> " + "|".join(dict.fromkeys(q.elems[b].types)), n) for n, (a, b) in enumerate(pairwise(q.required), 1)]
        named = spark.createDataFrame(spots, "subject string, ordinal int")
        found = statistics(index, q).groupBy("ordinal").agg(F.sum("completions").alias("completions")).join(named, "ordinal").select("subject", "completions").distinct()
        rows = rows.unionByName(found.select(F.lit("missing_pair").alias("check"), "subject", (F.col("completions") > 0).alias("ok"), F.when(F.col("completions") > 0, F.col("completions")).cast("long").alias("detail")))
    for c in q.constraints:
        firsts, seconds = list(q.elems[c.i - 1].types), list(q.elems[c.j - 1].types)
        best = F.min if c.side == "within" else F.max
        if exact:
            d = (F.col("ts_b") - F.col("ts_a")) if c.kind == "time" else (F.col("pos_b") - F.col("pos_a"))
            ends = index.traces().filter(F.col("activity").isin(firsts + seconds))
            earlier = W.partitionBy("trace_id").orderBy("pos").rowsBetween(W.unboundedPreceding, -1)
            # the closest pair: the latest first event before a second one; the farthest: the first one of the trace
            pick = F.last if c.side == "within" else F.first
            before = pick(F.when(F.col("activity").isin(firsts), F.struct("pos", "ts_us")), ignorenulls=True).over(earlier)
            near = ends.withColumn("a", before).filter(F.col("activity").isin(seconds) & F.col("a").isNotNull())
            value = near.select(F.col("a.pos").alias("pos_a"), F.col("a.ts_us").alias("ts_a"), F.col("pos").alias("pos_b"), F.col("ts_us").alias("ts_b")).agg(best(d).alias("v"))
        else:
            measure = f"{'min' if c.side == 'within' else 'max'}_{'dur' if c.kind == 'time' else 'gap'}"
            value = index.stats().filter(F.col("a_first").isin(firsts) & F.col("a_second").isin(seconds)).agg(best(measure).alias("v"))
        good = F.col("v") <= c.value if c.side == "within" else F.col("v") >= c.value
        rows = rows.unionByName(value.select(F.lit("unsatisfiable_constraint").alias("check"), F.lit(f"{c.kind} {c.side} ({c.i},{c.j}) {c.value}").alias("subject"), F.coalesce(good, F.lit(False)).alias("ok"), F.col("v").cast("long").alias("detail")))
    return rows


def explain_candidates(index, q: PatternQuery) -> DataFrame:
    """unit_id of traces that have all types of the pattern, often enough, and no occurrence."""
    need: dict[str, int] = {}
    for e in q.elems:
        need[e.types[0]] = need.get(e.types[0], 0) + 1
    events = index.type_rows(list(need), q.window)
    events = attach_groups(events, q.group_text) if q.group_text else events.withColumn("unit_id", F.col("trace_id"))
    counts = events.groupBy("unit_id").agg(*[F.sum((F.col("activity") == t).cast("int")).alias(f"n{i}") for i, t in enumerate(need)])
    full = counts.filter(" and ".join(f"n{i} >= {n}" for i, n in enumerate(need.values()))).select("unit_id")
    return full.join(matching_traces(index, q), "unit_id", "left_anti")


def expand_uncertain(events: DataFrame, uncertainty: int, step: int, max_copies: int = 201) -> DataFrame:
    """Copies of each event at every step within the uncertainty, with the cost of the change."""
    if step <= 0 or 2 * (uncertainty // step) + 1 > max_copies:
        raise ValueError("the step must be positive and the copies few")
    far = uncertainty // step
    return events.withColumn("shift", F.explode(F.sequence(F.lit(-far), F.lit(far)))).withColumn("new_ts", F.col("ts_us") + F.col("shift") * step).withColumn("cost", F.abs(F.col("shift")) * step).drop("shift")


def explain(index, q: PatternQuery, how: str = "join") -> DataFrame:
    """E5: trace_id, cost, elem, pos, ts_us, new_ts: the cheapest change of times below k that makes each candidate an answer.

    A chain of joins inside traces carries cost and drops partial matches at k and where they outlast a limit that is still open. Of partials that agree on what can still matter (the
    last time, the times that open constraints refer to, used events of repeated types) only the cheapest is kept."""
    k, uncertainty, step = q.check().explain_with
    p, types = len(q.elems), [e.types[0] for e in q.elems]
    events = index.type_rows(sorted(set(types)), q.window).join(explain_candidates(index, q).withColumnRenamed("unit_id", "trace_id"), "trace_id", "left_semi")
    if how == "nfa":
        return _explain_nfa(events, q, k, uncertainty, step)
    copies = expand_uncertain(events, uncertainty, step).filter(F.col("cost") < k)
    part = lambda n: copies.filter(F.col("activity") == types[n - 1]).select("trace_id", F.struct("pos", "ts_us", "new_ts").alias(f"b{n}"), F.col("new_ts").alias(f"n{n}"), F.col("pos").alias(f"p{n}"), F.col("cost").alias("c"))
    chain = part(1).withColumnRenamed("c", "cost")
    for n in range(2, p + 1):
        chain = chain.join(part(n), "trace_id").filter((F.col(f"n{n}") > F.col(f"n{n - 1}")) & (F.col("cost") + F.col("c") < k))
        for m in range(1, n):
            if types[m - 1] == types[n - 1]:
                chain = chain.filter(F.col(f"p{m}") != F.col(f"p{n}"))
        for c in q.constraints:
            if c.j == n:
                d = F.col(f"n{n}") - F.col(f"n{c.i}")
                chain = chain.filter(d <= c.value if c.side == "within" else d >= c.value)
            elif c.i < n < c.j and c.side == "within":  # the element that the limit is for comes later still
                chain = chain.filter(F.col(f"n{n}") - F.col(f"n{c.i}") < c.value)
        chain = chain.withColumn("cost", F.col("cost") + F.col("c")).drop("c")
        matters = [f"n{n}"] + sorted({f"n{c.i}" for c in q.constraints if c.i < n < c.j}) + [f"p{m}" for m in range(1, n + 1) if types[m - 1] in types[n:]]
        rest = [c for c in chain.columns if c not in {"trace_id", *matters}]
        if n < p:
            chain = chain.groupBy("trace_id", *matters).agg(F.min(F.struct("cost", *[c for c in rest if c != "cost"])).alias("x")).select("trace_id", *matters, "x.*")
    best = chain.groupBy("trace_id").agg(F.min(F.struct("cost", *[f"b{n}" for n in range(1, p + 1)])).alias("x"))
    bound = F.array(*[F.struct(F.lit(n).alias("elem"), F.col(f"x.b{n}").alias("b")) for n in range(1, p + 1)])
    return best.select("trace_id", F.col("x.cost").alias("cost"), F.explode(bound).alias("e")).select("trace_id", F.col("cost").cast("long").alias("cost"), "e.elem", "e.b.pos", "e.b.ts_us", "e.b.new_ts")


def _explain_nfa(events: DataFrame, q: PatternQuery, k: int, uncertainty: int, step: int) -> DataFrame:
    """Branch and bound over one trace at a time."""
    types = [e.types[0] for e in q.elems]
    shifts = sorted((s * step for s in range(-(uncertainty // step), uncertainty // step + 1)), key=abs)

    def one(trace: pd.DataFrame) -> pd.DataFrame:
        rows = list(zip(trace["pos"], trace["ts_us"], trace["activity"], strict=True))
        best: list = [k, None]

        def grow(chosen: list[tuple], cost: int) -> None:
            n = len(chosen)
            if n == len(types):
                if cost < best[0]:
                    best[:] = [cost, list(chosen)]
                return
            for pos, ts, a in rows:
                if a != types[n] or any(c[0] == pos for c in chosen):
                    continue
                for s in shifts:
                    if cost + abs(s) >= best[0]:
                        break
                    new = ts + s
                    if chosen and new <= chosen[-1][2]:
                        continue
                    if all((new - chosen[c.i - 1][2] <= c.value) if c.side == "within" else (new - chosen[c.i - 1][2] >= c.value) for c in q.constraints if c.j == n + 1):
                        grow([*chosen, (pos, ts, new)], cost + abs(s))

        grow([], 0)
        out = [(int(trace["trace_id"].iloc[0]), best[0], n, *b) for n, b in enumerate(best[1] or [], 1)]
        return pd.DataFrame(out, columns=["trace_id", "cost", "elem", "pos", "ts_us", "new_ts"])

    return events.select("trace_id", "pos", "ts_us", "activity").groupBy("trace_id").applyInPandas(one, "trace_id long, cost long, elem int, pos int, ts_us long, new_ts long")


def worlds(n: int, uncertainty: int, step: int) -> tuple[int, int]:
    """(copies, cases) of n uncertain events."""
    each = 2 * (uncertainty // step) + 1
    return n * each, each**n


__all__ = ["continuation", "diagnose", "expand_uncertain", "explain", "explain_candidates", "seq", "statistics", "worlds"]
