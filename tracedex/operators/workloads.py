"""Experiment workloads (W1-W10, WG), deterministic without engine-specific hashes."""

from __future__ import annotations

import random

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from tracedex.model import DAY, HOUR, IndexConfig, P, PatternQuery, seq

EPOCH = 1_704_067_200_000_000  # 2024-01-01


def carry_over(log: DataFrame, days: int = 10) -> DataFrame:
    """The first days as daily batches; a user's trace runs on into the next active day for a tenth of (user, day), else a new one starts."""
    e = log.withColumn("day", F.floor((F.col("ts_us") - EPOCH) / DAY).cast("int")).filter(F.col("day").between(0, days - 1))
    order = W.partitionBy("trace_id").orderBy("ts_us")
    before = F.lag("day").over(order)  # of events at one time, which are of one day, only one can follow another day
    fresh = F.when(before.isNull(), 1).when((before == F.col("day")) | ((F.col("trace_id") * 7 + F.col("day") * 13) % 10 == 0), 0).otherwise(1)
    runs = e.withColumn("f", fresh).withColumn("run", F.sum("f").over(order.rangeBetween(W.unboundedPreceding, W.currentRow)))
    return runs.select((F.col("trace_id") * 1000 + F.col("run")).alias("trace_id"), "day", "ts_us", "activity")


def random_patterns(log: DataFrame, length: int, n: int = 100, seed: int = 1) -> list[PatternQuery]:
    """WG: plain patterns that each occur in some trace: one trace and rising positions, by seeded integer arithmetic on the driver.

    Only the chosen traces' events (at most n traces) are collected."""
    lengths = log.groupBy("trace_id").count().filter(F.col("count") >= length)
    key = (F.col("trace_id") * 2_654_435_761 + seed * 97) % 1_000_003
    chosen = [r["trace_id"] for r in lengths.orderBy(key, "trace_id").limit(n).select("trace_id").collect()]
    rows = log.filter(F.col("trace_id").isin(chosen)).select("trace_id", "pos", "activity").collect()
    traces: dict[int, list] = {}
    for r in sorted(rows, key=lambda r: (r["trace_id"], r["pos"])):
        traces.setdefault(r["trace_id"], []).append(r["activity"])
    pick, out = random.Random(seed), []
    while len(out) < n and chosen:
        trace = traces[chosen[len(out) % len(chosen)]]
        out.append(seq(*[trace[i] for i in sorted(pick.sample(range(len(trace)), length))]))
    return out


def complexify(queries: list[PatternQuery], types: list[str], neg: float = 0.15, plus: float = 0.15, span: float = 0.15, span_us: int = 10 * DAY, seed: int = 1) -> list[PatternQuery]:
    """Simple patterns with negation, one-or-more and a first-last limit, each by chance."""
    pick, out = random.Random(seed), []
    for q in queries:
        elems = list(q.elems)
        if pick.random() < plus:
            k = pick.randrange(len(elems) - 1)
            elems[k] = elems[k].plus()
        if pick.random() < neg:
            k = pick.randrange(1, len(elems))
            elems.insert(k, P(pick.choice(types)).neg())
        new = PatternQuery(tuple(elems))
        out.append(new.max_span(span_us) if pick.random() < span else new)
    return out


def grid() -> list[IndexConfig]:
    """Layouts by stored columns; the pair-key layout stands for the second store."""
    return [IndexConfig(layout=layout, mode=mode, lookback_us=3 * DAY, split_every_days=5) for layout in ("segmented", "pair_key") for mode in ("pos", "ts")]


def growing(log: DataFrame, days: tuple[int, ...] = (1, 5, 10)) -> list[DataFrame]:
    """The log after so many days."""
    return [log.filter(F.col("ts_us") < EPOCH + d * DAY) for d in days]


def explain_grid(length: int = 3) -> list[PatternQuery]:
    """K varies at an uncertainty of two steps, then the uncertainty at the least k; step 2 h, first-last limit 6 h."""
    types = ["view", "click", "purchase", "signup", "error"][:length]
    base = seq(*types).within_time(1, length, 6 * HOUR)
    step = 2 * HOUR
    return [base.explain(k * step, 2 * step, step) for k in (2, 4, 6)] + [base.explain(2 * step, u * step, step) for u in (1, 2, 4)]


def large_pattern() -> PatternQuery:
    """Ten elements with every operator."""
    return seq(P("view"), P("click").plus(), P("error").neg(), P("purchase"), P("signup").star(), P("view").or_("click"), P("view"), P("error").star(), P("click"), P("purchase").or_("signup"))
