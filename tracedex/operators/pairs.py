"""Event pairs and their statistics."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

PAIR = ["a_first", "a_second", "trace_id", "pos_a", "pos_b", "ts_a", "ts_b"]


#: Where traces are told apart: one with more than so many events for each of its types is paired by intervals, a shorter one by a join inside the trace.
LONG = 16
#: A log whose longest trace is shorter has no trace worth telling apart: the join costs no more than the square of this for each trace.
SHORT = 500


def extract_pairs(log: DataFrame, lookback_us: int | None = None, policy: str = "non_overlap", new_from: DataFrame | None = None, long: int | None = None, carry: tuple[str, ...] = ()) -> DataFrame:
    """Pairs of a log. `new_from` (trace_id, new_pos): only pairs whose second event is at or after new_pos of its trace. `carry`: columns of the log that
    pairs take from their second event; the literal unused-second policy has none.

    For an event b with previous event p of its type, the one pair (A, b) that overlaps no other pair of its types starts at the
    earliest A after p that is young enough; (p, b) itself is the pair of equal types. So each b asks for the first event of every type in the
    interval from p on. In a short trace all earlier events are compared with b, which costs the square of its length. In a long one each b is
    laid among the events of each type in turn and takes the first event after where it stands: rows are events times types, dealt by
    trace and type, so that not even a trace of very many events lies in one task. `long` tells them apart (see `LONG`); without it all are
    taken for short. The pairs are the same. No loop, no state from batch to batch."""
    if policy == "unused_second":
        return _unused_second(log, lookback_us)
    order = W.partitionBy("trace_id", "activity").orderBy("pos")
    last = [F.lag("pos").over(order), F.lag("ts_us").over(order)]
    a = log.select("trace_id", F.col("activity").alias("a_first"), F.col("pos").alias("pos_a"), F.col("ts_us").alias("ts_a"))
    near, q_far = "pos_a >= p and pos_a < pos_b", "coalesce(q, -1) < p"
    if lookback_us is not None:
        near, q_far = f"{near} and ts_b - ts_a <= {int(lookback_us)}", f"{q_far} or ts_b - ts_q > {int(lookback_us)}"

    def joined(b: DataFrame) -> DataFrame:
        # positions and times of a trace rise together: the first event of a type that b may take is the one that follows one which it may not
        firsts = log.select("trace_id", F.col("activity").alias("a_first"), F.col("pos").alias("pos_a"), F.col("ts_us").alias("ts_a"), last[0].alias("q"), last[1].alias("ts_q"), *[F.col(c).alias(f"{c}_a") for c in carry if c == "batch"])
        # no event is of a later batch than one after it: asked all the same, as both sides then have the same columns and share one shuffle
        in_order = " and batch_a <= batch" if "batch" in carry else ""
        return firsts.join(b, "trace_id").filter(f"{near} and ({q_far}){in_order}").select("a_first", "a_second", "trace_id", "pos_a", "pos_b", "ts_a", "ts_b", *carry)

    b = log.select("trace_id", F.col("activity").alias("a_second"), F.col("pos").alias("pos_b"), F.col("ts_us").alias("ts_b"), F.coalesce(last[0], F.lit(0)).alias("p"), last[1].alias("ts_p"), *carry)
    if new_from is not None:
        b = b.join(new_from.select("trace_id", "new_pos"), "trace_id").filter("pos_b >= new_pos").drop("new_pos")
    if long is None:
        return joined(b.drop("ts_p"))
    sizes = log.groupBy("trace_id", "activity").agg(F.count("*").alias("n"))
    sizes = sizes.groupBy("trace_id").agg((F.sum("n") > F.count("*") * long).alias("is_long"), F.collect_list("activity").alias("types"))
    b = b.join(sizes, "trace_id")
    # the trace id as an expression: Spark 4.1 would zip the partitions of two sides that claim the same partitioning, though their numbers may differ at run time
    far = _by_intervals(a, b.filter("is_long"), sizes, lookback_us, carry).withColumn("trace_id", F.when(F.col("pos_b").isNotNull(), F.col("trace_id")))
    return joined(b.filter("not is_long").drop("is_long", "types", "ts_p")).unionByName(far)


def _by_intervals(a: DataFrame, b: DataFrame, sizes: DataFrame, lookback_us: int | None, carry: tuple[str, ...] = ()) -> DataFrame:
    """Pairs of long traces. Each b stands before the first event that it may take: at its interval's start p or, where the lookback begins later, at
    that time; positions and times of a trace rise together, so the later of both counts."""
    events = a.join(sizes.filter("is_long").select("trace_id"), "trace_id", "left_semi")
    # by time first: an event and a b of equal time are told apart by the position that b must not fall below
    low_ts = F.coalesce("ts_p", F.lit(-(1 << 62))) if lookback_us is None else F.greatest(F.coalesce("ts_p", F.lit(-(1 << 62))), F.col("ts_b") - int(lookback_us))
    asks = b.select("trace_id", F.explode("types").alias("a_first"), low_ts.alias("at_ts"), F.col("p").alias("at_pos"), "a_second", "pos_b", "ts_b", *carry)
    nothing = [F.lit(None).cast(t).alias(c) for c, t in (("a_second", "string"), ("pos_b", "int"), ("ts_b", "long"), *((c, b.schema[c].dataType) for c in carry))]
    both = events.select("trace_id", "a_first", F.col("ts_a").alias("at_ts"), F.col("pos_a").alias("at_pos"), *nothing, F.struct(F.col("pos_a"), F.col("ts_a")).alias("f"))
    both = both.unionByName(asks.withColumn("f", F.lit(None).cast("struct<pos_a:int,ts_a:bigint>")))
    # from the last to the first, as a frame that only grows is kept up; of rows at one place the event comes first, so that it is after its ask
    after = W.partitionBy("trace_id", "a_first").orderBy(F.col("at_ts").desc(), F.col("at_pos").desc(), F.col("f").isNull()).rowsBetween(W.unboundedPreceding, -1)
    taken = both.withColumn("g", F.last("f", ignorenulls=True).over(after)).filter("f is null and g is not null").filter("g.pos_a < pos_b")
    return taken.select("a_first", "a_second", "trace_id", F.col("g.pos_a").alias("pos_a"), "pos_b", F.col("g.ts_a").alias("ts_a"), "ts_b", *carry)


def _unused_second(log: DataFrame, lookback_us: int | None) -> DataFrame:
    """The literal rule: every first event takes the first later second event that is not used yet."""

    def one(trace: pd.DataFrame) -> pd.DataFrame:
        trace = trace.sort_values("pos")
        lists = {k: list(zip(g["pos"], g["ts_us"], strict=True)) for k, g in trace.groupby("activity", sort=True)}
        rows, tid = [], int(trace["trace_id"].iloc[0])
        for x, firsts in lists.items():
            for y, seconds in lists.items():
                k = 0
                for pa, ta in firsts:
                    while k < len(seconds) and seconds[k][0] <= pa:
                        k += 1
                    if k == len(seconds):
                        break
                    if lookback_us is None or seconds[k][1] - ta <= lookback_us:
                        rows.append((x, y, tid, pa, seconds[k][0], ta, seconds[k][1]))
                        k += 1
        return pd.DataFrame(rows, columns=PAIR)

    return log.select("trace_id", "pos", "ts_us", "activity").groupBy("trace_id").applyInPandas(one, "a_first string, a_second string, trace_id long, pos_a int, pos_b int, ts_a long, ts_b long")


def pair_stats(pairs: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """Counters that add up over batches (I10), apart for each `by`."""
    d, g = F.col("ts_b") - F.col("ts_a"), F.col("pos_b") - F.col("pos_a")
    return pairs.groupBy(*by, "a_first", "a_second").agg(F.count("*").alias("completions"), F.sum(d).alias("sum_dur"), F.min(d).alias("min_dur"), F.max(d).alias("max_dur"), F.min(g).alias("min_gap"), F.max(g).alias("max_gap"))


def merge_stats(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.unionByName(b).groupBy("a_first", "a_second").agg(*[f(c).alias(c) for c, f in (("completions", F.sum), ("sum_dur", F.sum), ("min_dur", F.min), ("max_dur", F.max), ("min_gap", F.min), ("max_gap", F.max))])


def frontier(pairs: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """Last completion of each pair in each trace."""
    return pairs.groupBy(*by, "a_first", "a_second", "trace_id").agg(F.max("ts_b").alias("last_ts"), F.max("pos_b").alias("last_pos"))


def inverted_lists(pairs: DataFrame) -> DataFrame:
    """One row a pair with all its entries (I17); for reading by people and tests, not for scans."""
    return pairs.groupBy("a_first", "a_second").agg(F.sort_array(F.collect_list(F.struct("trace_id", "pos_a", "pos_b"))).alias("entries"))


def stats_rollup(pairs: DataFrame) -> DataFrame:
    """Completions by first and second activity with subtotals."""
    return pairs.rollup("a_first", "a_second").agg(F.count("*").alias("completions"), F.grouping_id().alias("level"))


def bounds(log: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    return log.groupBy(*by, "trace_id").agg(F.count("*").alias("n_events"), F.min("ts_us").alias("first_ts"), F.max("ts_us").alias("last_ts"), F.max("pos").cast("int").alias("last_pos"))


def dictionary(log: DataFrame) -> DataFrame:
    return log.groupBy("activity").agg(F.count("*").alias("n_events"), F.count_distinct("trace_id").alias("n_traces"))
