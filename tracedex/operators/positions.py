"""Order and placement of events (I1, I11, I12, I13) and neighbours in time."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from tracedex.model import DAY, IndexConfig


def with_positions(log: DataFrame, tie: tuple[str, ...] = (), after: DataFrame | None = None, by: tuple[str, ...] = ()) -> DataFrame:
    """Numbers the events of each trace from 1 in (time, tie) order, those of one `by` after those of the one before; `after` (trace_id, last_pos)
    continues stored traces; its other columns stay."""
    order = W.partitionBy("trace_id").orderBy(*by, "ts_us", *tie, "activity")
    pos = F.row_number().over(order)
    if after is not None:
        log = log.join(after, "trace_id", "left")
        pos = pos + F.coalesce("last_pos", F.lit(0))
    return log.withColumn("pos", pos.cast("int")).drop("last_pos", *[c for c in tie if c.startswith("_tie")])


def segment(ts: str, config: IndexConfig) -> Column:
    """Interval of a time; pairs are placed by their second event."""
    return F.floor((F.col(ts) - config.origin_us) / (config.split_every_days * DAY)).cast("int")


def trace_bucket(config: IndexConfig) -> Column:
    return F.expr(f"trace_id div {int(config.trace_split)}")


def first_bucket(activity: Column | str, config: IndexConfig) -> Column:
    """A small number for the first activity, so that its name never is a path."""
    return F.pmod(F.xxhash64(activity), F.lit(config.first_buckets)).cast("int")


def latest_before(log: DataFrame, first: str, second: str) -> DataFrame:
    """As-of join: for each `second` event the latest earlier `first` event of its trace, in one pass."""
    earlier = W.partitionBy("trace_id").orderBy("pos").rowsBetween(W.unboundedPreceding, -1)
    seen = F.last(F.when(F.col("activity") == first, F.struct("pos", "ts_us")), ignorenulls=True).over(earlier)
    rows = log.filter(F.col("activity").isin(first, second)).withColumn("a", seen).filter((F.col("activity") == second) & F.col("a").isNotNull())
    return rows.select("trace_id", F.col("a.pos").alias("pos_a"), F.col("pos").alias("pos_b"), F.col("a.ts_us").alias("ts_a"), F.col("ts_us").alias("ts_b"))


def sessionize(events: DataFrame, key: str, ts_us: str, gap_us: int) -> DataFrame:
    """Traces from inactivity where no case id exists: a new session starts after a pause over `gap_us`."""
    order = W.partitionBy(key).orderBy(ts_us)
    starts = F.when(F.col(ts_us) - F.lag(ts_us).over(order) <= gap_us, 0).otherwise(1)
    return events.withColumn("_new", starts).withColumn("session", F.sum("_new").over(order.rowsBetween(W.unboundedPreceding, 0))).drop("_new")
