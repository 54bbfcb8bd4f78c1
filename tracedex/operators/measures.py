"""Cost and accuracy measures."""

from __future__ import annotations

import statistics as stat
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tracedex.model import PatternQuery
from tracedex.plans.detect import fetch, matching_traces, survivors
from tracedex.operators.validate import validate

GB = 1e9
#: Published unit prices in dollars: fixed values.
PRICES = {"object_gb_month": 0.023, "egress_gb": 0.009, "free_egress_gb": 100, "request_gb_month": 0.3, "write_million": 1.48, "read_million": 0.29}


def describe(log: DataFrame) -> DataFrame:
    """C14: one row of a log's characteristics; slope: of log count over log rank (0: uniform, about -1: power law)."""
    lengths = log.groupBy("trace_id").count()
    kinds = log.groupBy("activity").agg(F.count("*").alias("n"))
    from pyspark.sql import Window as W

    ranked = kinds.withColumn("r", F.row_number().over(W.orderBy(F.desc("n"), "activity")))  # a row a type
    shape = ranked.agg(F.count("*").alias("types"), F.round(F.max("n") / F.sum("n"), 6).alias("top_share"), F.round(F.regr_slope(F.log("n"), F.log("r")), 6).alias("slope"))
    one = lengths.agg(F.sum("count").cast("long").alias("events"), F.count("*").alias("traces"), F.round(F.avg("count"), 6).alias("mean_length"), F.min("count").alias("min_length"), F.max("count").alias("max_length"))
    return one.crossJoin(shape)  # one row each


def index_time(store) -> DataFrame:
    """Seconds, events and pairs of each batch."""
    return store.history().select("version", "batch_id", "seconds", "n_events", "n_pairs").orderBy("version")


def compare_build(log: DataFrame, builders: dict[str, Callable[[DataFrame], DataFrame]]) -> list[tuple[str, float]]:
    """Seconds that each system takes to build its index of one batch."""
    out = []
    for name, build in builders.items():
        began = time.time()
        build(log).write.format("noop").mode("overwrite").save()
        out.append((name, time.time() - began))
    return out


def saving(a: DataFrame, b: DataFrame) -> DataFrame:
    """C4: share of bytes that report `a` saves against report `b`, by table."""
    return a.select("table", F.col("bytes").alias("a")).join(b.select("table", F.col("bytes").alias("b")), "table").select("table", F.round(1 - F.col("a") / F.col("b"), 4).alias("saving"))


def cloud_cost(spark: SparkSession, kind: str, stored_bytes: float, months: float = 1, egress_bytes: float = 0, write_units: float = 0, read_units: float = 0, prices: dict = PRICES) -> DataFrame:
    """Dollars for storage, traffic and requests of given figures."""
    used = spark.createDataFrame([(kind, float(stored_bytes), float(egress_bytes), float(write_units), float(read_units))], "kind string, stored_bytes double, egress_bytes double, write_units double, read_units double")
    return cloud_costs(used, months, prices)


def cloud_costs(used: DataFrame, months: float = 1, prices: dict = PRICES) -> DataFrame:
    """Dollars for storage, traffic and requests of every row: kind (object or request), stored_bytes, egress_bytes, write_units, read_units."""
    stored, is_object = F.col("stored_bytes") / GB, F.col("kind") == "object"
    storage = stored * F.when(is_object, prices["object_gb_month"]).otherwise(prices["request_gb_month"]) * months
    traffic = F.when(is_object, F.greatest(F.lit(0.0), F.col("egress_bytes") / GB - prices["free_egress_gb"]) * prices["egress_gb"]).otherwise(0.0)
    requests = F.when(is_object, 0.0).otherwise(F.col("write_units") / 1e6 * prices["write_million"] + F.col("read_units") / 1e6 * prices["read_million"])
    return used.select("kind", F.round(storage, 6).alias("storage"), F.round(traffic, 6).alias("traffic"), F.round(requests, 6).alias("requests"), F.round(storage + traffic + requests, 6).alias("total"))


def stored_usage(rows: DataFrame) -> DataFrame:
    """What rows cost on either kind of store: each row written and read once as an item, and all of them fetched once. Two rows for `cloud_costs`."""
    b = F.greatest(_row_bytes(rows), F.lit(1))
    one = rows.select(_row_bytes(rows).alias("b"), F.ceil(b / 1024).alias("w"), F.ceil(b / 8192).alias("r"))
    one = one.agg(*[F.coalesce(F.sum(c), F.lit(0)).cast("double").alias(n) for c, n in (("b", "stored_bytes"), ("w", "write_units"), ("r", "read_units"))])
    return one.select(F.explode(F.array(F.lit("object"), F.lit("request"))).alias("kind"), "stored_bytes", F.col("stored_bytes").alias("egress_bytes"), "write_units", "read_units")


def _row_bytes(rows: DataFrame):
    return sum((F.coalesce(F.length(F.col(c).cast("string")), F.lit(0)) for c in rows.columns), F.lit(0))


def request_units(rows: DataFrame, group: list[str] | None = None) -> DataFrame:
    """Write units of 1 KB and read units of 8 KB when each row, or each group of rows, is an item."""
    items = rows.select(*(group or []), _row_bytes(rows).alias("b"))
    items = items.groupBy(*group).agg(F.sum("b").alias("b")) if group else items
    return items.agg(F.sum(F.ceil(F.greatest("b", F.lit(1)) / 1024)).cast("long").alias("write_units"), F.sum(F.ceil(F.greatest("b", F.lit(1)) / 8192)).cast("long").alias("read_units"))


def time_queries(run: Callable[[PatternQuery], DataFrame], queries: list[PatternQuery], timeout_s: float = 600) -> dict:
    """Mean, median and spread of seconds, and how many queries were cancelled at the time-out."""
    import threading

    seconds, late = [], 0
    for n, q in enumerate(queries):
        df = run(q)
        sc = df.sparkSession.sparkContext
        tag = f"tracedex-{id(df)}-{n}"
        sc.addJobTag(tag)
        timer = threading.Timer(timeout_s, sc.cancelJobsWithTag, [tag])
        timer.start()
        began = time.time()
        try:
            df.write.format("noop").mode("overwrite").save()
            seconds.append(time.time() - began)
        except Exception:
            if time.time() - began < timeout_s:
                raise
            late += 1
        finally:
            timer.cancel()
            sc.removeJobTag(tag)
    return {"n": len(queries), "late": late, "mean": stat.fmean(seconds) if seconds else None, "median": stat.median(seconds) if seconds else None, "spread": stat.pstdev(seconds) if seconds else None}


def phases(index, q: PatternQuery) -> dict[str, float]:
    """Seconds to fetch and prune, and to validate; the survivors' events are kept between the two."""
    began = time.time()
    events = fetch(index, q).persist()
    events.count()
    middle = time.time()
    validate(events, q).write.format("noop").mode("overwrite").save()
    end = time.time()
    events.unpersist()
    return {"fetch_and_prune": middle - began, "validate": end - middle}


def pruning(index, q: PatternQuery, prune: str = "any_alternative") -> DataFrame:
    """Survivors, answers, precision, recall and what validation removes."""
    left, right = survivors(index, q, prune).withColumn("s", F.lit(1)), matching_traces(index, q).select(F.col("unit_id").alias("trace_id")).withColumn("a", F.lit(1))
    both = left.join(right, "trace_id", "full")
    one = both.agg(F.count("s").alias("survivors"), F.count("a").alias("answers"), F.count(F.when(F.col("s").isNotNull() & F.col("a").isNotNull(), 1)).alias("hits"))
    return one.select("survivors", "answers", F.round(F.col("hits") / F.greatest("survivors", F.lit(1)), 6).alias("precision"), F.round(F.when(F.col("answers") > 0, F.col("hits") / F.col("answers")).otherwise(1.0), 6).alias("recall"), (F.col("survivors") - F.col("hits")).alias("removed"))


def agree(a: DataFrame, b: DataFrame) -> DataFrame:
    """Rows of one answer that the other lacks; 0 and 0 for agreement."""
    return a.exceptAll(b).agg(F.count("*").alias("only_a")).crossJoin(b.exceptAll(a).agg(F.count("*").alias("only_b")))


def _nodes(plan):
    """The executed plan's nodes, through adaptive stages; a stage that is read again counts once."""
    kind = plan.getClass().getSimpleName()
    if kind.startswith("Reused"):
        return
    yield kind, plan
    if kind == "AdaptiveSparkPlanExec":
        inner = [plan.executedPlan()]
    elif kind.endswith("QueryStageExec"):
        inner = [plan.plan()]
    else:
        children = plan.children()
        inner = [children.apply(i) for i in range(children.size())]
    for child in inner:
        yield from _nodes(child)


def shuffles(df: DataFrame) -> dict[str, int]:
    """How many exchanges, Python nodes and scans the planned query has."""
    text = df._jdf.queryExecution().executedPlan().toString()
    return {"exchanges": text.count("Exchange"), "python": text.count("FlatMapGroupsInPandas") + text.count("MapInArrow"), "scans": text.count("FileScan")}


def volume(df: DataFrame) -> dict[str, int]:
    """Runs a query and gives the rows and bytes that it shuffled, and the files and rows that it read."""
    run = df._jdf.queryExecution()
    run.toRdd().count()
    out = dict.fromkeys(("shuffle_bytes", "shuffle_rows", "files", "rows_read"), 0)
    wanted = {"ShuffleExchangeExec": {"shuffleBytesWritten": "shuffle_bytes", "shuffleRecordsWritten": "shuffle_rows"}, "FileSourceScanExec": {"numFiles": "files", "numOutputRows": "rows_read"}}
    for kind, node in _nodes(run.executedPlan()):
        for metric, name in wanted.get(kind, {}).items():
            value = node.metrics().get(metric)
            if value.isDefined():
                out[name] += value.get().value()
    return out
