"""Adapters from the given tables, files and generators to event logs: trace_id, pos, ts_us, activity."""

from __future__ import annotations

from datetime import datetime, timedelta

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from tracedex.deploy import ship
from tracedex.operators.positions import with_positions


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _as_counted(spark: SparkSession, sf_dir: str, name: str, ts: str) -> tuple[DataFrame, Column]:
    """A table and the microseconds of one of its times. Parquet stores a time without zone as its count, which Spark hands out where the time is read as an instant; turning
    one into microseconds by functions costs more than all else that is asked of an event here. Times of other kinds go through them."""
    df = read(spark, sf_dir, name)
    if not isinstance(df.schema[ts].dataType, T.TimestampNTZType):
        return df, _micros(ts)
    schema = T.StructType([T.StructField(f.name, T.TimestampType() if f.name == ts else f.dataType) for f in df.schema])
    return spark.read.schema(schema).parquet(f"{sf_dir}/{name}.parquet"), F.unix_micros(ts)


def log_from_df(df: DataFrame, trace: str, activity: Column | str, ts_us: Column | str, tie: tuple[str, ...] = ()) -> DataFrame:
    """Any table as a log; rows without trace, activity or time are not events and are rejected."""
    a, t = (F.col(x) if isinstance(x, str) else x for x in (activity, ts_us))
    log = df.select(F.col(trace).cast("long").alias("trace_id"), a.cast("string").alias("activity"), t.cast("long").alias("ts_us"), *[F.col(c).alias(f"_tie{i}") for i, c in enumerate(tie)])
    log = log.filter("trace_id is not null and activity is not null and ts_us is not null")
    return with_positions(log, tuple(f"_tie{i}" for i in range(len(tie)))).select("trace_id", "pos", "ts_us", "activity")


def _micros(name: str) -> Column:
    return F.expr(f"timestampdiff(MICROSECOND, timestamp_ntz'1970-01-01 00:00:00', cast({name} as timestamp_ntz))")


def events_log(spark: SparkSession, sf_dir: str, grain: str = "type", before_us: int | None = None) -> DataFrame:
    """Users' events; `type_k30` refines the type by the payload number modulo 30 (150 types). `before_us`: only earlier events, told by the stored time."""
    e, ts_us = _as_counted(spark, sf_dir, "events", "ts")
    if before_us is not None and isinstance(e.schema["ts"].dataType, T.TimestampType):
        e = e.filter(F.col("ts") < F.timestamp_micros(F.lit(before_us)))
    elif before_us is not None:
        e = e.filter(F.expr(f"cast(ts as timestamp_ntz) < timestamp_ntz'{datetime(1970, 1, 1) + timedelta(microseconds=before_us)}'"))
    activity = F.col("event_type") if grain == "type" else F.concat_ws(":", "event_type", (F.get_json_object("props", "$.k").cast("int") % 30).cast("string"))
    return log_from_df(e, "user_id", activity, ts_us, ("event_id",))


def orders_log(spark: SparkSession, sf_dir: str) -> DataFrame:
    return log_from_df(read(spark, sf_dir, "orders"), "o_custkey", F.concat_ws("/", "o_orderstatus", "o_orderpriority"), _micros("o_orderdate"), ("o_orderkey",))


def lineitem_log(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lines of orders by brand of the part."""
    lines = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_shipdate")
    parts = read(spark, sf_dir, "part").select(F.col("p_partkey").alias("l_partkey"), "p_brand")
    return log_from_df(lines.join(parts, "l_partkey"), "l_orderkey", "p_brand", _micros("l_shipdate"), ("l_linenumber", "l_partkey", "l_suppkey"))


def _ordinal(df: DataFrame, trace: str, items: Column) -> DataFrame:
    return df.select(F.col(trace).cast("long").alias("trace_id"), F.posexplode(items).alias("k", "activity")).select("trace_id", (F.col("k") + 1).cast("int").alias("pos"), (F.col("k") + 1).cast("long").alias("ts_us"), "activity")


def pages_log(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Opening tags of pages, in order."""
    return _ordinal(read(spark, sf_dir, "pages"), "page_id", F.regexp_extract_all("html", F.lit("<([a-z][a-z0-9]*)"), 1))


def documents_log(spark: SparkSession, sf_dir: str, top: int = 41) -> DataFrame:
    """Words of documents, the `top` commonest only: long and skewed traces."""
    words = _ordinal(read(spark, sf_dir, "documents"), "doc_id", F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), 0))
    common = words.groupBy("activity").count().orderBy(F.desc("count"), "activity").limit(top).select("activity")
    return with_positions(words.join(F.broadcast(common), "activity", "left_semi").drop("pos"))


def conversations_log(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = read(spark, sf_dir, "conversations")
    return log_from_df(c, "conv_id", "role", F.col("turn").cast("long"), ())


def synthetic_log(spark: SparkSession, n_traces: int, n_types: int = 150, lo: int = 50, hi: int = 150, dist: str = "uniform", seed: int = 1) -> DataFrame:
    """A generated log: lengths uniform in lo..hi, types uniform or Zipf; the same rows for the same seed at any partitioning."""
    unit = lambda *c: (F.pmod(F.xxhash64(F.lit(seed), *c), F.lit(1 << 30)) / float(1 << 30))
    traces = spark.range(n_traces).withColumnRenamed("id", "trace_id")
    length = (F.lit(lo) + F.floor(unit("trace_id", F.lit("n")) * (hi - lo + 1))).cast("int")
    rows = traces.select("trace_id", F.explode(F.sequence(F.lit(1), length)).alias("pos")).withColumn("pos", F.col("pos").cast("int"))
    u = unit("trace_id", "pos", F.lit("a"))
    kind = F.floor(u * n_types) if dist == "uniform" else F.least(F.floor(F.exp(u * F.log(F.lit(float(n_types + 1))))) - 1, F.lit(n_types - 1))
    return rows.select("trace_id", "pos", (F.col("pos").cast("long") * 60_000_000 + F.floor(unit("trace_id", "pos", F.lit("t")) * 59_000_000)).alias("ts_us"), F.concat(F.lit("T"), kind.cast("string")).alias("activity"))


def from_csv(spark: SparkSession, path: str, schema: str, trace: str, activity: str, ts: str, tie: tuple[str, ...] = ()) -> DataFrame:
    """CSV with a header and an explicit schema; a malformed row fails the read."""
    ship(spark)
    return log_from_df(spark.read.csv(path, schema=schema, header=True, mode="FAILFAST"), trace, activity, F.unix_micros(F.col(ts).cast("timestamp")), tie)


def from_json(spark: SparkSession, path: str, schema: str, trace: str, activity: str, ts: str, tie: tuple[str, ...] = ()) -> DataFrame:
    ship(spark)
    return log_from_df(spark.read.json(path, schema=schema, mode="FAILFAST"), trace, activity, F.unix_micros(F.col(ts).cast("timestamp")), tie)


def from_text(spark: SparkSession, path: str, pattern: str, trace: int = 1, ts: int = 2, activity: int = 3) -> DataFrame:
    """Raw lines; the pattern's groups give trace, time and activity. Lines that do not match are no events."""
    ship(spark)
    rows = spark.read.text(path).filter(F.col("value").rlike(pattern))
    part = lambda i: F.regexp_extract("value", pattern, i)
    return log_from_df(rows.select(part(trace).alias("t"), F.try_to_timestamp(part(ts)).alias("at"), part(activity).alias("a")), "t", "a", F.unix_micros("at"), ())


def follow_matrix(pairs: DataFrame) -> DataFrame:
    """Counts of pairs, first activities down, second ones across (pivot)."""
    return pairs.groupBy("a_first").pivot("a_second").count().na.fill(0)


def to_files(answers: DataFrame, path: str, kind: str = "json") -> None:
    """Answers as JSON lines or CSV."""
    answers.write.mode("overwrite").format(kind).option("header", True).save(path)
