"""Structured Streaming counterparts: incremental index, detection, sessions, counts and pairs within a time (V5)."""

from __future__ import annotations

import json
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from tracedex.model import PatternQuery
from tracedex.operators.validate import occurrences
from tracedex.store import IndexStore


def read_log(spark: SparkSession, path: str, schema, files_per_trigger: int = 1) -> DataFrame:
    """A folder of Parquet batches as a stream."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def index_stream(events: DataFrame, store: IndexStore, checkpoint: str, late: str = "quarantine"):
    """Every micro-batch becomes an index batch; a batch that is sent again after a failure changes nothing (I8, M5)."""
    return events.writeStream.foreachBatch(lambda df, n: None if df.isEmpty() else store.append_batch(df, f"stream-{n:08d}", late=late) and None).option("checkpointLocation", checkpoint).trigger(availableNow=True)


def detect_stream(events: DataFrame, q: PatternQuery, keep_us: int | None = None) -> DataFrame:
    """V5: occurrences as they complete: trace_id, occ_no, first_ts, last_ts. Events of a trace must arrive in the order of time.

    A pattern without operators and constraints binds each element to the first event that fits, so its state is the events bound so far. Any other
    pattern holds a trace's relevant events since its last occurrence, at most `keep_us` long; a limit between the first and the last
    element gives that length by itself, and without one `keep_us` must be given. A repetition at the end never ends in a stream."""
    if q.elems[-1].op in ("plus", "star"):
        raise ValueError("a repetition at the end takes the rest of a trace, which a stream does not have")
    direct = all(e.op == "one" for e in q.elems) and not q.constraints and q.policy == "next_match"
    if not direct and keep_us is None:
        spans = [c.value for c in q.constraints if (c.kind, c.side, c.i, c.j) == ("time", "within", 1, len(q.elems))]
        if not spans:
            raise ValueError("give keep_us, the time that a trace's events are held, or limit the pattern's span")
        keep_us = min(spans)
    types, wanted = set(q.types()), [set(e.types) for e in q.elems]

    def bound_directly(held: list, event: list) -> tuple[list, list | None]:
        if event[2] not in wanted[len(held)]:
            return held, None
        held = [*held, event]
        return ([], held) if len(held) == len(wanted) else (held, None)

    def bound_by_search(held: list, event: list) -> tuple[list, list | None]:
        held = [e for e in [*held, event] if event[1] - e[1] <= keep_us]
        found = next(occurrences([tuple(e) for e in held], q.all_matches(False)), None) if event[2] in wanted[-1] else None
        return ([], [e for _, e in found]) if found else (held, None)

    advance = bound_directly if direct else bound_by_search

    def step(key, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        held, n, seen = json.loads(state.get[0]) if state.exists else [[], 0, 0]
        new = pd.concat(list(frames)).sort_values("ts_us", kind="stable")
        out = []
        for ts, a in zip(new["ts_us"], new["activity"], strict=True):
            seen += 1
            if a not in types:
                continue
            held, found = advance(held, [seen, int(ts), a, int(key[0])])
            if found:
                n += 1
                times = [e[1] for e in found]
                out.append((int(key[0]), n, min(times), max(times)))
        state.update((json.dumps([held, n, seen]),))
        yield pd.DataFrame(out, columns=["trace_id", "occ_no", "first_ts", "last_ts"])

    return events.groupBy("trace_id").applyInPandasWithState(step, "trace_id long, occ_no int, first_ts long, last_ts long", "held string", "append", GroupStateTimeout.NoTimeout)


def type_counts(events: DataFrame, window: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Tumbling or sliding counts by type; `events` has `ts` (timestamp) and `activity`."""
    span = F.window("ts", window, slide) if slide else F.window("ts", window)
    return events.withWatermark("ts", late).groupBy(span, "activity").agg(F.count("*").alias("n"))


def sessions(events: DataFrame, key: str, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """Traces from inactivity gaps."""
    return events.withWatermark("ts", late).groupBy(F.session_window("ts", gap), key).agg(F.count("*").alias("n"))


def distinct_events(events: DataFrame, keys: list[str], late: str = "1 hour") -> DataFrame:
    """Repeated deliveries within the watermark count once (M6)."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(keys)


def pairs_within(events: DataFrame, first: str, second: str, span: str = "1 hour", late: str = "1 hour") -> DataFrame:
    """Stream-stream interval join: `second` after `first` within a time, in one trace."""
    a = events.filter(F.col("activity") == first).select(F.col("trace_id").alias("trace_id"), F.col("ts").alias("ts_a")).withWatermark("ts_a", late)
    b = events.filter(F.col("activity") == second).select(F.col("trace_id").alias("trace_b"), F.col("ts").alias("ts_b")).withWatermark("ts_b", late)
    return a.join(b, F.expr(f"trace_id = trace_b and ts_b > ts_a and ts_b <= ts_a + interval {span}")).select("trace_id", "ts_a", "ts_b")
