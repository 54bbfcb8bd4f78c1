"""Indexes: in memory (lazy plans over a log) and stored (Parquet tables with atomic commits)."""

from __future__ import annotations

import base64
import json
import re
import time
import uuid
from collections import deque
from collections.abc import Iterable
from concurrent.futures import ThreadPoolExecutor
from functools import lru_cache, reduce
from urllib.parse import quote

import xxhash
from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from tracedex.model import EVENT, IndexConfig
from tracedex.operators import pairs as P
from tracedex.operators.positions import first_bucket, segment, trace_bucket, with_positions


class LogIndex:
    """The index of a log as lazy DataFrames; nothing is stored."""

    def __init__(self, log: DataFrame, config: IndexConfig = IndexConfig()):
        self.config, self._log = config, log.select(*EVENT)
        self._pairs = P.extract_pairs(self._log, config.lookback_us, config.policy, long=config.long_traces)

    def traces(self) -> DataFrame:
        return self._log

    def pairs(self) -> DataFrame:
        return self._pairs

    def stats(self) -> DataFrame:
        return P.pair_stats(self.pairs())

    def dictionary(self) -> DataFrame:
        return P.dictionary(self.traces())

    def type_rows(self, types: list[str], window: tuple[int, int] | None = None) -> DataFrame:
        rows = self.traces().filter(F.col("activity").isin(types))
        return rows.filter(F.col("ts_us").between(*window)) if window else rows

    def pair_rows(self, wanted: list[tuple[str, str]], window: tuple[int, int] | None = None) -> DataFrame:
        rows = self.pairs().filter(_any_pair(wanted))
        return rows.filter(F.col("ts_b").between(*window)) if window else rows


def _any_pair(wanted):
    by_first: dict[str, list[str]] = {}
    for a, b in wanted:
        by_first.setdefault(a, []).append(b)
    out = F.lit(False)
    for a, seconds in sorted(by_first.items()):
        out = out | ((F.col("a_first") == a) & F.col("a_second").isin(seconds))
    return out


def _whole(events: DataFrame, *more: Column) -> DataFrame:
    return events.select("trace_id", "ts_us", "activity", *more).filter("trace_id is not null and ts_us is not null and activity is not null")


TABLES = ("type_index", "trace_store", "pair_index", "pair_frontier", "pair_stats", "trace_bounds")
#: Tables whose parts lie in segments, so that parts can be rewritten or dropped by segment.
SEGMENTED = ("type_index", "pair_index")
SCHEMAS = {
    "type_index": "trace_id long, pos int, ts_us long, activity string, part string, segment int, activity_bucket int",
    "trace_store": "trace_id long, pos int, ts_us long, activity string, trace_bucket long, part string",
    "pair_frontier": "a_first string, a_second string, trace_id long, last_ts long, last_pos int, trace_bucket long, part string",
    "pair_stats": "a_first string, a_second string, completions long, sum_dur long, min_dur long, max_dur long, min_gap int, max_gap int, part string",
    "trace_bounds": "trace_id long, n_events long, first_ts long, last_ts long, last_pos int, part string",
}
#: Folders of a part and order inside its files, of the tables by trace.
PLACES = {"trace_store": ([], ["trace_bucket", "trace_id", "pos"]), "pair_frontier": ([], ["trace_bucket", "a_first", "a_second"])}
STAGED = "a_first string, a_second string, trace_id long, pos_a int, pos_b int, ts_a long, ts_b long, batch int"
HISTORY = "version long, batch_id string, kind string, min_ts long, max_ts long, n_events long, n_pairs long, seconds double"
#: Live parts of a table beyond which an appended batch is followed by a compaction.
MOST_PARTS = 64
#: Due batches that are indexed in one pass.
AT_ONCE = 16


class IndexStore(LogIndex):
    """A named log database in a folder. Batches append files; a manifest a version, made only if nobody else has made it, names the parts that
    count, so a reader never sees half a batch and two writers never take one version. Which batches were applied is kept apart from the
    parts, so a batch that is sent again changes nothing, whatever was compacted, merged, rebuilt or expired since."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path.rstrip("/")
        self._seen: dict = {"version": -1}
        self._tables: dict[str, DataFrame] = {}
        self.config = IndexConfig.from_json(read_text(spark, f"{self.path}/config.json"))

    # --- commits
    def _manifest(self, version: int) -> str:
        return f"{self.path}/manifest/{version:012d}.json"

    def _state(self) -> dict:
        """The newest manifest: version, batch_id, parts (table -> part -> segments or none), expired (segments before it are gone)."""
        version = self._seen["version"]
        if version < 0:
            names = [int(n[:-5]) for n in children(self.spark, f"{self.path}/manifest") if n.endswith(".json")]
            version = max(names, default=0)
        while exists(self.spark, self._manifest(version + 1)):
            version += 1
        if version != self._seen["version"]:
            empty = {"version": 0, "batch_id": None, "parts": {t: {} for t in TABLES}, "expired": None}
            self._seen, self._tables = (json.loads(read_text(self.spark, self._manifest(version))) if version else empty), {}
        return self._seen

    def _commit(self, state: dict, kind: str, batch_id: str | None, parts: dict, figures: tuple, expired: int | None) -> None:
        new = {"version": state["version"] + 1, "batch_id": batch_id, "kind": kind, "parts": parts, "expired": expired}
        new |= dict(zip(("min_ts", "max_ts", "n_events", "n_pairs", "seconds"), figures, strict=True))
        create_text(self.spark, self._manifest(new["version"]), json.dumps(new))
        if batch_id is not None:
            self._mark(batch_id)

    def _applied(self, batch_id: str) -> str:
        return f"{self.path}/applied/{quote(batch_id, safe='')}"

    def _mark(self, batch_id: str) -> None:
        if not exists(self.spark, self._applied(batch_id)):
            create_text(self.spark, self._applied(batch_id), batch_id)

    def history(self) -> DataFrame:
        """What every version did and measured."""
        if not self._state()["version"]:
            return self.spark.createDataFrame([], HISTORY)
        return self.spark.read.schema(HISTORY).json(f"{self.path}/manifest")

    def _folders(self, name: str) -> list[str]:
        """Folders of a table's live parts, by segment where a part has been cut."""
        out = []
        for part, segments in self._state()["parts"][name].items():
            at = f"{self.path}/{name}/part={part}"
            out += [at] if segments is None else [f"{at}/segment={s}" for s in segments]
        return out

    def _schema(self, name: str) -> str:
        if name != "pair_index":
            return SCHEMAS[name]
        stored = {"pos": "pos_a int, pos_b int", "ts": "ts_a long, ts_b long", "both": "pos_a int, pos_b int, ts_a long, ts_b long"}[self.config.mode]
        return f"a_first string, a_second string, trace_id long, {stored}, part string, " + ("pair string" if self.config.layout == "pair_key" else "segment int, first_bucket int")

    def _read(self, name: str) -> DataFrame:
        """A table's live rows; listed once a version, with a known schema."""
        self._state()
        if name not in self._tables:
            folders = self._folders(name)
            reader = self.spark.read.schema(self._schema(name)).option("basePath", f"{self.path}/{name}")
            self._tables[name] = reader.parquet(*folders) if folders else self.spark.createDataFrame([], self._schema(name))
        return self._tables[name]

    def _write(self, df: DataFrame, name: str, parts: list[str], by: list[str], sort: list[str]) -> list[list[int] | None]:
        """Writes rows as parts of a table; `batch` tells whose place among `parts` a row has. `by`: folders of a part, few however many rows there are. Trace
        buckets grow with the traces, so they are no folders: a part is dealt by bucket and sorted by it, in as many files as its size asks for,
        and Parquet's own bounds tell which ranges of a file hold a bucket."""
        place = by or sort[:1]
        out = df.repartition("batch", *place) if place and "batch" in df.columns else df.repartition(*place) if place else df.coalesce(1) if name == "pair_stats" else df
        return self._save_parts(out, name, parts, by, sort)

    def _save_parts(self, df: DataFrame, name: str, parts: list[str], by: list[str], sort: list[str]) -> list[list[int] | None]:
        """Several parts are written at once, beside the table, and moved to it; one without rows has no folder then. Returns each part's segments, or none
        where it is not cut."""
        at, cut = f"{self.path}/{name}", by[:1] == ["segment"]
        if len(parts) == 1:
            rows = df.drop("batch")
            self._save(rows.sortWithinPartitions(*by, *sort) if by or sort else rows, f"{at}/part={parts[0]}", by)
        else:
            beside = f"{self.path}/staged/{name}-{parts[0]}"
            try:
                self._save(df.sortWithinPartitions("batch", *by, *sort), beside, ["batch", *by])
                for folder in children(self.spark, beside):
                    if folder.startswith("batch="):
                        move(self.spark, f"{beside}/{folder}", f"{at}/part={parts[int(folder[6:])]}")
            finally:
                delete(self.spark, beside)
        found = [children(self.spark, f"{at}/part={p}") for p in parts]
        return [sorted(int(f[8:]) for f in inner if f.startswith("segment=")) if cut or not inner else None for inner in found]

    def _save(self, df: DataFrame, at: str, by: list[str] | tuple[str, ...] = ()) -> None:
        df.write.mode("overwrite").option("compression", self.config.compression).option("maxRecordsPerFile", 20_000_000).partitionBy(*by).parquet(at)

    # --- reads
    def traces(self) -> DataFrame:
        return self._read("trace_store").select(*EVENT)

    def pairs(self) -> DataFrame:
        rows = self._read("pair_index").drop("part")
        if self.config.mode == "ts":  # positions come from the trace store when asked for
            at = self.traces().select("trace_id", "pos", "ts_us", "activity")
            a = at.select("trace_id", F.col("activity").alias("a_first"), F.col("ts_us").alias("ts_a"), F.col("pos").alias("pos_a"))
            b = at.select("trace_id", F.col("activity").alias("a_second"), F.col("ts_us").alias("ts_b"), F.col("pos").alias("pos_b"))
            return rows.join(a, ["trace_id", "a_first", "ts_a"]).join(b, ["trace_id", "a_second", "ts_b"])
        return rows

    def stats(self) -> DataFrame:
        rows = self._read("pair_stats").drop("part")
        return P.merge_stats(rows.limit(0), rows)

    def frontier(self) -> DataFrame:
        return self._read("pair_frontier").groupBy("a_first", "a_second", "trace_id").agg(F.max("last_ts").alias("last_ts"), F.max("last_pos").alias("last_pos"))

    def bounds(self) -> DataFrame:
        return self._read("trace_bounds").groupBy("trace_id").agg(F.sum("n_events").alias("n_events"), F.min("first_ts").alias("first_ts"), F.max("last_ts").alias("last_ts"), F.max("last_pos").alias("last_pos"))

    def dictionary(self) -> DataFrame:
        return P.dictionary(self.type_rows_all())

    def type_rows_all(self) -> DataFrame:
        return self._read("type_index").select(*EVENT)

    def type_rows(self, types: list[str], window: tuple[int, int] | None = None) -> DataFrame:
        rows = self._read("type_index").filter(F.col("activity_bucket").isin(self._buckets(types)))
        if window:
            rows = rows.filter(F.col("segment").between(*self._segments(window)) & F.col("ts_us").between(*window))
        return rows.filter(F.col("activity").isin(types)).select(*EVENT)

    def pair_rows(self, wanted: list[tuple[str, str]], window: tuple[int, int] | None = None) -> DataFrame:
        """Entries of some pairs. Without a window neither times nor positions are looked up in other tables (a time index has no positions then)."""
        rows = self._read("pair_index").drop("part")
        if "first_bucket" in rows.columns:
            rows = rows.filter(F.col("first_bucket").isin(self._buckets([a for a, _ in wanted])))
        else:
            rows = rows.filter(F.col("pair").isin([pair_key(a, b) for a, b in wanted]))
        rows = rows.filter(_any_pair(wanted))
        if window:
            if "segment" in rows.columns:
                rows = rows.filter(F.col("segment").between(*self._segments(window)))
            if "ts_b" in rows.columns:
                rows = rows.filter(F.col("ts_b").between(*window))
            else:  # position mode: the second event's time comes from the type index (P11)
                times = self.type_rows(sorted({b for _, b in wanted}), window).select("trace_id", F.col("pos").alias("pos_b"))
                rows = rows.join(times, ["trace_id", "pos_b"], "left_semi")
        return rows

    def _buckets(self, names: list[str]) -> list[int]:
        """Bucket numbers of a query's activities: the hash that places rows, computed here, without a job."""
        return sorted({bucket_of(n, self.config.first_buckets) for n in names})

    def _segments(self, window: tuple[int, int]) -> tuple[int, int]:
        return tuple(self._segment(t) for t in window)

    def _segment(self, ts_us: int) -> int:
        return (ts_us - self.config.origin_us) // (self.config.split_every_days * 86_400_000_000)

    # --- writes
    def append_batch(self, events: DataFrame, batch_id: str, strategy: str = "append", late: str = "error", most_parts: int = MOST_PARTS) -> dict:
        """I8: indexes new events (trace_id, ts_us, activity). Only touched traces' recent events are read, only pairs that end in a
        new event are made, so appended batches equal one build. strategy: `append` adds a part and compacts when there are over `most_parts`;
        `merge` is the literal way, which rewrites the segments that the batch touches, and only those. late: error, quarantine or
        rebuild (M6)."""
        return self.append_batches([(events, batch_id)], strategy, late, most_parts)[0]

    def append_table(self, events: DataFrame, batch_ids: list[str], strategy: str = "append", late: str = "error", most_parts: int = MOST_PARTS) -> list[dict]:
        """Due batches that lie in one table, where `batch` tells an event's place among `batch_ids`. As `append_batches` of its cuts, but a pass reads the table once."""
        return self._append([(None, b) for b in batch_ids], strategy, late, most_parts, events)

    def append_batches(self, batches: Iterable[tuple[DataFrame, str]], strategy: str = "append", late: str = "error", most_parts: int = MOST_PARTS) -> list[dict]:
        """Batches that are due, in their order, each with what `append_batch` does for it: a part and a version of its own, committed in that order, and where one
        fails none after it is. Up to `AT_ONCE` are indexed in one pass: as no event is at or before the end of its trace in an earlier batch, numbering
        them together gives what numbering one after the other gives, and a pair belongs to the batch of its second event. From a batch
        on that has late events the passes are of one batch again, and of twice as many after each that has none. A merge reads what its
        forerunner has written, so its passes are of one batch, and so are those of the literal unused-second policy."""
        return self._append(batches, strategy, late, most_parts)

    def _append(self, batches: Iterable[tuple[DataFrame | None, str]], strategy: str, late: str, most_parts: int, table: DataFrame | None = None) -> list[dict]:
        """Batches each with its events, or without them where `table` has them all; a cut of it is planned only where it is asked for, as plans take the driver's time."""
        out: list[dict] = []
        due: deque[tuple] = deque()
        state = self._state()
        if state["batch_id"] is not None:
            self._mark(state["batch_id"])  # a writer may have died between its commit and its mark
        for events, batch_id in batches:
            known = exists(self.spark, self._applied(batch_id)) or any(b == batch_id for _, b, _ in due)
            if not known:
                due.append((events, batch_id, len(out)))
            out.append({"skipped": batch_id} if known else {})
        most = at_most = 1 if strategy == "merge" or self.config.policy == "unused_second" else AT_ONCE
        while due:
            some = [due[i] for i in range(min(most, len(due)))]
            batch = self._place(some, table)
            self._settle(batch, strategy, most_parts, out, [due.popleft()[2] for _ in batch["ids"]])
            most = min(2 * most, at_most)
            if len(batch["ids"]) < len(some):
                events, batch_id, n = due.popleft()
                self._late(_whole(events if table is None else table.filter(F.col("batch") == n)), batch_id, n, strategy, late, most_parts, out)
                most = 1
        return out

    def _late(self, events: DataFrame, batch_id: str, n: int, strategy: str, late: str, most_parts: int, out: list[dict]) -> None:
        """A batch with events at or before the end of what is stored of their traces (M6)."""
        if late == "rebuild":
            out[n] = self._rebuild(events, batch_id)
            return
        if late != "quarantine":
            raise ValueError("the batch has events at or before the end of stored traces")
        known = self._ends()
        events.join(known, "trace_id").filter("ts_us <= last_ts").select("trace_id", "ts_us", "activity").write.mode("overwrite").parquet(f"{self.path}/late/batch={quote(batch_id, safe='')}")
        kept = events.join(known, "trace_id", "left").filter("last_ts is null or ts_us > last_ts").select("trace_id", "ts_us", "activity")
        self._settle(self._place([(kept, batch_id, n)]), strategy, most_parts, out, [n])

    def _ends(self) -> DataFrame:
        """Last time and position of each stored trace."""
        return self._read("trace_bounds").groupBy("trace_id").agg(F.max("last_ts").alias("last_ts"), F.max("last_pos").alias("last_pos"))

    def _place(self, due: list[tuple[DataFrame | None, str, int]], table: DataFrame | None = None) -> dict:
        """Numbers the events of batches after those that are stored and writes each batch's as a part of the trace store. What is asked of them, late events
        included, is counted as they are written. Batches from the first one with late events on are left out again: numbers go by batch, so
        those before it have theirs. `table` holds them all, by their places."""
        state, began = self._state(), time.time()
        if table is None:
            new = reduce(DataFrame.unionByName, [_whole(events, F.lit(i).alias("batch")) for i, (events, *_) in enumerate(due)])
        else:
            places = [n for *_, n in due]
            number = F.col("batch") if places == list(range(len(due))) else F.array_position(F.array(*map(F.lit, places)), F.col("batch").cast("int")) - 1
            new = _whole(table.filter(F.col("batch").isin(places)), number.cast("int").alias("batch"))
        if len(due) > 1:  # in the order that they are numbered in: up to the first batch with late events times rise, so the event before a batch's first one is the end
            order = W.partitionBy("trace_id").orderBy("batch", "ts_us", "activity")
            new = new.withColumn("end_ts", F.when(F.lag("batch").over(order) != F.col("batch"), F.lag("ts_us").over(order)))
        placed = with_positions(new, (), self._ends() if self._folders("trace_bounds") else None, ("batch",))
        batch = self._write_events(placed, [self._part(state, b, i) for i, (_, b, _) in enumerate(due)])
        fit = len(due) if batch["late"] is None else batch["late"]
        for part in batch["parts"][fit:]:
            delete(self.spark, f"{self.path}/trace_store/part={part}")
        kept = {k: batch[k][:fit] for k in ("parts", "figures", "segments")}
        return batch | kept | {"ids": [b for _, b, _ in due[:fit]], "began": began, "stored": self._folders("trace_store"), "expired": state["expired"]}

    def _write_events(self, placed: DataFrame, parts: list[str]) -> dict:
        """Writes parts of the trace store. Returns for each part first and last time and number of events, and for all the longest trace's last position, the
        first batch with late events and the trace buckets in which stored traces run on (where `placed` has the last stored time)."""
        stored = F.col("last_ts") if "last_ts" in placed.columns else F.lit(None).cast("long")
        end = F.greatest(stored, F.col("end_ts")) if "end_ts" in placed.columns else stored
        here = [F.col("batch") == i for i in range(len(parts))]
        seen, rows = Observation(), placed.withColumn("trace_bucket", trace_bucket(self.config))  # whole traces, as they were dealt to be numbered
        on = F.when(stored.isNotNull(), F.col("trace_bucket"))
        told = [F.max("pos").alias("longest"), F.min(F.when(F.col("ts_us") <= end, F.col("batch"))).alias("late"), F.min(on).alias("low"), F.max(on).alias("high")]
        for i, is_it in enumerate(here):
            told += [F.min(F.when(is_it, F.col("ts_us"))).alias(f"a{i}"), F.max(F.when(is_it, F.col("ts_us"))).alias(f"b{i}"), F.count_if(is_it).alias(f"events{i}")]
        segments = self._save_parts(rows.observe(seen, *told).select(*EVENT, "trace_bucket", "batch"), "trace_store", parts, *PLACES["trace_store"])
        return {k: seen.get[k] for k in ("longest", "late", "low", "high")} | {"parts": parts, "segments": segments, "figures": [tuple(seen.get[f"{k}{i}"] for k in ("a", "b", "events")) for i in range(len(parts))]}

    def _settle(self, batch: dict, strategy: str, most_parts: int, out: list[dict], places: list[int]) -> None:
        """Indexes batches that are placed and commits them one after the other; the time that a pass took is dealt to its batches in equal shares."""
        if not batch["ids"]:
            return
        n, made = self._make(batch, self._state() if strategy == "merge" else None)
        seconds = (time.time() - batch["began"]) / len(batch["ids"])
        for i, (batch_id, part) in enumerate(zip(batch["ids"], batch["parts"], strict=True)):
            state = self._state()
            parts = {t: dict(state["parts"][t]) for t in TABLES}
            for t in SEGMENTED if strategy == "merge" and self.config.layout != "pair_key" else ():  # older parts lose what was rewritten
                cut = {p: [s for s in segments if s not in made[t][i]] for p, segments in parts[t].items()}
                parts[t] = {p: segments for p, segments in cut.items() if segments}
            for t in TABLES:
                parts[t][part] = made[t][i]
            self._commit(state, strategy, batch_id, parts, (*batch["figures"][i], n[i], seconds), state["expired"])
            if strategy == "append" and len(parts["pair_stats"]) > most_parts:
                self.compact()
            out[places[i]] = {"batch": batch_id, "n_events": batch["figures"][i][2], "n_pairs": n[i], "seconds": seconds}

    @staticmethod
    def _part(state: dict, name: str, waiting: int = 0) -> str:
        return f"{state['version'] + 1 + waiting:08d}-{re.sub(r'[^A-Za-z0-9.-]', '-', name)[:80]}-{uuid.uuid4().hex[:8]}"

    def _events(self, folders: list[str]) -> DataFrame:
        """Rows of parts of the trace store, whether they are committed or not."""
        if not folders:
            return self.spark.createDataFrame([], SCHEMAS["trace_store"])
        return self.spark.read.schema(SCHEMAS["trace_store"]).option("basePath", f"{self.path}/trace_store").parquet(*folders)

    def _make(self, batch: dict, merge_into: dict | None = None) -> tuple[list[int], dict]:
        """Makes the pairs of placed batches and writes their parts of the other tables; returns the numbers of pairs and the parts' segments. What several
        tables are made from is read from files, the trace store's parts and a staged table of pairs: files are read in as few tasks as
        their size asks for, while rows kept in memory would stay in as many as the session shuffles to."""
        c, parts, long = self.config, batch["parts"], self._long(batch["longest"])
        which = F.array_position(F.array(*map(F.lit, parts)), F.col("part")) - 1 if len(parts) > 1 else F.lit(0)
        placed = self._events([f"{self.path}/trace_store/part={p}" for p, s in zip(parts, batch["segments"], strict=True) if s is None]).select(*EVENT, which.cast("int").alias("batch"))
        carry = () if c.policy == "unused_second" else ("batch",)
        if batch["low"] is not None:
            first = placed.groupBy("trace_id").agg(F.min("pos").alias("new_pos"), F.min("ts_us").alias("new_ts"))
            stored = self._events(batch["stored"]).filter(F.col("trace_bucket").between(batch["low"], batch["high"])).select(*EVENT).join(first, "trace_id")
            if c.lookback_us is not None:
                stored = stored.filter(F.col("ts_us") >= F.col("new_ts") - c.lookback_us)
            whole = stored.select(*EVENT, F.lit(-1).alias("batch")).unionByName(placed).repartition("trace_id")
            made = P.extract_pairs(whole, c.lookback_us, c.policy, first.select("trace_id", "new_pos"), long, carry)
        else:
            made = P.extract_pairs(placed.repartition("trace_id"), c.lookback_us, c.policy, long=long, carry=carry)
        if not carry:
            made = made.withColumn("batch", F.lit(0))
        staged, seen = f"{self.path}/staged/{parts[0]}", Observation()
        try:
            with ThreadPoolExecutor(1) as beside:  # these tables hold no pairs
                types = beside.submit(self._write_all, self._event_jobs(placed, batch["expired"], merge_into), parts)
                self._save(made.observe(seen, *[F.count_if(F.col("batch") == i).alias(f"n{i}") for i in range(len(parts))]), staged)
                done = self._write_all(self._pair_jobs(self.spark.read.schema(STAGED).parquet(staged), batch["expired"], merge_into), parts)
                return [seen.get[f"n{i}"] for i in range(len(parts))], done | types.result() | {"trace_store": batch["segments"]}
        finally:
            delete(self.spark, staged)

    def _long(self, longest: int | None) -> int | None:
        """Whether a batch has traces that are worth telling apart, by the last position of its longest one; pairs are the same either way."""
        if self.config.long_traces is not None:
            return self.config.long_traces
        return P.LONG if (longest or 0) > P.SHORT else None

    def _merged(self, rows: DataFrame, name: str, merge_into: dict | None) -> DataFrame:
        """With `merge_into`, the state whose rows of touched segments are written anew beside a batch's."""
        if merge_into is None or "segment" not in rows.columns:
            return rows
        touched = [r["segment"] for r in rows.select("segment").distinct().collect()]  # as many as the batch has segments
        return rows.unionByName(self._read(name).drop("part").filter(F.col("segment").isin(touched)).withColumn("batch", F.lit(0)))

    def _event_jobs(self, placed: DataFrame, expired: int | None, merge_into: dict | None) -> list[tuple]:
        types = placed.withColumn("segment", segment("ts_us", self.config)).withColumn("activity_bucket", first_bucket("activity", self.config))
        if expired is not None:
            types = types.filter(F.col("segment") >= expired)
        return [(self._merged(types, "type_index", merge_into), "type_index", ["segment", "activity_bucket"], ["activity", "trace_id", "pos"]), (P.bounds(placed, ("batch",)), "trace_bounds", [], [])]

    def _pair_jobs(self, made: DataFrame, expired: int | None, merge_into: dict | None) -> list[tuple]:
        c, dealt = self.config, ["batch", *PLACES["pair_frontier"][1][:1]]  # as its files are, so that they need no second shuffle
        stored = {"pos": ["pos_a", "pos_b"], "ts": ["ts_a", "ts_b"], "both": ["pos_a", "pos_b", "ts_a", "ts_b"]}[c.mode]
        rows = made.withColumn("segment", segment("ts_b", c)).withColumn("first_bucket", first_bucket("a_first", c))
        if expired is not None:
            rows = rows.filter(F.col("segment") >= expired)
        rows = rows.select("a_first", "a_second", "trace_id", *stored, "segment", "first_bucket", "batch")
        if c.layout == "pair_key":
            rows = rows.drop("segment", "first_bucket").withColumn("pair", F.concat_ws("|", F.base64(F.encode("a_first", "utf-8")), F.base64(F.encode("a_second", "utf-8"))))
        return [
            (self._merged(rows, "pair_index", merge_into), "pair_index", ["pair"] if c.layout == "pair_key" else ["segment", "first_bucket"], ["trace_id"] if c.layout == "pair_key" else ["a_first", "a_second", "trace_id"]),
            (P.frontier(made.withColumn("trace_bucket", trace_bucket(c)).repartition(*dealt), ("batch", "trace_bucket")), "pair_frontier", *PLACES["pair_frontier"]),
            (P.pair_stats(made, ("batch",)), "pair_stats", [], []),
        ]

    def _write_all(self, jobs: list[tuple], parts: list[str]) -> dict[str, list[list[int] | None]]:
        """Tables do not depend on each other: their jobs run side by side."""
        with ThreadPoolExecutor(len(jobs)) as pool:
            done = [(name, pool.submit(self._write, df, name, parts, by, sort)) for df, name, by, sort in jobs]
            return {name: segments.result() for name, segments in done}

    def _rebuild(self, new: DataFrame, batch_id: str) -> dict:
        """Everything anew from the stored traces and the batch; what has expired stays gone."""
        state, began = self._state(), time.time()
        part = self._part(state, batch_id)
        batch = self._write_events(with_positions(self.traces().select("trace_id", "ts_us", "activity").unionByName(new)).withColumn("batch", F.lit(0)), [part]) | {"expired": state["expired"]}
        [n], parts = self._make(batch)
        self._commit(state, "rebuild", batch_id, {t: {part: parts[t][0]} for t in TABLES}, (*batch["figures"][0], n, time.time() - began), state["expired"])
        return {"batch": batch_id, "rebuilt": True, "n_events": batch["figures"][0][2], "n_pairs": n, "seconds": time.time() - began}

    def compact(self, name: str = "compact") -> None:
        """M2: rewrites every table's live rows as one sorted part; readers change over with the commit. Nothing that has expired comes back, as
        each table is made from itself."""
        state, began = self._state(), time.time()
        part, keyed = self._part(state, name), self.config.layout == "pair_key"
        jobs = [
            (self._read("type_index").drop("part"), "type_index", ["segment", "activity_bucket"], ["activity", "trace_id", "pos"]),
            (self._read("trace_store").drop("part"), "trace_store", *PLACES["trace_store"]),
            (self._read("pair_index").drop("part"), "pair_index", ["pair"] if keyed else ["segment", "first_bucket"], ["trace_id"] if keyed else ["a_first", "a_second", "trace_id"]),
            (self.frontier().withColumn("trace_bucket", trace_bucket(self.config)), "pair_frontier", *PLACES["pair_frontier"]),
            (self.stats(), "pair_stats", [], []),
            (self.bounds(), "trace_bounds", [], []),
        ]
        parts = self._write_all(jobs, [part])
        f = self.bounds().agg(F.min("first_ts").alias("a"), F.max("last_ts").alias("b"), F.sum("n_events").alias("n")).collect()[0]
        n = self.stats().agg(F.sum("completions").alias("n")).collect()[0]["n"]
        self._commit(state, "compact", None, {t: {part: parts[t][0]} for t in TABLES}, (f["a"], f["b"], f["n"], n, time.time() - began), state["expired"])

    def _pairs_with_times(self) -> DataFrame:
        rows = self.pairs().drop("segment", "first_bucket", "pair")
        if "ts_a" in rows.columns and "pos_a" in rows.columns:
            return rows.select(*P.PAIR)
        at = self.traces()
        a, b = (at.select("trace_id", F.col("pos").alias(f"pos_{x}"), F.col("ts_us").alias(f"ts_{x}")) for x in "ab")
        return rows.join(a, ["trace_id", "pos_a"]).join(b, ["trace_id", "pos_b"]).select(*P.PAIR)

    def expire(self, before_us: int) -> int:
        """M3: pair and type segments that end before a time count no longer, for good; statistics and frontier are made anew from what is left. Files
        stay until `vacuum`, so running readers end in peace. Returns how many segments of parts went."""
        state, began = self._state(), time.time()
        if self.config.layout == "pair_key":
            raise ValueError("a folder a pair has no segments that could expire")
        last = max(self._segment(before_us), state["expired"] if state["expired"] is not None else -(1 << 62))
        parts = {t: dict(state["parts"][t]) for t in TABLES}
        n = 0
        for t in SEGMENTED:
            kept = {p: [s for s in segments if s >= last] for p, segments in parts[t].items()}
            n += sum(len(parts[t][p]) - len(k) for p, k in kept.items())
            parts[t] = {p: k for p, k in kept.items() if k}
        if not n:
            return 0
        part = self._part(state, "expire")
        left = self._pairs_with_times().filter(F.floor((F.col("ts_b") - self.config.origin_us) / (self.config.split_every_days * 86_400_000_000)) >= last).persist()
        try:
            self._write_all([(P.frontier(left).withColumn("trace_bucket", trace_bucket(self.config)), "pair_frontier", *PLACES["pair_frontier"]), (P.pair_stats(left), "pair_stats", [], [])], [part])
        finally:
            left.unpersist()
        parts |= {"pair_frontier": {part: None}, "pair_stats": {part: None}}
        self._commit(state, "expire", None, parts, (None, None, None, None, time.time() - began), last)
        return n

    def vacuum(self) -> int:
        """Deletes the folders that the newest manifest does not name; for a time when no older reader and no writer runs. Returns how many went."""
        state, n = self._state(), 0
        delete(self.spark, f"{self.path}/staged")  # left where a writer died
        for t in TABLES:
            for folder in children(self.spark, f"{self.path}/{t}"):
                part = folder.removeprefix("part=")
                if part not in state["parts"][t]:
                    delete(self.spark, f"{self.path}/{t}/{folder}")
                    n += 1
                    continue
                for inner in children(self.spark, f"{self.path}/{t}/{folder}") if state["parts"][t][part] is not None else ():
                    if inner.startswith("segment=") and int(inner[8:]) not in state["parts"][t][part]:
                        delete(self.spark, f"{self.path}/{t}/{folder}/{inner}")
                        n += 1
        return n

    def storage_report(self) -> DataFrame:
        """M4: files and bytes of each table's live parts."""
        rows = []
        for name in TABLES:
            sizes = [s for f in self._folders(name) for s in file_sizes(self.spark, f)]
            rows.append((name, len(sizes), sum(sizes)))
        return self.spark.createDataFrame(rows, "table string, files long, bytes long")

    def verify(self) -> DataFrame:
        """M9: check, bad; all counts are 0 in a sound index."""
        made, gone, pair = self._pairs_with_times(), self._state()["expired"], ["a_first", "a_second", "trace_id"]
        again = P.pair_stats(made)
        events = self.traces().filter(segment("ts_us", self.config) >= gone) if gone is not None else self.traces()
        # pairs and frontier meet in one shuffle: what the frontier should be, second events that are used twice and pairs out of order
        rows = made.select(*pair, "pos_b", "ts_b", F.lit(1).alias("n"), F.expr("pos_a >= pos_b or ts_a > ts_b").alias("turned"), F.lit(None).cast("long").alias("last_ts"))
        kept = self._read("pair_frontier").select(*pair, F.lit(None).cast("int").alias("pos_b"), F.lit(None).cast("long").alias("ts_b"), F.lit(0).alias("n"), F.lit(False).alias("turned"), "last_ts")
        rows = rows.unionByName(kept).repartition(*pair).groupBy(*pair, "pos_b").agg(F.sum("n").alias("n"), F.max("ts_b").alias("ts_b"), F.max("last_ts").alias("last_ts"), F.count_if("turned").alias("turned"))
        rows = rows.groupBy(*pair).agg(F.count_if(F.col("n") > 1).alias("second_events"), F.max("ts_b").alias("ts_b"), F.max("last_ts").alias("last_ts"), F.sum("turned").alias("turned"))
        rows = rows.agg(F.count_if(F.col("ts_b").isNotNull() & ~F.col("ts_b").eqNullSafe(F.col("last_ts"))).alias("frontier"), F.coalesce(F.sum("second_events"), F.lit(0)).alias("second_events"), F.coalesce(F.sum("turned"), F.lit(0)).alias("order"))
        parts = [rows, _differences(again, self.stats().select(*again.columns), "stats"), _differences(events, self.type_rows_all(), "types")]
        return reduce(DataFrame.unionByName, [r.select(F.inline(F.array(*[F.struct(F.lit(c).alias("check"), F.col(c).alias("bad")) for c in r.columns]))) for r in parts])


def _differences(a: DataFrame, b: DataFrame, name: str) -> DataFrame:
    """One row: how many rows `a` has that `b` has not (`name`), and the other way round (`name`_more). Both come from one comparison."""
    both = a.withColumn("_sign", F.lit(1)).unionByName(b.withColumn("_sign", F.lit(-1))).groupBy(*a.columns).agg(F.sum("_sign").alias("_d"))
    return both.agg(*[F.coalesce(F.sum(F.greatest(d, F.lit(0))), F.lit(0)).alias(c) for c, d in ((name, F.col("_d")), (f"{name}_more", -F.col("_d")))])


class Catalog:
    """Named log databases below a root folder (I16, M7)."""

    def __init__(self, spark: SparkSession, root: str):
        self.spark, self.root = spark, root.rstrip("/")

    def create(self, name: str, config: IndexConfig = IndexConfig()) -> IndexStore:
        at = f"{self.root}/{name}"
        if exists(self.spark, f"{at}/config.json"):
            raise ValueError(f"{name} exists")
        create_text(self.spark, f"{at}/config.json", config.to_json())
        return IndexStore(self.spark, at)

    def log(self, name: str) -> IndexStore:
        return IndexStore(self.spark, f"{self.root}/{name}")

    def list(self) -> list[str]:
        return sorted(children(self.spark, self.root))

    def drop(self, name: str) -> None:
        delete(self.spark, f"{self.root}/{name}")


@lru_cache(1)
def _path_class(jvm):
    """Hadoop's class of paths; each step of its name is a call to the JVM, so it is looked up once."""
    return jvm.org.apache.hadoop.fs.Path


def _fs(spark: SparkSession, path: str):
    at = _path_class(spark._jvm)(path)
    return at.getFileSystem(spark._jsc.hadoopConfiguration()), at


def exists(spark: SparkSession, path: str) -> bool:
    fs, at = _fs(spark, path)
    return fs.exists(at)


def shared_folder(spark: SparkSession) -> str:
    """A new folder below the cluster's shared checkpoint folder; only a local session may be without one."""
    at = spark.conf.get("spark.checkpoint.dir", None)
    if not at:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        at = "file:///tmp/tracedex-checkpoints"
    return f"{at.rstrip('/')}/logs-{uuid.uuid4().hex}"


def read_text(spark: SparkSession, path: str) -> str:
    """A small file, by Hadoop's file systems, so that any store works."""
    fs, at = _fs(spark, path)
    stream = fs.open(at)
    try:
        return bytes(spark._jvm.org.apache.commons.io.IOUtils.toByteArray(stream)).decode()
    finally:
        stream.close()


def create_text(spark: SparkSession, path: str, text: str) -> None:
    """Makes a small file that must not exist yet; of two writers one fails."""
    fs, at = _fs(spark, path)
    stream = fs.create(at, False)
    try:
        stream.write(bytearray(text.encode()))
    finally:
        stream.close()


def pair_key(first: str, second: str) -> str:
    """The folder of a pair where each pair has its own; names are encoded, as they may hold any sign."""
    return "|".join(base64.b64encode(x.encode()).decode() for x in (first, second))


def bucket_of(activity: str, buckets: int) -> int:
    """What `first_bucket` gives for a name: the same 64-bit hash, with Spark's seed."""
    h = xxhash.xxh64_intdigest(activity.encode(), seed=42)
    return (h - (1 << 64) if h >= 1 << 63 else h) % buckets


def children(spark: SparkSession, path: str) -> list[str]:
    fs, at = _fs(spark, path)
    return [s.getPath().getName() for s in fs.listStatus(at)] if fs.exists(at) else []


def delete(spark: SparkSession, path: str) -> None:
    fs, at = _fs(spark, path)
    fs.delete(at, True)


def move(spark: SparkSession, path: str, to: str) -> None:
    """Gives a folder another name in the same file system."""
    fs, at = _fs(spark, path)
    to_at = _path_class(spark._jvm)(to)
    fs.mkdirs(to_at.getParent())
    if not fs.rename(at, to_at):
        raise OSError(f"{path} could not be moved to {to}")


def file_sizes(spark: SparkSession, path: str) -> list[int]:
    fs, at = _fs(spark, path)
    if not fs.exists(at):
        return []
    out, it = [], fs.listFiles(at, True)
    while it.hasNext():
        f = it.next()
        if f.getPath().getName().endswith(".parquet"):
            out.append(f.getLen())
    return out
