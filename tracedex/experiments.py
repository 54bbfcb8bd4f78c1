"""Runs the experiment workloads (W1-W10) and gives each one's measures as rows.

    python -m tracedex.experiments --sf /root/testdata/sf0.1 --root file:///tmp/experiments W3 W7

Each function takes a `Setting` and returns rows of (experiment, system, case, measure, value), so results of different
scales and machines compare by a join. Loops here are over systems, days and queries, never over data."""

from __future__ import annotations

import argparse
from collections.abc import Callable, Iterator
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tracedex.model import DAY, HOUR, IndexConfig, P, PatternQuery, seq
from tracedex.operators import baselines, explore, measures, workloads
from tracedex.operators.pairs import LONG
from tracedex.plans.detect import detect
from tracedex.sources import logs
from tracedex.store import Catalog, IndexStore, LogIndex

Row = tuple[str, str, str, str, float]
SCHEMA = "experiment string, system string, case string, measure string, value double"


@dataclass
class Setting:
    """Where the tables are, where stores may be written, how many queries a case has, the time-out of one, and the daily batches."""

    spark: SparkSession
    sf_dir: str
    root: str
    queries: int = 100
    timeout_s: float = 600
    days: int = 10

    def store(self, name: str, config: IndexConfig) -> IndexStore:
        catalog = Catalog(self.spark, self.root)
        if name in catalog.list():
            catalog.drop(name)
        return catalog.create(name, config)

    def uniform(self) -> DataFrame:
        return logs.events_log(self.spark, self.sf_dir, "type_k30")

    def skewed(self) -> DataFrame:
        return logs.events_log(self.spark, self.sf_dir)


def _label(c: IndexConfig) -> str:
    return f"{c.layout}-{c.mode}"


def _grid(s: Setting) -> Iterator[tuple[str, DataFrame, IndexConfig]]:
    """Log and configuration; a folder a pair is for logs of few types only, as 150 types would make 22,500 folders."""
    for config in workloads.grid():
        yield "skewed", s.skewed(), config
        if config.layout == "segmented":
            yield "uniform", s.uniform(), config


def _days(s: Setting, log: DataFrame, config: IndexConfig, name: str, days: int = 10) -> IndexStore:
    """Ten daily batches, a tenth of the traces running on into the next day."""
    store, batches = s.store(name, config), workloads.carry_over(log, days)
    for day in range(days):
        store.append_batch(batches.filter(F.col("day") == day).select("trace_id", "ts_us", "activity"), f"day-{day + 1:02d}")
    return store


def _timed(s: Setting, name: str, system: str, case: str, run: Callable[[PatternQuery], DataFrame], qs: list[PatternQuery]) -> Iterator[Row]:
    out = measures.time_queries(run, qs, s.timeout_s)
    yield from ((name, system, case, m, float(out[m])) for m in ("mean", "median", "spread", "late") if out[m] is not None)


def daily_indexing(s: Setting) -> Iterator[Row]:
    """Seconds, events and pairs of each of ten daily batches, by layout and stored columns."""
    for case, log, config in _grid(s):
        store = _days(s, log, config, f"daily-{case}-{_label(config)}", s.days)
        for r in measures.index_time(store).collect():  # a row a day
            yield from (("W2", _label(config), f"{case} {r['batch_id']}", m, float(r[m])) for m in ("seconds", "n_events", "n_pairs"))


def index_sizes(s: Setting) -> Iterator[Row]:
    """Bytes after the last day, by layout, stored columns and codec."""
    codecs = [("uniform", s.uniform(), IndexConfig(mode="pos", lookback_us=3 * DAY, split_every_days=5, compression=c)) for c in ("lz4_raw", "zstd", "none")]
    for case, log, config in [*_grid(s), *codecs]:
        system = f"{_label(config)}-{config.compression}"
        store = _days(s, log, config, f"size-{case}-{system}", s.days)
        for r in store.storage_report().collect():  # a row a table
            yield "W3", system, f"{case} {r['table']}", "bytes", float(r["bytes"])


def build_order(s: Setting) -> Iterator[Row]:
    """Seconds that each system takes to index one batch, on a uniform and a skewed log."""
    systems = {
        "pairs": lambda log: LogIndex(log, IndexConfig(lookback_us=3 * DAY, long_traces=LONG)).pairs(),
        "signature": lambda log: baselines.SignatureIndex(log).signatures,
        "containment": lambda log: baselines.ContainmentIndex(log).lists,
        "search documents": baselines.search_documents,
    }
    for case, log in (("uniform", s.uniform()), ("skewed", logs.pages_log(s.spark, s.sf_dir)), ("short traces", logs.lineitem_log(s.spark, s.sf_dir)), ("long skewed", logs.documents_log(s.spark, s.sf_dir))):
        for system, seconds in measures.compare_build(log, systems):
            yield "W4", system, case, "seconds", seconds


def growing_log(s: Setting) -> Iterator[Row]:
    """Patterns of five on the log after one, five and ten days; the index against scans of the log, in seconds and in rows shuffled."""
    grown = [logs.with_positions(log.select("trace_id", "ts_us", "activity")) for log in workloads.growing(s.uniform())]
    for days, log in zip((1, 5, 10), grown, strict=True):
        store = s.store(f"growing-{days}", IndexConfig())
        store.append_batch(log.select("trace_id", "ts_us", "activity"), "all")
        qs = workloads.random_patterns(log, 5, s.queries) or workloads.random_patterns(grown[-1], 5, s.queries)  # a day may have no trace of five
        case = f"{days} days"
        yield from _timed(s, "W5", "index", case, lambda q, x=store: detect(x, q), qs)
        yield from _timed(s, "W5", "row_pattern_scan", case, lambda q, x=log: baselines.row_pattern_scan(x, q), qs)
        yield from _timed(s, "W5", "cep_scan", case, lambda q, x=log: baselines.cep_scan(x, q), qs)
        for system, df in (("index", detect(store, qs[0])), ("row_pattern_scan", baselines.row_pattern_scan(log, qs[0]))):
            yield from (("W5", system, case, m, float(v)) for m, v in measures.volume(df).items())


def stores_and_modes(s: Setting) -> Iterator[Row]:
    """Patterns of two and ten, by layout and stored columns."""
    for case, log, config in _grid(s):
        store = s.store(f"modes-{case}-{_label(config)}", config)
        store.append_batch(log.select("trace_id", "ts_us", "activity"), "all")
        for length in (2, 10):
            qs = workloads.random_patterns(log, length, s.queries)
            yield from _timed(s, "W6", _label(config), f"{case} length {length}", lambda q, x=store: detect(x, q), qs)


def _steps(q: PatternQuery) -> list[tuple[str, int, int]]:
    return [(e.types[0], 1, 100 if e.op == "plus" else 1) for e in q.elems if e.required]


def _systems(log: DataFrame, store: IndexStore) -> dict[str, Callable[[PatternQuery], DataFrame]]:
    signature, containment = baselines.SignatureIndex(log), baselines.ContainmentIndex(log)
    return {"index": lambda q: detect(store, q), "signature": signature.detect, "containment": containment.detect, "step_search": lambda q: baselines.step_search(log, _steps(q))}


def simple_queries(s: Setting) -> Iterator[Row]:
    """Plain patterns on logs of many traces, all systems; how time splits between pruning and validating."""
    for case, log, length in (("lines 2", logs.lineitem_log(s.spark, s.sf_dir), 2), ("orders 2", logs.orders_log(s.spark, s.sf_dir), 2), ("orders 10", logs.orders_log(s.spark, s.sf_dir), 10)):
        store = s.store(f"simple-{case.replace(' ', '-')}", IndexConfig())
        store.append_batch(log.select("trace_id", "ts_us", "activity"), "all")
        qs = workloads.random_patterns(log, length, s.queries)
        for system, run in _systems(log, store).items():
            yield from _timed(s, "W7", system, case, run, qs)
        for phase, seconds in measures.phases(store, qs[0]).items():
            yield "W7", "index", case, phase, seconds


def complex_queries(s: Setting) -> Iterator[Row]:
    """Negation, one-or-more and a first-last limit by chance; one large pattern; bounded runs."""
    log = s.uniform()
    store = s.store("complex", IndexConfig())
    store.append_batch(log.select("trace_id", "ts_us", "activity"), "all")
    types = [f"{t}:{k}" for t in ("view", "click") for k in range(3)]
    for length in (2, 10):
        qs = workloads.complexify(workloads.random_patterns(log, length, s.queries), types)
        for system, run in _systems(log, store).items():
            if system != "step_search":  # it knows neither negation nor all matches
                yield from _timed(s, "W8", system, f"length {length}", run, qs)
        yield from _timed(s, "W8", "cep_scan", f"length {length}", lambda q: baselines.cep_scan(log, q), qs)
    plain = s.skewed()
    yield from _timed(s, "W8b", "index", "ten elements", lambda q: detect(LogIndex(plain), q), [workloads.large_pattern()])
    runs = [seq(P("view").plus(), "purchase")]
    yield from _timed(s, "W8c", "step_search", "runs", lambda q: baselines.step_search(plain, _steps(q)), runs)
    yield from _timed(s, "W8c", "cep_scan", "runs", lambda q: baselines.cep_scan(plain, q), runs)


def explanations(s: Setting) -> Iterator[Row]:
    """Seconds to explain as the budget and then the uncertainty grows, for three and five elements; traces explained."""
    index = LogIndex(s.skewed())
    for length in (3, 5):
        for q in workloads.explain_grid(length):
            k, uncertainty, step = q.explain_with
            case = f"length {length}, k {k // HOUR} h, u {uncertainty // HOUR} h"
            yield from _timed(s, "W9", "index", case, lambda q: explore.explain(index, q), [q])
            yield "W9", "index", case, "copies", float(2 * (uncertainty // step) + 1)


def store_costs(s: Setting) -> Iterator[Row]:
    """Dollars a month for files, and for a store that bills requests, a row or a group of rows an item."""
    store = _days(s, s.uniform(), IndexConfig(mode="pos", lookback_us=3 * DAY, split_every_days=30), "costs", s.days)
    stored = float(store.storage_report().agg(F.sum("bytes")).collect()[0][0])
    rows = store.pairs().select("a_first", "a_second", "trace_id", "pos_a", "pos_b")
    yield "W10", "object", "files", "dollars", float(measures.cloud_cost(s.spark, "object", stored).collect()[0]["total"])
    for case, group in (("rows", None), ("grouped", ["a_first", "a_second"])):
        units = measures.request_units(rows, group).collect()[0]
        cost = measures.cloud_cost(s.spark, "request", stored, write_units=units["write_units"], read_units=units["read_units"]).collect()[0]
        yield "W10", "request", case, "write_units", float(units["write_units"])
        yield "W10", "request", case, "dollars", float(cost["total"])


EXPERIMENTS: dict[str, Callable[[Setting], Iterator[Row]]] = {
    "W2": daily_indexing, "W3": index_sizes, "W4": build_order, "W5": growing_log, "W6": stores_and_modes,
    "W7": simple_queries, "W8": complex_queries, "W9": explanations, "W10": store_costs,
}


def run(s: Setting, names: list[str] | None = None) -> DataFrame:
    """Measures of the named experiments, or of all."""
    return s.spark.createDataFrame([r for n in names or EXPERIMENTS for r in EXPERIMENTS[n](s)], SCHEMA)


def main() -> None:
    arguments = argparse.ArgumentParser(description=__doc__)
    arguments.add_argument("names", nargs="*", help=", ".join(EXPERIMENTS))
    arguments.add_argument("--sf", required=True)
    arguments.add_argument("--root", required=True, help="folder for stores, on a cluster one that executors share")
    arguments.add_argument("--queries", type=int, default=100)
    arguments.add_argument("--days", type=int, default=10, help="daily batches of W2, W3 and W10")
    given = arguments.parse_args()
    spark = SparkSession.builder.appName("experiments").getOrCreate()
    run(Setting(spark, given.sf, given.root, given.queries, days=given.days), given.names).show(10_000, truncate=False)


if __name__ == "__main__":
    main()
