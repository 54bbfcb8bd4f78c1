"""What the index is compared with (B0-B6): scans, a lossy step search, signature and containment indexes."""

from __future__ import annotations

from itertools import combinations, pairwise

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from tracedex.functions import masks
from tracedex.model import IndexConfig, PatternQuery
from tracedex.operators.validate import holds, validate, validate_linear, validate_nfa, validate_regex
from tracedex.plans.detect import fetch


def bruteforce(events: list[tuple], q: PatternQuery) -> list[tuple] | None:
    """The least position vector of a plain pattern by trying all; for tiny logs."""
    for chosen in combinations(events, len(q.elems)):
        if all(e[2] in x.types for e, x in zip(chosen, q.elems, strict=True)) and all(holds(c, chosen[c.i - 1], chosen[c.j - 1]) for c in q.constraints):
            return list(chosen)
    return None


def _scanned(log: DataFrame, q: PatternQuery) -> DataFrame:
    rows = log.filter(F.col("ts_us").between(*q.window)) if q.window else log
    return rows.withColumn("unit_id", F.col("trace_id"))


def cep_scan(log: DataFrame, q: PatternQuery) -> DataFrame:
    """B1: the automaton over the whole log at every query."""
    return validate_nfa(_scanned(log, q), q)


def row_pattern_scan(log: DataFrame, q: PatternQuery) -> DataFrame:
    """B2: set-oriented matching over a full scan sorted by trace."""
    return validate(_scanned(log, q), q) if q.constraints else validate_regex(_scanned(log, q), q)


def row_pattern_windows(log: DataFrame, q: PatternQuery) -> DataFrame:
    """B2, plain patterns by a chain of windows: unit_id, p1..pn of the first occurrence."""
    if not q.plain or q.constraints:
        raise ValueError("the window chain takes plain patterns without constraints")
    later = W.partitionBy("trace_id").orderBy("pos").rowsBetween(1, W.unboundedFollowing)
    rows = _scanned(log, q).select("unit_id", "trace_id", "pos", "activity")
    types = [e.types[0] for e in q.elems]
    nxt = None
    for n in range(len(types), 0, -1):  # from the last element: where the rest of the pattern would end up
        own = F.array(F.col("pos")) if nxt is None else F.concat(F.array(F.col("pos")), F.first(nxt, ignorenulls=True).over(later))
        rows = rows.withColumn(f"c{n}", F.when(F.col("activity") == types[n - 1], own))
        nxt = f"c{n}"
    first = rows.filter(F.size("c1") == len(types)).groupBy("unit_id").agg(F.min("c1").alias("c"))
    return first.select("unit_id", *[F.col("c")[i].alias(f"p{i + 1}") for i in range(len(types))])


def search_documents(log: DataFrame) -> DataFrame:
    """B3's index: one document a trace, its events in order."""
    return log.groupBy("trace_id").agg(F.array_sort(F.collect_list(F.struct("pos", "ts_us", "activity"))).alias("events"))


def step_search(log: DataFrame, steps: list[tuple[str, int, int]], maxspan_us: int | None = None, until: str | None = None) -> DataFrame:
    """A state machine a trace that keeps one partial a stage, newer replacing older, so it does not find all matches.

    steps: (activity, fewest, most) runs of 1 to 100; `until` ends the search of the trace where it occurs. A run takes events up to `most`
    until the next stage starts, which takes the longest run at hand that the span allows (a stage of the same activity starts at `most` only). The last run ends at `most`, at the first
    event of its activity out of the span, where the first stage starts anew, or with the search."""
    if any(not 1 <= lo <= hi <= 100 for _, lo, hi in steps):
        raise ValueError("runs are from 1 to 100")
    last = len(steps) - 1

    def one(trace: pd.DataFrame) -> pd.DataFrame:
        trace = trace.sort_values("pos")
        live: dict[tuple[int, int], list] = {}  # (stage, events of its run) -> first and last event
        out, tid = [], int(trace["trace_id"].iloc[0])

        def longest(stage: int, ts: int | None = None) -> tuple[int, int] | None:
            """The longest run of a stage that may be followed, at `ts` within the span."""
            for n in range(steps[stage][2], steps[stage][1] - 1, -1):
                if (stage, n) in live and (ts is None or fits(live[stage, n], ts)):
                    return stage, n
            return None

        def fits(partial: list, ts: int) -> bool:
            return maxspan_us is None or ts - partial[0][1] <= maxspan_us

        def emit(found: tuple[int, int]) -> None:
            out.append((tid, len(out) + 1, live[found][0][0], live[found][1][0]))
            live.clear()

        for pos, ts, a in zip(trace["pos"], trace["ts_us"], trace["activity"], strict=True):
            if until is not None and a == until:
                break
            whole = longest(last)
            if whole and (a == steps[last][0] and not fits(live[whole], ts) or a == steps[0][0] != steps[last][0]):
                emit(whole)
            for stage in range(last, -1, -1):
                name, _, most = steps[stage]
                if name != a:
                    continue
                for n in range(most - 1, 0, -1):
                    if (stage, n) in live and fits(live[stage, n], ts):
                        live[stage, n + 1] = [live.pop((stage, n))[0], (pos, ts)]
                if stage == 0:
                    live[0, 1] = [(pos, ts), (pos, ts)]
                elif (prior := longest(stage - 1, ts)) and (steps[stage - 1][0] != a or prior[1] == steps[stage - 1][2]):
                    live[stage, 1] = [live.pop(prior)[0], (pos, ts)]
                if stage == last and (last, most) in live:
                    emit((last, most))
                    break
        if whole := longest(last):
            emit(whole)
        return pd.DataFrame(out, columns=["trace_id", "occ_no", "first_pos", "last_pos"])

    return log.select("trace_id", "pos", "ts_us", "activity").groupBy("trace_id").applyInPandas(one, "trace_id long, occ_no int, first_pos int, last_pos int")


def preliminary_config(**options) -> IndexConfig:
    """The earlier engine's store: a folder a pair, times and positions, no segments."""
    return IndexConfig(layout="pair_key", mode="both", **options)


def preliminary_detect(store, q: PatternQuery) -> DataFrame:
    """The earlier engine: plain patterns only; traces that have every pair of the pattern, read whole, and the linear parser over them."""
    if not q.plain or q.constraints or q.window or q.group_text:
        raise ValueError("the earlier engine knows plain patterns only")
    return validate_linear(fetch(store, q, "required", "traces"), q)


class SignatureIndex:
    """A hashed bitmap of each trace's types and direct follows; a trace stays if its bitmap covers the query's."""

    def __init__(self, log: DataFrame, words: int = 4):
        self.log, self.words = log, words
        follow = W.partitionBy("trace_id").orderBy("pos")
        items = log.select("trace_id", F.col("activity").alias("item"))
        pairs = log.withColumn("next", F.lead("activity").over(follow)).filter("next is not null").select("trace_id", F.concat(F.col("activity"), F.lit("\x00"), F.col("next")).alias("item"))
        bits = items.union(pairs).select("trace_id", F.pmod(F.xxhash64("item"), F.lit(64 * words)).cast("int").alias("bit"))
        self.signatures = bits.groupBy("trace_id").agg(*[F.bit_or(F.when(F.expr(f"bit div 64 = {w}"), F.expr("shiftleft(1L, bit % 64)")).otherwise(F.lit(0).cast("long"))).alias(f"s{w}") for w in range(words)])

    def prune(self, q: PatternQuery) -> DataFrame:
        needs = [e.types for e in q.elems if e.required]
        strict = [f"{a[0]}\x00{b[0]}" for a, b in pairwise(needs)] if q.policy == "strict" else []
        test = F.lit(True)
        for types in [*needs, *[(s,) for s in strict]]:
            one = F.lit(False)
            for t in types:
                bit = F.pmod(F.xxhash64(F.lit(t)), F.lit(64 * self.words))
                word = F.element_at(F.array(*[F.col(f"s{w}") for w in range(self.words)]), F.floor(bit / 64).cast("int") + 1)
                one = one | (F.getbit(word, (bit % 64).cast("int")) == 1)
            test = test & one
        return self.signatures.filter(test).select("trace_id")

    def detect(self, q: PatternQuery) -> DataFrame:
        return validate(_scanned(self.log, q).join(self.prune(q), "trace_id", "left_semi"), q)


class ContainmentIndex:
    """Type -> traces; the lists of all query types are intersected, the survivors' whole traces validated."""

    def __init__(self, log: DataFrame):
        self.log, self.lists = log, log.select("activity", "trace_id").distinct()

    def prune(self, q: PatternQuery) -> DataFrame:
        needs = [e.types for e in q.elems if e.required]
        rows = self.lists.filter(F.col("activity").isin([t for n in needs for t in n]))
        found = rows.groupBy("trace_id").agg(*masks.met([F.col("activity").isin(list(t)) for t in needs]))
        return found.filter(masks.holds_all(set(range(len(needs))), len(needs))).select("trace_id")

    def bitmaps(self) -> DataFrame:
        """Compressed form: a bitmap of trace numbers for each type and bucket of numbers."""
        return self.lists.groupBy("activity", F.bitmap_bucket_number("trace_id").alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("trace_id")).alias("traces")).withColumn("n", F.bitmap_count("traces"))

    def detect(self, q: PatternQuery) -> DataFrame:
        return validate(_scanned(self.log, q).join(self.prune(q), "trace_id", "left_semi"), q)
