"""The engine's registered queries and the SQL that checks them, which shares no code with the engine."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tracedex.model import DAY, HOUR, IndexConfig, P, PatternQuery, seq
from tracedex import streaming
from tracedex.operators import baselines, explore, measures, pairs, workloads
from tracedex.operators.positions import latest_before, segment, sessionize, trace_bucket
from tracedex.plans.detect import count_matches, detect, fetch, matching_traces, register_answer, survivors
from tracedex.plans.parser import parse_query
from tracedex.sources import logs
from tracedex.store import Catalog, IndexStore, LogIndex, shared_folder

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}

V, C, E, B, S = P("view"), P("click"), P("error"), P("purchase"), P("signup")
TEN = "view click error view click purchase signup view click purchase".split()
JAN10, JAN12 = workloads.EPOCH + 9 * DAY, workloads.EPOCH + 12 * DAY - 1

# --- logs in SQL: trace_id, pos, ts_us, activity
LOGS = {
    "events": "SELECT user_id AS trace_id, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS pos, epoch_us(ts) AS ts_us, event_type AS activity FROM events",
    "type_k30": "SELECT user_id AS trace_id, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS pos, epoch_us(ts) AS ts_us, event_type || ':' || (CAST(json_extract(props, '$.k') AS INT) % 30) AS activity FROM events",
    "orders": "SELECT o_custkey AS trace_id, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS pos, epoch_us(o_orderdate) AS ts_us, o_orderstatus || '/' || o_orderpriority AS activity FROM orders",
    "lineitem": "SELECT l_orderkey AS trace_id, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_shipdate, l_linenumber, l_partkey, l_suppkey, p_brand) AS pos, epoch_us(l_shipdate) AS ts_us, p_brand AS activity FROM lineitem JOIN part ON l_partkey = p_partkey",
    "pages": "SELECT page_id AS trace_id, i AS pos, i AS ts_us, tags[i] AS activity FROM (SELECT page_id, tags, unnest(range(1, len(tags) + 1)) AS i FROM (SELECT page_id, regexp_extract_all(html, '<([a-z][a-z0-9]*)', 1) AS tags FROM pages))",
    "documents": "SELECT doc_id AS trace_id, row_number() OVER (PARTITION BY doc_id ORDER BY i) AS pos, i AS ts_us, activity FROM (SELECT doc_id, i, w[i] AS activity FROM (SELECT doc_id, w, unnest(range(1, len(w) + 1)) AS i FROM (SELECT doc_id, regexp_extract_all(lower(text), '[a-z]+') AS w FROM documents))) WHERE activity IN (SELECT x FROM (SELECT unnest(regexp_extract_all(lower(text), '[a-z]+')) AS x FROM documents) GROUP BY x ORDER BY count(*) DESC, x LIMIT 41)",
    "conv": "SELECT conv_id AS trace_id, row_number() OVER (PARTITION BY conv_id ORDER BY turn, role) AS pos, turn AS ts_us, role AS activity FROM conversations",
}
SOURCES: dict[str, Query] = {
    "events": logs.events_log,
    "type_k30": lambda s, d: logs.events_log(s, d, "type_k30"),
    "orders": logs.orders_log,
    "lineitem": logs.lineitem_log,
    "pages": logs.pages_log,
    "documents": logs.documents_log,
    "conv": logs.conversations_log,
}


def _log(name: str) -> str:
    return f"WITH log AS ({LOGS[name]})"


def _pairs(name: str, lookback: int | None = None) -> str:
    """Closed form: every event with the interval since the previous event of its type."""
    near = f" AND b.ts_us - a.ts_us <= {lookback}" if lookback else ""
    return f"""{_log(name)}, s AS (SELECT *, coalesce(lag(pos) OVER (PARTITION BY trace_id, activity ORDER BY pos), 0) AS p FROM log),
prs AS (SELECT a.activity AS a_first, b.activity AS a_second, b.trace_id, CAST(min(a.pos) AS BIGINT) AS pos_a, CAST(b.pos AS BIGINT) AS pos_b, min(a.ts_us) AS ts_a, b.ts_us AS ts_b
        FROM s b JOIN log a ON a.trace_id = b.trace_id AND a.pos >= b.p AND a.pos < b.pos{near} GROUP BY b.trace_id, a.activity, b.activity, b.pos, b.ts_us)"""


def _add(name: str, query: Query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql:
        ORACLES[name] = sql


def _index(s: SparkSession, d: str, log: str = "events", lookback: int | None = None) -> LogIndex:
    return LogIndex(SOURCES[log](s, d), IndexConfig(lookback_us=lookback, long_traces=pairs.LONG if log == "documents" else None))


def _long(df: DataFrame) -> DataFrame:
    """Integers as one type, so that results compare with SQL."""
    return df.select(*[F.col(c).cast("long").alias(c) if t in ("int", "smallint", "tinyint") else F.col(c) for c, t in df.dtypes])


# --- logs and index tables
for _n in LOGS:
    _add(
        f"log_describe_{_n}",
        lambda s, d, n=_n: _long(measures.describe(SOURCES[n](s, d)).withColumns({c: F.round(c, 4) for c in ("mean_length", "top_share", "slope")})),
        f"{_log(_n)}, k AS (SELECT n, row_number() OVER (ORDER BY n DESC, activity) AS r FROM (SELECT activity, count(*) AS n FROM log GROUP BY activity)) SELECT (SELECT CAST(count(*) AS BIGINT) FROM log) AS events, CAST(count(*) AS BIGINT) AS traces, round(avg(n), 4) AS mean_length, (SELECT count(DISTINCT activity) FROM log) AS types, CAST(min(n) AS BIGINT) AS min_length, CAST(max(n) AS BIGINT) AS max_length, (SELECT round(max(n) / sum(n), 4) FROM k) AS top_share, (SELECT round(regr_slope(ln(n), ln(r)), 4) FROM k) AS slope FROM (SELECT trace_id, count(*) AS n FROM log GROUP BY trace_id)",
    )
    _add(
        f"pairs_{_n}",
        lambda s, d, n=_n: _long(_index(s, d, n).pairs().select("a_first", "a_second", "trace_id", "pos_a", "pos_b")),
        f"{_pairs(_n)} SELECT a_first, a_second, trace_id, pos_a, pos_b FROM prs",
    )
_add("positions_events", lambda s, d: _long(logs.events_log(s, d)), f"{_log('events')} SELECT trace_id, CAST(pos AS BIGINT) AS pos, ts_us, activity FROM log")
_add("type_index_events", lambda s, d: _long(pairs.dictionary(logs.events_log(s, d))), f"{_log('events')} SELECT activity, count(*) AS n_events, count(DISTINCT trace_id) AS n_traces FROM log GROUP BY activity")
_add("trace_bounds_events", lambda s, d: _long(pairs.bounds(logs.events_log(s, d))), f"{_log('events')} SELECT trace_id, count(*) AS n_events, min(ts_us) AS first_ts, max(ts_us) AS last_ts, CAST(max(pos) AS BIGINT) AS last_pos FROM log GROUP BY trace_id")
_add("pairs_lookback_3d", lambda s, d: _long(_index(s, d, lookback=3 * DAY).pairs().select("a_first", "a_second", "trace_id", "pos_a", "pos_b")), f"{_pairs('events', 3 * DAY)} SELECT a_first, a_second, trace_id, pos_a, pos_b FROM prs")
#: The i-th first event takes the second event number i + max over m <= i of (seconds up to the m-th first event - m) + 1, if there is one.
_add("pairs_unused_second", lambda s, d: _long(pairs.extract_pairs(logs.events_log(s, d), policy="unused_second").groupBy("a_first", "a_second").agg(F.count("*").alias("n"), F.sum("pos_b").alias("sum_pos"))), f"""{_log('events')},
o AS (SELECT *, row_number() OVER (PARTITION BY trace_id, activity ORDER BY pos) AS i FROM log), y AS (SELECT DISTINCT trace_id, activity AS a_second FROM log),
f AS (SELECT o.trace_id, o.activity AS a_first, a_second, o.i, (SELECT count(*) FROM log b WHERE b.trace_id = o.trace_id AND b.activity = a_second AND b.pos <= o.pos) AS f FROM o JOIN y USING (trace_id)),
j AS (SELECT *, i + max(f - i) OVER (PARTITION BY trace_id, a_first, a_second ORDER BY i) + 1 AS j FROM f)
SELECT a_first, a_second, count(*) AS n, CAST(sum(o.pos) AS BIGINT) AS sum_pos FROM j JOIN o ON o.trace_id = j.trace_id AND o.activity = a_second AND o.i = j.j GROUP BY a_first, a_second""")
_add("pair_stats_type", lambda s, d: _long(_index(s, d).stats()), f"{_pairs('events')} SELECT a_first, a_second, count(*) AS completions, CAST(sum(ts_b - ts_a) AS BIGINT) AS sum_dur, min(ts_b - ts_a) AS min_dur, max(ts_b - ts_a) AS max_dur, min(pos_b - pos_a) AS min_gap, max(pos_b - pos_a) AS max_gap FROM prs GROUP BY a_first, a_second")
_add("frontier_type", lambda s, d: _long(pairs.frontier(_index(s, d).pairs())), f"{_pairs('events')} SELECT a_first, a_second, trace_id, max(ts_b) AS last_ts, max(pos_b) AS last_pos FROM prs GROUP BY a_first, a_second, trace_id")
_add("segments_5d", lambda s, d: _long(_index(s, d).pairs().withColumn("segment", segment("ts_b", IndexConfig(split_every_days=5))).groupBy("segment").agg(F.count("*").alias("n"))), f"{_pairs('events')} SELECT CAST(floor(ts_b / {5 * DAY}) AS BIGINT) AS segment, count(*) AS n FROM prs GROUP BY 1")
_add("rollup_stats", lambda s, d: _long(pairs.stats_rollup(_index(s, d).pairs()).select(F.coalesce("a_first", F.lit("*")).alias("a_first"), F.coalesce("a_second", F.lit("*")).alias("a_second"), "completions")), f"{_pairs('events')} SELECT coalesce(a_first, '*') AS a_first, coalesce(a_second, '*') AS a_second, count(*) AS completions FROM prs GROUP BY ROLLUP (a_first, a_second)")
_add("topk_pairs", lambda s, d: _long(_index(s, d).stats().orderBy(F.desc("completions"), "a_first", "a_second").limit(10).select("a_first", "a_second", "completions")), f"{_pairs('events')} SELECT a_first, a_second, count(*) AS completions FROM prs GROUP BY a_first, a_second ORDER BY completions DESC, a_first, a_second LIMIT 10")


def _incremental(s: SparkSession, d: str) -> DataFrame:
    """Pairs of ten daily cuts, each made from the new events and what is stored, against one build."""
    log = workloads.carry_over(logs.events_log(s, d))
    whole = logs.with_positions(log.select("trace_id", "ts_us", "activity", "day")).select("trace_id", "pos", "ts_us", "activity", "day")
    parts = None
    for day in range(10):
        first = whole.filter(F.col("day") == day).groupBy("trace_id").agg(F.min("pos").alias("new_pos"))
        touched = whole.filter(F.col("day") <= day).join(first.select("trace_id"), "trace_id", "left_semi")
        made = pairs.extract_pairs(touched, new_from=first)
        parts = made if parts is None else parts.unionByName(made)
    once = pairs.extract_pairs(whole)
    return parts.exceptAll(once).agg(F.count("*").alias("extra")).crossJoin(once.exceptAll(parts).agg(F.count("*").alias("missing")))


_add("incremental_equals_batch", _incremental, "SELECT CAST(0 AS BIGINT) AS extra, CAST(0 AS BIGINT) AS missing")


# --- detection
def _letters(types: list[str]) -> dict[str, str]:
    return {t: "abcdefghijklmnopqrstuvwxyz"[i] for i, t in enumerate(sorted(set(types)))}


def _regex_sql(pattern: str, types: list[str], log: str = "events", first: bool = False) -> str:
    """Occurrences of each trace: letters for the types that matter, RE2 for the pattern."""
    cases = " ".join(f"WHEN '{t}' THEN '{c}'" for t, c in _letters(types).items())
    names = ", ".join(f"'{t}'" for t in _letters(types))
    return f"{_log(log)}, t AS (SELECT trace_id, string_agg(CASE activity {cases} END, '' ORDER BY pos) AS s FROM log WHERE activity IN ({names}) GROUP BY trace_id) SELECT trace_id AS unit_id, CAST({'1' if first else 'n'} AS BIGINT) AS occurrences FROM (SELECT trace_id, len(regexp_extract_all(s, '{pattern}')) AS n FROM t) WHERE n > 0"


def _chain(required: list[str], negated: dict[int, list[str]] | None = None, types: list[str] | None = None) -> str:
    names = _letters(types or required)
    group = lambda e: "".join(names[x] for x in e.split("|"))
    out = f"[{group(required[0])}]"
    for k, e in enumerate(required[1:], 1):
        out += f"[^{group(e)}{''.join(names[x] for x in (negated or {}).get(k, []))}]*[{group(e)}]"
    return out


def _counted(q: PatternQuery, log: str = "events", **options) -> Query:
    return lambda s, d: _long(count_matches(_index(s, d, log), q, **options))


_K30 = ["view:1", "click:2"]
_add("detect_simple_2", _counted(seq("view", "click")), _regex_sql(_chain(["view", "click"]), ["view", "click"]))
_add("detect_simple_3", _counted(seq("view", "click", "purchase")), _regex_sql(_chain(["view", "click", "purchase"]), ["view", "click", "purchase"]))
_add("detect_simple_5", _counted(seq("view", "click", "error", "signup", "purchase")), _regex_sql(_chain(["view", "click", "error", "signup", "purchase"]), ["view", "click", "error", "signup", "purchase"]))
_add("detect_simple_10", _counted(seq(*TEN)), _regex_sql(_chain(TEN), TEN))
_add("detect_type_k30_2", _counted(seq(*_K30), "type_k30"), _regex_sql(_chain(_K30), _K30, "type_k30"))
_add("detect_brands_2", _counted(seq("Brand#11", "Brand#22"), "lineitem"), _regex_sql(_chain(["Brand#11", "Brand#22"]), ["Brand#11", "Brand#22"], "lineitem"))
_add("detect_repeated", _counted(seq("view", "click", "view", "click")), _regex_sql(_chain(["view", "click", "view", "click"]), ["view", "click"]))
_add("detect_plus", _counted(seq(S, V.plus(), B)), _regex_sql(_chain(["signup", "view", "purchase"]), ["signup", "view", "purchase"]))
_add("detect_star", _counted(seq(S, E.star(), B)), _regex_sql(_chain(["signup", "purchase"]), ["signup", "purchase"]))
_add("detect_neg", _counted(seq(V, E.neg(), B)), _regex_sql(_chain(["view", "purchase"], {1: ["error"]}, ["view", "error", "purchase"]), ["view", "error", "purchase"]))
_add("detect_or", _counted(seq(V, C.or_("signup"), B)), _regex_sql(_chain(["view", "click|signup", "purchase"], types=["view", "click", "signup", "purchase"]), ["view", "click", "signup", "purchase"]))
_add("detect_single_element", _counted(seq("purchase")), f"{_log('events')} SELECT trace_id AS unit_id, count(*) AS occurrences FROM log WHERE activity = 'purchase' GROUP BY trace_id")
_MIX = ["view", "click", "purchase", "view|click", "view", "click", "purchase|signup"]
_add("detect_mix10", _counted(workloads.large_pattern()), _regex_sql(_chain(_MIX, {2: ["error"]}, ["view", "click", "error", "purchase", "signup"]), ["view", "click", "error", "purchase", "signup"]))


def _plain_join(types: list[str], where: str, window: str = "true") -> str:
    n = range(1, len(types) + 1)
    tables = ", ".join(f"(SELECT * FROM log WHERE activity = '{t}' AND {window}) e{i}" for i, t in zip(n, types, strict=True))
    order = " AND ".join(f"e{i}.trace_id = e1.trace_id AND e{i}.pos > e{i - 1}.pos" for i in n if i > 1)
    cols = ", ".join(f"CAST(e{i}.pos AS BIGINT) AS p{i}" for i in n)
    names = ", ".join(f"p{i}" for i in n)
    return f"SELECT unit_id, {names} FROM (SELECT *, row_number() OVER (PARTITION BY unit_id ORDER BY {names}) AS k FROM (SELECT e1.trace_id AS unit_id, {cols} FROM {tables} WHERE {order} AND {where})) WHERE k = 1"


def _first(q: PatternQuery, **options) -> Query:
    """The first occurrence's positions, a column an element."""

    def run(s: SparkSession, d: str) -> DataFrame:
        bound = detect(_index(s, d), q, **options)
        return bound.groupBy("unit_id").agg(*[F.max(F.when(F.col("elem") == n, F.col("pos"))).cast("long").alias(f"p{n}") for n in range(1, len(q.elems) + 1)])

    return run


_VCB, _Q3 = ["view", "click", "purchase"], seq("view", "click", "purchase")
for _name, _q, _where in (
    ("detect_within_time", _Q3.within_time(1, 3, 24 * HOUR), f"e3.ts_us - e1.ts_us <= {24 * HOUR}"),
    ("detect_atleast_time", _Q3.atleast_time(1, 2, 28 * DAY), f"e2.ts_us - e1.ts_us >= {28 * DAY}"),
    ("detect_within_gap", _Q3.within_gap(1, 3, 2), "e3.pos - e1.pos <= 2"),
    ("detect_atleast_gap", _Q3.atleast_gap(2, 3, 60), "e3.pos - e2.pos >= 60"),
    ("detect_two_constraints", _Q3.within_time(1, 2, 12 * HOUR).atleast_gap(2, 3, 5), f"e2.ts_us - e1.ts_us <= {12 * HOUR} AND e3.pos - e2.pos >= 5"),
):
    _add(_name, _first(_q), f"{_log('events')} {_plain_join(_VCB, _where)}")
_add("detect_constraints_automaton", _first(_Q3.within_time(1, 3, 24 * HOUR), how="nfa"), ORACLES["detect_within_time"])
_add("detect_between", _first(_Q3.between(JAN10, JAN12)), f"{_log('events')} {_plain_join(_VCB, 'true', f'ts_us BETWEEN {JAN10} AND {JAN12}')}")
_add("detect_strict", _counted(PatternQuery((V, C), policy="strict")), _regex_sql("vc".replace("v", _letters(["click", "error", "purchase", "signup", "view"])["view"]).replace("c", _letters(["click"])["click"], 1), ["click", "error", "purchase", "signup", "view"]))


def _all_matches(s: SparkSession, d: str) -> DataFrame:
    bound = detect(_index(s, d), _Q3.all_matches())
    return bound.groupBy("unit_id").agg(F.max("occ_no").cast("long").alias("occurrences"))


_add("detect_all_matches", _all_matches, ORACLES["detect_simple_3"])
_GROUPED = f"WITH log0 AS ({LOGS['events']}), log AS (SELECT g AS trace_id, row_number() OVER (PARTITION BY g ORDER BY ts_us, trace_id, pos) AS pos, ts_us, activity FROM (SELECT *, CAST(CASE WHEN trace_id IN (1, 2, 3, 8) THEN 1 WHEN trace_id IN (5, 6, 7) THEN 2 END AS BIGINT) AS g FROM log0 WHERE activity IN ('view', 'click', 'purchase')) WHERE g IS NOT NULL)"
_add("detect_groups", lambda s, d: _long(count_matches(_index(s, d), _Q3.groups("{1..3,8} {5..7}"))), ORACLES["detect_simple_3"].replace(_log("events"), _GROUPED))

# --- pruning
_HAS = "SELECT trace_id FROM prs WHERE (a_first, a_second) IN (('view', 'click'), ('click', 'purchase')) GROUP BY trace_id HAVING count(DISTINCT a_first) = 2"
_KP = seq("view:1", "click:2", "purchase:3")
_OT = ["F/1-URGENT", "O/2-HIGH", "F/1-URGENT"]
_OP = seq(*_OT)
_E10 = [[f"{t}:{k}" for k in range(10)] for t in ("view", "click", "purchase")]
_TAGS = ["div", "p"] * 4


def _sql_view(s: SparkSession, d: str) -> DataFrame:
    """Q12 from SQL: a query's answer under a name."""
    register_answer(s, _index(s, d), "find view -> click|signup -> purchase all", "or_answers")
    return _long(s.sql("SELECT unit_id, max(occ_no) AS occurrences FROM or_answers GROUP BY unit_id"))


_KHAS = "SELECT trace_id FROM prs WHERE (a_first, a_second) IN (('view:1', 'click:2'), ('click:2', 'purchase:3')) GROUP BY trace_id HAVING count(DISTINCT a_first) = 2"
_add("prune_required", lambda s, d: survivors(_index(s, d), _Q3, "required"), f"{_pairs('events')} {_HAS}")
for _how in ("required", "any_alternative", "semijoin"):
    _add(f"prune_k30_{_how}", lambda s, d, h=_how: survivors(_index(s, d, "type_k30"), _KP, h), f"{_pairs('type_k30')} {_KHAS}")
_add("prune_or", lambda s, d: survivors(_index(s, d, "type_k30"), seq(P("view:1").or_("view:2"), "click:2")), f"{_pairs('type_k30')} SELECT DISTINCT trace_id FROM prs WHERE a_first IN ('view:1', 'view:2') AND a_second = 'click:2'")
_add("prune_containment", lambda s, d: baselines.ContainmentIndex(SOURCES["type_k30"](s, d)).prune(_KP), f"{_log('type_k30')} SELECT trace_id FROM log WHERE activity IN ('view:1', 'click:2', 'purchase:3') GROUP BY trace_id HAVING count(DISTINCT activity) = 3")
_add("prune_signature", lambda s, d: baselines.SignatureIndex(SOURCES["type_k30"](s, d)).prune(_KP))
_add("prune_quality", lambda s, d: _long(measures.pruning(_index(s, d, "orders"), _OP)), f"""WITH s AS ({_pairs('orders')} SELECT trace_id FROM prs WHERE (a_first, a_second) IN (('F/1-URGENT', 'O/2-HIGH'), ('O/2-HIGH', 'F/1-URGENT')) GROUP BY trace_id HAVING count(DISTINCT a_first) = 2), a AS ({_regex_sql(_chain(_OT), _OT, 'orders', True)})
SELECT (SELECT count(*) FROM s) AS survivors, (SELECT count(*) FROM a) AS answers, round((SELECT count(*) FROM s JOIN a ON trace_id = unit_id) / (SELECT count(*) FROM s), 6) AS precision, round((SELECT count(*) FROM s JOIN a ON trace_id = unit_id) / (SELECT count(*) FROM a), 6) AS recall, (SELECT count(*) FROM s) - (SELECT count(*) FROM s JOIN a ON trace_id = unit_id) AS removed""")
_add("matching_traces", lambda s, d: matching_traces(_index(s, d, "orders"), _OP), f"SELECT unit_id FROM ({_regex_sql(_chain(_OT), _OT, 'orders', True)})")
_add("prune_multiplicity", lambda s, d: survivors(_index(s, d, "orders"), seq(*_OT[:2], *_OT[:2])), f"{_pairs('orders')} SELECT trace_id FROM prs GROUP BY trace_id HAVING count(*) FILTER (WHERE a_first = '{_OT[0]}' AND a_second = '{_OT[1]}') >= 2 AND count(*) FILTER (WHERE a_first = '{_OT[1]}' AND a_second = '{_OT[0]}') >= 1")
_E8 = [f"view:{k}" for k in range(8)], [f"click:{k}" for k in range(8)]
_in = lambda xs: ", ".join(f"'{x}'" for x in xs)
_add("prune_64_pairs", lambda s, d: survivors(_index(s, d, "type_k30"), seq(P(_E8[0][0]).or_(*_E8[0][1:]), P(_E8[1][0]).or_(*_E8[1][1:]))), f"{_pairs('type_k30')} SELECT DISTINCT trace_id FROM prs WHERE a_first IN ({_in(_E8[0])}) AND a_second IN ({_in(_E8[1])})")
_add("prune_1000_alternatives", lambda s, d: survivors(_index(s, d, "type_k30"), seq(*[P(e[0]).or_(*e[1:]) for e in _E10])), f"{_pairs('type_k30')} SELECT trace_id FROM prs GROUP BY trace_id HAVING count(*) FILTER (WHERE a_first IN ({_in(_E10[0])}) AND a_second IN ({_in(_E10[1])})) > 0 AND count(*) FILTER (WHERE a_first IN ({_in(_E10[1])}) AND a_second IN ({_in(_E10[2])})) > 0")
_add("detect_1000_alternatives", _counted(seq(*[P(e[0]).or_(*e[1:]) for e in _E10]), "type_k30"), f"{_log('type_k30')}, t AS (SELECT trace_id, string_agg(substr(activity, 1, 1), '' ORDER BY pos) AS s FROM log WHERE activity IN ({_in(_E10[0] + _E10[1] + _E10[2])}) GROUP BY trace_id) SELECT trace_id AS unit_id, len(regexp_extract_all(s, 'v[^c]*c[^p]*p')) AS occurrences FROM t WHERE regexp_matches(s, 'v[^c]*c[^p]*p')")
_MANY = (["view", "click", "error", "purchase", "signup"] * 20)[:74]
_add("detect_74_elements", _counted(seq(*_MANY)), _regex_sql(_chain(_MANY), _MANY))
_add("detect_70_long_traces", _counted(seq(*_TAGS), "pages"), _regex_sql(_chain(_TAGS), _TAGS, "pages"))
_add("detect_linear", _counted(_Q3, how="linear"), ORACLES["detect_simple_3"])
_add("detect_text_dialect", lambda s, d: _long(count_matches(_index(s, d), parse_query("find view -> !error -> purchase"))), ORACLES["detect_neg"])
_add("detect_sql_view", _sql_view, ORACLES["detect_or"])
_add("fetch_pairs", lambda s, d: _long(fetch(_index(s, d, "orders"), _OP, source="pairs").select("trace_id", "pos", "activity")), f"""{_pairs('orders')}, sv AS (SELECT trace_id FROM prs WHERE (a_first, a_second) IN (('F/1-URGENT', 'O/2-HIGH'), ('O/2-HIGH', 'F/1-URGENT')) GROUP BY trace_id HAVING count(DISTINCT a_first) = 2)
SELECT DISTINCT trace_id, pos, activity FROM (SELECT trace_id, pos_a AS pos, a_first AS activity FROM prs WHERE (a_first, a_second) IN (('F/1-URGENT', 'O/2-HIGH'), ('O/2-HIGH', 'F/1-URGENT')) UNION ALL SELECT trace_id, pos_b, a_second FROM prs WHERE (a_first, a_second) IN (('F/1-URGENT', 'O/2-HIGH'), ('O/2-HIGH', 'F/1-URGENT'))) WHERE trace_id IN (SELECT trace_id FROM sv)""")
_add("fetch_traces", lambda s, d: _long(fetch(_index(s, d, "orders"), _OP, source="traces").select("trace_id", "pos", "activity")), f"{_pairs('orders')} SELECT trace_id, CAST(pos AS BIGINT) AS pos, activity FROM log WHERE trace_id IN (SELECT trace_id FROM prs WHERE (a_first, a_second) IN (('F/1-URGENT', 'O/2-HIGH'), ('O/2-HIGH', 'F/1-URGENT')) GROUP BY trace_id HAVING count(DISTINCT a_first) = 2)")

# --- exploration and explanation
_add("stats_pattern", lambda s, d: _long(explore.statistics(_index(s, d), _Q3).drop("mean_dur")), f"{_pairs('events')} SELECT CASE a_first WHEN 'view' THEN 1 ELSE 2 END::BIGINT AS ordinal, a_first, a_second, count(*) AS completions, CAST(sum(ts_b - ts_a) AS BIGINT) AS sum_dur, min(ts_b - ts_a) AS min_dur, max(ts_b - ts_a) AS max_dur FROM prs WHERE (a_first, a_second) IN (('view', 'click'), ('click', 'purchase')) GROUP BY a_first, a_second")
_add("continuation_bound", lambda s, d: _long(explore.continuation(_index(s, d), seq("view", "click"), "bound").drop("mean_dur")), f"{_pairs('events')}, st AS (SELECT a_first, a_second, count(*) AS n FROM prs GROUP BY a_first, a_second) SELECT a_second AS activity, least(n, (SELECT n FROM st WHERE a_first = 'view' AND a_second = 'click')) AS completions FROM st WHERE a_first = 'click'")
_FIVE = ["click", "error", "purchase", "signup", "view"]


def _continued_sql(where: str = "true") -> str:
    """view, click and any third event: occurrences of each of the five patterns."""
    parts = []
    for x in _FIVE:
        one = _regex_sql(_chain(["view", "click", x]), ["view", "click", x])
        parts.append(f"SELECT '{x}' AS activity, coalesce(CAST(sum(occurrences) AS BIGINT), 0) AS completions FROM ({one})")
    return f"SELECT * FROM ({' UNION ALL '.join(parts)}) WHERE completions > 0 AND {where}"


_add("continuation_exact", lambda s, d: _long(explore.continuation(_index(s, d), seq("view", "click"), "exact").drop("mean_dur")), _continued_sql())
_add("continuation_hybrid", lambda s, d: _long(explore.continuation(_index(s, d), seq("view", "click"), "hybrid", 2).drop("mean_dur")), f"""WITH bound AS ({ORACLES['continuation_bound']}), top AS (SELECT activity FROM bound ORDER BY completions DESC, activity LIMIT 2)
SELECT activity, completions, true AS exact FROM ({_continued_sql()}) WHERE activity IN (SELECT activity FROM top) UNION ALL SELECT activity, completions, false FROM bound WHERE activity NOT IN (SELECT activity FROM top)""")
_add("continuation_is_bounded", lambda s, d: _long(explore.continuation(_index(s, d, "pages"), seq("div", "p"), "exact").select("activity", F.col("completions").alias("e")).join(explore.continuation(_index(s, d, "pages"), seq("div", "p"), "bound").select("activity", F.col("completions").alias("b")), "activity", "left").agg(F.count("*").alias("activities"), F.count(F.when(F.coalesce("b", F.lit(0)) < F.col("e"), 1)).alias("above"))),
     f"""{_log('pages')}, x AS (SELECT trace_id, min(pos) AS p FROM log WHERE activity = 'div' GROUP BY trace_id), y AS (SELECT trace_id, min(pos) AS q FROM log JOIN x USING (trace_id) WHERE activity = 'p' AND pos > p GROUP BY trace_id)
SELECT count(DISTINCT activity) AS activities, CAST(0 AS BIGINT) AS above FROM log JOIN y USING (trace_id) WHERE pos > q""")
_T = f"{_pairs('events')}, st AS (SELECT a_first, a_second, count(*) AS n, min(ts_b - ts_a) AS d FROM prs GROUP BY a_first, a_second)"
_add("diagnose_query", lambda s, d: _long(explore.diagnose(_index(s, d), seq("view", "click", "nothing").within_time(1, 2, HOUR))), f"""{_T}
SELECT 'unknown_type' AS check, t AS subject, t IN (SELECT activity FROM log) AS ok, CAST(NULL AS BIGINT) AS detail FROM (SELECT unnest(['click', 'nothing', 'view']) AS t)
UNION ALL SELECT 'missing_pair', x || ' -> ' || y, n IS NOT NULL, n FROM (VALUES ('view', 'click'), ('click', 'nothing')) v(x, y) LEFT JOIN st ON a_first = x AND a_second = y
UNION ALL SELECT 'unsatisfiable_constraint', 'time within (1,2) {HOUR}', coalesce(min(d) <= {HOUR}, false), min(d) FROM st WHERE a_first = 'view' AND a_second = 'click'""")
_add("diagnose_exact", lambda s, d: _long(explore.diagnose(_index(s, d), seq("view", "click").within_time(1, 2, HOUR).atleast_gap(1, 2, 70), exact=True)), f"""{_T},
m AS (SELECT min(b.ts_us - a.ts_us) AS d, max(b.pos - a.pos) AS g FROM log a JOIN log b ON a.trace_id = b.trace_id AND a.pos < b.pos WHERE a.activity = 'view' AND b.activity = 'click')
SELECT 'unknown_type' AS check, t AS subject, t IN (SELECT activity FROM log) AS ok, CAST(NULL AS BIGINT) AS detail FROM (SELECT unnest(['click', 'view']) AS t)
UNION ALL SELECT 'missing_pair', x || ' -> ' || y, n IS NOT NULL, n FROM (VALUES ('view', 'click')) v(x, y) LEFT JOIN st ON a_first = x AND a_second = y
UNION ALL SELECT 'unsatisfiable_constraint', 'time within (1,2) {HOUR}', d <= {HOUR}, d FROM m UNION ALL SELECT 'unsatisfiable_constraint', 'gap atleast (1,2) 70', g >= 70, CAST(g AS BIGINT) FROM m""")
_add("stats_alternatives", lambda s, d: _long(explore.statistics(_index(s, d), seq("view", C.or_("signup"), "purchase")).select("ordinal", "a_first", "a_second", "completions")), f"{_T} SELECT CAST(o AS BIGINT) AS ordinal, a_first, a_second, n AS completions FROM (VALUES (1, 'view', 'click'), (1, 'view', 'signup'), (2, 'click', 'purchase'), (2, 'signup', 'purchase')) v(o, x, y) JOIN st ON a_first = x AND a_second = y")


def _explained(k: int, u: int, how: str = "join", types: tuple[str, ...] = ("view", "click", "purchase")) -> Query:
    q = seq(*types).within_time(1, len(types), 6 * HOUR).explain(k * HOUR, u * HOUR, 2 * HOUR)
    return lambda s, d: explore.explain(_index(s, d), q, how).filter("elem = 1").select("trace_id", "cost")


def _explain_sql(k: int, u: int, types: tuple[str, ...] = ("view", "click", "purchase")) -> str:
    """All altered bindings by joins, the least cost of each trace that has the types and no answer."""
    n, span = len(types), 6 * HOUR
    names, steps = ", ".join(f"'{t}'" for t in types), [f"b1 AS (SELECT trace_id, t AS t1, t, cost FROM c WHERE activity = '{types[0]}')"]
    for i in range(2, n + 1):
        steps.append(f"b{i} AS (SELECT b.trace_id, t1, c.t, min(b.cost + c.cost) AS cost FROM b{i - 1} b JOIN c ON c.trace_id = b.trace_id AND c.activity = '{types[i - 1]}' AND c.t > b.t AND c.t <= t1 + {span} WHERE b.cost + c.cost < {k * HOUR} GROUP BY b.trace_id, t1, c.t)")
    return f"""{_log('events')}, ans AS ({_plain_join(list(types), f'e{n}.ts_us - e1.ts_us <= {span}')}),
cand AS (SELECT trace_id FROM log WHERE activity IN ({names}) GROUP BY trace_id HAVING count(DISTINCT activity) = {n} AND trace_id NOT IN (SELECT unit_id FROM ans)),
c AS (SELECT trace_id, pos, activity, ts_us + i * {2 * HOUR} AS t, abs(i) * {2 * HOUR} AS cost FROM log, range({-(u // 2)}, {u // 2 + 1}) r(i) WHERE trace_id IN (SELECT trace_id FROM cand)),
{', '.join(steps)}
SELECT trace_id, CAST(min(cost) AS BIGINT) AS cost FROM b{n} GROUP BY trace_id"""


_add("explain_q3", _explained(4, 2), _explain_sql(4, 2))
_add("explain_q3_wide", _explained(8, 4), _explain_sql(8, 4))
_add("explain_q3_branch_and_bound", _explained(4, 2, "nfa"), _explain_sql(4, 2))
_EXPLAIN5 = ("view", "click", "error", "signup", "purchase")
# five elements within six hours: the join of all answers would be large, so the answers are the chains of cost nought
_add("explain_q5", _explained(8, 2, types=_EXPLAIN5), _explain_sql(8, 2, _EXPLAIN5).replace(f"({_plain_join(list(_EXPLAIN5), f'e5.ts_us - e1.ts_us <= {6 * HOUR}')})", f"""(WITH z1 AS (SELECT trace_id, ts_us AS t1, ts_us AS t FROM log WHERE activity = 'view'), {', '.join(f"z{i} AS (SELECT DISTINCT z.trace_id, t1, l.ts_us AS t FROM z{i - 1} z JOIN log l ON l.trace_id = z.trace_id AND l.activity = '{_EXPLAIN5[i - 1]}' AND l.ts_us > z.t AND l.ts_us <= t1 + {6 * HOUR})" for i in range(2, 6))} SELECT DISTINCT trace_id AS unit_id FROM z5)"""))


def _grid(s: SparkSession, d: str) -> DataFrame:
    """W9, three elements: traces explained and their cost as the budget and then the uncertainty grows."""
    out = None
    for k, u in _GRID:
        one = _explained(k, u)(s, d).agg(F.count("*").alias("traces"), F.coalesce(F.sum("cost"), F.lit(0)).cast("long").alias("cost")).select(F.lit(k).cast("long").alias("k"), F.lit(u).cast("long").alias("u"), "traces", "cost")
        out = one if out is None else out.unionByName(one)
    return out


_GRID = [(2, 2), (4, 2), (6, 2), (4, 4)]
_add("workload_explain_grid", _grid, " UNION ALL ".join(f"SELECT CAST({k} AS BIGINT) AS k, CAST({u} AS BIGINT) AS u, count(*) AS traces, coalesce(CAST(sum(cost) AS BIGINT), 0) AS cost FROM ({_explain_sql(k, u)})" for k, u in _GRID))

# --- baselines: the same answers by scans
_add("scan_cep", lambda s, d: _long(baselines.cep_scan(logs.events_log(s, d), _Q3.all_matches()).groupBy("unit_id").agg(F.max("occ_no").alias("occurrences"))), ORACLES["detect_simple_3"])
_add("scan_row_pattern", lambda s, d: _long(baselines.row_pattern_scan(logs.events_log(s, d), _Q3.all_matches()).groupBy("unit_id").agg(F.max("occ_no").alias("occurrences"))), ORACLES["detect_simple_3"])
_add("scan_windows", lambda s, d: _long(baselines.row_pattern_windows(logs.events_log(s, d), _Q3)), f"{_log('events')} {_plain_join(_VCB, 'true')}")
_add("signature_detect", lambda s, d: _long(baselines.SignatureIndex(logs.events_log(s, d)).detect(_Q3.all_matches()).groupBy("unit_id").agg(F.max("occ_no").alias("occurrences"))), ORACLES["detect_simple_3"])
_add("containment_detect", lambda s, d: _long(baselines.ContainmentIndex(logs.events_log(s, d)).detect(_Q3.all_matches()).groupBy("unit_id").agg(F.max("occ_no").alias("occurrences"))), ORACLES["detect_simple_3"])
def _runs(log: DataFrame, steps: list[tuple[str, int, int]], until: str | None = None) -> DataFrame:
    return _long(baselines.step_search(log, steps, until=until).groupBy(F.col("trace_id").alias("unit_id")).agg(F.max("occ_no").alias("occurrences")))


_add("step_search_until", lambda s, d: _runs(logs.events_log(s, d), [("view", 1, 1), ("click", 1, 1), ("purchase", 1, 1)], "error"), f"""{_log('events')}, cut AS (SELECT trace_id, min(pos) AS stop FROM log WHERE activity = 'error' GROUP BY trace_id),
t AS (SELECT trace_id, string_agg(substr(activity, 1, 1), '' ORDER BY pos) AS s FROM log LEFT JOIN cut USING (trace_id) WHERE activity IN ('view', 'click', 'purchase') AND pos < coalesce(stop, 1000000) GROUP BY trace_id)
SELECT trace_id AS unit_id, CAST(len(regexp_extract_all(s, 'vp*c[vc]*p')) AS BIGINT) AS occurrences FROM t WHERE regexp_matches(s, 'vp*c[vc]*p')""")
_add("step_search_runs", lambda s, d: _runs(logs.events_log(s, d), [("view", 1, 100), ("purchase", 1, 100)]), f"""{_log('events')}, t AS (SELECT trace_id, string_agg(substr(activity, 1, 1), '' ORDER BY pos) AS s FROM log WHERE activity IN ('view', 'purchase') GROUP BY trace_id)
SELECT trace_id AS unit_id, CAST(len(regexp_extract_all(s, 'v{{1,100}}p{{1,100}}')) AS BIGINT) AS occurrences FROM t WHERE regexp_matches(s, 'vp')""")
_add("step_search_two_runs", lambda s, d: _runs(logs.orders_log(s, d), [("F/1-URGENT", 1, 3), ("O/2-HIGH", 1, 1)]), f"""{_log('orders')}, t AS (SELECT trace_id, string_agg(substr(activity, 1, 1), '' ORDER BY pos) AS s FROM log WHERE activity IN ('F/1-URGENT', 'O/2-HIGH') GROUP BY trace_id)
SELECT trace_id AS unit_id, CAST(len(regexp_extract_all(s, 'F{{1,3}}O')) AS BIGINT) AS occurrences FROM t WHERE regexp_matches(s, 'FO')""")

# --- measures, workloads, operators around
_add("workload_carry10", lambda s, d: _long(workloads.carry_over(logs.events_log(s, d)).groupBy("trace_id").agg(F.count("*").alias("n"), F.count_distinct("day").alias("days"))), f"""{_log('events')}, e AS (SELECT *, CAST(floor((ts_us - {workloads.EPOCH}) / {DAY}) AS BIGINT) AS day FROM log WHERE ts_us < {workloads.EPOCH + 10 * DAY}),
a AS (SELECT DISTINCT trace_id, day FROM e), f AS (SELECT *, CASE WHEN row_number() OVER (PARTITION BY trace_id ORDER BY day) = 1 THEN 1 WHEN (trace_id * 7 + day * 13) % 10 = 0 THEN 0 ELSE 1 END AS f FROM a),
r AS (SELECT trace_id, day, sum(f) OVER (PARTITION BY trace_id ORDER BY day) AS run FROM f)
SELECT CAST(e.trace_id * 1000 + run AS BIGINT) AS trace_id, count(*) AS n, count(DISTINCT e.day) AS days FROM e JOIN r ON e.trace_id = r.trace_id AND e.day = r.day GROUP BY 1""")
_SIZE = "length(a_first) + length(a_second) + length(CAST(trace_id AS VARCHAR)) + length(CAST(pos_a AS VARCHAR)) + length(CAST(pos_b AS VARCHAR)) + length(CAST(ts_a AS VARCHAR)) + length(CAST(ts_b AS VARCHAR))"
_UNITS = "CAST(sum(ceil(greatest(b, 1) / 1024)) AS BIGINT) AS write_units, CAST(sum(ceil(greatest(b, 1) / 8192)) AS BIGINT) AS read_units"
# a year of the events' pair index on either kind of store, written item by item and fetched once
_add("cloud_cost", lambda s, d: measures.cloud_costs(measures.stored_usage(_index(s, d).pairs()), 12), f"""{_pairs('events')}, z AS (SELECT {_SIZE} AS b FROM prs), u AS (SELECT coalesce(sum(b), 0)::DOUBLE AS b, coalesce(sum(ceil(greatest(b, 1) / 1024)), 0)::DOUBLE AS w, coalesce(sum(ceil(greatest(b, 1) / 8192)), 0)::DOUBLE AS r FROM z),
c AS (SELECT 'object' AS kind, b / 1e9 * 0.023::DOUBLE * 12 AS storage, greatest(0, b / 1e9 - 100) * 0.009::DOUBLE AS traffic, 0.0::DOUBLE AS requests FROM u UNION ALL SELECT 'request', b / 1e9 * 0.3::DOUBLE * 12, 0.0, w / 1e6 * 1.48::DOUBLE + r / 1e6 * 0.29::DOUBLE FROM u)
SELECT kind, round(storage, 6) AS storage, round(traffic, 6) AS traffic, round(requests, 6) AS requests, round(storage + traffic + requests, 6) AS total FROM c""")
_add("request_units", lambda s, d: measures.request_units(_index(s, d).pairs()).withColumn("how", F.lit("rows")).unionByName(measures.request_units(_index(s, d).pairs(), ["a_first", "a_second"]).withColumn("how", F.lit("grouped"))), f"{_pairs('events')}, z AS (SELECT a_first, a_second, {_SIZE} AS b FROM prs) SELECT {_UNITS}, 'rows' AS how FROM z UNION ALL SELECT {_UNITS}, 'grouped' FROM (SELECT sum(b) AS b FROM z GROUP BY a_first, a_second)")
_add("asof_latest_before", lambda s, d: _long(latest_before(logs.events_log(s, d), "view", "purchase").select("trace_id", "pos_a", "pos_b")), f"{_log('events')} SELECT * FROM (SELECT b.trace_id, CAST((SELECT max(a.pos) FROM log a WHERE a.trace_id = b.trace_id AND a.activity = 'view' AND a.pos < b.pos) AS BIGINT) AS pos_a, CAST(b.pos AS BIGINT) AS pos_b FROM log b WHERE b.activity = 'purchase') WHERE pos_a IS NOT NULL")
_add("sessionize", lambda s, d: _long(sessionize(logs.events_log(s, d), "trace_id", "ts_us", 12 * HOUR).groupBy("trace_id").agg(F.max("session").alias("sessions"))), f"{_log('events')} SELECT trace_id, CAST(sum(CASE WHEN g <= {12 * HOUR} THEN 0 ELSE 1 END) AS BIGINT) AS sessions FROM (SELECT trace_id, ts_us - lag(ts_us) OVER (PARTITION BY trace_id ORDER BY pos) AS g FROM log) GROUP BY trace_id")
_add("daily_counts", lambda s, d: _long(logs.events_log(s, d).groupBy(F.floor(F.col("ts_us") / DAY).alias("day"), "activity").agg(F.count("*").alias("n"))), f"{_log('events')} SELECT CAST(floor(ts_us / {DAY}) AS BIGINT) AS day, activity, count(*) AS n FROM log GROUP BY 1, 2")
_add("intersect_traces", lambda s, d: LogIndex(SOURCES["type_k30"](s, d)).pair_rows([("view:1", "click:2")]).select("trace_id").intersect(LogIndex(SOURCES["type_k30"](s, d)).pair_rows([("click:2", "purchase:3")]).select("trace_id")), f"{_pairs('type_k30')} {_KHAS}")
_add("except_nonanswers", lambda s, d: survivors(_index(s, d, "orders"), _OP, multiplicity=False).exceptAll(matching_traces(_index(s, d, "orders"), _OP).withColumnRenamed("unit_id", "trace_id")), f"{_pairs('orders')} SELECT trace_id FROM prs WHERE (a_first, a_second) IN (('F/1-URGENT', 'O/2-HIGH'), ('O/2-HIGH', 'F/1-URGENT')) GROUP BY trace_id HAVING count(DISTINCT a_first) = 2 EXCEPT SELECT unit_id FROM ({_regex_sql(_chain(_OT), _OT, 'orders', True)})")
_add("inverted_lists", lambda s, d: _long(pairs.inverted_lists(_index(s, d).pairs()).select("a_first", "a_second", F.size("entries").alias("n"), F.array_join(F.transform("entries", lambda e: F.concat_ws("/", e["trace_id"].cast("string"), e["pos_a"].cast("string"), e["pos_b"].cast("string"))), " ").alias("entries"))), f"{_pairs('events')} SELECT a_first, a_second, count(*) AS n, string_agg(trace_id || '/' || pos_a || '/' || pos_b, ' ' ORDER BY trace_id, pos_a, pos_b) AS entries FROM prs GROUP BY a_first, a_second")
_add("trace_buckets", lambda s, d: _long(logs.orders_log(s, d).groupBy(trace_bucket(IndexConfig(trace_split=100)).alias("bucket")).agg(F.count("*").alias("n"))), f"{_log('orders')} SELECT CAST(trace_id // 100 AS BIGINT) AS bucket, count(*) AS n FROM log GROUP BY 1")
_add("follow_matrix", lambda s, d: _long(logs.follow_matrix(_index(s, d).pairs())), f"{_pairs('events')} SELECT a_first, " + ", ".join(f"count(*) FILTER (WHERE a_second = '{t}') AS {t}" for t in _FIVE) + " FROM prs GROUP BY a_first")
_add("containment_bitmaps", lambda s, d: _long(baselines.ContainmentIndex(logs.events_log(s, d)).bitmaps().groupBy("activity").agg(F.sum("n").alias("n"))), f"{_log('events')} SELECT activity, count(DISTINCT trace_id) AS n FROM log GROUP BY activity")
_add("growing_log", lambda s, d: _long(_grown(s, d)), f"{_log('events')} " + " UNION ALL ".join(f"SELECT CAST({n} AS BIGINT) AS days, count(*) AS events, count(DISTINCT trace_id) AS traces FROM log WHERE ts_us < {workloads.EPOCH + n * DAY}" for n in (1, 5, 10)))
_add("index_and_scan_agree", lambda s, d: _both_ways(s, d), f"WITH o AS ({ORACLES['detect_simple_5']}) SELECT (SELECT CAST(sum(occurrences) AS BIGINT) FROM o) AS n, CAST(0 AS BIGINT) AS only_a, CAST(0 AS BIGINT) AS only_b")


def _grown(s: SparkSession, d: str) -> DataFrame:
    out = None
    for n, log in zip((1, 5, 10), workloads.growing(logs.events_log(s, d)), strict=True):
        one = log.agg(F.count("*").alias("events"), F.count_distinct("trace_id").alias("traces")).select(F.lit(n).alias("days"), "events", "traces")
        out = one if out is None else out.unionByName(one)
    return out


def _both_ways(s: SparkSession, d: str) -> DataFrame:
    """Occurrences by the index, and those that only the index or only the scan has."""
    q = seq("view", "click", "error", "signup", "purchase").all_matches()
    a, b = detect(_index(s, d), q).drop("activity"), baselines.cep_scan(logs.events_log(s, d), q).drop("activity")
    return _long(a.groupBy("unit_id").agg(F.max("occ_no").alias("k")).agg(F.sum("k").alias("n")).crossJoin(measures.agree(a, b)))  # one row each


# --- sources, sinks and streams
def _through(s: SparkSession, d: str, kind: str) -> DataFrame:
    """The orders log written as CSV, JSON or text and read again."""
    at = f"{shared_folder(s)}/{kind}"
    rows = logs.orders_log(s, d).select("trace_id", F.timestamp_micros("ts_us").cast("string").alias("at"), "activity", "pos")
    if kind == "text":
        rows.select(F.concat_ws(" ", F.col("trace_id").cast("string"), F.translate("at", " ", "T"), "activity", F.col("pos").cast("string"))).write.mode("overwrite").text(at)
        return _long(logs.from_text(s, at, r"^(\d+) (\S+) (.+) \d+$").select("trace_id", "ts_us", "activity"))
    logs.to_files(rows, at, kind)
    schema, read = "trace_id long, at string, activity string, pos int", logs.from_csv if kind == "csv" else logs.from_json
    return _long(read(s, at, schema, "trace_id", "activity", "at", ("pos",)))


for _kind in ("csv", "json"):
    _add(f"source_{_kind}", lambda s, d, k=_kind: _through(s, d, k), f"{_log('orders')} SELECT trace_id, CAST(pos AS BIGINT) AS pos, ts_us, activity FROM log")
_add("source_text", lambda s, d: _through(s, d, "text"), f"{_log('orders')} SELECT trace_id, ts_us, activity FROM log")


def _timed_events(s: SparkSession, d: str) -> DataFrame:
    return logs.events_log(s, d).withColumn("ts", F.timestamp_micros("ts_us"))


_add("stream_counts_as_batch", lambda s, d: _long(streaming.type_counts(_timed_events(s, d)).select(F.expr(f"unix_micros(window.start) div {DAY}").alias("day"), "activity", "n")), ORACLES["daily_counts"])
_add("stream_pairs_within_as_batch", lambda s, d: _long(streaming.pairs_within(_timed_events(s, d), "view", "purchase", "6 hours").select("trace_id", F.unix_micros("ts_a").alias("ts_a"), F.unix_micros("ts_b").alias("ts_b"))), f"{_log('events')} SELECT a.trace_id, a.ts_us AS ts_a, b.ts_us AS ts_b FROM log a JOIN log b ON a.trace_id = b.trace_id AND b.ts_us > a.ts_us AND b.ts_us <= a.ts_us + {6 * HOUR} WHERE a.activity = 'view' AND b.activity = 'purchase'")
_add("stream_sessions_as_batch", lambda s, d: _long(streaming.sessions(_timed_events(s, d), "trace_id", "12 hours").groupBy("trace_id").agg(F.count("*").alias("sessions"))), f"{_log('events')} SELECT trace_id, CAST(sum(CASE WHEN g < {12 * HOUR} THEN 0 ELSE 1 END) AS BIGINT) AS sessions FROM (SELECT trace_id, ts_us - lag(ts_us) OVER (PARTITION BY trace_id ORDER BY pos) AS g FROM log) GROUP BY trace_id")


def _streamed(s: SparkSession, d: str) -> DataFrame:
    """V5: the log as a stream of four files in the order of time, occurrences as they complete."""
    at, log = f"{shared_folder(s)}/stream", logs.events_log(s, d)
    for k in range(4):
        log.filter(F.floor((F.col("ts_us") - workloads.EPOCH) / (8 * DAY)) == k).coalesce(1).write.mode("append").parquet(f"{at}/in")
    found = streaming.detect_stream(streaming.read_log(s, f"{at}/in", log.schema), _Q3)
    name = f"found_{uuid.uuid4().hex}"
    running = found.writeStream.format("memory").queryName(name).outputMode("append").option("checkpointLocation", f"{at}/checkpoint").trigger(availableNow=True).start()
    running.awaitTermination()
    return _long(s.table(name).groupBy(F.col("trace_id").alias("unit_id")).agg(F.max("occ_no").alias("occurrences")))


_add("stream_detect", _streamed, ORACLES["detect_simple_3"])

# --- the stored index: ten daily batches, a tenth of the traces running on into the next day
LOGS["carry"] = f"""SELECT trace_id, row_number() OVER (PARTITION BY trace_id ORDER BY ts_us, activity) AS pos, ts_us, activity, day FROM (WITH e AS (SELECT *, CAST(floor((ts_us - {workloads.EPOCH}) / {DAY}) AS BIGINT) AS day FROM ({LOGS['events']}) WHERE ts_us < {workloads.EPOCH + 10 * DAY}),
a AS (SELECT DISTINCT trace_id, day FROM e), f AS (SELECT *, CASE WHEN row_number() OVER (PARTITION BY trace_id ORDER BY day) = 1 THEN 1 WHEN (trace_id * 7 + day * 13) % 10 = 0 THEN 0 ELSE 1 END AS f FROM a),
r AS (SELECT trace_id, day, sum(f) OVER (PARTITION BY trace_id ORDER BY day) AS run FROM f)
SELECT CAST(e.trace_id * 1000 + run AS BIGINT) AS trace_id, e.day, ts_us, activity FROM e JOIN r ON e.trace_id = r.trace_id AND e.day = r.day)"""
_CUT = workloads.EPOCH + 4 * DAY  # what expires before
_STORES: dict[tuple, IndexStore] = {}
_DAYS: dict[tuple, DataFrame] = {}


def _carried(s: SparkSession, d: str) -> DataFrame:
    return workloads.carry_over(logs.events_log(s, d, before_us=workloads.EPOCH + 10 * DAY))


def _days(s: SparkSession, d: str) -> DataFrame:
    """The ten days' events in a folder a day, so that a batch reads its own; made once a session and table folder."""
    key = (s.sparkContext.applicationId, d)
    if key not in _DAYS:
        days = f"{shared_folder(s)}/days"
        _carried(s, d).write.partitionBy("day").parquet(days)
        _DAYS[key] = s.read.schema("trace_id long, ts_us long, activity string, day int").parquet(days)
    return _DAYS[key]


def _store(s: SparkSession, d: str, kind: str) -> IndexStore:
    """A store of the ten days, made once a session and table folder."""
    key = (s.sparkContext.applicationId, d, kind)
    if key not in _STORES:
        options = {"ten": {}, "packed": {}, "expired": {}, "ts": {"mode": "ts"}, "pos": {"mode": "pos"}, "keyed": {"layout": "pair_key"}, "merged": {"mode": "pos"}, "zstd": {"compression": "zstd"}, "rebuilt": {}, "lookback": {"lookback_us": DAY}}[kind]
        store = Catalog(s, shared_folder(s)).create(kind, IndexConfig(split_every_days=2, first_buckets=8, trace_split=10_000, **options))
        batches = _carried(s, d) if kind == "ten" else _days(s, d)
        cuts = list(range(11)) if kind == "ten" else [0, 5, 10] if kind != "rebuilt" else [0, 10]
        if kind == "ten":  # due at once: one pass over their table
            store.append_table(batches.withColumnRenamed("day", "batch"), [f"day-{b}" for b in cuts[1:]])
        else:
            due = [(batches.filter(F.col("day").between(a, b - 1)).select("trace_id", "ts_us", "activity"), f"day-{b}") for a, b in zip(cuts, cuts[1:])]
            if kind == "rebuilt":  # the odd days come late
                due = [(batches.filter(f"day % 2 = {odd}").select("trace_id", "ts_us", "activity"), b) for odd, b in ((0, "even"), (1, "day-10"))]
            store.append_batches(due, strategy="merge" if kind == "merged" else "append", late="rebuild" if kind == "rebuilt" else "error")
        if kind == "packed":
            store.compact()
        if kind == "expired":
            store.expire(_CUT)
            store.compact()
        store.append_batch(batches.select("trace_id", "ts_us", "activity"), f"day-{cuts[-1]}", late="rebuild")  # sent again: nothing changes
        _STORES[key] = store
    return _STORES[key]


_POS = ["a_first", "a_second", "trace_id", "pos_a", "pos_b"]
_PAIR_SQL = "SELECT a_first, a_second, trace_id, pos_a, pos_b FROM prs"
for _kind in ("ten", "packed", "pos", "keyed", "merged", "zstd", "rebuilt"):
    _add(f"store_pairs_{_kind}", lambda s, d, k=_kind: _long(_store(s, d, k).pairs().select(*_POS)), f"{_pairs('carry')} {_PAIR_SQL}")
_add("store_pairs_ts", lambda s, d: _long(_store(s, d, "ts").pairs().select(*_POS, "ts_a", "ts_b")), f"{_pairs('carry')} SELECT a_first, a_second, trace_id, pos_a, pos_b, ts_a, ts_b FROM prs")
_add("store_pairs_lookback", lambda s, d: _long(_store(s, d, "lookback").pairs().select(*_POS)), f"{_pairs('carry', DAY)} {_PAIR_SQL}")
_add("store_pairs_expired", lambda s, d: _long(_store(s, d, "expired").pairs().select(*_POS)), f"{_pairs('carry')} {_PAIR_SQL} WHERE ts_b >= {_CUT // (2 * DAY) * (2 * DAY)}")
_STATS_SQL = "SELECT a_first, a_second, count(*) AS completions, CAST(sum(ts_b - ts_a) AS BIGINT) AS sum_dur, min(ts_b - ts_a) AS min_dur, max(ts_b - ts_a) AS max_dur, min(pos_b - pos_a) AS min_gap, max(pos_b - pos_a) AS max_gap FROM prs"
for _kind, _where in (("ten", ""), ("packed", ""), ("expired", f" WHERE ts_b >= {_CUT // (2 * DAY) * (2 * DAY)}")):
    _add(f"store_stats_{_kind}", lambda s, d, k=_kind: _long(_store(s, d, k).stats()), f"{_pairs('carry')} {_STATS_SQL}{_where} GROUP BY a_first, a_second")
    _add(f"store_frontier_{_kind}", lambda s, d, k=_kind: _long(_store(s, d, k).frontier()), f"{_pairs('carry')} SELECT a_first, a_second, trace_id, max(ts_b) AS last_ts, max(pos_b) AS last_pos FROM prs{_where} GROUP BY a_first, a_second, trace_id")
    _add(f"store_type_index_{_kind}", lambda s, d, k=_kind: _long(_store(s, d, k).type_rows_all()), f"{_log('carry')} SELECT trace_id, CAST(pos AS BIGINT) AS pos, ts_us, activity FROM log{_where.replace('ts_b', 'ts_us')}")
for _kind in ("ten", "merged", "rebuilt"):
    _add(f"store_traces_{_kind}", lambda s, d, k=_kind: _long(_store(s, d, k).traces()), f"{_log('carry')} SELECT trace_id, CAST(pos AS BIGINT) AS pos, ts_us, activity FROM log")
_add("store_bounds_ten", lambda s, d: _long(_store(s, d, "ten").bounds()), f"{_log('carry')} SELECT trace_id, count(*) AS n_events, min(ts_us) AS first_ts, max(ts_us) AS last_ts, CAST(max(pos) AS BIGINT) AS last_pos FROM log GROUP BY trace_id")
_add("store_type_rows", lambda s, d: _long(_store(s, d, "ten").type_rows(["click", "error"])), f"{_log('carry')} SELECT trace_id, CAST(pos AS BIGINT) AS pos, ts_us, activity FROM log WHERE activity IN ('click', 'error')")
_add("store_pair_rows_window", lambda s, d: _long(_store(s, d, "pos").pair_rows([("view", "click"), ("error", "error")], (workloads.EPOCH + 3 * DAY, workloads.EPOCH + 7 * DAY - 1)).select(*_POS)), f"{_pairs('carry')} {_PAIR_SQL} WHERE (a_first, a_second) IN (('view', 'click'), ('error', 'error')) AND ts_b BETWEEN {workloads.EPOCH + 3 * DAY} AND {workloads.EPOCH + 7 * DAY - 1}")
for _kind in ("ten", "packed", "pos", "ts", "keyed", "merged", "rebuilt"):
    _add(f"store_detect_{_kind}", lambda s, d, k=_kind: _long(count_matches(_store(s, d, k), seq("view", "click"))), _regex_sql(_chain(["view", "click"]), ["view", "click"], "carry"))
_add("store_detect_operators", lambda s, d: _long(count_matches(_store(s, d, "ten"), seq(V, E.neg(), C.or_("signup").plus(), B))), _regex_sql(_chain(["view", "click|signup", "purchase"], {1: ["error"]}, ["view", "click", "error", "purchase", "signup"]), ["view", "click", "error", "purchase", "signup"], "carry"))
_add("store_detect_window", lambda s, d: _long(count_matches(_store(s, d, "pos"), seq("view", "click").between(workloads.EPOCH + 2 * DAY, workloads.EPOCH + 8 * DAY - 1))), _regex_sql(_chain(["view", "click"]), ["view", "click"], "carry").replace("WHERE activity IN", f"WHERE ts_us BETWEEN {workloads.EPOCH + 2 * DAY} AND {workloads.EPOCH + 8 * DAY - 1} AND activity IN"))
_add("store_preliminary_engine", lambda s, d: _long(baselines.preliminary_detect(_store(s, d, "keyed"), seq("view", "click", "purchase").all_matches()).groupBy("unit_id").agg(F.max("occ_no").alias("occurrences"))), _regex_sql(_chain(["view", "click", "purchase"]), ["view", "click", "purchase"], "carry"))
_add("store_history", lambda s, d: _long(_store(s, d, "ten").history().filter("kind = 'append'").select("batch_id", "n_events", "n_pairs")), f"{_pairs('carry')} SELECT 'day-' || (day + 1) AS batch_id, count(*) AS n_events, CAST(sum(n) AS BIGINT) AS n_pairs FROM (SELECT log.trace_id, log.pos, day, (SELECT count(*) FROM prs WHERE prs.trace_id = log.trace_id AND prs.pos_b = log.pos) AS n FROM log) GROUP BY day")
_add("store_verify", lambda s, d: _store(s, d, "ten").verify().unionByName(_store(s, d, "expired").verify()).groupBy("check").agg(F.sum("bad").cast("long").alias("bad")), "SELECT unnest(['stats', 'stats_more', 'frontier', 'second_events', 'order', 'types', 'types_more']) AS check, CAST(0 AS BIGINT) AS bad")
_add("store_continuation", lambda s, d: _long(explore.continuation(_store(s, d, "ten"), seq("view"), "bound").select("activity", "completions")), f"{_pairs('carry')} SELECT a_second AS activity, count(*) AS completions FROM prs WHERE a_first = 'view' GROUP BY a_second")
