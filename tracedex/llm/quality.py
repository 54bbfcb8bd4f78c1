"""Quality classifier: a sparse rule ensemble over text statistics (operator 2).

One pass of array code turns each whole text into a few statistics. Boosted shallow trees are grown on a
bounded, documented sample of labelled rows; every path from a root to a node becomes a rule, a conjunction
of threshold tests; a lasso logistic regression keeps few rules, which are compiled into Spark column
expressions, so scoring after the statistics is generated JVM code.

Defined cases: null counts as empty and gets a score like any text; without labels of both classes the score is
the base rate (0.5 without any); repeated rows are scored alike; other columns pass untouched.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from tracedex.llm.common import flat_utf8, mix64, slices, spans, table, words_of

#: Byte classes by which texts are counted.
KINDS = ["lower", "upper", "digit", "space", "line", "stop", "bang", "sign", "bar", "quote", "wide", "other"]
STATS = ["log_bytes", "upper", "digit", "space", "line", "stop", "bang", "sign", "bar", "quote", "wide", "other", "word_bytes", "distinct_words", "distinct_lines", "sign_runs", "top_word", "line_words"]
#: Labelled rows that the ensemble is fitted on at most; statistics of all documents are computed all the same.
SAMPLE = 12_000


def _kinds() -> np.ndarray:
    kind = np.full(256, KINDS.index("other"), np.int64)
    for name, members in (("lower", range(97, 123)), ("upper", range(65, 91)), ("digit", range(48, 58)), ("space", (9, 32)), ("line", (10, 13)), ("stop", b".,;:"), ("bang", b"!?"), ("sign", b"#$%&*+<=>@^~\\{}[]_"), ("bar", b"|"), ("quote", b"\"'()-`/"), ("wide", range(128, 256))):
        kind[list(members)] = KINDS.index(name)
    return kind


def _repeats(hashes: np.ndarray, doc: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """(distinct, count of the commonest) of the hashes of each document."""
    if not len(hashes):
        return np.zeros(n), np.zeros(n)
    key = np.sort(mix64(hashes ^ (doc.astype(np.uint64) << np.uint64(40))) >> np.uint64(24) | doc.astype(np.uint64) << np.uint64(40))
    first = np.flatnonzero(np.r_[True, key[1:] != key[:-1]])
    owner = (key[first] >> np.uint64(40)).astype(np.int64)
    top = np.zeros(n, np.int64)
    np.maximum.at(top, owner, np.diff(np.r_[first, len(key)]))
    return np.bincount(owner, minlength=n), top


def statistics(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """A row of STATS for each text."""
    kind, k, out = _kinds(), len(KINDS), []
    for i, j in spans(offsets):
        x, at = data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i]
        n, sizes = j - i, np.diff(at).astype(float)
        doc = np.repeat(np.arange(n), np.diff(at))
        kinds = kind[x]
        counts = np.bincount(doc * k + kinds, minlength=n * k).reshape(n, k).astype(float)
        hashes, start, owner = words_of(x, at)
        words = np.bincount(owner, minlength=n).astype(float)
        distinct, top = _repeats(hashes, owner, n)
        # lines: hashes of runs between line feeds, from sums of position-free word hashes in each line
        line = np.cumsum(x == 10) + doc  # a number that rises at every line and document
        line_id, place = (np.unique(line[start], return_inverse=True)) if len(start) else (np.zeros(0), np.zeros(0, int))
        sums = np.zeros(len(line_id), np.uint64)
        np.add.at(sums, place, hashes)
        line_owner = np.zeros(len(line_id), np.int64)
        line_owner[place] = owner
        lines = np.bincount(line_owner, minlength=n).astype(float)
        lines_distinct, _ = _repeats(sums, line_owner, n)
        both = (kinds[1:] == KINDS.index("sign")) & (kinds[:-1] == KINDS.index("sign")) & (doc[1:] == doc[:-1])
        runs = np.bincount(doc[1:][both], minlength=n)
        size, w = np.maximum(sizes, 1), np.maximum(words, 1)
        letters = counts[:, [0, 1, 2, KINDS.index("wide")]].sum(1)
        out.append(np.column_stack([np.log1p(sizes), *(counts[:, 1:] / size[:, None]).T, letters / w, distinct / w, lines_distinct / np.maximum(lines, 1), runs / size, top / w, words / np.maximum(lines, 1)]))
    return np.round(np.concatenate(out), 6) if out else np.zeros((0, len(STATS)))


def with_statistics(docs: DataFrame, text: str = "text", keep: list[str] | None = None, prefix: str = "stat_") -> DataFrame:
    """`keep` columns of docs (all unless given) and one column for each statistic."""
    keep = docs.columns if keep is None else keep
    names = [prefix + s for s in STATS]
    once = text in keep and isinstance(docs.schema[text].dataType, T.StringType)  # a kept text travels once
    at = keep.index(text) if once else len(keep)
    carried = docs.select(*[F.col(c) for c in keep], *([] if once else [F.col(text).cast("string").alias("_text_")]))
    schema = T.StructType([docs.schema[c] for c in keep] + [T.StructField(c, T.DoubleType()) for c in names])

    def run(batches):
        for b in slices(batches, at):
            stats = statistics(*flat_utf8(b.column(at)))
            yield pa.RecordBatch.from_arrays([*(b.column(i) for i in range(len(keep))), *(pa.array(stats[:, i]) for i in range(len(names)))], [*keep, *names])

    return carried.mapInArrow(run, schema)


Test = tuple[int, bool, float]  # statistic, over it, threshold


@dataclass
class RuleEnsemble:
    """rules with their weights; a rule is the conjunction of its tests."""

    base: float = 0.0
    rules: list[tuple[tuple[Test, ...], float]] = field(default_factory=list)

    def column(self, prefix: str = "stat_") -> Column:
        """The score, 0 to 1, as one column expression over the statistics."""
        z = F.lit(float(self.base))
        for tests, weight in self.rules:
            hit = None
            for s, over, cut in tests:
                c = F.col(prefix + STATS[s])
                one = c > F.lit(cut) if over else c <= F.lit(cut)
                hit = one if hit is None else hit & one
            z = z + F.when(hit, F.lit(float(weight))).otherwise(F.lit(0.0))
        return F.lit(1.0) / (F.lit(1.0) + F.exp(-z))


def _tree(bins: np.ndarray, gradient: np.ndarray, hessian: np.ndarray, cuts: list[np.ndarray], depth: int, least: int) -> tuple[list[tuple[Test, ...]], np.ndarray]:
    """Paths to all nodes of a tree grown by second-order gains, and its prediction for each row."""
    paths: list[tuple[Test, ...]] = []
    value = np.zeros(len(gradient))
    todo = [(np.arange(len(gradient)), (), depth)]
    while todo:
        rows, path, left = todo.pop()
        g, h = gradient[rows], hessian[rows]
        value[rows] = -g.sum() / (h.sum() + 1)
        if path:
            paths.append(path)
        if not left or len(rows) < 2 * least:
            continue
        best = (1e-3, -1, 0)
        for s, cut in enumerate(cuts):
            if not len(cut):
                continue
            b, m = bins[rows, s], len(cut) + 1
            gs, hs, ns = np.cumsum(np.bincount(b, g, m))[:-1], np.cumsum(np.bincount(b, h, m))[:-1], np.cumsum(np.bincount(b, minlength=m))[:-1]
            gain = gs**2 / (hs + 1) + (g.sum() - gs) ** 2 / (h.sum() - hs + 1) - g.sum() ** 2 / (h.sum() + 1)
            gain[(ns < least) | (len(rows) - ns < least)] = -1
            k = int(np.argmax(gain))
            if gain[k] > best[0]:
                best = (gain[k], s, k)
        if best[1] >= 0:
            _, s, k = best
            low = bins[rows, s] <= k
            todo += [(rows[low], (*path, (s, False, float(cuts[s][k]))), left - 1), (rows[~low], (*path, (s, True, float(cuts[s][k]))), left - 1)]
    return paths, value


def fit(stats: np.ndarray, label: np.ndarray, trees: int = 24, depth: int = 3, rate: float = 0.3, lasso: float = 2e-3, steps: int = 300, seed: int = 7) -> RuleEnsemble:
    """Trees on half samples, their paths as rules, then lasso logistic weights by accelerated proximal steps."""
    y = label.astype(float)
    if len(y) < 20 or y.min() == y.max():
        rate_ = (y.sum() + 1) / (len(y) + 2)
        return RuleEnsemble(float(np.log(rate_ / (1 - rate_))))
    random = np.random.default_rng(seed)
    cuts = [np.unique(np.quantile(stats[:, s], np.linspace(0, 1, 33)[1:-1], method="lower")) for s in range(stats.shape[1])]
    bins = np.column_stack([np.searchsorted(c, stats[:, s], "left") for s, c in enumerate(cuts)])
    z, rules = np.full(len(y), np.log(y.mean() / (1 - y.mean()))), {}
    for _ in range(trees):
        p = 1 / (1 + np.exp(-z))
        use = random.random(len(y)) < 0.5
        paths, _ = _tree(bins[use], (p - y)[use], (p * (1 - p))[use], cuts, depth, max(5, len(y) // 400))
        rules |= dict.fromkeys(tuple(sorted(p)) for p in paths)
        if not paths:
            break
        hit = np.column_stack([_hits(stats, r) for r in paths])
        _, place = np.unique(hit @ 2.0 ** np.arange(len(paths)), return_inverse=True)  # rows in the same nodes share a leaf
        g, h = np.bincount(place, y - p), np.bincount(place, p * (1 - p))
        z = z + rate * (g / (h + 1))[place]
    kept = list(rules)
    if not kept:
        return RuleEnsemble(float(z[0]))
    x = np.column_stack([_hits(stats, r) for r in kept]).astype(float)
    x, first = np.unique(x, axis=1, return_index=True)  # rules that hold for the same rows count once
    kept = [kept[i] for i in first]
    mean, scale = x.mean(0), np.maximum(x.std(0), 0.05)
    a = (x - mean) / scale
    step = 4 * len(y) / np.linalg.norm(a, 2) ** 2
    w = v = np.zeros(a.shape[1])
    b, t = float(np.log(y.mean() / (1 - y.mean()))), 1.0
    for _ in range(steps):
        r = 1 / (1 + np.exp(-(a @ v + b))) - y
        b -= 4 * r.mean()
        new = v - step * (a.T @ r) / len(y)
        new = np.sign(new) * np.maximum(np.abs(new) - step * lasso, 0)
        t2 = (1 + np.sqrt(1 + 4 * t * t)) / 2
        v, w, t = new + (t - 1) / t2 * (new - w), new, t2
    weight = w / scale
    return RuleEnsemble(float(b - weight @ mean), [(kept[i], float(weight[i])) for i in np.flatnonzero(weight)])


def _hits(stats: np.ndarray, rule: tuple[Test, ...]) -> np.ndarray:
    out = np.ones(len(stats), bool)
    for s, over, cut in rule:
        out &= (stats[:, s] > cut) if over else (stats[:, s] <= cut)
    return out


def held_out() -> Column:
    return F.crc32(F.col("doc_id").cast("string")) % 5 == 0


def train(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> RuleEnsemble:
    """Fits on at most `sample` labelled rows that are not held out, taken in the order of a hash of their id."""
    some = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("quality").cast("int").alias("quality")).filter("doc_id is not null and quality is not null").filter(~held_out())
    some = some.orderBy(F.xxhash64("doc_id"), "quality").limit(sample)  # a bounded side: two numbers a row
    names = ["stat_" + s for s in STATS]
    rows = with_statistics(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(F.broadcast(some), "doc_id"), keep=["doc_id", "quality"])
    # a row for each labelled id and label, however often the id occurs among the documents: at most `sample` reach the driver
    rows = rows.groupBy("doc_id", "quality").agg(F.min(F.struct(*names)).alias("s")).select("doc_id", "quality", "s.*").toPandas()
    rows = rows.sort_values(["doc_id", "quality"], kind="stable")
    return fit(rows[names].to_numpy(float), rows["quality"].to_numpy())


def _prefix(names: list[str]) -> str:
    """A prefix of statistics' names that no column has."""
    prefix = "stat_"
    while any(c.lower().startswith(prefix) for c in names):
        prefix = "_" + prefix
    return prefix


def accepted(docs: DataFrame, model: RuleEnsemble, least: float) -> DataFrame:
    """The rows that score at least `least`, with the columns they came with."""
    prefix = _prefix(docs.columns)
    return with_statistics(docs, prefix=prefix).filter(model.column(prefix) >= least).select(*docs.columns)


def score(docs: DataFrame, model: RuleEnsemble, keep: list[str] | None = None) -> DataFrame:
    """`keep` columns (all unless given; one named `score` is replaced) and the score, 0 to 1; higher: label 1 likelier."""
    keep = [c for c in (docs.columns if keep is None else keep) if c != "score"]
    prefix = _prefix(keep)
    return with_statistics(docs, keep=keep, prefix=prefix).select(*keep, model.column(prefix).alias("score"))


def op2_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Scores of every document."""
    docs = table(spark, sf_dir, "documents")
    scored = score(docs, train(docs, table(spark, sf_dir, "labels")), ["doc_id"])
    return scored.select("doc_id", F.coalesce(held_out(), F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))
