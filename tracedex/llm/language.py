"""Language identification by multilingual mixture inference (operator 9).

Trigram counts of each language, over words of lower-cased bytes, give a likelihood of every word under every
language. A document is a mixture: expectation-maximisation estimates the proportions of the languages over
its words, and nested sets of the likeliest languages are compared by penalised likelihood.

Defined cases: null text or text without a letter is `und` with score 0; rows without a language teach nothing; without
any taught language every text is `und`; more than `MOST_LANGUAGES` taught languages raise an error; repeated rows are predicted alike; other columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from tracedex.llm.common import IS_WORD, LOWER, flat_utf8, spans, table

BUCKETS = 1 << 16
#: Languages that a model may have: its tables then take 64 MB at most where they are broadcast.
MOST_LANGUAGES = 256


def _letters(data: np.ndarray) -> np.ndarray:
    """Lower-cased bytes with everything but word bytes blanked, digits too."""
    low = LOWER[data]
    low[~IS_WORD[data] | ((data >= 48) & (data < 58))] = 32
    return low


def _trigrams(low: np.ndarray) -> np.ndarray:
    """Bucket of the trigram around each byte; the ends are blank."""
    x = np.concatenate([[32], low, [32]]).astype(np.uint32)
    key = x[:-2] * np.uint32(65599) * np.uint32(65599) + x[1:-1] * np.uint32(65599) + x[2:]
    key *= np.uint32(2654435761)
    return (key >> np.uint32(16)).astype(np.int64)


def _marked(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(trigram of each byte, word starts, word ends, document of each word)."""
    low = _letters(data)
    word = low != 32
    opens, closes = word.copy(), word.copy()
    opens[1:] &= ~word[:-1]
    closes[:-1] &= ~word[1:]
    inner = offsets[1:-1]
    inner = inner[(inner > 0) & (inner < len(data))]
    opens[inner], closes[inner - 1] = word[inner], word[inner - 1]
    start, end = np.flatnonzero(opens), np.flatnonzero(closes) + 1
    return _trigrams(low), start, end, np.searchsorted(offsets, start, "right") - 1


@dataclass
class Languages:
    names: list[str]
    logs: np.ndarray  # (languages, BUCKETS), 32-bit


def train(docs: DataFrame) -> Languages:
    """Counts over all the documents given (`text`, `lang`); what reaches the driver is one bounded table a language."""

    def run(batches):
        sums: dict[str, np.ndarray] = {}
        for b in batches:
            langs = b.column(1).to_pylist()
            data, offsets = flat_utf8(b.column(0))
            for i, j in spans(offsets):
                x = data[offsets[i] : offsets[j]]
                tri = _trigrams(_letters(x))
                names = sorted(set(langs[i:j]))
                kind = np.repeat(np.array([names.index(v) for v in langs[i:j]]), np.diff(offsets[i : j + 1]))
                keep = _letters(x) != 32
                counts = np.bincount(kind[keep] * BUCKETS + tri[keep], minlength=len(names) * BUCKETS).reshape(-1, BUCKETS)
                for name, c in zip(names, counts, strict=True):
                    sums[name] = sums.get(name, 0) + c
        for name, c in sums.items():
            at = np.flatnonzero(c)
            yield pa.RecordBatch.from_arrays([pa.array([name] * len(at), pa.string()), pa.array(at, pa.int32()), pa.array(c[at], pa.int64())], ["lang", "bucket", "n"])

    counted = docs.select(F.col("text").cast("string"), F.col("lang").cast("string")).filter("text is not null and lang is not null").mapInArrow(run, "lang string, bucket int, n long")
    # a list of counts a language is all that reaches the driver, and one language more than may be shows that there are too many
    each = counted.groupBy("lang", "bucket").agg(F.sum("n").alias("n")).groupBy("lang").agg(F.collect_list(F.struct("bucket", "n")).alias("counts"))
    rows = sorted(each.limit(MOST_LANGUAGES + 1).collect(), key=lambda r: r["lang"])
    if len(rows) > MOST_LANGUAGES:
        raise ValueError(f"more than {MOST_LANGUAGES} languages: raise MOST_LANGUAGES if 256 KB each may be broadcast")
    logs = np.zeros((len(rows), BUCKETS), np.float32)
    for i, r in enumerate(rows):
        own = np.full(BUCKETS, 0.05)
        own[[c["bucket"] for c in r["counts"]]] += [c["n"] for c in r["counts"]]
        logs[i] = np.log(own / own.sum())
    return Languages([r["lang"] for r in rows], logs)


def _mixture(like: np.ndarray, first: np.ndarray, doc: np.ndarray, share: np.ndarray, steps: int) -> tuple[np.ndarray, np.ndarray]:
    """Expectation-maximisation: (shares, log-likelihood) of each document; like: (words, languages), words in document order."""
    n, total = np.diff(np.r_[first, len(like)]), np.zeros(0)
    for _ in range(steps):
        joint = like * share[doc]
        total = joint.sum(1)
        joint /= np.maximum(total, 1e-300)[:, None]
        share = np.add.reduceat(joint, first, axis=0) / n[:, None]
    return share, np.add.reduceat(np.log(np.maximum(total, 1e-300)), first)


def proportions(data: np.ndarray, offsets: np.ndarray, model: Languages, steps: int = 8, penalty: float = 3.0) -> np.ndarray:
    """(documents, languages) shares; languages outside the selected set are 0, documents without words all 0."""
    k, out = len(model.names), np.zeros((len(offsets) - 1, len(model.names)))
    for i, j in spans(offsets, 1 << 21):
        tri, start, end, doc = _marked(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i])
        if not len(start):
            continue
        like = np.empty((len(start), k))
        for g in range(k):
            sums = np.concatenate([[0.0], np.cumsum(model.logs[g][tri], dtype=np.float64)])
            like[:, g] = sums[end] - sums[start]
        like -= like.max(1, keepdims=True)
        like = np.maximum(np.exp(np.maximum(like, -30)), 1e-12)
        first = np.flatnonzero(np.r_[True, doc[1:] != doc[:-1]])
        own = doc[first]
        place = np.repeat(np.arange(len(first)), np.diff(np.r_[first, len(doc)]))
        share, _ = _mixture(like, first, place, np.full((len(first), k), 1 / k), steps)
        order = np.argsort(-share, axis=1, kind="stable")
        rank = np.argsort(order, axis=1, kind="stable")
        words = np.diff(np.r_[first, len(doc)])
        best = np.full(len(first), -np.inf)
        chosen = share
        for size in range(1, k + 1):
            part = np.where(rank < size, share, 0)
            part /= np.maximum(part.sum(1, keepdims=True), 1e-300)
            refined, likelihood = _mixture(like, first, place, part, 3 if size > 1 else 1)
            worth = likelihood - penalty * (size - 1) * np.log(words + 1)
            better = worth > best
            best = np.where(better, worth, best)
            chosen = np.where(better[:, None], refined, chosen)
        out[i + own] = chosen
    return out


def predict(docs: DataFrame, model: Languages) -> DataFrame:
    """doc_id, lang_pred, score (the share of that language), languages (the selected set)."""
    names, schema = model.names, "doc_id long, lang_pred string, score double, languages array<string>"
    held = docs.sparkSession.sparkContext.broadcast(model)  # a fixed number of buckets for each language

    def run(batches):
        for b in batches:
            texts = b.column(1)
            data, offsets = flat_utf8(texts)
            n = len(offsets) - 1
            shares = proportions(data, offsets, held.value) if names else np.zeros((n, 0))
            ascii_ = np.concatenate([[0], np.cumsum(((data | 32) >= 97) & ((data | 32) <= 122))])
            has = ascii_[offsets[1:]] > ascii_[offsets[:-1]]
            rest = np.flatnonzero(~has & (np.diff(offsets) > 0))
            for d in rest:
                has[d] = any(c.isalpha() for c in texts[int(d)].as_py())
            top = shares.argmax(1) if names else np.zeros(n, int)
            some = has & (shares.sum(1) > 0) if names else np.zeros(n, bool)
            yield pa.RecordBatch.from_arrays([
                b.column(0), pa.array([names[t] if ok else (names[0] if h and names else "und") for t, ok, h in zip(top, some, has, strict=True)], pa.string()),
                pa.array(np.where(some, np.clip(shares.max(1), 0, 1), 0.0) if names else np.zeros(n)),
                pa.array([[names[g] for g in np.flatnonzero(s > 0.02)] if ok else [] for s, ok in zip(shares, some, strict=True)], pa.list_(pa.string())),
            ], ["doc_id", "lang_pred", "score", "languages"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, schema)


def held_out() -> Column:
    return F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 4 == 2, F.lit(False))


def op9_language_mixture(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The language of every document."""
    docs = table(spark, sf_dir, "documents")
    found = predict(docs, train(docs.filter(~held_out())))
    return found.select("doc_id", held_out().alias("held_out"), "lang_pred", "score", F.array_join("languages", ",").alias("languages"))
