"""Benchmark decontamination by a prefix-filtered set join (operator 7); DataFrame functions only.

A window is `size` consecutive words of an item. A document that holds a window holds its rarest word, so the
words of documents are joined with one necessary word a window, chosen by counts over the whole corpus.
The word's place gives where the window would start, which must lie inside the document (positional and
length bounds). Each place travels with the words around it, so candidates are compared word by word at once and
no text is ever shuffled; verified hits meet by document, so a passage that a third of all documents share is no hot key.

Defined cases: null text has no words; documents without words are clean; null items and items without words
match nothing; repeated rows get equal reports; equal items each count; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from tracedex.llm.common import table

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
BREAKS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
#: A benchmark of more windows than this is joined by a shuffle instead of a broadcast; a hashed set of its prefix words, of fixed size, goes before.
BROADCAST_WINDOWS = 200_000
FILTER_BITS = 1 << 23
#: Parts that the places of one word are dealt to in that join.
SALTS = 16


def words(text: Column) -> Column:
    """Lower-cased runs of ASCII letters, digits and non-ASCII characters."""
    return F.filter(F.split(F.translate(F.coalesce(text, F.lit("")), UPPER, LOWER), BREAKS), lambda w: w != "")


def windows(items: DataFrame, size: int) -> DataFrame:
    """window, item_id, length, body (words joined by blanks), word, at: one row for each word of a window."""
    cut = items.select(F.col("item_id").cast("string").alias("item_id"), words(F.col("text").cast("string")).alias("w")).filter("size(w) > 0")
    starts = F.sequence(F.lit(1), F.greatest(F.size("w") - (size - 1), F.lit(1)))
    each = cut.select("item_id", F.explode(F.transform(starts, lambda s: F.slice("w", s, size))).alias("w"))
    each = each.groupBy("w").agg(F.array_sort(F.collect_set("item_id")).alias("items"))  # equal windows once
    body = F.array_join("w", " ")
    return each.select(F.xxhash64(body).alias("window"), "items", F.size("w").alias("length"), body.alias("body"), F.posexplode("w").alias("at", "word"))


def _hashed_set(words_: DataFrame) -> Callable[[Column], Column]:
    """A test that every given word passes and hardly another: bits of word hashes, at most `FILTER_BITS` of them, in a literal."""
    bit = F.pmod(F.xxhash64("word"), F.lit(FILTER_BITS))
    rows = words_.select(bit.alias("h")).groupBy(F.expr("h div 32768").alias("at")).agg(F.bitmap_construct_agg(F.expr("h % 32768")).alias("bits")).collect()  # 4 KB for each 32,768 bits
    held = bytearray(FILTER_BITS // 8)
    for r in rows:
        held[r["at"] * 4096 : (r["at"] + 1) * 4096] = r["bits"]
    literal = F.lit(bytes(held))

    def test(word: Column) -> Column:
        h = F.pmod(F.xxhash64(word), F.lit(FILTER_BITS))
        byte = F.conv(F.hex(F.substring(literal, F.floor(h / 8).cast("int") + 1, F.lit(1))), 16, 10).cast("int")
        return F.getbit(byte, (h % 8).cast("int")) == 1

    return test


NO_ID = -(1 << 63)


def _keyed(docs: DataFrame) -> list[Column]:
    """A row's key: repeated rows share it and have equal reports."""
    return [F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID)).alias("_id"), F.xxhash64(F.col("text").cast("string")).alias("_hash")]


def _found(docs: DataFrame, items: DataFrame, size: int) -> DataFrame:
    """_id, _hash, times (rows with this key), n_words, n_hit, items (sorted ids)."""
    token = windows(items, size)
    few = token.select("window").distinct().count() <= BROADCAST_WINDOWS
    small = F.broadcast if few else (lambda x: x)
    spread = docs.select(*_keyed(docs), words(F.col("text").cast("string")).alias("w"))
    vocabulary = token.select("word").distinct()
    counts = spread.select(F.explode("w").alias("word")).join(small(vocabulary), "word").groupBy("word").agg(F.count("*").alias("n"))
    rarest = F.row_number().over(W.partitionBy("window").orderBy("n", "at"))
    # a window with a word that no document has cannot occur and needs no prefix
    whole = F.count("n").over(W.partitionBy("window")) == F.col("length")
    prefix = token.join(small(counts), "word", "left").withColumn("whole", whole).filter("whole").withColumn("k", rarest).filter("k = 1").select("word", "at", "length", "body", "items")
    prefix = prefix.checkpoint()  # no larger than the benchmark, and used twice: the corpus is counted once
    at = F.sequence(F.lit(1), F.size("w"))
    if few:
        rare = [r["word"] for r in prefix.select("word").distinct().collect()]
        at = F.filter(at, lambda i: F.element_at("w", i).isin(rare)) if rare else F.array().cast("array<int>")
    else:
        known = _hashed_set(prefix)
        at = F.filter(at, lambda i: known(F.element_at("w", i)))
    at = F.when(F.size("w") > 0, at)
    # each place of a prefix word with the words around it, as far as a window can reach
    near = F.transform(at, lambda i: F.struct(i.alias("i"), F.element_at("w", i).alias("word"), F.slice("w", F.greatest(i - (size - 1), F.lit(1)), 2 * size - 1).alias("around")))
    placed = spread.select("_id", "_hash", F.size("w").alias("n_words"), F.explode(near).alias("c")).select("_id", "_hash", "n_words", "c.i", "c.word", "c.around")
    start = F.col("i") - F.col("at")  # from 1
    fits = (start >= 1) & (start + F.col("length") - 1 <= F.col("n_words"))
    same = F.array_join(F.slice("around", start - F.greatest(F.col("i") - (size - 1), F.lit(1)) + 1, F.col("length")), " ") == F.col("body")
    if few:
        met = placed.join(F.broadcast(prefix), "word")
    else:  # a word that very many documents hold meets its windows in several tasks
        salted = prefix.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        met = placed.withColumn("salt", F.pmod(F.xxhash64("_id", "_hash", "i"), F.lit(SALTS)).cast("int")).join(salted, ["word", "salt"])
    hits = met.filter(fits).filter(same).select("_id", "_hash", start.cast("int").alias("start"), "length", "items")
    covered = hits.groupBy("_id", "_hash").agg(F.collect_set(F.struct("start", "length", "items")).alias("h"))
    n_hit = F.size(F.array_distinct(F.flatten(F.transform("h", lambda h: F.sequence(h["start"], h["start"] + h["length"] - 1)))))
    names = F.array_sort(F.array_distinct(F.flatten(F.transform("h", lambda h: h["items"]))))
    rows = spread.groupBy("_id", "_hash").agg(F.count("*").alias("times"), F.max(F.size("w")).cast("long").alias("n_words"))
    both = rows.join(covered.select("_id", "_hash", n_hit.cast("long").alias("n_hit"), names.alias("items")), ["_id", "_hash"], "left")
    return both.select("_id", "_hash", "times", "n_words", F.coalesce("n_hit", F.lit(0)).cast("long").alias("n_hit"), F.coalesce("items", F.array().cast("array<string>")).alias("items"))


def _bad(share: int) -> Column:
    return (F.col("n_hit") > 0) & (F.lit(share) * F.col("n_hit") >= F.col("n_words"))


def report(docs: DataFrame, items: DataFrame, size: int = 13, share: int = 20) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items_sha256, contaminated of every row."""
    found = _found(docs, items, size).withColumn("_", F.explode(F.sequence(F.lit(1).cast("long"), F.col("times"))))
    doc_id = F.when(F.col("_id") != NO_ID, F.col("_id")).alias("doc_id")
    return found.select(doc_id, "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), _bad(share).alias("contaminated"))


def clean(docs: DataFrame, items: DataFrame, size: int = 13, share: int = 20) -> DataFrame:
    """`docs` without the contaminated rows, columns as they were."""
    bad = _found(docs, items, size).filter(_bad(share)).select("_id", "_hash")
    row = docs.select(F.struct(*docs.columns).alias("row"), *_keyed(docs))
    return row.join(bad, ["_id", "_hash"], "left_anti").select("row.*")


def op7_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The report of every document against every benchmark item."""
    return report(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


ORACLE = r"""
WITH d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
b AS (SELECT CAST(item_id AS VARCHAR) AS item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
bw AS (SELECT DISTINCT item_id, least(len(w), 13) AS n, array_to_string(w[s:s + least(len(w), 13) - 1], ' ') AS body FROM (SELECT item_id, w, unnest(range(1, greatest(len(w) - 11, 2))) AS s FROM b WHERE len(w) > 0)),
lens AS (SELECT DISTINCT n FROM bw),
dw AS (SELECT doc_id, s, n, array_to_string(w[s:s + n - 1], ' ') AS body FROM (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS s FROM d, lens WHERE len(w) >= n)),
hit AS (SELECT doc_id, s, dw.n, item_id FROM dw JOIN bw ON dw.n = bw.n AND dw.body = bw.body),
pos AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(s, s + n)) AS p FROM hit) GROUP BY doc_id),
its AS (SELECT doc_id, count(*) AS n_items, string_agg(item_id, ',' ORDER BY item_id) AS ids FROM (SELECT DISTINCT doc_id, item_id FROM hit) GROUP BY doc_id)
SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items, sha256(coalesce(ids, '')) AS items_sha256,
       coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(w) AS contaminated
FROM d LEFT JOIN pos USING (doc_id) LEFT JOIN its USING (doc_id)
"""
