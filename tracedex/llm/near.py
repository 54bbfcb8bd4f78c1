"""N-gram Jaccard join by MinHash banding (operator 4).

Documents with one set of word n-grams form a class with one representative, whatever their ids. Representatives get banded
MinHash signatures, with bands and rows chosen so that a pair at the threshold is missed with a stated
probability. Each representative belongs to the region of the least one that it reaches through two buckets, and regions are cut into blocks. Two blocks are
compared if some bucket has members of both, so work follows the buckets and not the components that weak hits would chain together. A task
holds the full n-gram sets of two blocks, verifies every pair of them exactly, and emits one row a member (links counted,
and one edge to a linked member each block), never one row a pair. Connected components of the verified
edges are the near-duplicate classes.

Defined cases: null and empty texts link to nothing; a text of fewer words than an n-gram is one n-gram; a text
without words has itself as its only n-gram; repeated rows are copies of each other, and rows that share an id or have none but differ in text are
rows of their own; a class without any id has none; other columns are ignored.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from tracedex.llm.common import U, flat_utf8, mix64, slices, slots, table, words_of

WORDS, THRESHOLD = 5, 0.8
#: Chance that a pair exactly at the threshold shares no band.
MISS = 1e-4
BLOCK = 512  # representatives of a block
BLOCK_GRAMS = 1 << 19  # n-grams of a block


def bands_for(threshold: float, miss: float = MISS, rows: int = 4) -> tuple[int, int]:
    """(bands, rows): as many bands as the recall asks for."""
    return max(1, math.ceil(math.log(miss) / math.log(1 - threshold**rows))), rows


def shingles(data: np.ndarray, offsets: np.ndarray, n: int = WORDS) -> tuple[np.ndarray, np.ndarray]:
    """(document, hash) of the distinct n-grams of each document, sorted."""
    hashes, start, doc = words_of(data, offsets)
    count = np.bincount(doc, minlength=len(offsets) - 1)
    own, value = [], []
    with np.errstate(over="ignore"):
        if len(hashes) >= n:
            grams = np.zeros(len(hashes) - n + 1, U)
            for k in range(n):
                grams = grams * U(0x9E3779B97F4A7C15) + hashes[k : len(hashes) - n + 1 + k]
            inside = doc[: len(grams)] == doc[n - 1 :]
            own.append(doc[: len(grams)][inside])
            value.append(mix64(grams[inside]))
        first = np.concatenate([[0], np.cumsum(count)])
        for d in np.flatnonzero((count < n) & (np.diff(offsets) > 0)):
            if count[d]:
                few = hashes[first[d] : first[d + 1]]
                gram = U(len(few))
                for h in few:
                    gram = gram * U(0x9E3779B97F4A7C15) + h
            else:
                gram = mix64(np.frombuffer(data[offsets[d] : offsets[d + 1]].tobytes().ljust(-(-int(offsets[d + 1] - offsets[d]) // 8) * 8, b"\0"), U)).sum(dtype=U) + U(offsets[d + 1] - offsets[d])
            own.append(np.array([d]))
            value.append(mix64(np.array([gram], U)))
    if not own:
        return np.zeros(0, np.int64), np.zeros(0, U)
    own, value = np.concatenate(own), np.concatenate(value)
    order = np.lexsort((value, own))
    own, value = own[order], value[order]
    new = np.ones(len(own), bool)
    new[1:] = (own[1:] != own[:-1]) | (value[1:] != value[:-1])
    return own[new], value[new]


def signatures(own: np.ndarray, value: np.ndarray, bands: int, rows: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(documents with n-grams, 128-bit set hashes, band hashes) — one multiply and one shift a permutation and n-gram."""
    first = np.flatnonzero(np.r_[True, own[1:] != own[:-1]]) if len(own) else np.zeros(0, np.int64)
    with np.errstate(over="ignore"):
        if not len(first):
            return first, np.zeros((0, 2), U), np.zeros((0, bands), U)
        whole = np.column_stack([mix64(np.add.reduceat(mix64(value + U(77 * k)), first) ^ np.add.reduceat(mix64(value ^ U(0xABCDEF123 * k)), first) * U(0x9E3779B97F4A7C15)) for k in (1, 2)])
        seeds = mix64(np.arange(1, bands * rows + 1, dtype=U)) | U(1)
        keys = np.empty((len(first), bands), U)
        for b in range(bands):
            h = np.full(len(first), U(b + 1))
            for r in range(rows):
                least = np.minimum.reduceat((value ^ (seeds[b * rows + r] << U(7))) * seeds[b * rows + r], first)
                h = mix64(h * U(0xD6E8FEB86659FD93) + least)
            keys[:, b] = h
    return own[first], whole, keys


def _signed(x: np.ndarray) -> np.ndarray:
    return x.view(np.int64) if x.dtype == U else x


def components(edges: DataFrame) -> DataFrame:
    """(node, root) of the connected components of `edges` (a, b): each round every node and its label learn the least label among
    neighbours, then labels jump to their own label, until nothing changes. Only counts reach the driver."""
    both = edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct().checkpoint()
    labels = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("root")).select(F.col("a").alias("node"), "root").checkpoint()
    while True:
        near = both.join(labels, both["b"] == labels["node"]).groupBy("a").agg(F.min("root").alias("least"))
        hooked = labels.join(near, labels["node"] == near["a"]).select("node", "root", F.least("root", "least").alias("least"))
        # the least label that any node of a component has seen is offered to the component's label
        offers = hooked.groupBy(F.col("root").alias("of")).agg(F.min("least").alias("offer"))
        merged = hooked.join(offers, hooked["root"] == offers["of"]).select("node", "root", F.least("least", "offer").alias("new"))
        jump = merged.select(F.col("node").alias("of"), F.col("new").alias("jump"))
        step = merged.join(jump, merged["new"] == jump["of"], "left").select("node", F.least("new", F.coalesce("jump", "new")).alias("new_root"), "root").checkpoint()
        changed = step.filter("new_root != root").limit(1).count()
        labels = step.select("node", F.col("new_root").alias("root"))
        if not changed:
            return labels


def _marked(docs: DataFrame) -> DataFrame:
    """bare (no id), id and mark (hash of the text) of each row, which stand for a row and its copies, and the text."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    return docs.select(F.col("doc_id").isNull().alias("bare"), F.coalesce(F.col("doc_id").cast("long"), F.lit(0)).alias("id"), F.sha2(text, 256).alias("mark"), text.alias("text")).filter("text != ''")


def signed_batches(batches, bands: int, rows: int, words: int):
    """What `signed_docs` makes of Arrow batches of marked rows."""
    for b in slices(batches, "text"):
        own, value = shingles(*flat_utf8(pa.array([t.lower() for t in b.column("text").to_pylist()], pa.large_string())), words)
        at, whole, keys = signatures(own, value, bands, rows)
        n = np.bincount(own, minlength=len(b))[at] if len(at) else at
        flat, take = pa.array(_signed(keys.reshape(-1))), pa.array(at)
        yield pa.RecordBatch.from_arrays([
            *(b.column(c).take(take) for c in ("bare", "id", "mark")), *(pa.array(_signed(np.ascontiguousarray(whole[:, k]))) for k in (0, 1)), pa.array(n.astype(np.int64)),
            pa.ListArray.from_arrays(pa.array(np.arange(len(at) + 1, dtype=np.int32) * bands), flat),
        ], ["bare", "id", "mark", "set_a", "set_b", "n_grams", "keys"])


def signed_docs(docs: DataFrame, threshold: float, words: int) -> DataFrame:
    """bare, id, mark, set_a and set_b (hash of the n-gram set), n_grams, keys (band hashes) of the rows with a text."""
    bands, rows = bands_for(threshold)

    def run(batches):
        return signed_batches(batches, bands, rows, words)

    return _marked(docs).mapInArrow(run, "bare boolean, id long, mark string, set_a long, set_b long, n_grams long, keys array<long>")


def verify_pairs(members: DataFrame, threshold: float, words: int, parts: int) -> DataFrame:
    """members: i, j (blocks compared, i = j for one with itself), block (the member's own), rep, weight, text. Out: rep, links (weights of
    linked representatives), edge (one linked representative), a row for each member and pair of blocks that has links."""
    dealt = members.repartition(parts, "i", "j").sortWithinPartitions("i", "j", "block", "rep")

    def batch_of(rows):
        return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], pa.int64()) for i in range(3)], ["rep", "links", "edge"])

    def run(batches):
        held, at, out = [], None, []
        for b in slices(batches, "text"):
            for i, j, block, rep, weight, text in zip(*(b.column(c).to_pylist() for c in ("i", "j", "block", "rep", "weight", "text")), strict=True):
                if at != (i, j):
                    if held:
                        out += _block(held, at[0] != at[1], threshold, words)
                    held, at = [], (i, j)
                    if len(out) > 20_000:
                        yield batch_of(out)
                        out = []
                held.append((block, rep, weight, text))
        if held:
            out += _block(held, at[0] != at[1], threshold, words)
        if out:
            yield batch_of(out)

    return dealt.mapInArrow(run, "rep long, links long, edge long")


def _block(rows: list[tuple], crossed: bool, threshold: float, words: int) -> list[tuple]:
    """Exact Jaccard of all pairs of one block, or across two."""
    n = len(rows)
    block = np.array([r[0] for r in rows])
    if n < 2 or crossed and (block == block[0]).all():
        return []
    rep, weight = np.array([r[1] for r in rows]), np.array([r[2] for r in rows])
    own, value = shingles(*flat_utf8(pa.array([r[3].lower() for r in rows], pa.large_string())), words)
    size = np.bincount(own, minlength=n)
    codes, place, count = np.unique(value, return_inverse=True, return_counts=True)
    shared = count[place] > 1
    own, place = own[shared], np.unique(place[shared], return_inverse=True)[1]
    both = np.zeros((n, n), np.float32)
    for low in range(0, int(place.max()) + 1 if len(place) else 0, 4096):
        some = (place >= low) & (place < low + 4096)
        grid = np.zeros((n, 4096), np.float32)
        grid[own[some], place[some] - low] = 1
        both += grid @ grid.T
    linked = both >= threshold * (size[:, None] + size[None, :] - both) - 1e-6
    np.fill_diagonal(linked, False)
    if crossed:
        linked &= block[:, None] != block[None, :]
    total = linked @ weight
    return [(int(rep[i]), int(total[i]), int(rep[int(np.argmax(linked[i]))])) for i in np.flatnonzero(linked.any(1))] + _joins(linked, rep)


def _joins(linked: np.ndarray, rep: np.ndarray) -> list[tuple]:
    """Edges of a spanning forest, so that first links alone never leave a component of the block apart."""
    n, seen, out = len(rep), np.zeros(len(rep), bool), []
    for s in range(n):
        if seen[s]:
            continue
        seen[s], todo = True, [s]
        while todo:
            i = todo.pop()
            new = np.flatnonzero(linked[i] & ~seen)
            seen[new] = True
            out += [(int(rep[i]), 0, int(rep[k])) for k in new]
            todo += new.tolist()
    return out


def blocked_pairs(sets: DataFrame) -> DataFrame:
    """sets: rep, n_grams, keys. Out: i, j, block, rep: every member of the blocks i and j, for all blocks that share a bucket."""
    keyed = sets.select("rep", F.posexplode("keys").alias("band", "key"))
    buckets = keyed.groupBy("band", "key").agg(F.count("*").alias("n"), F.min("rep").alias("least")).filter("n > 1").drop("n")
    shared = keyed.join(buckets, ["band", "key"])
    # the region of a representative: the least one that it reaches through two buckets
    one = shared.groupBy("rep").agg(F.min("least").alias("one"))
    further = shared.select("rep", "band", "key").join(one, "rep").groupBy("band", "key").agg(F.min("one").alias("two"))
    region = shared.select("rep", "band", "key").join(further, ["band", "key"]).groupBy("rep").agg(F.min("two").alias("region")).join(sets.select("rep", "n_grams"), "rep")
    sizes = region.groupBy("region").agg(F.ceil(F.greatest(F.count("*") / BLOCK, F.sum("n_grams") / BLOCK_GRAMS)).alias("blocks"))
    blocks = region.join(sizes, "region").select("rep", F.xxhash64("region", F.pmod(F.xxhash64("rep"), F.col("blocks"))).alias("block")).checkpoint()
    met = shared.select("rep", "band", "key").join(blocks, "rep").select("band", "key", "block").distinct()
    other = met.withColumnRenamed("block", "j")
    across = met.withColumnRenamed("block", "i").join(other, ["band", "key"]).filter("i < j").select("i", "j").distinct()
    within = blocks.groupBy("block").agg(F.count("*").alias("n")).filter("n > 1").select(F.col("block").alias("i"), F.col("block").alias("j"))
    sides = across.select("i", "j", F.explode(F.array("i", "j")).alias("block")).unionByName(within.withColumn("block", F.col("i")))
    return sides.join(blocks, "block")


def _classes(signed: DataFrame, docs: DataFrame, threshold: float, words: int) -> DataFrame:
    """rep, set_a, set_b, weight (rows), head (first row), least (least id), root (its near-duplicate class), links of every n-gram set."""
    head = F.min(F.struct("bare", "id", "mark")).alias("head")
    sets = signed.groupBy("set_a", "set_b").agg(head, F.count("*").alias("weight"), F.min(F.when(~F.col("bare"), F.col("id"))).alias("least"), F.first("n_grams").alias("n_grams"), F.first("keys").alias("keys"))
    sets = sets.withColumn("rep", F.monotonically_increasing_id()).checkpoint()  # numbered once and for all
    dealt = blocked_pairs(sets.select("rep", "n_grams", "keys"))
    wanted = dealt.select("rep").distinct().join(sets.select("rep", "head.*"), "rep")
    text = _marked(docs).join(wanted, ["bare", "id", "mark"]).groupBy("rep").agg(F.any_value("text").alias("text"))  # repeated rows hold the same
    members = dealt.join(sets.select("rep", "weight"), "rep").join(text, "rep").select("i", "j", "block", "rep", "weight", "text")
    verified = verify_pairs(members, threshold, words, slots(docs.sparkSession)).checkpoint()
    roots = components(verified.select(F.col("rep").alias("a"), F.col("edge").alias("b")))
    links = verified.groupBy("rep").agg(F.sum("links").alias("links"))
    linked = sets.drop("keys", "n_grams").join(roots.select(F.col("node").alias("rep"), "root"), "rep", "left").join(links, "rep", "left")
    return linked.withColumn("root", F.coalesce("root", "rep")).withColumn("links", F.coalesce("links", F.lit(0)))


def near_classes(docs: DataFrame, threshold: float = THRESHOLD, words: int = WORDS) -> DataFrame:
    """doc_id, class_id (least doc_id of its near-duplicate class), copy_of (least doc_id with the same n-grams), n_links (other documents whose
    n-gram Jaccard similarity is at least the threshold). A row for each document."""
    signed = signed_docs(docs, threshold, words).checkpoint()
    classes = _classes(signed, docs, threshold, words)
    ids = classes.groupBy("root").agg(F.min("least").alias("class_id"))
    by_set = classes.join(ids, "root").select("set_a", "set_b", "class_id", F.col("least").alias("copy_of"), (F.col("links") + F.col("weight") - 1).alias("n_links"))
    found = signed.select("bare", "id", "set_a", "set_b").join(by_set, ["set_a", "set_b"])
    found = found.select(F.when(~F.col("bare"), F.col("id")).alias("doc_id"), "class_id", "copy_of", "n_links")
    empty = docs.filter(F.coalesce(F.col("text").cast("string"), F.lit("")) == "").select(F.col("doc_id").cast("long").alias("doc_id"))
    return found.unionByName(empty.select("doc_id", F.col("doc_id").alias("class_id"), F.col("doc_id").alias("copy_of"), F.lit(0).cast("long").alias("n_links")))


def keep_one(docs: DataFrame, threshold: float = THRESHOLD, words: int = WORDS) -> DataFrame:
    """`docs` with one row of each near-duplicate class, the one of least id (rows without an id last; of rows equal in id and text, one), and all rows
    without text."""
    classes = _classes(signed_docs(docs, threshold, words).checkpoint(), docs, threshold, words)
    kept = classes.groupBy("root").agg(F.min("head").alias("head")).select(F.col("head.bare").alias("_bare"), F.col("head.id").alias("_id"), F.col("head.mark").alias("_mark"))
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    plain = [F.col(f.name) for f in docs.schema.fields if "map" not in f.dataType.simpleString()]
    keyed = docs.select(F.struct(*docs.columns).alias("_row"), F.xxhash64(*plain).alias("_tie"), F.col("doc_id").isNull().alias("_bare"), F.coalesce(F.col("doc_id").cast("long"), F.lit(0)).alias("_id"), F.sha2(text, 256).alias("_mark"), (text == "").alias("_empty"))
    key = ["_bare", "_id", "_mark"]
    one = keyed.filter("not _empty").join(kept, key).withColumn("_n", F.row_number().over(W.partitionBy(*key).orderBy("_tie"))).filter("_n = 1")
    return one.select("_row.*").unionByName(docs.filter(text == ""))


def op4_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Class and number of links of every document."""
    return near_classes(table(spark, sf_dir, "documents"))
