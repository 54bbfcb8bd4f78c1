"""Improbable-feature digests of documents (operator 1).

Every window of `window` bytes is a feature. Its empirical entropy gives a rarity rank: the farther the
entropy lies from what ordinary text shows, the lower the rank. In each run of `vote` neighbouring
features the leftmost one of lowest rank wins a vote, and features with enough votes are selected.
Selected features set bits in Bloom filters; a full filter is followed by the next of the chain. Two
digests are compared filter by filter by the overlap of their bits, normalised by what chance gives.

Defined cases: null counts as empty; an empty text has the digest ``0:``; a text shorter than a window is
one feature; equal texts have equal digests; repeated rows are kept; other columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tracedex.llm.common import U, byte_codes, flat_utf8, mix64, powers, sliding_min, slots, spans, table


@dataclass(frozen=True)
class DigestSpec:
    window: int = 32  # bytes of a feature
    vote: int = 32  # neighbouring features that elect one
    votes: int = 12  # votes that select a feature
    usual: float = 3.6  # bits a byte of ordinary windows; ranks fall with the distance from it
    bits: int = 2048  # of one Bloom filter
    probes: int = 5
    capacity: int = 160  # features a filter takes before the next is chained
    chance: float = 0.3  # share of the possible overlap above chance that still counts as none


#: Bytes of text that a part is meant to hold, and the most parts.
PART_BYTES, PARTS = 32 << 20, 20_000


def _entropies(data: np.ndarray, width: int) -> np.ndarray:
    """Entropy in 1/1024 bits of each window, kept up to date as it slides by integer steps."""
    n = len(data)
    behind, ahead = np.zeros(n, np.uint8), np.zeros(n, np.uint8)
    for d in range(1, width + 1):
        same = (data[d:] == data[:-d]).view(np.uint8) if d < n else np.zeros(0, np.uint8)
        if d < n:
            behind[d:] += same
            ahead[:-d] += same
    counts = np.arange(width + 3, dtype=np.float64)
    phi = np.rint(counts * np.log2(np.maximum(counts, 1)) * 1024).astype(np.int64)
    gain = np.append(np.diff(phi), 0)
    total = np.cumsum(gain[behind])  # exact for the first window, corrected below for what has left
    # when x[i] enters, the byte x[i-width] is still counted; it leaves with the count `ahead` saw
    total[width:] -= np.cumsum(gain[ahead[: n - width]])
    total = total[width - 1 :]
    return (np.log2(width) * 1024 - total / width).astype(np.int64)


def select_features(data: np.ndarray, offsets: np.ndarray, spec: DigestSpec) -> tuple[np.ndarray, np.ndarray]:
    """(document, hash) of the selected features in text order."""
    w, n = spec.window, len(data)
    sizes = np.diff(offsets)
    owner, hashes = [], []
    long = np.flatnonzero(sizes >= w)
    if len(long):
        rarity = _entropies(data, w)
        starts = np.arange(len(rarity))
        doc = np.searchsorted(offsets, starts, "right") - 1
        inside = starts + w <= offsets[doc + 1]
        rank = 4096 - np.minimum(np.abs(rarity - int(spec.usual * 1024)), 4095)  # low: unusual
        key = np.where(inside, (rank << 40) + starts, np.int64(1) << 60)
        won = np.zeros(len(rarity), np.int64)
        best = sliding_min(key, spec.vote)
        if len(best):
            ends = starts[: len(best)] + spec.vote - 1
            whole = inside[: len(best)] & inside[ends] & (doc[: len(best)] == doc[ends])
            np.add.at(won, best[whole] & ((1 << 40) - 1), 1)
        few = long[sizes[long] - w + 1 < spec.vote]  # fewer features than one vote takes: one vote over all
        for d in few:
            a, b = offsets[d], offsets[d + 1] - w + 1
            won[a + int(np.argmin(key[a:b]))] = spec.votes
        most = np.zeros(len(sizes), np.int64)
        at = np.flatnonzero(won)
        np.maximum.at(most, doc[at], won[at])
        at = at[won[at] >= np.minimum(spec.votes, most[doc[at]])]
        with np.errstate(over="ignore"):
            grid = byte_codes(3)[data[at[:, None] + np.arange(w)]] * powers(0x9FB21C651E98DF25, w)
            hashes.append(mix64(grid.sum(axis=1, dtype=U)))
        owner.append(doc[at])
    for d in np.flatnonzero((sizes > 0) & (sizes < w)):
        whole = hashlib.blake2b(data[offsets[d] : offsets[d + 1]].tobytes(), digest_size=8).digest()
        owner.append(np.array([d]))
        hashes.append(np.frombuffer(whole, U))
    if not owner:
        return np.zeros(0, np.int64), np.zeros(0, U)
    owner, hashes = np.concatenate(owner), np.concatenate(hashes)
    order = np.argsort(owner, kind="stable")
    return owner[order], hashes[order]


def digests(data: np.ndarray, offsets: np.ndarray, spec: DigestSpec) -> list[np.ndarray]:
    """The chained filters of each document, a (filters, bits / 8) array."""
    out: list[np.ndarray] = []
    for i, j in spans(offsets):
        owner, hashes = select_features(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i], spec)
        n = np.bincount(owner, minlength=j - i)
        first = np.concatenate([[0], np.cumsum(n)])
        filters = -(-n // spec.capacity)
        base = np.concatenate([[0], np.cumsum(filters)])
        row = base[owner] + (np.arange(len(owner)) - first[owner]) // spec.capacity
        chain = np.zeros((int(base[-1]), spec.bits), bool)
        for p in range(spec.probes):
            with np.errstate(over="ignore"):
                chain[row, (mix64(hashes + U(p * 0x632BE59BD9B4E019 % (1 << 64))) % U(spec.bits)).astype(np.int64)] = True
        packed = np.packbits(chain, axis=1)
        out += [packed[base[d] : base[d + 1]] for d in range(j - i)]
    return out


def likeness(a: np.ndarray, b: np.ndarray, spec: DigestSpec = DigestSpec()) -> float:
    """0 to 1: the mean, over the shorter chain, of the best normalised overlap with the other chain."""
    if a.shape == b.shape and (a == b).all():
        return 1.0
    if not len(a) or not len(b):
        return 0.0
    if len(a) > len(b):
        a, b = b, a
    na, nb = np.bitwise_count(a).sum(axis=1, dtype=np.int64), np.bitwise_count(b).sum(axis=1, dtype=np.int64)
    best = []
    for x, n in zip(a, na, strict=True):
        both = np.bitwise_count(b & x).sum(axis=1, dtype=np.int64)
        most, chance = np.minimum(nb, n).astype(float), nb * n / spec.bits
        floor = chance + spec.chance * (most - chance)
        best.append(float(np.max(np.clip((both - floor) / np.maximum(most - floor, 1e-9), 0, 1))))
    return float(np.mean(best))


def show(chain: np.ndarray) -> str:
    """Text form: number of filters, then their bits in base 64."""
    return f"{len(chain)}:{base64.b64encode(chain.tobytes()).decode()}"


def parse(text: str, spec: DigestSpec = DigestSpec()) -> np.ndarray:
    n, _, bits = text.partition(":")
    return np.frombuffer(base64.b64decode(bits), np.uint8).reshape(int(n), spec.bits // 8)


def fingerprint(docs: DataFrame, spec: DigestSpec = DigestSpec(), text: str = "text", out: str = "fingerprint") -> DataFrame:
    """`docs` with the digest of each text in a new column; one pass, no shuffle."""
    from pyspark.sql import types as T

    schema = T.StructType([f for f in docs.schema.fields if f.name != out] + [T.StructField(out, T.StringType())])

    def run(batches):
        for batch in batches:
            marks = [show(x) for x in digests(*flat_utf8(batch.column(text)), spec)]
            kept = [x for x in batch.schema.names if x != out]
            yield pa.RecordBatch.from_arrays([batch.column(x) for x in kept] + [pa.array(marks, pa.string())], [*kept, out])

    return docs.mapInArrow(run, schema)


def with_next(docs: DataFrame, parts: int | None = None) -> DataFrame:
    """(part, ghost, doc_id, text) sorted within partitions by part, ghost, doc_id: each part is a range of ids and ends
    with a ghost of the row that follows it, so that neighbours meet without a global sort in one task.

    Parts follow the size of the texts; cut points come from approximate quantiles of the ids, and each part is a task of its own. What
    reaches the driver is one id a part, at most `PARTS` of them."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    if parts is None:
        size = docs.agg(F.sum(F.octet_length("text")).alias("n")).collect()[0]["n"] or 0
        parts = min(PARTS, max(slots(docs.sparkSession), -(-size // PART_BYTES)))
    cuts = sorted(set(docs.approxQuantile("doc_id", [i / parts for i in range(1, parts)], 0.2 / parts))) if parts > 1 else []
    part = F.lit(0)
    if cuts:
        at = F.array(*[F.lit(int(c)) for c in cuts])
        part = F.coalesce(F.size(F.filter(at, lambda c: c < F.col("doc_id"))), F.lit(0))
    docs = docs.withColumn("part", part.cast("int"))
    lead = F.struct(F.col("doc_id").isNotNull().alias("known"), "doc_id", "text")
    ids = docs.groupBy("part").agg(F.min(F.coalesce("doc_id", F.lit(-(1 << 63)))).alias("least")).orderBy("part").collect()
    if not ids:
        return docs.select("part", F.lit(0).alias("ghost"), "doc_id", "text")
    before = {r["part"]: ids[i - 1]["part"] for i, r in enumerate(ids)}
    heads = F.create_map(*[F.lit(v) for r in ids for v in (r["part"], r["least"])])
    to = F.create_map(*[F.lit(v) for p, q in before.items() for v in (p, q)])
    firsts = docs.filter(F.coalesce("doc_id", F.lit(-(1 << 63))) == heads[F.col("part")]).groupBy("part").agg(F.min(lead).alias("x"))
    ghosts = firsts.select(to[F.col("part")].alias("part"), F.lit(1).alias("ghost"), "x.doc_id", "x.text")
    return docs.select("part", F.lit(0).alias("ghost"), "doc_id", "text").unionByName(ghosts).repartitionById(parts, "part").sortWithinPartitions("part", "ghost", "doc_id", "text")


RESULT = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"


def edit_probe(docs: DataFrame, spec: DigestSpec = DigestSpec()) -> DataFrame:
    """Each text and its edited form (last quarter replaced by the head of the next document) with their likeness."""

    def group(rows: list[tuple]) -> pa.RecordBatch:
        """rows: (doc_id, text, head of the next text, digest or None); the last is there for its digest only."""
        texts, edited = [r[1] for r in rows], []
        for (_, t, _), (_, nxt, _) in zip(rows[:-1], rows[1:], strict=True):
            k = len(t) // 4
            edited.append(t[: len(t) - k] + nxt[:k] if k else t)
        marks = digests(*flat_utf8(pa.array(texts + edited, pa.large_string())), spec)
        own, changed = marks[: len(texts)], marks[len(texts) :]
        n = len(rows) - 1
        return pa.RecordBatch.from_pydict({
            "doc_id": pa.array([r[0] for r in rows[:-1]], pa.int64()), "n_chars": pa.array([len(t) for t in texts[:-1]], pa.int64()),
            "edited_sha256": [hashlib.sha256(e.encode()).hexdigest() for e in edited],
            "fingerprint": [show(x) for x in own[:-1]], "edited_fingerprint": [show(x) for x in changed],
            "near_edited": [likeness(own[i], changed[i], spec) for i in range(n)], "near_next": [likeness(own[i], own[i + 1], spec) for i in range(n)],
        })

    def run(batches):
        held: list[tuple] = []  # rows of the current part that await their next row
        size = 0
        for batch in batches:
            for part, doc, text in zip(*(batch.column(c).to_pylist() for c in ("part", "doc_id", "text")), strict=True):
                if held and held[-1][2] != part:
                    if len(held) > 1:
                        yield group(held)
                    held, size = [], 0
                held.append((doc, text, part))
                size += len(text)
                if size > 4_000_000 and len(held) > 1:
                    yield group(held)
                    held, size = held[-1:], len(text)
        if len(held) > 1:
            yield group(held)

    return with_next(docs).mapInArrow(run, RESULT)


def op1_fingerprint_digests(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Digests of every document and of its edited form."""
    return edit_probe(table(spark, sf_dir, "documents"))
