"""Best-fit packing with swap-based local search (operator 5).

Documents become token ids and an end id, and only those longer than a sequence are cut. How many pieces
there are of each length is all that a packing needs: the driver gets at most `size` counts whatever the
corpus. The search begins with every piece in a bin of its own. Whole bins move first, in falling order of length, to the fullest bin with
room; then underfull bins exchange one or two items for none or one, and one for two. Every step makes a bin fuller than its
partner was, so the sum of squared fills rises throughout, until bins are empty. Equal bins are one pattern with a multiplicity and
move together, so the work follows the number of lengths and not of documents. Pieces are dealt to the places of their
length by their rank within it; ranks are counted in salted groups, so one very common length is no hot key.

Defined cases: null text counts as empty, and an empty document is its end id alone; repeated rows are
packed one by one; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import bisect
import heapq
import zlib
from collections import Counter
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from tracedex.llm.common import slices, table
from tracedex.llm.tokens import chunk_ids, word_tokenizer

Bin = tuple[int, ...]  # lengths, falling
#: The search has settled when a round empties and fills fewer than one in so many of the underfull bins.
SETTLED = 10_000


def moved(counts: dict[int, int], size: int, squares: list[int] | None = None) -> Counter:
    """The search's moves of whole bins: every piece begins in a bin of its own, and in falling order of length each bin's piece moves to the
    fullest bin with room for it, which empties its own. Pattern -> how many bins have it; bins that are alike move at once, as many as the
    receivers take. A bin never moves to an emptier one, so every move raises the sum of squared fills; `squares` collects it."""
    open_bins: dict[int, list[list]] = {}  # room left -> [pattern, multiplicity] of receivers
    rooms: list[int] = []
    done: Counter = Counter()
    square = sum(length**2 * n for length, n in counts.items())

    def put(room: int, pattern: Bin, times: int) -> None:
        if not times:
            return
        if not room:
            done[pattern] += times
            return
        if room not in open_bins:
            open_bins[room] = []
            bisect.insort(rooms, room)
        open_bins[room].append([pattern, times])

    def rise(fill: int, length: int, each: int, times: int) -> None:
        nonlocal square
        square += times * ((fill + each * length) ** 2 - fill**2 - each * length**2)
        if squares is not None and each * times:
            squares.append(square)

    for length in sorted(counts, reverse=True):
        left = counts[length]
        while left > 0:
            k = bisect.bisect_left(rooms, length)
            if k == len(rooms):  # no room elsewhere: bins of this length receive others of it
                each = size // length
                put(size - each * length, (length,) * each, left // each)
                rise(length, length, each - 1, left // each)
                if rest := left % each:
                    put(size - rest * length, (length,) * rest, 1)
                    rise(length, length, rest - 1, 1)
                break
            room = rooms[k]
            group = open_bins[room]
            pattern, times = group.pop()
            if not group:
                del open_bins[room]
                rooms.pop(k)
            each = room // length
            full = min(times, left // each)
            put(room - each * length, pattern + (length,) * each, full)
            rise(size - room, length, each, full)
            left -= full * each
            if times > full:
                rest = min(left, each)  # fewer than fill one more bin
                put(room - rest * length, pattern + (length,) * rest, 1)
                rise(size - room, length, rest, 1)
                put(room, pattern, times - full - 1)
                left -= rest
    for room, group in open_bins.items():
        for pattern, times in group:
            done[pattern] += times
    return done


@lru_cache(5000)
def _sums(pattern: Bin) -> tuple[int, int]:
    """Bit masks of the weights of one item and of two items of a bin."""
    counts = Counter(pattern)
    ones = sum(1 << a for a in counts)
    twos = 0
    for a, n in counts.items():
        twos |= (ones if n > 1 else ones ^ (1 << a)) << a
    return ones, twos


def _items(pattern: Bin, weight: int) -> Bin:
    """One or two items of a bin with this weight."""
    counts = Counter(pattern)
    if counts[weight]:
        return (weight,)
    return next((a, weight - a) for a in counts if counts[weight - a] > (a == weight - a))


class _Offers:
    """What underfull bins would take and what they have.

    capacity -> room -> (pattern, item it would give back): the capacity is the room plus the item given back, so the least capacity that
    holds a weight leaves the fullest bin, and the largest room in it takes the most. `mask` has a bit for each capacity on offer, and `has` one
    for each length that some underfull bin holds."""

    def __init__(self, size: int):
        self.size, self.mask, self.has = size, 0, 0
        self.of: dict[int, dict[int, dict[tuple[Bin, Bin], None]]] = {}
        self.holders: dict[int, dict[Bin, None]] = {}

    def add(self, pattern: Bin) -> None:
        room = self.size - sum(pattern)
        for t in (0, *set(pattern)):
            self.mask |= 1 << (room + t)
            self.of.setdefault(room + t, {}).setdefault(room, {})[pattern, (t,) if t else ()] = None
            if t:
                self.has |= 1 << t
                self.holders.setdefault(t, {})[pattern] = None

    def drop(self, pattern: Bin) -> None:
        room = self.size - sum(pattern)
        for t in (0, *set(pattern)):
            rooms = self.of[room + t]
            del rooms[room][pattern, (t,) if t else ()]
            if not rooms[room]:
                del rooms[room]
            if not rooms:
                del self.of[room + t]
                self.mask ^= 1 << (room + t)
            if t:
                del self.holders[t][pattern]
                if not self.holders[t]:
                    self.has ^= 1 << t

    def give(self, source: Bin, alone: bool) -> tuple[Bin, Bin, Bin, Bin] | None:
        """(giver, receiver, items over, items back) of the exchange that moves one or two items of `source` against none or one and leaves the
        fullest receiver; it ends fuller than the giver began."""
        ones, twos = _sums(source)
        weights = ones | twos
        for left in range(self.size - sum(source)):
            hit = (weights << left) & self.mask
            while hit:
                capacity = hit.bit_length() - 1
                for room in sorted(self.of[capacity], reverse=True):
                    if room <= left:
                        break
                    for target, back in self.of[capacity][room]:
                        if target != source or not alone:
                            return source, target, _items(source, capacity - left), back
                hit ^= 1 << capacity
        return None

    def take(self, target: Bin, alone: bool) -> tuple[Bin, Bin, Bin, Bin] | None:
        """The same, of the exchange that brings one item to `target` against two and fills it most."""
        _, twos = _sums(target)
        fill = sum(target)
        for gain in range(self.size - fill, 0, -1):
            hit = (twos << gain) & self.has
            while hit:
                item = hit.bit_length() - 1
                for source in self.holders[item]:
                    if sum(source) < fill + gain and (source != target or not alone):
                        return source, target, (item,), _items_of_two(target, item - gain)
                hit ^= 1 << item
        return None


def _items_of_two(pattern: Bin, weight: int) -> Bin:
    counts = Counter(pattern)
    return next((a, weight - a) for a in counts if counts[weight - a] > (a == weight - a))


def _without(pattern: Bin, out: Bin, more: Bin) -> Bin:
    left = list(pattern)
    for x in out:
        left.remove(x)
    return tuple(sorted([*left, *more], reverse=True))


def improve_patterns(bins: Counter, size: int, squares: list[int] | None = None) -> Counter:
    """Local search over all underfull bins, kept as patterns with multiplicities.

    A step takes the emptiest bin that can give and moves one or two of its items to the bin that they fill most, against none or one
    item of that bin, as often as both patterns have bins; where no bin can give, the fullest bins take one item against two. The receiver ends
    fuller than the giver began, so the sum of squared fills rises with every step; `squares` collects it. The search ends at the lower bound
    of bins, or when a whole round over all underfull bins empties and fills fewer than one bin in `SETTLED`."""
    bins = Counter({p: n for p, n in bins.items() if p and n})
    full = Counter({p: n for p, n in bins.items() if sum(p) == size})
    bins -= full
    total, least = sum(bins.values()), -(-sum(sum(p) * n for p, n in bins.items()) // size)
    square, offers = sum(sum(p) ** 2 * n for p, n in (bins + full).items()), _Offers(size)
    for p in bins:
        offers.add(p)
    taking, stale = False, 0
    while total > least and stale < 2:  # rounds of giving and of taking, until one of each is in vain
        before = total, sum(full.values())
        bins = +bins
        waiting = [(-sum(p) if taking else sum(p), p) for p in bins]
        heapq.heapify(waiting)
        while waiting and total > least:
            order, p = heapq.heappop(waiting)
            if not bins[p]:
                continue
            step = (offers.take if taking else offers.give)(p, bins[p] == 1)
            if step is None:
                continue
            source, target, out, back = step
            times = min(bins[source], bins[target]) if target != source else bins[source] // 2
            rest, filled = _without(source, out, back), _without(target, back, out)
            square += times * (sum(rest) ** 2 + sum(filled) ** 2 - sum(source) ** 2 - sum(target) ** 2)
            if squares is not None:
                squares.append(square)
            bins[source] -= times
            bins[target] -= times
            for q in {source, target}:
                if not bins[q]:
                    offers.drop(q)
            total -= times * (not rest)
            for q in (rest, filled):
                if sum(q) == size:
                    full[q] += times
                    total, least = total - times, least - times
                elif q:
                    if not bins[q]:  # it has its turn in the next round
                        offers.add(q)
                    bins[q] += times
            if bins[p]:
                heapq.heappush(waiting, (order, p))
        gain = before[0] - total + 2 * (sum(full.values()) - before[1])  # a filled bin leaves the total as well
        if gain * SETTLED > before[0]:
            stale = 0
        else:
            taking, stale = not taking, stale + 1
    return +bins + full


def improve(bins: list[list[int]], size: int) -> list[list[int]]:
    """`improve_patterns` on single bins."""
    better = improve_patterns(Counter(tuple(sorted(b, reverse=True)) for b in bins), size)
    return [list(p) for p in better.elements()]


def plan(counts: dict[int, int], size: int) -> list[tuple[Bin, int]]:
    """Patterns with multiplicities."""
    return sorted((p, n) for p, n in improve_patterns(moved(counts, size), size).items() if n)


def places(patterns: list[tuple[Bin, int]]) -> list[tuple[int, int, int, int, int, int]]:
    """(length, first rank, end rank, first bin, items of the length a bin, their first offset)."""
    out, ranks, first = [], Counter(), 0
    for pattern, times in patterns:
        at = 0
        for length, each in sorted(Counter(pattern).items(), reverse=True):
            out.append((length, ranks[length], ranks[length] + times * each, first, each, at))
            ranks[length] += times * each
            at += each * length
        first += times
    return out


def cut(docs: DataFrame, size: int = 4096, path: str | None = None, end_id: int = 1) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32 of every piece."""
    path = path or word_tokenizer()

    def run(batches):
        chunks = chunk_ids(path)
        end = np.array([end_id], "<u4").tobytes()
        for batch in slices(batches, 1):
            rows = []
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                ids = chunks.ids(text.as_py()) + end
                for piece, at in enumerate(range(0, len(ids), 4 * size)):
                    part = ids[at : at + 4 * size]
                    rows.append((doc, piece, at // 4, len(part) // 4, zlib.crc32(part)))
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate((pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()))], ["doc_id", "piece", "start", "length", "ids_crc32"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, piece int, start long, length long, ids_crc32 long")


def pack(docs: DataFrame, size: int = 4096, path: str | None = None, salts: int = 64) -> DataFrame:
    """Pieces with their sequence_id and offset. Tokenised once: the pieces (a few numbers each) are checkpointed."""
    pieces = cut(docs, size, path).withColumn("salt", F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32"), F.lit(salts)).cast("int")).checkpoint()
    groups = pieces.groupBy("length", "salt").agg(F.count("*").alias("n"))
    counts = {r["length"]: r["n"] for r in groups.groupBy("length").agg(F.sum("n").alias("n")).collect()}  # at most `size` rows
    spots = places(plan(counts, size))
    spark = docs.sparkSession
    # as an Arrow table: from a list of rows each executor would start Python workers of another kind
    spots = spark.createDataFrame(pa.table({c: pa.array([s[i] for s in spots], pa.int64()) for i, c in enumerate(("length", "low", "high", "bin", "each", "at"))}))
    before = F.coalesce(F.sum("n").over(W.partitionBy("length").orderBy("salt").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    groups = groups.select("length", "salt", before.alias("before"))
    rank = F.row_number().over(W.partitionBy("length", "salt").orderBy("doc_id", "piece", "ids_crc32")) - 1
    ranked = pieces.withColumn("rank", rank).join(groups, ["length", "salt"]).withColumn("rank", F.col("rank") + F.col("before"))
    # the plan has a few rows a length and never more than the steps of best fit, whatever the corpus
    found = ranked.join(F.broadcast(spots), (ranked["length"] == spots["length"]) & (F.col("rank") >= F.col("low")) & (F.col("rank") < F.col("high")))
    turn = F.col("rank") - F.col("low")
    return found.select(
        "doc_id", "piece", "start", ranked["length"], "ids_crc32",
        (F.col("bin") + F.expr("(rank - low) div each")).alias("sequence_id"), (F.col("at") + turn % F.col("each") * ranked["length"]).alias("offset"),
    )


def op5_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document's pieces in sequences of at most 4096 ids."""
    return pack(table(spark, sf_dir, "documents"))
