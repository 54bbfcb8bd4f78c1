"""Exact removal of repeated byte strings by column-wise suffix ordering (operator 3).

Every window of `width` bytes has an anchor: the leftmost of the smallest hashes of its `gram`-byte strings.
Equal windows have equal anchors at equal places, so consecutive windows of one anchor form a run, and only runs
whose anchor occurs again can hold repeats; the others never leave their document. Runs are dealt out by anchor
and laid under one another with anchors in one column. Within a task the documents of that collection are
then sorted column by column from the right: each round inserts one symbol of every document in front of the
suffixes sorted so far, which keeps their order (the collection's Burrows-Wheeler order) and the common prefixes of
neighbours up to date with sequential passes. The columns of symbols lie one behind another in a scratch file, each read from front to end in its
round; order and prefixes go through a second one between two rounds. A round holds one column, not the collection. The files belong to one task, nobody
else reads them; a task that is run again makes them anew. Suffixes that share `width` symbols are one window; all but its first occurrence are marked. An
anchor with more contexts than a collection takes is sorted in turns: each turn sorts the next contexts together with those earlier ones that
brought a new window, so copies, however many, are never held.

Whole copies of a text need none of this: one of them is read, the others are removed as a whole.

Defined cases: null counts as empty; texts shorter than a window keep all bytes; of repeated rows of one doc_id the
order is by their text; a null doc_id comes first; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import os
import tempfile
from contextlib import ExitStack

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from tracedex.llm.common import byte_codes, flat_utf8, mix64, sliding_min, spans, table, window_hashes

WIDTH, GRAM = 100, 16
#: Contexts of a collection.
BATCH = 30_000
#: An anchor with more runs than this in one batch of a task is first settled there; what is sent on is one run, or those that differ.
HOT = 200


def runs(data: np.ndarray, offsets: np.ndarray, width: int = WIDTH, gram: int = GRAM) -> tuple[np.ndarray, ...]:
    """(document, anchor hash, first window, windows, bytes from first window to anchor) of all runs."""
    hashes = window_hashes(byte_codes(5)[data], gram)
    grams = width - gram + 1
    if len(hashes) < grams:
        return tuple(np.zeros(0, np.int64) for _ in range(5))
    places = np.arange(len(hashes), dtype=np.uint64)
    low = np.uint64((1 << 28) - 1)
    at = (sliding_min((hashes & ~low) | places, grams) & low).astype(np.int64)  # anchor of each window
    start = np.arange(len(at))
    doc = np.searchsorted(offsets, start, "right") - 1
    inside = start + width <= offsets[doc + 1]
    new = np.ones(len(at), bool)
    new[1:] = (at[1:] != at[:-1]) | (doc[1:] != doc[:-1]) | ~inside[:-1]
    new &= inside
    first = np.flatnonzero(new)
    # a run ends before the next run or where windows would leave the document
    last = np.minimum(np.r_[first[1:], len(at)], offsets[doc[first] + 1] - width + 1) if len(first) else first
    return doc[first], hashes[at[first]].view(np.int64), first - offsets[doc[first]], last - first, at[first] - first


class Columns:
    """The symbols of a collection by column, and its order and common prefixes, in two scratch files that are opened once."""

    def __init__(self, contexts: list[bytes], begin: np.ndarray, columns: int):
        self.n, sizes = len(contexts), np.fromiter(map(len, contexts), np.int64, len(contexts))
        step = max(1, (1 << 22) // columns)
        self.folder = tempfile.TemporaryDirectory()
        with ExitStack() as stack:
            self.of_symbols, self.of_order = (stack.enter_context(open(os.path.join(self.folder.name, name), "w+b", buffering=0)) for name in ("symbols", "order"))
            for a in range(0, self.n, step):  # blocks of documents, each behind the last one in every column
                b = min(self.n, a + step)
                flat = np.frombuffer(b"".join(contexts[a:b]), np.uint8)
                row = np.repeat(np.arange(b - a), sizes[a:b])
                column = np.arange(len(flat)) - np.repeat(np.cumsum(sizes[a:b]) - sizes[a:b], sizes[a:b]) + np.repeat(begin[a:b], sizes[a:b])
                part = np.zeros((columns, b - a), np.uint8)
                part[column, row] = flat
                for j, at, symbols in [(0, 0, part)] if b - a == self.n else [(j, a, symbols) for j, symbols in enumerate(part)]:
                    _put(self.of_symbols, j * self.n + at, symbols)
            stack.pop_all()

    def symbols(self, j: int) -> np.ndarray:
        return np.frombuffer(_get(self.of_symbols, j * self.n, self.n), np.uint8)

    def put(self, order: np.ndarray, prefix: np.ndarray) -> None:
        """In the place of the last round's: a file that is cut to nothing and filled again waits for the disk every time."""
        _put(self.of_order, 0, np.concatenate([order, prefix]).astype(np.int32))

    def get(self) -> tuple[np.ndarray, np.ndarray]:
        both = np.frombuffer(_get(self.of_order, 0, 4 * (2 * self.n + 1)), np.int32)
        return both[: self.n].astype(np.int64), both[self.n :]

    def close(self) -> None:
        self.of_symbols.close()
        self.of_order.close()
        self.folder.cleanup()


def _put(file, at: int, values: np.ndarray) -> None:
    rest = memoryview(values).cast("B")
    while len(rest):
        done = os.pwrite(file.fileno(), rest, at)
        rest, at = rest[done:], at + done


def _get(file, at: int, size: int) -> bytes:
    out = os.pread(file.fileno(), size, at)
    while len(out) < size:
        more = os.pread(file.fileno(), size - len(out), at + len(out))
        if not more:
            raise OSError("a scratch file ends too soon")
        out += more
    return out


def sort_columns(columns: Columns, present_from: np.ndarray, present_to: np.ndarray, group: np.ndarray, n_columns: int):
    """Yields (column, order, common prefixes) from the last column to the first. Documents of different groups never share a prefix."""
    n = len(group)
    columns.put(np.arange(n), np.zeros(n + 1))
    for j in range(n_columns - 1, -1, -1):
        order, prefix = columns.get()
        here = (present_from <= j) & (j < present_to)
        if not here.any():
            columns.put(order, np.zeros(n + 1))
            continue
        symbol = np.where(here, columns.symbols(j).astype(np.int64) + 1, 0)
        key = (group * 512 + symbol)[order]
        moved = np.argsort(key, kind="stable")
        key = key[moved]
        order = order[moved]
        p, q = moved[:-1], moved[1:]
        alike = (key[1:] == key[:-1]) & (key[1:] % 512 > 0)
        least = prefix[q]
        far = np.flatnonzero(alike & (q > p + 1))
        if len(far):
            cuts = np.column_stack([p[far] + 1, q[far] + 1]).ravel()
            least[far] = np.minimum.reduceat(prefix, cuts)[::2]
        prefix = np.concatenate([[0], np.where(alike, least + 1, 0), [0]]).astype(np.int32)
        columns.put(order, prefix)
        yield j, order, prefix[:n]


def mark(contexts: list[bytes], group: np.ndarray, windows: np.ndarray, ahead: np.ndarray, width: int = WIDTH, gram: int = GRAM) -> np.ndarray:
    """(context, first window, end window) of windows that an earlier context of the list holds at the same distance from the anchor.

    contexts[i] holds `windows[i]` windows, the anchor `ahead[i]` bytes after its start; equal groups are neighbours."""
    n, left = len(contexts), width - gram
    sizes = np.fromiter(map(len, contexts), np.int64, n)
    begin = left - ahead
    marked = np.zeros((n, left + 2), np.int8)  # by column, with an empty one at the end
    columns = Columns(contexts, begin, left + width)
    try:
        for j, order, prefix in sort_columns(columns, begin, begin + sizes, group, left + width):
            if j > left:
                continue
            classes = np.flatnonzero(prefix < width)
            if len(classes) == n:
                continue
            firsts = np.minimum.reduceat(order, classes)
            members = np.repeat(firsts, np.diff(np.r_[classes, n])) != order
            marked[order[members], j] = 1
    finally:
        columns.close()
    edges = np.diff(np.concatenate([np.zeros((n, 1), np.int8), marked], axis=1), axis=1)
    i, start = np.nonzero(edges == 1)
    _, end = np.nonzero(edges == -1)
    return np.column_stack([i, start - begin[i], end - begin[i]])


def _grouped(values: np.ndarray) -> tuple[np.ndarray, ...]:
    """(distinct values, place of each value among them, how often each occurs, where it first occurs)."""
    distinct, first, place, times = np.unique(values, return_index=True, return_inverse=True, return_counts=True)
    return distinct, place, times, first


RESULT = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string"


def remove_repeats(docs: DataFrame, width: int = WIDTH, gram: int = GRAM, with_text: bool = False) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 of every row; `with_text` adds what is left (bytes) and the removed spans."""
    low = F.lit(-(1 << 63))
    rows = docs.select(F.coalesce(F.col("doc_id").cast("long"), low).alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    # the one shuffle of texts; every step below that needs them reads this exchange again
    base = rows.withColumn("rn", F.row_number().over(W.partitionBy("doc_id").orderBy("text")))
    shas = base.select("doc_id", "rn", F.sha2("text", 256).alias("sha"))
    firsts = shas.groupBy("sha").agg(F.min(F.struct("doc_id", "rn")).alias("f")).select("f.doc_id", "f.rn")
    firsts = firsts.groupBy("doc_id").agg(F.collect_list("rn").alias("firsts"))
    flagged = base.join(firsts, "doc_id", "left").withColumn("first", F.coalesce(F.array_contains("firsts", F.col("rn")), F.lit(False))).drop("firsts")

    def find(batches):
        for b in batches:
            ids, rns = b.column("doc_id").to_numpy(), b.column("rn").to_numpy()
            data, offsets = flat_utf8(b.column("text"))
            for i, j in spans(offsets):
                doc, anchor, start, count, ahead = runs(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i], width, gram)
                pack = (start << 16) | (count << 8) | ahead
                # a frequent anchor is known to occur again: one of its runs goes where the anchor goes and says so, the others go anywhere
                _, place, times, first = _grouped(anchor)
                known = times[place] > HOT
                route = np.where(known & (first[place] != np.arange(len(anchor))), mix64(anchor.view(np.uint64) + np.arange(len(anchor), dtype=np.uint64)).view(np.int64), anchor)
                for k in range(0, len(doc), 100_000):
                    s = slice(k, k + 100_000)
                    yield pa.RecordBatch.from_arrays([pa.array(route[s]), pa.array(known[s]), pa.array(anchor[s], mask=(route == anchor)[s]), pa.array(ids[i + doc[s]]), pa.array(rns[i + doc[s]].astype(np.int32)), pa.array(pack[s])], ["route", "known", "anchor", "doc_id", "rn", "pack"])

    found = flagged.filter("first").select("doc_id", "rn", "text").mapInArrow(find, "route long, known boolean, anchor long, doc_id long, rn int, pack long")

    def repeated(batches):
        """Keeps runs that are known to occur again or share a route; only one row is carried from batch to batch."""
        carry, carried_again = None, False
        for b in batches:
            b = b if carry is None else pa.Table.from_batches([carry, b]).combine_chunks().to_batches()[0]
            anchor = b.column("route").to_numpy()
            same = np.zeros(len(anchor) + 1, bool)
            same[1:-1] = anchor[1:] == anchor[:-1]
            again = same[:-1] | same[1:]
            if len(again):
                again[0] |= carried_again
                again |= b.column("known").to_numpy(zero_copy_only=False)
                yield b.slice(0, len(anchor) - 1).filter(pa.array(again[:-1]))
                carry, carried_again = b.slice(len(anchor) - 1), bool(again[-1])
        if carry is not None and carried_again:
            yield carry

    again = found.repartition("route").sortWithinPartitions("route").mapInArrow(repeated, found.schema).withColumn("anchor", F.coalesce("anchor", "route"))
    per_doc = again.groupBy("doc_id").agg(F.collect_list(F.struct("rn", "pack", "anchor")).alias("runs"))

    def cut(batches):
        for b in batches:
            out = []
            for doc, rn, text, parts in zip(b.column("doc_id").to_pylist(), b.column("rn").to_pylist(), b.column("text"), b.column("runs"), strict=True):
                body, parts = text.as_buffer(), parts.values
                rns, packs, anchors = (parts.field(k).to_numpy(zero_copy_only=False) for k in range(3))
                body = body.to_pybytes()
                for r, p, a in zip(rns.tolist(), packs.tolist(), anchors.tolist(), strict=True):
                    if r == rn:
                        s = p >> 16
                        out.append((a, doc, rn, p, body[s : s + (p >> 8 & 255) + width - 1]))
                if len(out) > 50_000:
                    yield contexts_of(out)
                    out = []
            if out:
                yield contexts_of(out)

    def contexts_of(out):
        """Contexts to be dealt out by anchor. Those of a frequent anchor are settled here first: their repeats leave as marks (no
        context, dealt out anywhere), and only contexts with a window that is new here are sent on."""
        out.sort()
        anchor = np.fromiter((r[0] for r in out), np.int64, len(out))
        _, place, times, _ = _grouped(anchor)
        hot = np.flatnonzero(times[place] > HOT)
        rows = [r for r, t in zip(out, times[place].tolist(), strict=True) if t <= HOT]
        if len(hot):
            pack = np.fromiter((out[k][3] for k in hot), np.int64, len(hot))
            marks = mark([out[k][4] for k in hot], np.cumsum(np.r_[0, np.diff(place[hot]) != 0]), pack >> 8 & 255, pack & 255, width, gram)
            done = np.zeros(len(hot), np.int64)
            np.add.at(done, marks[:, 0], marks[:, 2] - marks[:, 1])
            rows += [out[hot[k]] for k in np.flatnonzero(done < (pack >> 8 & 255))]
            rows += [(hash((int(m[0]), r[1], int(m[1]))), r[1], r[2], (((r[3] >> 16) + int(m[1])) << 16) | int(m[2] - m[1]), None) for m in marks for r in (out[hot[m[0]]],)]
        kinds = (pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.binary())
        return pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*rows, strict=True), kinds, strict=True)] if rows else [pa.array([], t) for t in kinds], ["anchor", "doc_id", "rn", "pack", "context"])

    contexts = base.join(per_doc, "doc_id").mapInArrow(cut, "anchor long, doc_id long, rn int, pack long, context binary")

    def order(batches):
        held, n, old = [], 0, None  # rows to be sorted, how many, and contexts of the first one's anchor that brought a new window before
        for b in batches:
            held.append(b)
            n += len(b)
            if n < BATCH:
                continue
            whole = pa.Table.from_batches(held).combine_chunks()
            anchor = whole.column("anchor").to_numpy()
            end = int(np.searchsorted(anchor, anchor[-1], "left"))  # the last anchor may go on
            if end:
                yield from marks_of(whole.slice(0, end), old)[0]
                held, n, old = whole.slice(end).combine_chunks().to_batches(), len(whole) - end, None
            else:
                out, old = marks_of(whole, old)
                yield from out
                held, n = [], 0
        if n:
            yield from marks_of(pa.Table.from_batches(held).combine_chunks(), old)[0]

    def marks_of(rows, old):
        """(marks of the rows, contexts of the last anchor that bring a new window, the old ones among them); `old` goes before the first anchor's rows."""
        out = []
        settled = rows.filter(pc.is_null(rows.column("context")))
        if len(settled):
            pack = settled.column("pack").to_numpy()
            low = pack >> 16
            out.append(pa.RecordBatch.from_arrays([settled.column("doc_id").combine_chunks(), settled.column("rn").combine_chunks(), pa.array(low), pa.array(low + (pack & 0xFFFF) + width - 1)], ["doc_id", "rn", "low", "high"]))
        last = rows.column("anchor")[len(rows) - 1].as_py()
        rows = rows.filter(pc.is_valid(rows.column("context")))
        if old is not None and len(rows) and old.column("anchor")[0] != rows.column("anchor")[0]:
            old = None
        before = len(old) if old is not None else 0
        if not len(rows):
            return out, old
        if before:
            rows = pa.concat_tables([old, rows]).combine_chunks()
        anchor, pack = rows.column("anchor").to_numpy(), rows.column("pack").to_numpy()
        group = np.cumsum(np.r_[0, anchor[1:] != anchor[:-1]])
        marks = mark(rows.column("context").to_pylist(), group, pack >> 8 & 255, pack & 255, width, gram)
        done = np.zeros(len(rows), np.int64)
        np.add.at(done, marks[:, 0], marks[:, 2] - marks[:, 1])
        done[:before] = 0  # they brought a new window in their turn
        marks = marks[marks[:, 0] >= before]
        if len(marks):
            start = pack[marks[:, 0]] >> 16
            out.append(pa.RecordBatch.from_arrays([pa.array(rows.column("doc_id").to_numpy()[marks[:, 0]]), pa.array(rows.column("rn").to_numpy()[marks[:, 0]]), pa.array(start + marks[:, 1]), pa.array(start + marks[:, 2] + width - 1)], ["doc_id", "rn", "low", "high"]))
        return out, rows.filter(pa.array((done < (pack >> 8 & 255)) & (anchor == last)))

    marks = contexts.repartition("anchor").sortWithinPartitions("anchor", "doc_id", "rn", "pack").mapInArrow(order, "doc_id long, rn int, low long, high long")
    marks = marks.groupBy("doc_id").agg(F.collect_list(F.struct("rn", "low", "high")).alias("marks"))

    def finish(batches):
        for b in batches:
            out = []
            for doc, rn, text, first, spans_ in zip(*(b.column(c).to_pylist() for c in ("doc_id", "rn", "text", "first", "marks")), strict=True):
                body = text.encode()
                n = len(body)
                change = np.zeros(n + 1, np.int32)
                if not first and n >= width:
                    change[0] += 1
                for m in spans_ or []:
                    if m["rn"] == rn:
                        change[m["low"]] += 1
                        change[m["high"]] -= 1
                gone = np.cumsum(change[:n]) > 0
                kept = np.frombuffer(body, np.uint8)[~gone].tobytes()
                edge = np.diff(np.concatenate([[0], gone.view(np.int8), [0]]))
                row = [None if doc == -(1 << 63) else doc, n, int(gone.sum()), int((edge == 1).sum()), hashlib.sha256(kept).hexdigest()]
                out.append(row + [kept, list(zip(np.flatnonzero(edge == 1).tolist(), np.flatnonzero(edge == -1).tolist(), strict=True))] if with_text else row)
            kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string()] + ([pa.binary(), pa.list_(pa.struct([("low", pa.int64()), ("high", pa.int64())]))] if with_text else [])
            if with_text:
                out = [[*r[:6], [{"low": a, "high": z} for a, z in r[6]]] for r in out]
            names = ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept", "spans"][: len(kinds)]
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], k) for i, k in enumerate(kinds)], names)

    schema = RESULT + (", kept binary, spans array<struct<low: long, high: long>>" if with_text else "")
    return flagged.join(marks, "doc_id", "left").select("doc_id", "rn", "text", "first", "marks").mapInArrow(finish, schema)


def op3_repeated_strings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document without its repeated 100-byte strings, in figures."""
    return remove_repeats(table(spark, sf_dir, "documents"))
