"""Training-order materialisation of token ids (operator 8).

Documents become ids and an end id. Buckets of documents, by a hash of id and text, are laid end to end in the order of their ids and cut into
sequences of `stride` ids (the last of a bucket is padded), so neither files nor partitions of the input change a sequence. Sequences get dense
numbers, a keyed Feistel network with cycle-walking permutes the numbers, and each sequence's image is its global slot. Slots are dense,
so the range of slots of every shard is known by arithmetic: a shard file holds `per_shard` consecutive slots, uncompressed, as records of
one stride: the ids, 16 bits each, and a line feed. Slot s lies in shard s div per_shard at byte (s mod per_shard) * (2 * stride + 1);
any range can be read in order, and reading can resume at any slot. An index of JSON lines beside the shards has each slot (s), its number of ids (n), their checksum (c) and its documents (d).

Defined cases: null text counts as empty and gives its end id alone; an empty table writes no shard;
repeated rows each appear; other columns are ignored.
"""

from __future__ import annotations

import uuid
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from tracedex.llm.common import U, mix64, table
from tracedex.llm.tokens import chunk_ids, word_tokenizer


def permute(index: np.ndarray, n: int, key: int, rounds: int = 6) -> np.ndarray:
    """A keyed bijection of 0..n-1: a balanced Feistel network on the next even power of two, walked until inside."""
    if n <= 1:
        return np.zeros(len(index), np.int64)
    half = max(1, ((n - 1).bit_length() + 1) // 2)
    mask = U((1 << half) - 1)
    keys = mix64(np.arange(1, rounds + 1, dtype=U) * U(0x9E3779B97F4A7C15) + U(key % (1 << 64)))
    x = index.astype(U)
    todo = np.arange(len(x))
    while len(todo):
        y = x[todo]
        left, right = y >> U(half), y & mask
        for k in keys:
            with np.errstate(over="ignore"):
                left, right = right, left ^ (mix64(right + k) & mask)
        y = (left << U(half)) | right
        x[todo] = y
        todo = todo[y >= U(n)]
    return x.astype(np.int64)


def tokenised(docs: DataFrame, path: str, end_id: int = 1) -> DataFrame:
    """bucket key, doc_id and ids (little-endian 16-bit, compressed) of every row."""

    def run(batches):
        import zstandard

        chunks, end, pack = chunk_ids(path, "<u2"), np.array([end_id], "<u2").tobytes(), zstandard.ZstdCompressor(level=6, write_content_size=True).compress
        for batch in batches:
            sizes, bodies = [], []
            for text in batch.column(2):
                ids = chunks.ids(text.as_py()) + end
                sizes.append(len(ids) // 2)
                bodies.append(pack(ids))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(sizes, pa.int64()), pa.array(bodies, pa.binary())], ["bucket", "doc_id", "n", "ids"])

    return docs.mapInArrow(run, "bucket int, doc_id long, n long, ids binary")


def _cut(stride: int, pad_id: int, key: int):
    """Rows in the order of the stream -> slot, n_ids, ids_crc32, doc_ids, ids (compressed) of every sequence of a bucket."""

    def run(batches):
        import zstandard

        pack, unpack = zstandard.ZstdCompressor(level=6, write_content_size=True).compress, zstandard.ZstdDecompressor().decompress
        width, pad = 2 * stride, np.full(stride, pad_id, "<u2").tobytes()
        at, held, owners, local = None, bytearray(), [], 0  # (bucket, first number, sequences in all); ids not cut yet; (doc, where it ends in them)
        rows: list[tuple] = []

        def cut(last: bool) -> None:
            nonlocal held, owners, local
            done, k = 0, 0
            while len(held) - done >= width or last and done < len(held):
                ids = bytes(held[done : done + width])
                stop, j = done + len(ids), k
                while owners[j][1] < stop:
                    j += 1
                rows.append((at[1] + local, len(ids) // 2, zlib.crc32(ids), [d for d, _ in owners[k : j + 1]], pack(ids + pad[len(ids) :])))
                done, local, k = stop, local + 1, j + (owners[j][1] == stop)
            held, owners = held[done:], [(d, e - done) for d, e in owners[k:]]

        def out() -> pa.RecordBatch:
            slots = permute(np.array([r[0] for r in rows], np.int64), at[2], key)
            kinds = (pa.int32(), pa.int64(), pa.list_(pa.int64()), pa.binary())
            made = pa.RecordBatch.from_arrays([pa.array(slots), *(pa.array([r[i] for r in rows], t) for i, t in enumerate(kinds, 1))], ["slot", "n_ids", "ids_crc32", "doc_ids", "ids"])
            made = made.append_column("total", pa.array([at[2]] * len(rows), pa.int64()))
            rows.clear()
            return made

        for b in batches:
            for bucket, doc, ids, first, n in zip(*(b.column(c) for c in ("bucket", "doc_id", "ids", "first", "n_sequences")), strict=True):
                here = bucket.as_py(), first.as_py(), n.as_py()
                if here != at:
                    if at is not None:
                        cut(True)
                    at, local = here, 0
                held += unpack(ids.as_buffer())
                owners.append((doc.as_py(), len(held)))
                if len(held) > 1 << 21:
                    cut(False)
                if len(rows) >= 2000:
                    yield out()
        if at is not None:
            cut(True)
        if rows:
            yield out()

    return run


def _records(batches):
    """Two lines a sequence: its ids as they are, and its entry in the index."""
    import json

    import zstandard

    unpack = zstandard.ZstdDecompressor().decompress
    for b in batches:
        for i in range(0, len(b), 1000):
            part = b.slice(i, 1000)
            slots, owners = part.column("slot").to_pylist(), part.column("doc_ids").to_pylist()
            index = [json.dumps({"s": s, "n": n, "c": c, "d": d}, separators=(",", ":")).encode() for s, n, c, d in zip(slots, part.column("n_ids").to_pylist(), part.column("ids_crc32").to_pylist(), owners, strict=True)]
            bodies = [unpack(x.as_buffer()) for x in part.column("ids")]
            for kind, values in (("ids", bodies), ("index", index)):
                yield pa.RecordBatch.from_arrays([pa.array([kind] * len(slots)), part.column("shard"), part.column("slot"), pa.array(values, pa.binary())], ["kind", "shard", "slot", "value"])


def shared_folder(spark: SparkSession, name: str) -> str:
    """A new folder below the cluster's shared checkpoint folder; only a local session may be without one."""
    at = spark.conf.get("spark.checkpoint.dir", None)
    if not at:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        at = "file:///tmp/tracedex-checkpoints"
    return f"{at.rstrip('/')}/{name}-{uuid.uuid4().hex}"


#: Rows of a bucket of documents that are laid end to end, and the most buckets there are.
BUCKET_ROWS, BUCKETS = 4096, 1 << 16


def materialise(docs: DataFrame, out: str, stride: int = 1024, per_shard: int = 16_384, key: int = 20240101, path: str | None = None, pad_id: int = 0) -> DataFrame:
    """Writes shards to `out` and returns one row a sequence: slot, shard, byte_offset, n_ids, ids_crc32, doc_ids.

    Texts become ids once. Buckets count their ids; what is counted (a row a bucket, 65,536 at most) is broadcast back and numbers the sequences."""
    spark, path = docs.sparkSession, path or word_tokenizer()
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    size = rows.agg(F.count("*").alias("n"), F.coalesce(F.sum(F.octet_length("text")), F.lit(0)).alias("bytes")).collect()[0]
    buckets = min(BUCKETS, max(1, -(-size["n"] // BUCKET_ROWS)))  # by the rows of the table alone, so that files and partitions change no sequence
    rows = rows.select(F.pmod(F.xxhash64("doc_id", "text"), F.lit(buckets)).cast("int").alias("bucket"), "doc_id", "text")
    dealt = tokenised(rows, path).repartitionById(buckets, "bucket")
    # every column is used here and the join filters none of its left rows, so that this exchange is the one that the sequences are cut from
    counts = dealt.groupBy("bucket").agg(F.when(F.count("doc_id") >= 0, F.sum(F.when(F.length("ids") > 0, F.col("n")))).alias("n"))
    counts = counts.select("bucket", F.expr(f"(n + {stride - 1}) div {stride}").alias("n"))
    everywhere = W.orderBy("bucket").rowsBetween(W.unboundedPreceding, -1)  # a row a bucket
    starts = counts.select("bucket", F.coalesce(F.sum("n").over(everywhere), F.lit(0)).alias("first"), F.sum("n").over(W.partitionBy(F.lit(0))).alias("n_sequences"))
    stream = dealt.join(F.broadcast(starts), "bucket", "left").sortWithinPartitions("bucket", "doc_id", "n", "ids")
    placed = stream.select("bucket", "doc_id", "ids", "first", "n_sequences").mapInArrow(_cut(stride, pad_id, key), "slot long, n_ids int, ids_crc32 long, doc_ids array<long>, ids binary, total long")
    placed = placed.withColumn("shard", F.expr(f"cast(slot div {per_shard} as int)"))
    # slots are dense, so ranges of shards are known by arithmetic: a task takes neighbouring shards, whole; how many tasks there are changes nothing
    tasks = max(1, min(BUCKETS, -(-size["bytes"] // (4 * stride * per_shard)) + 1))
    ordered = placed.repartitionById(tasks, F.expr(f"cast(shard * {tasks}L div ((total + {per_shard - 1}) div {per_shard}) as int)"))
    lines = ordered.mapInArrow(_records, "kind string, shard int, slot long, value binary").sortWithinPartitions("kind", "shard", "slot")
    lines.select(F.col("value").cast("string").alias("value"), "kind", "shard").write.mode("overwrite").partitionBy("kind", "shard").text(out)
    schema = "s long, n int, c long, d array<long>"
    made = spark.read.schema(schema).json(f"{out}/kind=index") if size["n"] else spark.createDataFrame([], schema)
    made = made.select(F.col("s").alias("slot"), F.col("n").alias("n_ids"), F.col("c").alias("ids_crc32"), F.col("d").alias("doc_ids"))
    return made.select("slot", F.expr(f"slot div {per_shard}").alias("shard"), (F.col("slot") % per_shard * (2 * stride + 1)).alias("byte_offset"), "n_ids", "ids_crc32", "doc_ids")


def read_slots(spark: SparkSession, out: str, first: int, last: int, stride: int = 1024, per_shard: int = 16_384) -> DataFrame:
    """slot, ids of first <= slot < last in slot order: a resumable sequential read of the shards that hold them, at computed places."""
    files = spark.read.format("binaryFile").load(f"{out}/kind=ids").filter(F.col("shard").between(first // per_shard, max(first, last - 1) // per_shard))
    record = 2 * stride + 1
    slots = F.sequence(F.lit(0).cast("long"), F.expr(f"length div {record} - 1"))
    each = files.select("content", F.col("shard").cast("long").alias("shard"), F.explode(slots).alias("k")).withColumn("slot", F.col("shard") * per_shard + F.col("k")).filter((F.col("slot") >= first) & (F.col("slot") < last))
    return each.select("slot", F.expr(f"substring(content, cast(k * {record} + 1 as int), {2 * stride})").alias("ids")).orderBy("slot")


def op8_training_order(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document's ids in shards, in keyed training order; one row a sequence."""
    return materialise(table(spark, sf_dir, "documents"), shared_folder(spark, "training-order"))
