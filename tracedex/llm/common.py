"""Helpers that several corpus operators share: Arrow text buffers, hashing, sizing."""

from __future__ import annotations

import ctypes

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession

from tracedex.deploy import ship

U = np.uint64
GOLDEN = 0x9E3779B97F4A7C15


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table, read by Spark so that any store works."""
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def slots(spark: SparkSession) -> int:
    """Partitions to shuffle to, as the session says."""
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))


def flat_utf8(column) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of an Arrow string column without copying its text; null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = pc.fill_null(column.cast(pa.large_string()), "")
    n, buffers = len(column), column.buffers()
    if not n or buffers[1] is None:
        return np.zeros(0, np.uint8), np.zeros(n + 1, np.int64)
    offsets = np.frombuffer(buffers[1], np.int64)[column.offset : column.offset + n + 1]
    data = np.frombuffer(buffers[2], np.uint8) if buffers[2] is not None else np.zeros(0, np.uint8)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0]


def spans(offsets: np.ndarray, limit: int = 1 << 20):
    """Runs [i, j) of whole documents of about `limit` bytes, so that scratch arrays stay small."""
    n, i = len(offsets) - 1, 0
    while i < n:
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + limit, "right")) - 1)
        yield i, min(j, n)
        i = min(j, n)


#: Bytes of text of which Python holds objects or scratch arrays at once.
SLICE = 1 << 18


def slices(batches, text: str | int):
    """Arrow batches in slices of whole rows of about `SLICE` bytes of text, so that what Python makes of their texts does not grow with the session's
    batches. After the last one the worker, which Spark keeps for later tasks, gives its free memory back."""
    for b in batches:
        for i, j in spans(flat_utf8(b.column(text))[1], SLICE):
            yield b.slice(i, j - i)
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # GNU's C library only
    if trim:
        trim(0)


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser on 64-bit words."""
    x = x.astype(U, copy=True)
    x ^= x >> U(30)
    x *= U(0xBF58476D1CE4E5B9)
    x ^= x >> U(27)
    x *= U(0x94D049BB133111EB)
    x ^= x >> U(31)
    return x


def byte_codes(seed: int) -> np.ndarray:
    """A pseudo-random 64-bit word for each byte value."""
    return mix64((np.arange(256, dtype=U) + U(seed)) * U(GOLDEN))


def powers(base: int, n: int) -> np.ndarray:
    """base**0 .. base**(n-1) modulo 2**64."""
    out = np.full(max(n, 1), U(base), U)
    out[0] = 1
    return np.cumprod(out, dtype=U)[:n]


def window_hashes(codes: np.ndarray, width: int) -> np.ndarray:
    """Polynomial hashes of all `width` consecutive codes, by doubling."""
    out, have, base = None, 0, 0xD6E8FEB86659FD93
    part, size = codes, 1
    with np.errstate(over="ignore"):
        while size <= width:
            if width & size:
                if out is None:
                    out, have = part, size
                else:
                    n = len(codes) - have - size + 1
                    if n <= 0:
                        return np.zeros(0, U)
                    out = out[:n] * U(pow(base, size, 1 << 64)) + part[have : have + n]
                    have += size
            if 2 * size <= width:
                n = len(codes) - 2 * size + 1
                if n <= 0:
                    return np.zeros(0, U)
                part = part[:n] * U(pow(base, size, 1 << 64)) + part[size : size + n]
            size *= 2
    return mix64(out)


def sliding_min(values: np.ndarray, width: int) -> np.ndarray:
    """Minimum of each run of `width` values, by doubling."""
    if len(values) < width:
        return values[:0]
    size = 1
    while 2 * size <= width:
        values = np.minimum(values[:-size], values[size:])
        size *= 2
    rest = width - size
    return np.minimum(values[: len(values) - rest], values[rest:]) if rest else values


#: Word characters: ASCII digits, letters and every byte of a longer code point.
IS_WORD = np.zeros(256, bool)
IS_WORD[48:58] = IS_WORD[65:91] = IS_WORD[97:123] = IS_WORD[128:] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


def words_of(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(hash, start, document) of every word; words never cross documents."""
    with np.errstate(over="ignore"):
        is_word = IS_WORD[data]
        opens = is_word.copy()
        opens[1:] &= ~is_word[:-1]
        closes = is_word.copy()
        closes[:-1] &= ~is_word[1:]
        inner = offsets[1:-1]
        inner = inner[(inner > 0) & (inner < len(data))]
        opens[inner] = is_word[inner]
        closes[inner - 1] = is_word[inner - 1]
        start, end = np.flatnonzero(opens), np.flatnonzero(closes) + 1
        base = 0xA24BAED4963EE407 | 1
        sums = np.zeros(len(data) + 1, U)
        np.cumsum(byte_codes(11)[LOWER[data]] * powers(base, len(data)), dtype=U, out=sums[1:])
        back = powers(pow(base, -1, 1 << 64), len(data))
        hashes = mix64((sums[end] - sums[start]) * back[start] + (end - start).astype(U)) if len(start) else np.zeros(0, U)
    return hashes, start, np.searchsorted(offsets, start, "right") - 1
