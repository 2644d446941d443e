"""Helpers that several training-data operators share."""

from __future__ import annotations

import ctypes

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from nbflow.session import discard, settle, shared_dir, work_dir  # noqa: F401

#: Stands for a missing doc_id inside the operators: the smallest number.
NO_ID = -(1 << 63)

#: Bytes that separate words (fixed values): space and the five ASCII controls 9 to 13.
WORD = r"[^\x20\x09-\x0D]+"


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


#: Rows and bytes of a batch that a task hands to Python at most: texts are long, and workers' memory is small.
BATCH_ROWS, BATCH_BYTES = 1000, 8 << 20


def small_batches(spark: SparkSession) -> None:
    """Lower the session's limits of Arrow batches to those of this module; limits lower still are left."""
    for key, most in (("spark.sql.execution.arrow.maxRecordsPerBatch", BATCH_ROWS), ("spark.sql.execution.arrow.maxBytesPerBatch", BATCH_BYTES)):
        now = spark.conf.get(key).rstrip("bB")
        if not now.isdigit() or not 0 < int(now) <= most:
            spark.conf.set(key, str(most))


def trim() -> None:
    """Give freed memory back to the machine: workers live long, and many large arrays leave their heap full of holes."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


def fresh(columns: list[str], *names: str) -> list[str]:
    """Names for helper columns that clash with none of ``columns``, whatever the case of their letters."""
    taken, out = {c.lower() for c in columns}, []
    for name in names:
        while name.lower() in taken:
            name += "_"
        taken.add(name.lower())
        out.append(name)
    return out


def buckets_for(rows: DataFrame, bytes_each: int = 8 << 20) -> int:
    """Buckets of bounded size for the texts of ``rows``: one for so many bytes, and one per partition at least."""
    size = rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    return max(partitions(rows.sparkSession), -(-size // bytes_each))


def shared_ids(rows: DataFrame) -> bool:
    """Whether several rows have one doc_id."""
    return bool(rows.groupBy("doc_id").count().filter("count > 1").limit(1).count())


#: Keys that may be hot, and rows that a key has at least to be so.
MOST_HOT, HOT_ROWS = 1000, 1000


def joined_with_hot_keys(left: DataFrame, right: DataFrame, key: str, n: str, rows: int, how: str = "inner") -> DataFrame:
    """The inner or semi join of ``left``, which has ``rows`` rows, with ``right``, which has one row per key, with the
    number ``n`` of the key's rows in ``left``. No more than ``MOST_HOT`` keys can each have more than that share of all
    rows, so those are broadcast, and their rows never meet in one task; the other keys' groups are small. Without hot
    keys it is a plain join."""
    is_hot = F.col(n) > max(HOT_ROWS, rows // MOST_HOT)
    if rows <= HOT_ROWS or right.filter(is_hot).isEmpty():
        return left.join(right.drop(n), key, how)
    hot, cool = F.broadcast(right.filter(is_hot).drop(n)), right.filter(~is_hot).drop(n)
    rest = left.join(hot.select(key), key, "left_anti")
    return left.join(hot, key, how).unionByName(rest.join(cool, key, how))


def with_both(pairs: DataFrame, rows: DataFrame, value: str) -> DataFrame:
    """``pairs`` (a, b), written already, with v_a and v_b: the ``value`` that ``rows`` (key, value) has of each. A key that
    is in very many pairs is spread over parts, each of which gets a copy of its value."""
    n_pairs, out = pairs.count(), pairs
    for side in ("b", "a"):
        parts = pairs.groupBy(side).agg(F.count("*").alias("times")).withColumn("parts", F.ceil(F.col("times") / HOT_ROWS).cast("int"))
        if n_pairs <= HOT_ROWS or parts.filter("parts > 1").isEmpty():
            out = out.join(rows.select(F.col("key").alias(side), F.col(value).alias(f"v_{side}")), side)
            continue
        out = joined_with_hot_keys(out, parts, side, "times", n_pairs).withColumn("part", F.pmod(F.xxhash64("a", "b"), "parts").cast("int")).drop("parts")
        values = rows.join(parts.select(F.col(side).alias("key"), "parts"), "key").select(F.col("key").alias(side), F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"), F.col(value).alias(f"v_{side}"))
        out = out.join(values, [side, "part"]).drop("part")
    return out


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def text_or_empty(name: str = "text") -> Column:
    return F.coalesce(F.col(name), F.lit(""))


def text_views(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string or binary column without copying its bytes; null counts as empty."""
    if pa.types.is_string(column.type) or pa.types.is_binary(column.type):
        kind = np.int32
    elif pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type):
        kind = np.int64
    else:
        raise TypeError(f"not a text column: {column.type}")
    if column.null_count:
        column = column.fill_null("" if "string" in str(column.type) else b"")
    buffers = column.buffers()
    offsets = np.frombuffer(buffers[1], dtype=kind)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    data = np.frombuffer(buffers[2], dtype=np.uint8) if buffers[2] is not None else np.zeros(0, np.uint8)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0]


def pieces_of(batches, limit: int, rows: int = 60_000):
    """(doc ids, bytes, offsets) pieces of at most ``limit`` bytes and ``rows`` rows, or of one text that is longer."""
    for batch in batches:
        ids = batch.column(0).fill_null(NO_ID).to_numpy(zero_copy_only=False)
        data, offsets = text_views(batch.column(1))
        a = 0
        while a < len(ids):
            b = max(a + 1, int(np.searchsorted(offsets, offsets[a] + limit, side="right")) - 1)
            b = min(b, a + rows, len(ids))
            yield ids[a:b], data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a]
            a = b
        del batch, data
        trim()


def is_space(data: np.ndarray) -> np.ndarray:
    return (data == 32) | ((data >= 9) & (data <= 13))


def word_spans(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(start, end, number of words before each document) of the words; none crosses a document's end."""
    n = len(data)
    if not n:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(len(offsets), np.int64)
    space = is_space(data)
    before = np.empty(n, bool)
    before[0], before[1:] = True, space[:-1]
    inner = offsets[(offsets > 0) & (offsets < n)]
    before[inner] = True
    after = np.empty(n, bool)
    after[-1], after[:-1] = True, space[1:]
    after[inner - 1] = True
    solid = ~space
    starts, ends = np.flatnonzero(solid & before), np.flatnonzero(solid & after) + 1
    return starts, ends, np.searchsorted(starts, offsets)


#: Odd multipliers for rolling sums modulo 2**64, and the finishing rounds of a 64-bit mixer (fixed values).
P_BYTE, P_WORD, P_CHECK = 0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0xD6E8FEB86659FD93
MIX_A, MIX_B = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)


def mixed(x: np.ndarray) -> np.ndarray:
    x = x ^ (x >> np.uint64(30))
    x *= MIX_A
    x ^= x >> np.uint64(27)
    x *= MIX_B
    x ^= x >> np.uint64(31)
    return x


_powers: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def _power_tables(base: int, n: int) -> tuple[np.ndarray, np.ndarray]:
    held = _powers.get(base)
    if held is None or len(held[0]) < n:
        size = 1 << max(12, int(n - 1).bit_length())
        tables = []
        for p in (base, pow(base, -1, 1 << 64)):
            t = np.full(size, p, np.uint64)
            t[0] = 1
            tables.append(np.cumprod(t, dtype=np.uint64))
        held = _powers[base] = (tables[0], tables[1])
    return held


class Rolling:
    """Hashes of any slice of a sequence of numbers, each in constant time after one pass."""

    def __init__(self, values: np.ndarray, base: int):
        n = len(values)
        power, self.inverse = _power_tables(base, n + 1)
        self.sums = np.zeros(n + 1, np.uint64)
        v = values.astype(np.uint64)
        v += np.uint64(1)
        v *= power[:n]
        np.cumsum(v, out=self.sums[1:])

    def of(self, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        out = self.sums[ends] - self.sums[starts]
        out *= self.inverse[starts]
        return mixed(out)

    def windows(self, k: int) -> np.ndarray:
        """Of every window of k values, in order of its start."""
        n = len(self.sums) - k
        if n <= 0:
            return np.zeros(0, np.uint64)
        out = self.sums[k:] - self.sums[:n]
        out *= self.inverse[:n]
        return mixed(out)


def lowered(data: np.ndarray) -> np.ndarray:
    """A-Z as a-z; other bytes stay."""
    return data + ((data >= 65) & (data <= 90)).astype(np.uint8) * np.uint8(32)


def distinct_words(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, list[bytes]]:
    """(number of each word, the different words by number). Words are compared byte by byte."""
    bounds = np.concatenate(([0], np.cumsum(ends - starts)))
    body = np.ascontiguousarray(data[~is_space(data)])
    words = pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(starts), [None, pa.py_buffer(bounds), pa.py_buffer(body)]).dictionary_encode()
    return words.indices.to_numpy(zero_copy_only=False), words.dictionary.to_pylist()


def word_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, seed: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """Two independent 64-bit hashes of each word: the halves of its 128-bit xxhash, taken once per different word."""
    if not len(starts):
        return np.zeros(0, np.uint64), np.zeros(0, np.uint64)
    numbers, words = distinct_words(data, starts, ends)
    halves = np.frombuffer(b"".join([xxhash.xxh3_128_digest(w, seed) for w in words]), "<u8").reshape(-1, 2)
    return halves[numbers, 0], halves[numbers, 1]


def runs_of(mask: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the runs of True."""
    edge = np.diff(np.concatenate(([0], mask.astype(np.int8), [0])))
    return np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
