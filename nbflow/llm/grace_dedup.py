"""Exact deduplication by Grace hash partitioning.

Each task first folds equal texts of its own rows, so that a text held by a third of all rows reaches
the next step once per task. Spark's shuffle is the first partitioning pass; within a task the records
of a partition are split again and again over spill files until the distinct texts of a file fit an
open-addressing table, which compares whole texts.

Defined cases: a null text counts as empty; an empty text is a text like others; no word or length
limit holds; a row without doc_id stays only if no equal text has one; of rows that repeat both doc_id
and text one stays; an empty table gives an empty result; other columns are ignored and may have any
name.
"""

from __future__ import annotations

import hashlib
import os
import struct
import tempfile

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from nbflow.llm.common import fresh, small_batches, text_or_empty, text_views

#: Bytes of distinct text that a table holds in memory, and spill files of one partitioning pass.
TABLE_BYTES, FANOUT = 48 << 20, 16
_HEAD = struct.Struct("<qqqq")  # hash, largest doc_id, rows, length of the text
_NO_ID = -(1 << 63)


class TextTable:
    """Open addressing with linear probing over whole texts; a slot holds an entry's number plus one."""

    def __init__(self) -> None:
        self.slots, self.mask = [0] * 1024, 1023
        self.hashes: list[int] = []
        self.texts: list[bytes] = []
        self.largest: list[int] = []
        self.rows: list[int] = []
        self.held = 0

    def add(self, hashed: int, text: bytes, doc_id: int, rows: int) -> None:
        at, slots, mask = hashed & self.mask, self.slots, self.mask
        while found := slots[at]:
            if self.hashes[found - 1] == hashed and self.texts[found - 1] == text:
                self.rows[found - 1] += rows
                if doc_id > self.largest[found - 1]:
                    self.largest[found - 1] = doc_id
                return
            at = (at + 1) & mask
        self.hashes.append(hashed)
        self.texts.append(text)
        self.largest.append(doc_id)
        self.rows.append(rows)
        self.held += len(text) + 100
        slots[at] = len(self.hashes)
        if 2 * len(self.hashes) > mask:
            self._grow()

    def _grow(self) -> None:
        self.mask = 4 * (self.mask + 1) - 1
        self.slots = [0] * (self.mask + 1)
        for n, hashed in enumerate(self.hashes, 1):
            at = hashed & self.mask
            while self.slots[at]:
                at = (at + 1) & self.mask
            self.slots[at] = n

    def entries(self):
        return zip(self.hashes, self.texts, self.largest, self.rows, strict=True)


def resolved(records, folder: str, budget: int = TABLE_BYTES, fanout: int = FANOUT, depth: int = 0):
    """Entries (hash, text, largest doc_id, rows), one for each distinct text of ``records``.

    While the table fits, nothing is spilled. Once it doesn't, what it holds and all that follows go to
    ``fanout`` files by the next bits of the hash, and each file is resolved alone. Records of one hash
    can't be split any further: 16 levels use up its bits, and then only equal hashes are left."""
    table, files = TextTable(), []
    bits = fanout.bit_length() - 1

    def put(hashed: int, text: bytes, doc_id: int, rows: int) -> None:
        out = files[(hashed >> (60 - bits * depth)) & (fanout - 1)]
        out.write(_HEAD.pack(hashed, doc_id, rows, len(text)))
        out.write(text)

    for hashed, text, doc_id, rows in records:
        if files:
            put(hashed, text, doc_id, rows)
            continue
        table.add(hashed, text, doc_id, rows)
        if table.held > budget and bits * depth < 60:
            files = [open(os.path.join(folder, f"{depth}-{os.urandom(6).hex()}"), "w+b") for _ in range(fanout)]
            for entry in table.entries():
                put(*entry)
            table = TextTable()
    yield from table.entries()
    del table
    for out in files:
        out.seek(0)
        yield from resolved(_read(out), folder, budget, fanout, depth + 1)
        out.close()
        os.unlink(out.name)


def _read(file):
    while head := file.read(_HEAD.size):
        hashed, doc_id, rows, length = _HEAD.unpack(head)
        yield hashed, file.read(length), doc_id, rows


_FOLDED = pa.schema([("h", pa.int64()), ("body", pa.binary()), ("largest", pa.int64()), ("rows", pa.int64())])
_CLASSES = pa.schema([("text_sha256", pa.string()), ("keep_id", pa.int64()), ("group_size", pa.int64())])


def _batches(entries, schema: pa.Schema, row, most: int = 8 << 20):
    rows, held = [], 0
    for entry in entries:
        rows.append(row(entry))
        held += len(entry[1]) + 64
        if held > most:
            yield _batch(rows, schema)
            rows, held = [], 0
    if rows:
        yield _batch(rows, schema)


def _batch(rows: list[tuple], schema: pa.Schema) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), schema, strict=True)], schema=schema)


def _fold(batches):
    """Equal texts of a task become one record; a full table is passed on and begun anew."""
    table = TextTable()
    for batch in batches:
        data, offsets = text_views(batch.column(1))
        body, at = data.tobytes(), offsets.tolist()
        ids = batch.column(0).fill_null(_NO_ID).to_pylist()
        for i, hashed in enumerate(batch.column(2).to_pylist()):
            table.add(hashed, body[at[i] : at[i + 1]], ids[i], 1)
            if table.held > TABLE_BYTES:
                yield from _batches(table.entries(), _FOLDED, tuple)
                table = TextTable()
    yield from _batches(table.entries(), _FOLDED, tuple)


def _resolve(batches):
    def records():
        for batch in batches:
            yield from zip(*(c.to_pylist() for c in batch.columns), strict=True)

    with tempfile.TemporaryDirectory() as folder:
        yield from _batches(
            resolved(records(), folder),
            _CLASSES,
            lambda e: (hashlib.sha256(e[1]).hexdigest(), None if e[2] == _NO_ID else e[2], e[3]),
        )


def text_classes(docs: DataFrame) -> DataFrame:
    """One row per distinct text: text_sha256, keep_id (largest doc_id) and group_size."""
    small_batches(docs.sparkSession)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_or_empty().alias("body")).withColumn("h", F.xxhash64("body"))
    folded = rows.mapInArrow(_fold, "h long, body binary, largest long, rows long")
    return folded.repartition("h").mapInArrow(_resolve, "text_sha256 string, keep_id long, group_size long")


def exact_dedup(docs: DataFrame) -> DataFrame:
    """One row per document: doc_id, keep_id, group_size, kept, text_sha256.

    The documents join their classes on the digest; the side of the documents may be skewed, and Spark
    splits it at run time, as the other side has one row per key."""
    ids = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.sha2(text_or_empty(), 256).alias("text_sha256"))
    ids = ids.withColumn("nth", F.row_number().over(Window.partitionBy("text_sha256", "doc_id").orderBy("doc_id")))
    found = ids.join(text_classes(docs), "text_sha256")
    kept = F.col("doc_id").eqNullSafe(F.col("keep_id")) & (F.col("nth") == 1)
    return found.select("doc_id", "keep_id", "group_size", kept.alias("kept"), "text_sha256")


def without_copies(docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` that stay, with all their columns: of equal texts the one with the largest doc_id.

    Digest and doc_id together are the key of the join, so that a large group of copies is spread."""
    digest, sha, keep, nth = fresh(docs.columns, "digest", "sha", "keep", "nth")
    classes = text_classes(docs).select(F.col("text_sha256").alias(sha), F.col("keep_id").alias(keep))
    mine = docs.withColumn(digest, F.sha2(text_or_empty(), 256))
    found = mine.join(classes, (F.col(digest) == F.col(sha)) & F.col("doc_id").eqNullSafe(F.col(keep)))
    first = F.row_number().over(Window.partitionBy(digest, "doc_id").orderBy("doc_id"))
    return found.withColumn(nth, first).filter(F.col(nth) == 1).select(docs.columns)
