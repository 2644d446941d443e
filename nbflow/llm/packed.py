"""Two exchanges by which documents learn which of their many hashes others hold too.

A row per hash would cost more than the texts. So a task sends, for each range of hashes, one block of
sorted hashes with short references to a list of its documents; byte planes keep the leading bytes
together, which the shuffle's codec squeezes. Whoever gets a range sees every holder of a hash, picks
what to tell whom, and sends blocks back by document. Equal hashes always meet, so nothing is lost; two
different contents that share a hash only make a false candidate, which callers check.

A hash that very many documents hold would still fill one range. So callers fold: what the holders within one
piece of the input settle among themselves is answered there, and of such a hash a piece sends on no more than
a fixed number of entries, however many of its documents hold it.
"""

from __future__ import annotations

import struct
from collections.abc import Callable, Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from nbflow.llm.common import trim

BITS = 48
MASK = np.uint64((1 << BITS) - 1)
_HEAD = struct.Struct("<IIBBBB")
_BLOCKS = pa.schema([("bucket", pa.int32()), ("block", pa.binary())])
#: What a block is: entries for whoever has their range, or answers for whoever has their documents.
QUESTION, ANSWER = b"Q", b"A"


@dataclass
class Holders:
    """Hashes with their holders: ``owner`` points into ``keys`` and ``sizes``; ``flags`` marks some entries. ``checks``:
    64 more bits of each hash, for those that must not be mistaken for one another; ``notes``: a number of each entry."""

    hashes: np.ndarray
    owner: np.ndarray
    keys: np.ndarray
    sizes: np.ndarray
    flags: np.ndarray
    checks: np.ndarray | None = None
    notes: np.ndarray | None = None

    def at(self, order) -> Holders:
        return Holders(self.hashes[order], self.owner[order], self.keys, self.sizes, self.flags[order], *(None if x is None else x[order] for x in (self.checks, self.notes)))

    def ordered(self) -> Holders:
        return self.at(np.argsort(self.hashes, kind="stable") if self.checks is None else np.lexsort((self.checks, self.hashes)))

    def groups(self) -> np.ndarray:
        """Where each run of equal hashes (and checks) of ordered entries begins."""
        new = self.hashes[1:] != self.hashes[:-1]
        if self.checks is not None:
            new |= self.checks[1:] != self.checks[:-1]
        return np.flatnonzero(np.concatenate(([len(self.hashes) > 0], new)))

    def holder(self) -> np.ndarray:
        return self.keys[self.owner]


def spread(starts: np.ndarray, n: int) -> np.ndarray:
    """The number of the group of each of ``n`` entries."""
    return np.repeat(np.arange(len(starts)), np.diff(np.append(starts, n)))


def _planes(values: np.ndarray, kind: str, width: int) -> bytes:
    size = np.dtype(kind).itemsize
    return np.ascontiguousarray(values.astype(kind).view(np.uint8).reshape(-1, size)[:, :width].T).tobytes()


def _packed(h: Holders, bits: int = BITS) -> bytes:
    wide, width = 2 if len(h.keys) <= 1 << 16 else 4, bits // 8
    parts = [_HEAD.pack(len(h.hashes), len(h.keys), wide, width, h.checks is not None, h.notes is not None), h.keys.astype("<i8").tobytes(), h.sizes.astype("<i4").tobytes()]
    parts += [_planes(h.hashes, "<u8", width), _planes(h.owner, "<u4", wide)]
    parts += [x.astype(kind).tobytes() for x, kind in ((h.checks, "<u8"), (h.notes, "<u4")) if x is not None]
    return b"".join((*parts, np.packbits(h.flags).tobytes()))


def _unpacked(block: bytes) -> Holders:
    n, docs, wide, width, checked, noted = _HEAD.unpack_from(block)
    at = _HEAD.size
    keys = np.frombuffer(block, "<i8", docs, at)
    sizes = np.frombuffer(block, "<i4", docs, at := at + 8 * docs)
    planes = np.frombuffer(block, np.uint8, width * n, at := at + 4 * docs).reshape(width, n)
    refs = np.frombuffer(block, np.uint8, wide * n, at := at + width * n).reshape(wide, n)
    at += wide * n
    checks = np.frombuffer(block, "<u8", n, at) if checked else None
    notes = np.frombuffer(block, "<u4", n, at := at + 8 * n * checked) if noted else None
    flags = np.unpackbits(np.frombuffer(block, np.uint8, -1, at + 4 * n * noted), count=n).astype(bool)
    hashes, owner = np.zeros((n, 8), np.uint8), np.zeros((n, 4), np.uint8)
    hashes[:, :width], owner[:, :wide] = planes.T, refs.T
    return Holders(hashes.view("<u8").ravel(), owner.view("<u4").ravel().astype(np.int64), keys, sizes, flags, checks, notes)


def _narrowed(h: Holders, part: slice | np.ndarray) -> Holders:
    used, owner = np.unique(h.owner[part], return_inverse=True)
    return Holders(h.hashes[part], owner, h.keys[used], h.sizes[used], h.flags[part], *(None if x is None else x[part] for x in (h.checks, h.notes)))


def _pooled(some: Iterable[Holders], least: int = 600_000) -> Iterator[Holders]:
    """Small chunks' holders together, so that blocks are long though texts are hashed in small pieces."""
    held, size = [], 0
    for h in some:
        held.append(h)
        size += len(h.hashes)
        if size >= least:
            yield _joined(held)
            held, size = [], 0
    if held:
        yield _joined(held)


def _merged(blocks: list[bytes]) -> Holders:
    return _joined([_unpacked(b) for b in blocks])


def _joined(all_of: list[Holders]) -> Holders:
    shift = np.cumsum([0, *(len(x.keys) for x in all_of)])
    return Holders(
        np.concatenate([x.hashes for x in all_of]),
        np.concatenate([x.owner + s for x, s in zip(all_of, shift[:-1], strict=True)]),
        np.concatenate([x.keys for x in all_of]),
        np.concatenate([x.sizes for x in all_of]),
        np.concatenate([x.flags for x in all_of]),
        None if all_of[0].checks is None else np.concatenate([x.checks for x in all_of]),
        None if all_of[0].notes is None else np.concatenate([x.notes for x in all_of]),
    )


def _rows(rows: list[tuple[int, bytes]]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int32()), pa.array([r[1] for r in rows], pa.binary())], schema=_BLOCKS)


def _sent(blocks: Iterable[tuple[int, bytes]], most: int = 4 << 20) -> Iterator[pa.RecordBatch]:
    held, size = [], 0
    for bucket, block in blocks:
        held.append((bucket, block))
        size += len(block)
        if size > most:
            yield _rows(held)
            held, size = [], 0
    if held:
        yield _rows(held)


def buckets_in_order(batches) -> Iterator[tuple[int, list[bytes]]]:
    """The blocks of each bucket of a partition whose rows are sorted by bucket."""
    now, blocks = None, []
    for batch in batches:
        for bucket, block in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            if bucket != now and blocks:
                yield now, blocks
                blocks = []
                trim()
            now = bucket
            blocks.append(block)
    if blocks:
        yield now, blocks


def decided(batches, decide: Callable[[list[memoryview]], Iterable[tuple[int, bytes]]]) -> Iterator[tuple[int, bytes]]:
    """Blocks by bucket of the document: answers that senders gave are passed on as they come; the questions of each
    bucket (rows are sorted by bucket) go to ``decide``, which answers them."""
    now, got = None, []
    for batch in batches:
        for bucket, block in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            if block[:1] == ANSWER:
                yield bucket, block[1:]
                continue
            if bucket != now and got:
                yield from decide(got)
                got = []
                trim()
            now = bucket
            got.append(memoryview(block)[1:])
    if got:
        yield from decide(got)


def dealt(df: DataFrame, buckets: int) -> DataFrame:
    """Rows of a bucket together, bucket after bucket, so that a task holds one bucket at a time."""
    return df.repartition(buckets, "bucket").sortWithinPartitions("bucket")


def addressed(h: Holders, places: np.ndarray, values: np.ndarray, buckets: int) -> Iterator[tuple[int, bytes]]:
    """Blocks, by bucket of the document, that tell the holders of entries at ``places`` the values."""
    owner = h.owner[places]
    to = (h.keys[owner].astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(33)) % np.uint64(buckets)
    order = np.lexsort((owner, to))
    to, owner, values = to[order], owner[order], values[order]
    bounds = np.searchsorted(to, np.arange(buckets + 1))
    for b in np.flatnonzero(bounds[1:] > bounds[:-1]).tolist():
        part = slice(bounds[b], bounds[b + 1])
        yield b, _packed(_narrowed(Holders(values, owner, h.keys, h.sizes, np.zeros(len(values), bool)), part), 64)


def told(
    docs: DataFrame,
    hashed: Callable[[Iterable], Iterator[Holders]],
    pick: Callable[[Holders, np.ndarray], tuple[np.ndarray, np.ndarray]],
    buckets: int,
    bits: int = BITS,
    fold: Callable[[Holders, np.ndarray], tuple[Holders, np.ndarray, np.ndarray]] | None = None,
    noted: tuple[int, Callable[[Holders, np.ndarray], np.ndarray]] | None = None,
) -> DataFrame:
    """Rows (key, size, values): per document what it is told, as different little-endian unsigned 64-bit numbers in order.

    hashed: from the batches of ``docs`` to hashes (of ``bits`` bits at most) with their holders, chunk by chunk.
    pick: gets the holders of a range, sorted by hash, and the starts of the groups of equal hashes;
    gives the places of the entries to be told and their values.
    fold: gets the same of one piece of the input; gives the entries to send on, and the places and values of those to
    be told at once.
    noted: (key, f): values that f finds in a range's holders are told to the document ``key``, which no row has."""

    def out(batches):
        def blocks():
            for h in _pooled(hashed(batches)):
                h = h.ordered()
                if fold is not None and len(h.hashes):
                    kept, places, values = fold(h, h.groups())
                    for b, block in addressed(h, places, values, buckets):
                        yield b, ANSWER + block
                    h = kept
                bounds = _bounds(h.hashes, buckets, bits)
                for b in np.flatnonzero(bounds[1:] > bounds[:-1]).tolist():
                    yield b, QUESTION + _packed(_narrowed(h, slice(bounds[b], bounds[b + 1])), bits)

        yield from _sent(blocks())

    def met(batches):
        def answers(got):
            h = _merged(got).ordered()
            starts = h.groups()
            yield from addressed(h, *pick(h, starts), buckets)
            if noted is not None and len(values := noted[1](h, starts)):
                one = Holders(values, np.zeros(len(values), np.int64), np.array([noted[0]]), np.zeros(1, np.int32), np.zeros(len(values), bool))
                yield from addressed(one, np.arange(len(values)), values, buckets)

        yield from _sent(decided(batches, answers))

    blocks = "bucket int, block binary"
    there = dealt(docs.mapInArrow(out, blocks), buckets).mapInArrow(met, blocks)
    return dealt(there, buckets).mapInArrow(_by_key, "key long, size int, values binary")


def _bounds(hashes: np.ndarray, buckets: int, bits: int) -> np.ndarray:
    """Where each bucket's range of sorted hashes begins, and the end."""
    edges = np.array([(b << bits) // buckets for b in range(buckets)], dtype=np.uint64)
    return np.append(np.searchsorted(hashes, edges), len(hashes))


_KEYED = pa.schema([("key", pa.int64()), ("size", pa.int32()), ("values", pa.binary())])


def _by_key(batches):
    for _, got in buckets_in_order(batches):
        h = _merged(got)
        keys = h.holder()
        order = np.lexsort((h.hashes, keys))
        keys, values, sizes = keys[order], h.hashes[order], h.sizes[h.owner][order]
        if not len(keys):
            continue
        new = np.concatenate(([True], (keys[1:] != keys[:-1]) | (values[1:] != values[:-1])))
        keys, values, sizes = keys[new], values[new], sizes[new]
        starts = np.flatnonzero(np.concatenate(([True], keys[1:] != keys[:-1])))
        ends = np.append(starts[1:], len(keys))
        for a in range(0, len(starts), 2000):
            s, e = starts[a : a + 2000], ends[a : a + 2000]
            rows = [values[i:j].tobytes() for i, j in zip(s, e, strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(keys[s]), pa.array(sizes[s], pa.int32()), pa.array(rows, pa.binary())], schema=_KEYED)
