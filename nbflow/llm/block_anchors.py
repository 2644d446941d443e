"""Removal of repeated word passages by fixed-block anchors.

Every document is cut into non-overlapping reference blocks of half a window; any window, wherever it
starts, holds a whole block. All rolling windows of a block's length probe the index of blocks, and where
a probe meets a block of another document, that anchor is extended: each window around it is followed
over all documents that have it, to the smallest doc_id, and windows that follow on one another make up
the maximal exact repeats. Only windows around anchors are followed, so what no other document has is
never sent on.

Anchors are found by 48 bits of hash, which may only make too many; a window that is followed is known by the
128-bit cryptographic digest of its words, so no two different ones are taken for the same. Of a hash that several
documents of one piece of the input hold, two go on, as blocks of the first and the last of them; of a followed window,
its first document in the piece. So a passage that a third of all documents share is met once or twice per piece.

Defined cases: words are runs of bytes other than space and 9 to 13, unchanged; a null or empty text has
none, and one with fewer words than a window loses none; repeats within one document stay; rows that
share a doc_id count as one document; a missing doc_id counts as the smallest; an empty table gives an
empty result; other columns are ignored.
"""

from __future__ import annotations

import itertools
from functools import cached_property
from hashlib import blake2b

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from nbflow.llm.common import NO_ID, P_WORD, Rolling, buckets_for, discard, is_space, pieces_of, runs_of, settle, shared_ids, small_batches, text_or_empty, word_hashes, word_spans
from nbflow.llm.packed import BITS, Holders, spread, told

CHUNK = 1 << 20


class Words:
    """The words of a piece of the table, with hashes of their windows."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray):
        self.data = data
        self.starts, self.ends, self.before = word_spans(data, offsets)
        self.doc = np.repeat(np.arange(len(offsets) - 1), np.diff(self.before))
        self.local = np.arange(len(self.doc)) - self.before[:-1][self.doc]

    @cached_property
    def rolling(self) -> Rolling:
        return Rolling(word_hashes(self.data, self.starts, self.ends)[0], P_WORD)

    def whole(self, k: int) -> np.ndarray:
        """Starts of the windows of k words that end in the document they start in."""
        n = len(self.doc) - k + 1
        return np.flatnonzero(self.doc[:n] == self.doc[k - 1 :]) if n > 0 else np.zeros(0, np.int64)

    def digests(self, at: np.ndarray, k: int) -> np.ndarray:
        """The digests of windows of k words, joined by one space, as rows of two 64-bit numbers."""
        lengths = self.ends - self.starts
        ends = np.cumsum(lengths + 1)
        body = self.data[~is_space(self.data)]
        text = np.full(int(ends[-1]) if len(ends) else 0, 32, np.uint8)
        text[np.arange(len(body)) + np.repeat(np.arange(len(lengths)), lengths)] = body
        text, first, last = text.tobytes(), (ends - lengths - 1)[at].tolist(), (ends[at + k - 1] - 1).tolist()
        return np.frombuffer(b"".join([blake2b(text[i:j], digest_size=16).digest() for i, j in zip(first, last, strict=True)]), "<u8").reshape(-1, 2)


def _probes(block: int):
    def run(batches):
        for ids, data, offsets in pieces_of(batches, CHUNK):
            w = Words(data, offsets)
            at = w.whole(block)
            hashes = w.rolling.windows(block)[at] >> np.uint64(64 - BITS)
            yield Holders(hashes, w.doc[at], ids, np.zeros(len(ids), np.int32), w.local[at] % block == 0)

    return run


def _common(h: Holders, starts: np.ndarray):
    """Within a piece: a hash that two of its documents hold is an anchor of all its holders there. One entry of the
    smallest and one of the largest doc_id go on as blocks, so that others learn of it."""
    keys, group = h.holder(), spread(starts, len(h.hashes))
    low, high = np.minimum.reduceat(keys, starts), np.maximum.reduceat(keys, starts)
    several = (low < high)[group]
    speakers = []
    for end in (low, high):
        at = np.flatnonzero(several & (keys == end[group]))
        speakers.append(at[np.unique(group[at], return_index=True)[1]])
    speakers = np.concatenate(speakers)
    keep = ~several
    keep[speakers] = True
    flags = h.flags.copy()
    flags[speakers] = True
    places = np.flatnonzero(several)
    return Holders(h.hashes, h.owner, h.keys, h.sizes, flags).at(keep), places, h.hashes[places]


def _anchored(h: Holders, starts: np.ndarray):
    """Entries whose hash is that of a reference block of another document."""
    keys, group = h.holder(), spread(starts, len(h.hashes))
    low = np.minimum.reduceat(np.where(h.flags, keys, np.iinfo(np.int64).max), starts)
    high = np.maximum.reduceat(np.where(h.flags, keys, np.iinfo(np.int64).min), starts)
    hit = (low <= high)[group] & ((low[group] != keys) | (high[group] != keys))
    places = np.flatnonzero(hit)
    return places, h.hashes[places]


def _told_sets(batches):
    """(ids, bytes, offsets, what was told, document of each) pieces of batches whose third column holds what was told."""
    for batch in batches:
        at = 0
        for ids, data, offsets in pieces_of([batch], CHUNK):
            values = batch.column(2).slice(at, len(ids)).to_pylist()
            at += len(ids)
            sets = [np.frombuffer(v or b"", "<u8") for v in values]
            owner = np.repeat(np.arange(len(ids)), [len(s) for s in sets])
            yield ids, data, offsets, np.concatenate(sets) if sets else np.zeros(0, np.uint64), owner


def _among(hashes: np.ndarray, doc: np.ndarray, told_hashes: np.ndarray, owner: np.ndarray) -> np.ndarray:
    """Whether a document was told each of its hashes."""
    if not len(told_hashes):
        return np.zeros(len(hashes), bool)
    by_doc = np.uint64(0x9E3779B97F4A7C15)
    mixed_known = told_hashes ^ (owner.astype(np.uint64) * by_doc)
    mixed_mine = hashes ^ (doc.astype(np.uint64) * by_doc)
    return np.isin(mixed_mine, mixed_known)


def _followed(window: int, block: int):
    def run(batches):
        for ids, data, offsets, known, owner in _told_sets(batches):
            w = Words(data, offsets)
            at = w.whole(block)
            hit = at[_among(w.rolling.windows(block)[at] >> np.uint64(64 - BITS), w.doc[at], known, owner)]
            full = w.whole(window)
            near = np.searchsorted(hit, full + (window - block), side="right") > np.searchsorted(hit, full, side="left")
            full = full[near]
            digests = w.digests(full, window)
            notes = w.local[full].astype(np.uint32)
            yield Holders(digests[:, 0], w.doc[full], ids, np.zeros(len(ids), np.int32), np.zeros(len(full), bool), digests[:, 1], notes)

    return run


def _told_place(h: Holders, places: np.ndarray) -> np.ndarray:
    """A window's place in its document, and 32 bits of its digest: rows may share a doc_id, but not their places."""
    return (h.notes[places].astype(np.uint64) << np.uint64(32)) | (h.hashes[places] >> np.uint64(32))


def _later(h: Holders, starts: np.ndarray):
    """Entries of a window that a smaller doc_id has too."""
    keys = h.holder()
    places = np.flatnonzero(keys > np.minimum.reduceat(keys, starts)[spread(starts, len(keys))])
    return places, _told_place(h, places)


def _first_of_piece(h: Holders, starts: np.ndarray):
    """Within a piece: what isn't the first of its window is a repeat, whoever else has the window."""
    places, values = _later(h, starts)
    keep = np.ones(len(h.hashes), bool)
    keep[places] = False
    return h.at(keep), places, values


_KEPT = pa.schema(
    [("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_removed", pa.int64()), ("spans", pa.list_(pa.struct([("start", pa.int64()), ("length", pa.int64())]))), ("kept", pa.string())]
)


def _cut(window: int, shared: bool):
    def run(batches):
        for ids, data, offsets, known, owner in _told_sets(batches):
            w = Words(data, offsets)
            gone = np.zeros(len(w.doc) + 1, np.int32)
            local = (known >> np.uint64(32)).astype(np.int64)
            fits = local + window <= np.diff(w.before)[owner]
            bad, check = w.before[owner[fits]] + local[fits], known[fits] & np.uint64(0xFFFFFFFF)
            if shared:  # a place may be that of another row with the same doc_id
                bad = bad[w.digests(bad, window)[:, 0] >> np.uint64(32) == check]
            np.add.at(gone, bad, 1)
            np.add.at(gone, bad + window, -1)
            gone = np.cumsum(gone)[:-1] > 0
            body, bounds, before = data.tobytes(), offsets.tolist(), w.before.tolist()
            n_words, n_gone = np.diff(w.before), np.diff(np.concatenate(([0], np.cumsum(gone)))[w.before])
            kept, spans = [], []
            for i in range(len(ids)):
                words = body[bounds[i] : bounds[i + 1]].split()
                if n_gone[i]:
                    mine = gone[before[i] : before[i + 1]]
                    a, b = runs_of(mine)
                    spans.append([{"start": s, "length": e - s} for s, e in zip(a.tolist(), b.tolist(), strict=True)])
                    words = itertools.compress(words, (~mine).tolist())
                else:
                    spans.append([])
                kept.append(b" ".join(words))
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(n_words, pa.int64()), pa.array(n_gone, pa.int64()), pa.array(spans, _KEPT.field("spans").type), pa.array(kept, pa.binary()).cast(pa.string())], schema=_KEPT)

    return run


def remove_repeated_passages(docs: DataFrame, window: int = 50) -> DataFrame:
    """One row per document: doc_id, n_words, n_removed, spans (word positions of the runs cut out), kept (text)."""
    spark = docs.sparkSession
    small_batches(spark)
    block = window // 2
    rows = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID)).alias("doc_id"), text_or_empty().alias("text"))
    buckets = buckets_for(rows)
    anchors = settle(told(rows, _probes(block), _anchored, buckets, fold=_common).select(F.col("key").alias("doc_id"), "values"), "anchors")
    later = told(rows.join(anchors, "doc_id"), _followed(window, block), _later, buckets, 64, _first_of_piece)
    later = settle(later.select(F.col("key").alias("doc_id"), "values"), "repeats")
    discard(anchors)
    kept = rows.join(later, "doc_id", "left").mapInArrow(_cut(window, shared_ids(rows)), "doc_id long, n_words long, n_removed long, spans array<struct<start: long, length: long>>, kept string")
    return kept.withColumn("doc_id", F.nullif("doc_id", F.lit(NO_ID)))
