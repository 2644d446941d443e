"""Removal of repeated byte strings through a Burrows-Wheeler transform that grows column by column.

Sorting the suffixes of all texts at once fits no machine, so texts are first cut where it does no harm:
every window of ``length`` bytes belongs to the segment of its minimizer (the least hash among its
grams), and equal windows have equal minimizers. A segment holds successive windows of one minimizer.
Segments whose minimizer occurs once in all texts hold no repeat; the others travel to the bucket of
their minimizer. There each collection of segments gets its suffix order by column-wise construction over
symbols of a few bytes (a divisor of ``length``): a segment is read in as many phases as a symbol has
bytes, each phase a document of the collection, so that every byte begins one suffix. Round j puts the
suffixes of j symbols, one of each document, among the shorter ones, by counting symbols in the transform
built so far, and computes the common prefixes of what it inserts from those already known. The columns
of the construction (transform, common prefixes, document, suffix length) live in files that a round reads
and writes from front to back. Suffixes in a run of common prefixes of at least ``length`` bytes are
repeats of the earliest of them.

A minimizer with more segments than one construction takes is split by where its windows begin: windows
of one half of the places share all bytes between the outermost of them, and those bytes are the key of
the half. Places halve until a part fits. Minimizers that are hot over all texts (a bounded list, as only so many
can have that many segments) are split by the senders already, the deeper the hotter, so that the parts go to different
buckets; the last split leaves the windows themselves as keys, and equal ones fold.

Copies of a segment are folded before the exchange, in the task that reads them: all but the earliest are
repeats already. So the most frequent passage reaches its bucket once per ``FOLD_BYTES`` of segments at most.

Defined cases: texts are UTF-8 bytes, a null text is empty; matches never cross documents; rows that
share a doc_id count as one document; a missing doc_id counts as the smallest; an empty table gives an
empty result; other columns are ignored.
"""

from __future__ import annotations

import os
import pickle
import struct
import tempfile
from collections import defaultdict

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from nbflow.llm.block_anchors import _among, _told_sets
from nbflow.llm.common import NO_ID, P_BYTE, Rolling, buckets_for, discard, mixed, pieces_of, runs_of, settle, shared_ids, small_batches, text_or_empty, trim
from nbflow.llm.packed import ANSWER, BITS, MASK, QUESTION, Holders, _by_key, _sent, addressed, dealt, decided, spread, told

CHUNK = 1 << 20
#: Bytes of a gram, bytes of segments that one construction takes, and sizes of a symbol: the first that divides the length.
GRAM, COLLECTION, SYMBOLS = 40, 200_000, (5, 4, 2, 1)
#: Bytes of segments that a sender folds at a time; segments from which a minimizer is hot, or one in so many of all
#: bytes, whichever is more: so no more than that many minimizers can be hot.
FOLD_BYTES, HOT_SEGMENTS, MOST_HOT = 24 << 20, 4096, 1_000_000
#: The document that stands for the list of hot minimizers in what is told; its values have a level in their upper bits.
HOT_KEY = (1 << 63) - 1


def sliding_least(values: np.ndarray, width: int) -> np.ndarray:
    """The least of every window of ``width`` values, by running minima of blocks from both ends."""
    n = len(values) - width + 1
    if n <= 0:
        return values[:0]
    blocks = -(-len(values) // width)
    padded = np.full(blocks * width, np.iinfo(values.dtype).max, values.dtype)
    padded[: len(values)] = values
    padded = padded.reshape(blocks, width)
    ahead = np.minimum.accumulate(padded, axis=1).ravel()
    behind = np.minimum.accumulate(padded[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(behind[:n], ahead[width - 1 : width - 1 + n])


def segments(data: np.ndarray, offsets: np.ndarray, length: int, gram: int):
    """(start, number of windows, minimizer's hash, document, minimizer's place in the segment) of the segments;
    starts count within ``data``."""
    n = len(data) - length + 1
    if n <= 0:
        none = np.zeros(0, np.int64)
        return none, none, np.zeros(0, np.uint64), none, none
    grams = Rolling(data, P_BYTE).windows(gram)
    place = np.arange(len(grams), dtype=np.uint64)
    least = (sliding_least((grams & ~np.uint64(0xFFFFFFFF)) | place, length - gram + 1) & np.uint64(0xFFFFFFFF)).astype(np.int64)
    doc = np.repeat(np.arange(len(offsets) - 1), np.diff(offsets))
    whole = doc[:n] == doc[length - 1 :]
    new = np.ones(n, bool)
    new[1:] = (least[1:] != least[:-1]) | ~whole[:-1] | (doc[1:n] != doc[: n - 1])
    edge = np.flatnonzero(new | ~whole)
    size = np.diff(np.append(edge, n))
    edge, size = edge[whole[edge]], size[whole[edge]]
    # minimizers are the least of many hashes: mixed once more, so that their ranges are even
    return edge, size, mixed(grams[least[edge]]) >> np.uint64(64 - BITS), doc[edge], least[edge] - edge


def _minimizers(length: int, gram: int):
    """Each minimizer of a document once, with its number of segments; the flag says that there are several (as periodic
    texts have)."""

    def run(batches):
        for ids, data, offsets in pieces_of(batches, CHUNK):
            _, _, hashes, doc, _ = segments(data, offsets, length, gram)
            both, times = np.unique((doc.astype(np.uint64) << np.uint64(BITS)) | hashes, return_counts=True)
            yield Holders(both & MASK, (both >> np.uint64(BITS)).astype(np.int64), ids, np.zeros(len(ids), np.int32), times > 1, notes=times.astype(np.uint32))

    return run


def _several(h: Holders, starts: np.ndarray) -> np.ndarray:
    return (np.diff(np.append(starts, len(h.hashes))) > 1) | np.logical_or.reduceat(h.flags, starts)


def _repeated(h: Holders, starts: np.ndarray):
    places = np.flatnonzero(_several(h, starts)[spread(starts, len(h.hashes))])
    return places, h.hashes[places]


def _repeated_here(h: Holders, starts: np.ndarray):
    """Within a piece: a minimizer that it has twice is repeated for all its holders there; one entry goes on for all."""
    several, group = _several(h, starts), spread(starts, len(h.hashes))
    notes, flags, keep = h.notes.copy(), h.flags.copy(), ~several[group]
    notes[starts] = np.minimum(np.add.reduceat(h.notes.astype(np.int64), starts), 0xFFFFFFFF)
    flags[starts[several]] = keep[starts] = True
    places, values = _repeated(h, starts)
    return Holders(h.hashes, h.owner, h.keys, h.sizes, flags, notes=notes).at(keep), places, values


def _hot(limit: int):
    """Minimizers of more than ``limit`` segments, each with how often its places are to be halved in front."""

    def run(h: Holders, starts: np.ndarray) -> np.ndarray:
        count = np.add.reduceat(h.notes.astype(np.int64), starts)
        hot = count > limit
        level = np.clip(np.ceil(np.log2(count[hot] / limit)), 1, 8).astype(np.uint64)
        return (level << np.uint64(BITS)) | h.hashes[starts[hot]]

    return run


def _check(text: bytes) -> int:
    return xxhash.xxh3_64_intdigest(text) >> 40


def _runs(runs: list[tuple[int, int, int, int]], buckets: int):
    """Blocks, by bucket of the document, of runs of windows (document, start, number, check) that begin earlier elsewhere."""
    if not runs:
        return
    docs, starts, sizes, checks = np.array(runs, np.int64).T
    keys, owner = np.unique(docs, return_inverse=True)
    values = (starts.astype(np.uint64) << np.uint64(32)) | (sizes.astype(np.uint64) << np.uint64(24)) | checks.astype(np.uint64)
    h = Holders(values, owner, keys, np.zeros(len(keys), np.int32), np.zeros(len(owner), bool))
    yield from addressed(h, np.arange(len(owner)), values, buckets)


def split_by_place(segments_of: list[tuple], low: int, high: int, length: int):
    """Halves of a minimizer's segments (document, start, place, text), by how far ahead of the minimizer (low to
    high bytes) windows begin; in a half, segments go by the bytes that all its windows have."""
    mid = (low + high + 1) // 2
    for a, b in ((low, mid - 1), (mid, high)):
        parts = defaultdict(list)
        for doc, start, place, text in segments_of:
            most, least = min(b, place), max(a, place - (len(text) - length))
            if most >= least and a <= b:
                cut = place - most
                common = text[place - a : place - b + length]
                parts[common].append((doc, start + cut, most, text[cut : place - least + length]))
        for part in parts.values():
            yield part, a, b


def divided(some: list[tuple], low: int, high: int, length: int, levels: int):
    """Parts (segments, low, high) after ``levels`` halvings, or as many as the places allow."""
    todo = [(some, low, high, levels)]
    while todo:
        some, low, high, levels = todo.pop()
        if levels and low < high:
            todo += [(*part, levels - 1) for part in split_by_place(some, low, high, length)]
        else:
            yield some, low, high


def part_key(segment: tuple, hashed: int, low: int, high: int, length: int) -> int:
    """48 bits for the bucket and the group of a hot minimizer's part: windows of the part have these bytes in common."""
    _, _, place, text = segment
    return xxhash.xxh3_64_intdigest(text[place - low : place - high + length] + struct.pack("<QHH", hashed, low, high)) >> (64 - BITS)


def _folded(length: int, gram: int, buckets: int, hot: np.ndarray, checked: bool):
    """Rows (bucket, block): questions are segments for the bucket of their minimizer or part, answers are runs already
    known to begin earlier. hot: minimizers with their levels in front, in order of the minimizers."""
    hot_hashes, levels = hot & MASK, (hot >> np.uint64(BITS)).astype(np.int64)

    def parts(batches):
        """(key, low, high, segments) of each piece's segments that may have repeats."""
        for ids, data, offsets, known, owner in _told_sets(batches):
            edge, size, hashes, doc, place = segments(data, offsets, length, gram)
            use = np.flatnonzero(_among(hashes, doc, known, owner))
            edge, size, hashes, doc, place = edge[use], size[use], hashes[use], doc[use], place[use]
            at = np.minimum(np.searchsorted(hot_hashes, hashes), max(len(hot_hashes) - 1, 0))
            level = np.where(hot_hashes[at] == hashes, levels[at], 0) if len(hot_hashes) else np.zeros(len(hashes), np.int64)
            body, ids = data.tobytes(), ids.tolist()
            rows = zip(hashes.tolist(), level.tolist(), doc.tolist(), (edge - offsets[doc]).tolist(), place.tolist(), edge.tolist(), (edge + size + length - 1).tolist(), strict=True)
            for hashed, lv, d, start, p, a, b in rows:
                one = (ids[d], start, p, body[a:b])
                if not lv:
                    yield hashed, 0, length - gram, one
                    continue
                for some, low, high in divided([one], 0, length - gram, length, lv):
                    yield part_key(some[0], hashed, low, high, length), low, high, some[0]

    def blocks(batches):
        first: dict[bytes, tuple] = {}
        later: list[tuple] = []
        held = 0

        def flushed():
            for to, block in _runs(later, buckets):
                yield to, ANSWER + block
            rows = list(first.values())
            to = np.array([(r[0] * buckets) >> BITS for r in rows], np.int64)
            order = np.argsort(to, kind="stable")
            cuts = np.flatnonzero(np.diff(to[order], prepend=-1)).tolist()
            for a, b in zip(cuts, [*cuts[1:], len(rows)], strict=True):
                yield int(to[order[a]]), QUESTION + pickle.dumps([rows[i] for i in order[a:b].tolist()], protocol=5)

        for key, low, high, one in parts(batches):
            there = first.get(one[3])  # equal texts have equal windows, so equal keys
            if there is None:
                first[one[3]] = (key, low, high, one)
                held += len(one[3]) + 200
            else:
                if one[:2] < there[3][:2]:
                    first[one[3]] = (key, low, high, one)
                    one = there[3]
                later.append((*one[:2], len(one[3]) - length + 1, _check(one[3]) if checked else 0))
            if held + 40 * len(later) > FOLD_BYTES:
                yield from flushed()
                first, later, held = {}, [], 0
        if first:
            yield from flushed()

    def run(batches):
        yield from _sent(blocks(batches))

    return run


class ColumnFiles:
    """The columns of a construction, one file each and round; read and written from front to back."""

    def __init__(self, folder: str):
        self.folder, self.round, self.kinds = folder, 0, {}

    def write(self, **columns: np.ndarray) -> None:
        before, self.round = self.round, self.round + 1
        for name, values in columns.items():
            self.kinds[name] = values.dtype
            values.tofile(f"{self.folder}/{name}.{self.round}")
            if before:
                os.unlink(f"{self.folder}/{name}.{before}")

    def read(self, name: str) -> np.ndarray:
        return np.fromfile(f"{self.folder}/{name}.{self.round}", self.kinds[name])

    def drop(self) -> None:
        for name in self.kinds:
            os.unlink(f"{self.folder}/{name}.{self.round}")


def _range_least(values: np.ndarray, low: np.ndarray, high: np.ndarray) -> np.ndarray:
    """The least of values[low..high] for each pair (both ends included), by a pyramid of pairwise minima."""
    out = np.full(len(low), 255, values.dtype)
    at, low, high = np.arange(len(low)), low.copy(), high.copy()
    while len(at):
        odd = (low & 1).astype(bool)
        out[at[odd]] = np.minimum(out[at[odd]], values[low[odd]])
        even = ~(high & 1).astype(bool)
        out[at[even]] = np.minimum(out[at[even]], values[high[even]])
        low, high = (low + 1) >> 1, (high - 1) >> 1
        go = low <= high
        at, low, high = at[go], low[go], high[go]
        if len(at):
            if len(values) & 1:
                values = np.append(values, values.dtype.type(255))
            values = np.minimum(values[::2], values[1::2])
    return out


def sorted_suffixes(body: np.ndarray, lengths: np.ndarray, folder: str, cap: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(transform, common prefixes up to ``cap``, text, suffix length) of all suffixes of texts, in order.

    body: the symbols (from 1) of all texts, one text after the other. Symbol 0 of the transform marks a whole
    text. Equal suffixes are in order of their texts. A round costs one stable sort of the transform's
    symbols, which is where every suffix goes once its preceding symbol is put in front, and one pass over
    the columns."""
    m, kind = len(lengths), body.dtype
    ends = np.cumsum(lengths)

    def before(text: np.ndarray, have: int) -> np.ndarray:
        """The symbol in front of the suffix of ``have`` bytes."""
        out = np.zeros(len(text), kind)
        more = lengths[text] > have
        out[more] = body[ends[text[more]] - have - 1]
        return out

    fresh_text = np.arange(m)
    files = ColumnFiles(folder)
    fresh = np.ones(m, bool)
    files.write(bwt=before(fresh_text, 0), lcp=np.zeros(m, np.uint8), text=fresh_text.astype(np.int32), size=np.zeros(m, np.uint16))
    have = 0
    while True:
        bwt = files.read("bwt")
        mine = bwt[fresh]
        go = mine > 0
        if not go.any():
            break
        have += 1
        order = np.argsort(bwt, kind="stable")
        order = order[np.searchsorted(bwt[order], 1) :] if (bwt == 0).any() else order
        new = fresh[order]
        inserted = np.argsort(mine[go], kind="stable")
        fresh_text = fresh_text[go][inserted]
        lcp = files.read("lcp")
        # what is inserted, and what then follows it, gets a common prefix with the suffix in front
        touched = new.copy()
        touched[1:] |= new[:-1]
        at = np.flatnonzero(touched)
        at = at[at > 0]
        same = bwt[order[at]] == bwt[order[at - 1]]
        value = np.zeros(len(at), np.uint8)
        near = at[same]
        value[same] = np.minimum(_range_least(lcp, order[near - 1] + 1, order[near]).astype(np.int64) + 1, cap)
        total = m + len(order)
        fresh = np.zeros(total, bool)
        fresh[m:] = new
        old = ~fresh
        old_tail = np.flatnonzero(old[m:])

        def merged(name: str, values: np.ndarray) -> np.ndarray:
            column = files.read(name)
            out = np.empty(total, column.dtype)
            out[:m] = column[:m]
            out[m:][old_tail] = column[m:]
            out[m:][new] = values
            return out

        next_lcp = merged("lcp", np.zeros(len(fresh_text), np.uint8))
        next_lcp[m + at] = value
        if total > m:
            next_lcp[m] = 0
        files.write(
            bwt=merged("bwt", before(fresh_text, have)),
            lcp=next_lcp,
            text=merged("text", fresh_text.astype(np.int32)),
            size=merged("size", np.full(len(fresh_text), have, np.uint16)),
        )
    out = tuple(files.read(c) for c in ("bwt", "lcp", "text", "size"))
    files.drop()
    return out


def phases(texts: list[bytes], q: int) -> tuple[np.ndarray, np.ndarray]:
    """(symbols, lengths) of the documents that reading each text in ``q`` phases gives: document q * i + p is
    text i from byte p on, in whole symbols of q bytes, numbered from 1 in their order."""
    sizes = np.array([len(t) for t in texts], np.int64)
    begin = np.cumsum(sizes) - sizes
    body = np.frombuffer(b"".join(texts) + bytes(q), np.uint8).astype(np.uint64)
    code = np.zeros(len(body) - q, np.uint64)
    for i in range(q):
        code = (code << np.uint64(8)) | body[i : len(body) - q + i]
    phase = np.tile(np.arange(q), len(texts))
    lengths = np.maximum(np.repeat(sizes, q) - phase, 0) // q
    doc = np.repeat(np.arange(len(lengths)), lengths)
    nth = np.arange(len(doc)) - np.repeat(np.cumsum(lengths) - lengths, lengths)
    known, ranks = np.unique(code[begin[doc // q] + phase[doc] + q * nth], return_inverse=True)
    return (ranks + 1).astype(np.uint8 if len(known) < 255 else np.uint16 if len(known) < 65535 else np.uint32), lengths


def repeats(texts: list[bytes], docs: np.ndarray, starts: np.ndarray, length: int, folder: str):
    """(document, start, text, place in it) of the windows of ``length`` bytes that begin earlier too; earlier: smaller
    document, then start."""
    q = next(x for x in SYMBOLS if length % x == 0)
    symbols, lengths = phases(texts, q)
    _, lcp, text, size = sorted_suffixes(symbols, lengths, folder, length // q)
    group = np.cumsum((lcp < length // q) | (size < length // q))
    at = np.flatnonzero(size >= length // q)
    group, text, size = group[at], text[at].astype(np.int64), size[at].astype(np.int64)
    many = np.bincount(group)[group] > 1 if len(group) else np.zeros(0, bool)
    group, text, size = group[many], text[many], size[many]
    place = text % q + q * (lengths[text] - size)
    text //= q
    doc, start = docs[text], starts[text] + place
    order = np.lexsort((start, doc, group))
    again = np.concatenate(([False], group[order][1:] == group[order][:-1])) if len(order) else np.zeros(0, bool)
    return tuple(x[order][again] for x in (doc, start, text, place))


def _ordered(length: int, buckets: int, checked: bool):
    """The runs (start, number of windows) of every document that a bucket of minimizers decides."""

    def runs(got: list[memoryview], folder: str):
        later: list[tuple] = []

        def again(doc: int, start: int, text: bytes):
            later.append((doc, start, len(text) - length + 1, _check(text) if checked else 0))

        def folded(some):
            """The earliest of each text; the others' windows all begin earlier."""
            first: dict[bytes, tuple] = {}
            for one in some:
                there = first.setdefault(one[3], one)
                if there is not one:
                    first[one[3]] = min(one, there)
                    again(*max(one, there)[:2], one[3])
            return list(first.values())

        batch: list[tuple] = []
        held = 0

        def flush():
            nonlocal held
            if batch:
                texts = [x[3] for x in batch]
                doc, start, text, place = repeats(texts, np.array([x[0] for x in batch]), np.array([x[1] for x in batch]), length, folder)
                for d, s, t, p in zip(doc.tolist(), start.tolist(), text.tolist(), place.tolist(), strict=True):
                    again(d, s, texts[t][p : p + length])
                batch.clear()
                held = 0
                trim()

        groups = defaultdict(list)
        for block in got:
            for key, low, high, one in pickle.loads(block):
                groups[key, low, high].append(one)
        todo = [(some, low, high) for (_, low, high), some in groups.items() if len(some) > 1]
        del groups
        while todo:
            some, low, high = todo.pop()
            some = folded(some)
            if len(some) < 2:  # no other segment to compare
                continue
            size = sum(len(x[3]) for x in some)
            if size > COLLECTION and low < high:
                todo += [x for x in split_by_place(some, low, high, length) if len(x[0]) > 1]
                continue
            batch += some
            held += size
            if held > COLLECTION:
                flush()
        flush()
        return later

    def run(batches):
        with tempfile.TemporaryDirectory() as folder:
            yield from _sent(decided(batches, lambda got: _runs(runs(got, folder), buckets)))

    return run


_KEPT = pa.schema(
    [("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("n_removed", pa.int64()), ("spans", pa.list_(pa.struct([("start", pa.int64()), ("length", pa.int64())]))), ("kept", pa.binary())]
)


def _cut(length: int, checked: bool):
    def told_runs(text: bytes, told_: bytes | None):
        """Starts and ends of the runs of bytes to go. Rows may share a doc_id, but not what they have at a place."""
        v = np.frombuffer(told_ or b"", "<u8")
        start = (v >> np.uint64(32)).astype(np.int64)
        end = start + (v >> np.uint64(24) & np.uint64(0xFF)).astype(np.int64) + length - 1
        if checked:
            mine = [b <= len(text) and _check(text[a:b]) == c for a, b, c in zip(start.tolist(), end.tolist(), (v & np.uint64(0xFFFFFF)).tolist(), strict=True)]
            start, end = start[mine], end[mine]
        return start, end

    def run(batches):
        for batch in batches:
            at = 0
            for ids, data, offsets in pieces_of([batch], CHUNK):
                values = batch.column(2).slice(at, len(ids)).to_pylist()
                at += len(ids)
                body, bounds = data.tobytes(), offsets.tolist()
                rows = []
                for i, told_ in enumerate(values):
                    text = body[bounds[i] : bounds[i + 1]]
                    start, end = told_runs(text, told_)
                    if len(start):
                        edges = np.zeros(len(text) + 1, np.int32)
                        np.add.at(edges, start, 1)
                        np.add.at(edges, end, -1)
                        gone = np.cumsum(edges)[:-1] > 0
                        a, b = runs_of(gone)
                        kept = np.frombuffer(text, np.uint8)[~gone].tobytes()
                        rows.append((int(ids[i]), len(text), int(gone.sum()), [{"start": s, "length": e - s} for s, e in zip(a.tolist(), b.tolist(), strict=True)], kept))
                    else:
                        rows.append((int(ids[i]), len(text), 0, [], text))
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), _KEPT, strict=True)], schema=_KEPT)

    return run


def remove_repeated_bytes(docs: DataFrame, length: int = 100, gram: int = GRAM, hot_segments: int = HOT_SEGMENTS) -> DataFrame:
    """One row per document: doc_id, n_bytes, n_removed, spans (byte positions of the maximal runs cut out), kept (bytes)."""
    if not 0 <= length - gram < 255:
        raise ValueError("a gram is at most as long as a window, and less than 255 bytes shorter")
    spark = docs.sparkSession
    small_batches(spark)
    rows = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID)).alias("doc_id"), text_or_empty().alias("text"))
    buckets, checked = buckets_for(rows), shared_ids(rows)
    limit = max(hot_segments, (rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0) // MOST_HOT)
    shared = told(rows, _minimizers(length, gram), _repeated, buckets, fold=_repeated_here, noted=(HOT_KEY, _hot(limit)))
    shared = settle(shared.select(F.col("key").alias("doc_id"), "values"), "minimizers")
    noted = shared.filter(F.col("doc_id") == HOT_KEY).first()  # one row, of MOST_HOT numbers at most
    hot = np.frombuffer(noted["values"] if noted else b"", "<u8")
    hot = hot[hot > MASK]
    hot = hot[np.argsort(hot & MASK)]
    blocks = "bucket int, block binary"
    sent = rows.join(shared, "doc_id").mapInArrow(_folded(length, gram, buckets, hot, checked), blocks)
    found = dealt(dealt(sent, buckets).mapInArrow(_ordered(length, buckets, checked), blocks), buckets).mapInArrow(_by_key, "key long, size int, values binary")
    found = settle(found.select(F.col("key").alias("doc_id"), "values"), "byte-runs")
    discard(shared)
    kept = rows.join(found, "doc_id", "left").mapInArrow(_cut(length, checked), "doc_id long, n_bytes long, n_removed long, spans array<struct<start: long, length: long>>, kept binary")
    return kept.withColumn("doc_id", F.nullif("doc_id", F.lit(NO_ID)))
