"""Quality scores of documents by a factorisation machine over hashed words and structure statistics.

Every occurrence of a hashed word and every statistic is a feature with a weight and a short vector; two
features interact by the product of their vectors. All interactions together cost one pass over the
features: half of (the square of the sum of scaled vectors, less the sum of their squares). Training runs
on the driver over a bounded sample of labelled documents; scoring runs over everything, in batches.

The inputs are the text and what follows from it (lengths count as metadata): never labels, language,
source or doc_id.

Defined cases: a null text counts as empty and is scored; labels other than 0 and 1, and null ones, teach
nothing; several labels of a document all count; without labels of both kinds every score is 1, so nothing
is rejected; rows that share a doc_id are scored each; an empty table gives an empty result; other columns
are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from nbflow.llm.common import P_BYTE, Rolling, discard, lowered, pieces_of, settle, small_batches, text_or_empty, text_views, word_spans

#: Labelled rows and bytes of text that training reads at most, hash slots of words, length of a feature's vector, epochs, seed.
SAMPLE_ROWS, SAMPLE_BYTES, SLOTS, FACTORS, EPOCHS, SEED = 6000, 64 << 20, 1 << 16, 8, 12, 7
THRESHOLD = 0.7
CHUNK = 1 << 20
#: Classes of bytes whose shares are statistics (fixed values).
CLASSES = {"upper": b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", "digit": b"0123456789", "space": b" ", "line": b"\n", "stop": b".,;:", "shout": b"!?", "bar": b"|\t", "sign": b"#$%&*^~@+=<>_\\/", "bracket": b"()[]{}\"'`-"}
STATISTICS = ("bytes", "words", "word_length", "lines", "line_length", "other_bytes", "upper_words", "distinct_words", "distinct_lines", "word_again", *CLASSES)


def _per_doc(values: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    sums = np.concatenate(([0], np.cumsum(values, dtype=np.int64)))
    return sums[bounds[1:]] - sums[bounds[:-1]]


def _distinct(hashes: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    doc = np.repeat(np.arange(len(bounds) - 1), np.diff(bounds))
    both = np.unique((doc.astype(np.uint64) << np.uint64(44)) | (hashes >> np.uint64(20)))
    return np.bincount((both >> np.uint64(44)).astype(np.int64), minlength=len(bounds) - 1)


def features(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(slot of each word, words before each document and after the last, statistics by document)."""
    starts, ends, before = word_spans(data, offsets)
    low = Rolling(lowered(data), P_BYTE) if len(data) else None
    hashes = low.of(starts, ends) if len(starts) else np.zeros(0, np.uint64)
    size, words = np.diff(offsets), np.diff(before)
    some, any_words = np.maximum(size, 1), np.maximum(words, 1)
    table = np.full(256, len(CLASSES), np.uint8)
    for i, members in enumerate(CLASSES.values()):
        table[list(members)] = i
    kind = table[data]
    shares = [_per_doc(kind == i, offsets) / some for i in range(len(CLASSES))]
    upper = np.concatenate(([0], np.cumsum(kind == 0)))
    shouted = (upper[ends] - upper[starts]) * 2 > (ends - starts) if len(starts) else np.zeros(0, bool)
    line_end = np.flatnonzero(data == 10)
    edges = np.unique(np.concatenate((offsets, line_end + 1)))
    line_bounds = np.searchsorted(edges, offsets)
    line_hash = low.of(edges[:-1], edges[1:]) if low is not None and len(edges) > 1 else np.zeros(0, np.uint64)
    lines = np.diff(line_bounds)
    again = np.zeros(len(hashes), bool)
    again[1:] = hashes[1:] == hashes[:-1]
    again[before[:-1][before[:-1] < len(again)]] = False
    stats = np.stack(
        [
            np.log1p(size),
            np.log1p(words),
            (size - _per_doc((data == 32) | (data == 10), offsets)) / any_words,
            np.log1p(lines),
            np.log1p(size / np.maximum(lines, 1)),
            _per_doc(data >= 128, offsets) / some,
            _per_doc(shouted, before) / any_words,
            _distinct(hashes, before) / any_words,
            _distinct(line_hash, line_bounds) / np.maximum(lines, 1),
            _per_doc(again, before) / any_words,
            *shares,
        ],
        axis=1,
    )
    return (hashes >> np.uint64(48)).astype(np.int64) % SLOTS, before, stats


@dataclass
class Model:
    """bias; weights and vectors of word slots, then of statistics; centre and scale of the statistics."""

    bias: float
    weights: np.ndarray
    vectors: np.ndarray
    centre: np.ndarray
    scale: np.ndarray

    def scores(self, slots: np.ndarray, before: np.ndarray, stats: np.ndarray) -> np.ndarray:
        words = np.diff(before)
        x = 1 / np.sqrt(np.maximum(words, 1))
        z = np.clip((stats - self.centre) / self.scale, -6, 6)
        w, v = self.weights, self.vectors
        squares = (v[:SLOTS] ** 2).sum(1)

        def summed(values):
            sums = np.concatenate((np.zeros((1, *values.shape[1:])), np.cumsum(values, axis=0, dtype=np.float64)))
            return sums[before[1:]] - sums[before[:-1]]

        linear = x * summed(w[:SLOTS][slots]) + z @ w[SLOTS:]
        total = x[:, None] * summed(v[:SLOTS][slots]) + z @ v[SLOTS:]
        alone = x**2 * summed(squares[slots]) + (z**2) @ (v[SLOTS:] ** 2).sum(1)
        return 1 / (1 + np.exp(-np.clip(self.bias + linear + 0.5 * ((total**2).sum(1) - alone), -30, 30)))


def trained(rows: list[tuple[np.ndarray, np.ndarray, np.ndarray, int]], factors: int = FACTORS, epochs: int = EPOCHS, seed: int = SEED) -> Model | None:
    """rows: (slots, counts, statistics, label). Adaptive gradient steps on the logistic loss, batch after batch."""
    labels = np.array([r[3] for r in rows], float)
    if not len(rows) or labels.min() == labels.max():
        return None
    rng = np.random.default_rng(seed)
    stats = np.array([r[2] for r in rows])
    centre, scale = stats.mean(0), stats.std(0) + 1e-6
    z_all = np.clip((stats - centre) / scale, -6, 6)
    n_stats = stats.shape[1]
    w, v = np.zeros(SLOTS + n_stats), rng.normal(0, 0.02, (SLOTS + n_stats, factors))
    bias, seen_b = float(np.log(labels.mean() / (1 - labels.mean()))), 1e-6
    # the features of all rows, one row after the other, numbered among the slots that occur
    stat_at, ones = np.arange(SLOTS, SLOTS + n_stats), np.ones(n_stats)
    known, feature = np.unique(np.concatenate([x for r in rows for x in (r[0], stat_at)]), return_inverse=True)
    count_of = np.concatenate([x for r in rows for x in (r[1], ones)])
    value_of = np.concatenate([x for r, z in zip(rows, z_all, strict=True) for x in (np.full(len(r[0]), 1 / np.sqrt(max(1, r[1].sum()))), z)])
    length = np.array([len(r[0]) + n_stats for r in rows])
    first, m = np.cumsum(length) - length, len(known)
    w_, v_ = w[known], v[known]
    seen_w, seen_v = np.full(m, 1e-6), np.full((m, factors), 1e-6)
    for epoch in range(epochs):
        rate = 0.05 / (1 + 0.3 * epoch)
        for batch in np.array_split(rng.permutation(len(rows)), max(1, len(rows) // 64)):
            size = length[batch]
            begin = np.cumsum(size) - size
            at = np.repeat(np.arange(len(batch)), size)
            place = (first[batch] - begin)[at] + np.arange(len(at))
            index, value, count = feature[place], value_of[place], count_of[place]
            vx = v_[index] * value[:, None]
            total = np.add.reduceat(vx * count[:, None], begin)
            raw = bias + np.add.reduceat(w_[index] * value * count, begin) + 0.5 * ((total**2).sum(1) - np.add.reduceat((vx**2).sum(1) * count, begin))
            error = (1 / (1 + np.exp(-np.clip(raw, -30, 30))) - labels[batch]) / len(batch)
            pull = error[at] * value * count
            used = np.flatnonzero(np.bincount(index, minlength=m))
            g_w = np.bincount(index, pull, m)[used] + 1e-5 * w_[used]
            g_v = np.stack([np.bincount(index, pull * (total[at, f] - vx[:, f]), m)[used] for f in range(factors)], axis=1) + 1e-4 * v_[used]
            seen_w[used] += g_w**2
            seen_v[used] += g_v**2
            w_[used] -= rate * g_w / np.sqrt(seen_w[used])
            v_[used] -= rate * g_v / np.sqrt(seen_v[used])
            g_b = float(error.sum())
            seen_b += g_b**2
            bias -= rate * g_b / np.sqrt(seen_b)
    w[known], v[known] = w_, v_
    return Model(bias, w, v, centre, scale)


_SAMPLE = pa.schema([("label", pa.int32()), ("slots", pa.binary()), ("counts", pa.binary()), ("stats", pa.binary())])


def _sampled(batches):
    for batch in batches:
        data, offsets = text_views(batch.column(1))
        slots, before, stats = features(data, offsets)
        out = []
        for i, label in enumerate(batch.column(2).to_pylist()):
            used, counts = np.unique(slots[before[i] : before[i + 1]], return_counts=True)
            out.append((label, used.astype("<i4").tobytes(), counts.astype("<i4").tobytes(), stats[i].astype("<f8").tobytes()))
        if out:
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*out, strict=True), _SAMPLE, strict=True)], schema=_SAMPLE)


def held_out(doc_id="doc_id"):
    """Rows that training never sees: the CRC-32 of doc_id as text leaves 2 when divided by 4."""
    return F.coalesce(F.pmod(F.crc32(F.col(doc_id).cast("string").cast("binary")), F.lit(4)) == 2, F.lit(False))


def train(docs: DataFrame, labels: DataFrame, sample_rows: int = SAMPLE_ROWS, sample_bytes: int = SAMPLE_BYTES) -> Model | None:
    """A model of ``labels.quality`` from at most ``sample_rows`` labelled rows and about ``sample_bytes`` of their
    texts, the first by a hash of doc_id."""
    small_batches(docs.sparkSession)
    usable = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("quality").cast("int").alias("label")).filter("label in (0, 1) and doc_id is not null")
    sample = usable.filter(~held_out()).orderBy(F.xxhash64("doc_id"), "doc_id", "label").limit(sample_rows)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_or_empty().alias("text")).join(F.broadcast(sample), "doc_id").select("doc_id", "text", "label")
    rows = settle(rows, "labelled")
    order = Window.partitionBy(F.lit(0)).orderBy(F.xxhash64("doc_id"), "doc_id", "label", "size")  # of sample_rows rows and their repeats
    sized = rows.select("doc_id", "label", F.octet_length("text").alias("size")).withColumn("ahead", F.sum("size").over(order) - F.col("size"))
    ids = sized.filter(F.col("ahead") < sample_bytes).select("doc_id").distinct()
    found = rows.join(F.broadcast(ids), "doc_id", "left_semi").mapInArrow(_sampled, "label int, slots binary, counts binary, stats binary").collect()
    discard(rows)
    unpacked = [(np.frombuffer(r["slots"], "<i4").astype(np.int64), np.frombuffer(r["counts"], "<i4").astype(float), np.frombuffer(r["stats"], "<f8"), r["label"]) for r in found]
    unpacked.sort(key=lambda r: (r[3], r[2].tobytes(), r[0].tobytes()))  # the tasks' order is no matter
    return trained(unpacked)


_SCORES = pa.schema([("doc_id", pa.int64()), ("score", pa.float64())])


def _scored(model):
    def run(batches):
        for batch in batches:
            ids = batch.column(0)
            at = 0
            for _, data, offsets in pieces_of([batch], CHUNK):
                n = len(offsets) - 1
                scores = model.value.scores(*features(data, offsets)) if model.value is not None else np.ones(n)
                yield pa.RecordBatch.from_arrays([ids.slice(at, n), pa.array(scores)], schema=_SCORES)
                at += n

    return run


def quality_scores(docs: DataFrame, labels: DataFrame, model: Model | None = None) -> DataFrame:
    """One row per document: doc_id, held_out, score, predicted (1 from ``THRESHOLD`` on)."""
    shared = docs.sparkSession.sparkContext.broadcast(model or train(docs, labels))
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_or_empty().alias("text"))
    scored = rows.mapInArrow(_scored(shared), "doc_id long, score double")
    return scored.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))


def _accepted(model, text_at: int):
    def run(batches):
        for batch in batches:
            at = 0
            for _, data, offsets in pieces_of([pa.RecordBatch.from_arrays([pa.array(np.zeros(batch.num_rows, np.int64)), batch.column(text_at)], names=["i", "t"])], CHUNK):
                n = len(offsets) - 1
                good = model.value.scores(*features(data, offsets)) >= THRESHOLD if model.value is not None else np.ones(n, bool)
                yield batch.slice(at, n).filter(pa.array(good))
                at += n

    return run


def accepted(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The rows of ``docs`` that the classifier accepts, with all their columns."""
    shared = docs.sparkSession.sparkContext.broadcast(train(docs, labels))
    return docs.mapInArrow(_accepted(shared, docs.columns.index("text")), docs.schema)
