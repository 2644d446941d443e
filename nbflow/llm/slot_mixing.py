"""Mixing of sources to target weights by blocks and permuted slots.

The words of each source, its documents one after the other, are cut into blocks of fixed length. A
source's target gives it a number of slots in the mix; output shards draw their source counts at random
under these totals (multinomial draws, given their sums: the totals are halved again and again by
multivariate hypergeometric draws, each seeded by its place, so any shard finds its counts alone). The
n-th slot of a source takes the block that the source's pseudorandom permutation of block numbers gives;
once all blocks are used, another permutation follows. Slots and blocks meet by number.

Defined cases: a null text has no words; a null source is a source, last in order; a source without
words gets nothing; rows that share a doc_id are documents each, and rows equal in doc_id, source and text stand for
one another; reruns agree; an empty table gives an empty result; other columns are ignored and may have any name.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from nbflow.llm.common import WORD, fresh, is_space, partitions, settle, small_batches, text_views

#: Weights of the sources in order, repeating (fixed values), and the mix's size in sizes of all sources.
WEIGHTS, SHARE, MOST = (5, 2, 1), 1.5, 2.0
BLOCK_WORDS, SHARD_SLOTS, SEED = 128, 1024, 20240
#: Documents of a part, whose words are numbered in one task, and the total that the library's exact draw takes.
PART_DOCS, EXACT_DRAW = 1_000_000, 10**9


def targets(sizes: list[int], weights: list[float], total: float, most: float = MOST) -> list[float]:
    """Shares of ``total`` by weight, none above ``most`` times its size; what is cut off is shared again."""
    out, open_ = [0.0] * len(sizes), [i for i, n in enumerate(sizes) if n]
    left = total
    while open_:
        unit = left / sum(weights[i] for i in open_)
        over = [i for i in open_ if weights[i] * unit > most * sizes[i]]
        if not over:
            for i in open_:
                out[i] = weights[i] * unit
            break
        for i in over:
            out[i] = most * sizes[i]
            left -= out[i]
        open_ = [i for i in open_ if i not in over]
    return out


def _halves(counts: np.ndarray, left: int, rng: np.random.Generator) -> np.ndarray:
    """How many of ``left`` slots, drawn at random from all, fall to each source. Beyond the totals that the library
    draws from exactly, each source in turn is drawn by the limit that its law has there: a binomial one for the few
    slots of a small source, a normal one of the same mean and spread for others."""
    total = int(counts.sum())
    if total < EXACT_DRAW:
        return rng.multivariate_hypergeometric(counts, left, method="marginals")
    out, open_ = np.zeros(len(counts), np.int64), total
    for i, mine in enumerate(map(int, counts)):
        others = open_ - mine
        low, high = max(0, left - others), min(mine, left)
        mean = left * mine / open_ if open_ else 0.0
        if mine < 100_000:
            drawn = int(rng.binomial(mine, left / open_)) if open_ else 0
        else:
            drawn = round(rng.normal(mean, math.sqrt(max(mean * (others / open_) * ((open_ - left) / max(open_ - 1, 1)), 0.0))))
        out[i] = min(max(drawn, low), high)
        left, open_ = left - int(out[i]), others
    return out


def row_keys(columns: tuple[str, ...] = ("doc_id", "source", "text")) -> list:
    """Two independent hashes of a row's doc_id, source and text."""
    parts = [x for c in columns for x in (F.isnull(c), F.col(c))]
    return [F.xxhash64(F.lit(n), *parts) for n in (1, 2)]


def shard_counts(shard: int, shards: int, slots: np.ndarray, per_shard: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
    """(counts, slots of each source in earlier shards) of one output shard."""
    low, high, counts, before = 0, shards, slots.astype(np.int64), np.zeros(len(slots), np.int64)
    while high - low > 1:
        mid = (low + high) // 2
        left = _halves(counts, (mid - low) * per_shard, np.random.default_rng([seed, low, high]))
        if shard < mid:
            high, counts = mid, left
        else:
            low, counts, before = mid, counts - left, before + left
    return counts, before


def permuted(index: np.ndarray, n: int, key: int) -> np.ndarray:
    """A pseudorandom permutation of 0..n-1: a four-round Feistel network, walked until it lands inside."""
    if n <= 1:
        return np.zeros_like(index)
    half = np.uint64(max(1, (int(n - 1).bit_length() + 1) // 2))
    mask = np.uint64((1 << int(half)) - 1)
    rounds = np.random.default_rng(key).integers(1, 1 << 63, 4, dtype=np.uint64) | np.uint64(1)
    x, out, at = index.astype(np.uint64), np.empty(len(index), np.int64), np.arange(len(index))
    while len(x):
        a, b = x >> half, x & mask
        for r in rounds:
            f = (b + r) * np.uint64(0xBF58476D1CE4E5B9)
            f ^= f >> np.uint64(29)
            f *= r
            a, b = b, a ^ ((f >> np.uint64(32)) & mask)
        x = (a << half) | b
        done = x < n
        out[at[done]] = x[done]
        x, at = x[~done], at[~done]
    return out


def _slots(blocks: list[int], slots: list[int], shards: int, seed: int):
    schema = pa.schema([("source_no", pa.int32()), ("block", pa.int64())])
    n_slots = np.array(slots, np.int64)

    def run(batches):
        for batch in batches:
            for shard in batch.column(0).to_pylist():
                counts, before = shard_counts(shard, shards, n_slots, SHARD_SLOTS, seed)
                who, what = [], []
                for s in np.flatnonzero(counts).tolist():
                    slot = before[s] + np.arange(counts[s])
                    turn = slot // blocks[s]
                    for t in np.unique(turn).tolist():
                        what.append(permuted(slot[turn == t] % blocks[s], blocks[s], seed * 1_000_003 + s * 1009 + t))
                        who.append(np.full(len(what[-1]), s))
                if who:
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(who), pa.int32()), pa.array(np.concatenate(what), pa.int64())], schema=schema)

    return run


def mixing_plan(docs: DataFrame, block_words: int = BLOCK_WORDS, seed: int = SEED) -> tuple[DataFrame, DataFrame]:
    """(documents, pieces). Documents: row_no parts (source_no, part, nth), hashes (k1, k2) of doc_id, source and text,
    doc_id, source, size, source_size, target. Pieces: the same key and hashes, first (word of the document), words,
    times (how often the mix takes them)."""
    small_batches(docs.sparkSession)
    spark = docs.sparkSession
    size = F.coalesce(F.regexp_count("text", F.lit(WORD)), F.lit(0)).cast("long")
    k1, k2 = row_keys()
    sizes = settle(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "source", size.alias("size"), k1.alias("k1"), k2.alias("k2")), "sizes")
    parts = max(16, partitions(spark), -(-sizes.count() // PART_DOCS))
    sizes = sizes.withColumn("part", F.pmod("k1", F.lit(parts)).cast("int"))
    sums = sizes.groupBy("source", "part").agg(F.sum("size").alias("words"))
    # one row per source comes to the driver: the targets of all sources depend on one another
    found = sorted(((r["source"], r["words"]) for r in sums.groupBy("source").agg(F.sum("words").alias("words")).collect()), key=lambda x: (x[0] is None, x[0] or ""))
    totals = [n for _, n in found]
    wanted = targets(totals, [WEIGHTS[i % len(WEIGHTS)] for i in range(len(found))], SHARE * sum(totals))
    blocks = [math.ceil(n / block_words) for n in totals]
    slots = [min(2 * b, round(t * b / n)) if n else 0 for t, b, n in zip(wanted, blocks, totals, strict=True)]
    names = spark.createDataFrame([(i, s, n, t) for i, ((s, n), t) in enumerate(zip(found, wanted, strict=True))], "source_no int, name string, source_size long, target double")

    named = sizes.join(names, sizes["source"].eqNullSafe(names["name"]))
    ahead = Window.partitionBy("source_no").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    bases = sums.join(names.select("source_no", "name"), F.col("source").eqNullSafe(F.col("name"))).select("source_no", "part", F.coalesce(F.sum("words").over(ahead), F.lit(0)).alias("base"))
    inside = Window.partitionBy("source_no", "part").orderBy("doc_id", "k1", "k2")
    placed = named.join(bases, ["source_no", "part"]).withColumn("nth", F.row_number().over(inside))
    placed = placed.withColumn("at", F.col("base") + F.coalesce(F.sum("size").over(inside.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    placed = placed.select("source_no", "part", "nth", "k1", "k2", "doc_id", "source", "size", "source_size", "target", "at")

    shards = -(-sum(slots) // SHARD_SLOTS)
    drawn = spark.range(shards).mapInArrow(_slots(blocks, slots, shards, seed), "source_no int, block long").groupBy("source_no", "block").agg(F.count("*").alias("times"))
    # the plan's estimate of what the shards draw is far too small: a merge join, whatever it says
    cover = F.expr(f"sequence(at div {block_words}, (at + size - 1) div {block_words})")
    pieces = placed.filter("size > 0").withColumn("block", F.explode(cover)).join(drawn.hint("merge"), ["source_no", "block"])
    first = F.greatest(F.col("block") * block_words, F.col("at"))
    last = F.least((F.col("block") + 1) * block_words, F.col("at") + F.col("size"))
    pieces = pieces.select("source_no", "part", "nth", "k1", "k2", (first - F.col("at")).alias("first"), (last - first).alias("words"), "times")
    return placed.drop("at"), pieces


def mix(docs: DataFrame) -> DataFrame:
    """One row per document: doc_id, size, source_size, target (of its source), taken (words, repeats counted)."""
    placed, pieces = mixing_plan(docs)
    key = ["source_no", "part", "nth"]
    taken = pieces.groupBy(key).agg(F.sum(F.col("words") * F.col("times")).alias("taken"))
    return placed.join(taken, key, "left").select("doc_id", "size", "source_size", "target", F.coalesce("taken", F.lit(0)).cast("long").alias("taken"))


def _sliced(fields: list[str], taken_name: str):
    """Rows of documents with the text that a pass of the mix takes; ``taken_name`` holds (first, words, times) triples."""

    def spans(triples, turn):
        out = []
        for first, words, times in sorted(triples):
            if times >= turn:
                if out and out[-1][1] == first:
                    out[-1][1] = first + words
                else:
                    out.append([first, first + words])
        return out

    def run(batches):
        for batch in batches:
            names = batch.schema.names
            text_at = names.index("text")
            data, offsets = text_views(batch.column(text_at))
            taken = batch.column(names.index(taken_name)).to_pylist()
            rows, texts = [], []
            for i, triples in enumerate(taken):
                body = data[offsets[i] : offsets[i + 1]]
                solid = ~is_space(body)
                edge = np.diff(np.concatenate(([0], solid.astype(np.int8), [0])))
                starts, ends = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
                for turn in range(1, 1 + max((t["times"] for t in triples), default=0)):
                    parts = spans([(t["first"], t["words"], t["times"]) for t in triples], turn)
                    whole = parts == [[0, len(starts)]]
                    rows.append(i)
                    texts.append((body.tobytes() if whole else b"\n".join(body[starts[a] : ends[b - 1]].tobytes() for a, b in parts)).decode("utf-8", "replace"))
            if rows:
                picked = batch.take(pa.array(rows))
                columns = [pa.array(texts, pa.string()) if n == "text" else pa.array([len(t) for t in texts], picked.column(names.index(n)).type) if n == "n_chars" else picked.column(names.index(n)) for n in fields]
                yield pa.RecordBatch.from_arrays(columns, names=fields)

    return run


def mixed_documents(docs: DataFrame) -> DataFrame:
    """The mix as documents, with the columns of ``docs``: a document comes once for each pass that takes words
    of it, with those words of its text (all of it, unchanged, where a pass takes the whole); n_chars follows."""
    _, pieces = mixing_plan(docs)
    a, b, nth, taken = fresh(docs.columns, "k1", "k2", "nth", "taken")
    plan = pieces.groupBy("source_no", "part", "nth", "k1", "k2").agg(F.array_sort(F.collect_list(F.struct("first", "words", "times"))).alias("taken"))
    plan = plan.groupBy(F.col("k1").alias(a), F.col("k2").alias(b)).agg(F.array_sort(F.collect_list("taken")).alias(taken))
    k1, k2 = row_keys()
    mine = docs.withColumn(a, k1).withColumn(b, k2).withColumn(nth, F.row_number().over(Window.partitionBy(a, b).orderBy(F.lit(0))))
    met = mine.join(plan.hint("merge"), [a, b]).filter(F.col(nth) <= F.size(taken)).withColumn(taken, F.element_at(taken, F.col(nth)))
    return met.select(*docs.columns, taken).mapInArrow(_sliced(docs.columns, taken), docs.schema)
