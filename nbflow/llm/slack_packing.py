"""Packing of documents into token sequences by minimum bin slack.

A document's ids are cut into whole windows and one remainder. The remainders of a group of documents
are a multiset of lengths; each window is opened by the longest one left, and a bitset of subset sums
over the others finds the multiset that comes closest to the window's end, with the counts traced back.
A multiset found is used again as often as the counts allow. Groups are dealt by a hash of doc_id and ids and
hold the pieces of a bounded number of documents, so that every task is small at any size of the table.

Defined cases: a null text counts as empty and is one id, the end mark; rows that repeat a doc_id are
packed each; a missing doc_id is kept as null; an empty table gives an empty result; other columns are
ignored.
"""

from __future__ import annotations

import json
import zlib
from collections import defaultdict
from functools import lru_cache

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from nbflow.llm.common import NO_ID, small_batches, text_or_empty, text_views

#: Where the vocabulary lies, unless the caller names another file; documents of a packing group.
VOCABULARY = "byte_bpe_50k.json"
GROUP_DOCS = 4096
END_ID = 1
#: How the vocabulary splits text before merging (fixed value of that vocabulary).
SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path(VOCABULARY)


def _byte_of() -> dict[str, int]:
    """The characters by which a byte-level vocabulary writes bytes: printable ones as themselves, the others from 256 on."""
    plain = [*range(ord("!"), ord("~") + 1), *range(ord("¡"), ord("¬") + 1), *range(ord("®"), ord("ÿ") + 1)]
    table = {chr(b): b for b in plain}
    rest = [b for b in range(256) if b not in plain]
    return table | {chr(256 + n): b for n, b in enumerate(rest)}


class ByteBpe:
    """Ids of a byte-level BPE vocabulary file, by the faster of two libraries that read it.

    The merges of such a file are in the order of their ids, so ids serve as merge ranks. A text on which
    the faster library gives up (very long runs), or that holds the literal of an added token, goes to the other."""

    def __init__(self, path: str):
        import tiktoken

        self.path, self.slow = path, None
        with open(path, encoding="utf-8") as file:
            model = json.load(file)
        special = {t["content"] for t in model.get("added_tokens", [])}
        byte_of = _byte_of()
        ranks = {bytes(byte_of[c] for c in token): n for token, n in model["model"]["vocab"].items() if token not in special}
        self.added = sorted(special)
        self.fast = tiktoken.Encoding("vocabulary", pat_str=SPLIT, mergeable_ranks=ranks, special_tokens={})

    def ids(self, text: str) -> np.ndarray:
        if any(x in text for x in self.added):
            return np.array(self.slow_ids(text), dtype="<u4")
        try:
            return np.array(self.fast.encode_ordinary(text), dtype="<u4")
        except BaseException as error:  # the library panics with a class of its own
            if isinstance(error, (KeyboardInterrupt, SystemExit, MemoryError)):
                raise
            return np.array(self.slow_ids(text), dtype="<u4")

    def slow_ids(self, text: str) -> list[int]:
        if self.slow is None:
            from tokenizers import Tokenizer

            self.slow = Tokenizer.from_file(self.path)
        return self.slow.encode(text, add_special_tokens=False).ids


@lru_cache(maxsize=2)
def byte_bpe(path: str) -> ByteBpe:
    """The vocabulary, read once per worker."""
    return ByteBpe(path)


_PIECES = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64()), ("doc_tokens", pa.int64())])


def _pieces(path: str, window: int):
    def run(batches):
        encoder = byte_bpe(path)
        for batch in batches:
            ids_of, rows = batch.column(0).to_pylist(), []
            data, offsets = text_views(batch.column(1))
            body, at = data.tobytes(), offsets.tolist()
            for i, doc_id in enumerate(ids_of):
                ids = np.append(encoder.ids(body[at[i] : at[i + 1]].decode("utf-8", "replace")), np.array([END_ID], "<u4"))
                for start in range(0, len(ids), window):
                    part = ids[start : start + window]
                    rows.append((doc_id, start, len(part), zlib.crc32(part.tobytes()), len(ids)))
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows, strict=True)], schema=_PIECES)

    return run


def fill(counts: dict[int, int], capacity: int) -> dict[int, int]:
    """The multiset of lengths, within ``counts``, whose sum comes closest to ``capacity`` from below."""
    reach, mask, steps = 1, (1 << (capacity + 1)) - 1, []
    for length in sorted((x for x in counts if x <= capacity and counts[x]), reverse=True):
        left, take = min(counts[length], capacity // length), 1
        while left:
            take = min(take, left)
            steps.append((length, take, reach))
            reach |= (reach << (length * take)) & mask
            left -= take
            take *= 2
        if reach >> capacity & 1:
            break
    total, chosen = reach.bit_length() - 1, defaultdict(int)
    for length, take, before in reversed(steps):
        if not before >> total & 1:
            chosen[length] += take
            total -= length * take
    return dict(chosen)


def packed(lengths: np.ndarray, window: int) -> tuple[np.ndarray, np.ndarray]:
    """(sequence, offset) of each length; sequences count from 0. Lengths are 1 to ``window``."""
    stacks: dict[int, list[int]] = defaultdict(list)
    for i in range(len(lengths) - 1, -1, -1):
        stacks[int(lengths[i])].append(i)
    counts = {x: len(s) for x, s in stacks.items()}
    sequence, offset = np.empty(len(lengths), np.int64), np.empty(len(lengths), np.int64)
    now = 0
    for longest in sorted(stacks, reverse=True):
        while counts[longest]:
            counts[longest] -= 1
            chosen = fill(counts, window - longest) if longest < window else {}
            counts[longest] += 1
            need = dict(chosen)
            need[longest] = need.get(longest, 0) + 1
            for _ in range(min(counts[x] // n for x, n in need.items())):
                at = 0
                for length in sorted(need, reverse=True):
                    for _ in range(need[length]):
                        i = stacks[length].pop()
                        sequence[i], offset[i] = now, at
                        at += length
                now += 1
            for x, n in need.items():
                counts[x] = len(stacks[x])
    return sequence, offset


def _pack_group(window: int):
    def run(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["doc_id", "start", "ids_crc32", "doc_tokens"], kind="stable", ignore_index=True)
        sequence, offset = packed(pdf["length"].to_numpy(), window)
        return pdf.assign(sequence_id=sequence + (int(key[0]) << 32), offset=offset).drop(columns="group")

    return run


def pack_documents(docs: DataFrame, window: int = 2048, vocabulary: str | None = None) -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset."""
    small_batches(docs.sparkSession)
    groups = max(1, -(-docs.count() // GROUP_DOCS))
    rows = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID)).alias("doc_id"), text_or_empty().alias("text"))
    pieces = rows.mapInArrow(_pieces(vocabulary or default_vocabulary(), window), "doc_id long, start long, length long, ids_crc32 long, doc_tokens long")
    grouped = pieces.withColumn("group", F.pmod(F.xxhash64("doc_id", "start", "ids_crc32", "doc_tokens"), F.lit(groups))).groupBy("group")
    packed_ = grouped.applyInPandas(_pack_group(window), "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long")
    return packed_.withColumn("doc_id", F.nullif("doc_id", F.lit(NO_ID)))
