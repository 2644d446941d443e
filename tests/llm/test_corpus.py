"""Rollups, packing, quality, mixing and the pipeline."""

from __future__ import annotations

import base64
import random
import uuid
import zlib

import numpy as np
import public_tokenizers
import pytest
import tiktoken
from pyspark.sql import functions as F
from test_dedup import brute_groups
from tokenizers import Tokenizer

import corpus_pipeline
from nbflow.llm import factor_classifier, grace_dedup, multi_order_join, queries, slack_packing, slot_mixing, token_rollup
from nbflow.llm.common import documents, shared_dir

SF = "/root/testdata/sf0.001"
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def table(spark, texts, ids=None, sources=None):
    ids = ids or range(len(texts))
    return spark.createDataFrame([(i, t, "en", s, len(t or "")) for i, t, s in zip(ids, texts, sources or [None] * len(texts), strict=True)], SCHEMA)


TEXTS = [None, "", " ", "a b c", "a b c", "word " * 5000, "x" * 20000, "é ñ 中文 🙂", "<|endoftext|>", "\n\n\n"]


# --- token counts


def rollup(spark):
    return token_rollup.TokenRollup(spark, f"{shared_dir(spark)}/rollup-{uuid.uuid4().hex}")


def totals(r):
    return {(x["source"], x["lang"], x["tokenizer"]): (x["n_docs"], x["n_tokens"]) for x in r.totals().collect()}


def words(text="text"):
    return F.coalesce(F.regexp_count(text, F.lit(r"\S+")), F.lit(0))


def test_rollup_of_inserts_deletes_and_revisions(spark):
    docs, r = table(spark, TEXTS, sources=["s", None] * 5), rollup(spark)
    assert totals(r) == {}
    assert r.commit(1, token_rollup.changes(docs, "words", words()))
    count = lambda t: len((t or "").split())
    assert totals(r) == {("s", "en", "words"): (5, sum(map(count, TEXTS[0::2]))), (None, "en", "words"): (5, sum(map(count, TEXTS[1::2])))}
    assert r.commit(2, token_rollup.changes(docs.filter("source is null"), "words", words(), -1))
    assert not r.commit(2, token_rollup.changes(docs, "words", words(), -1))
    assert set(totals(r)) == {("s", "en", "words")}
    r.commit(3, token_rollup.revisions(docs.filter("doc_id = 4"), "words", F.lit(3), F.lit(10)))
    after = totals(r)
    assert after["s", "en", "words"][1] == sum(map(count, TEXTS[0::2])) + 7
    r.compact()
    assert totals(r) == after and not r.commit(3, token_rollup.changes(docs, "words", words())) and len(r.live()) == 1
    r.commit(9, token_rollup.changes(docs.filter("false"), "chars", F.length("text")))
    r.commit(5, token_rollup.changes(docs.filter("false"), "chars", F.length("text")))
    r.compact()
    r.clean()
    assert totals(r) == after
    assert sorted((x["low"], x["high"]) for x in r._ranges().collect()) == [(1, 3), (5, 5), (9, 9)]
    assert r.loose([0, 1, 2, 3, 4, 5, 9, 10]) == {0, 4, 10}


def test_a_batch_that_was_cut_short_is_written_again(spark):
    r = rollup(spark)
    rows = token_rollup.changes(table(spark, ["a b"]), "words", words())
    rows.groupBy("source", "lang", "tokenizer").agg(F.sum("n_docs").alias("n_docs"), F.sum("n_tokens").alias("n_tokens")).write.parquet(f"{r.path}/batch=5")
    r._fs.delete(r._path(f"{r.path}/batch=5/_SUCCESS"), False)
    assert totals(r) == {} and r.commit(5, rows)
    assert totals(r) == {(None, "en", "words"): (1, 2)}


def by_the_libraries():
    """Counts of both vocabularies by the libraries themselves."""
    library = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), "rb"))}
    multi = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    return {"byte_bpe_50k": lambda t: len(library.encode(t or "", add_special_tokens=False).ids), "byte_bpe_multi_50k": lambda t: len(multi.encode_ordinary(t or ""))}


PATHS = {token_rollup.version(f): public_tokenizers.path(f) for f in token_rollup.VERSIONS}


def test_counts_are_the_libraries(spark):
    docs = table(spark, TEXTS)
    for c in ("tokens", "byte_bpe_50k", "n_docs", "tokenizer", "guess"):
        docs = docs.withColumn(c, F.lit(1))
    rows = token_rollup.counted(docs, PATHS).collect()
    for name, count in by_the_libraries().items():
        assert {r["doc_id"]: r[name] for r in rows} == {i: count(t) for i, t in enumerate(TEXTS)}
    assert token_rollup.counted(docs.filter("false"), PATHS).count() == 0


def test_a_text_that_the_fast_library_gives_up_on():
    count = token_rollup.counter(PATHS["byte_bpe_multi_50k"])
    assert count(" " * 2_000_000) > 0 and count("x" * 300_000) > 0


def test_token_totals_against_brute_force(spark):
    docs, toxic = documents(spark, SF).collect(), {r["doc_id"] for r in spark.read.parquet(f"{SF}/labels.parquet").collect() if r["toxic"] == 1}
    expected: dict = {}
    for name, count in by_the_libraries().items():
        for r in docs:
            if r["doc_id"] not in toxic:
                n, total = expected.get((r["source"], r["lang"], name), (0, 0))
                expected[r["source"], r["lang"], name] = n + 1, total + count(r["text"])
    got = {(x["source"], x["lang"], x["tokenizer"]): (x["n_docs"], x["n_tokens"]) for x in queries.queries()["op1_delta_token_rollup"](spark, SF).collect()}
    assert got == expected


# --- packing


def test_ids_are_those_of_the_vocabulary():
    path, rng = slack_packing.default_vocabulary(), random.Random(3)
    encoder, library = slack_packing.ByteBpe(path), Tokenizer.from_file(path)
    signs = "ab cdé ñ中文\n\t  '’123½Ⅳ<|endoftext|>🙂  ́"
    for text in [*map(lambda t: t or "", TEXTS), *("".join(rng.choice(signs) for _ in range(rng.randint(0, 40))) for _ in range(300))]:
        assert encoder.ids(text).tolist() == library.encode(text, add_special_tokens=False).ids


def test_fill_is_the_closest_sum():
    rng = random.Random(4)
    for _ in range(200):
        counts = {rng.randint(1, 30): rng.randint(1, 3) for _ in range(rng.randint(1, 6))}
        capacity = rng.randint(1, 60)
        sums = {0}
        for length, n in counts.items():
            sums = {s + length * k for s in sums for k in range(n + 1) if s + length * k <= capacity}
        chosen = slack_packing.fill(counts, capacity)
        assert sum(x * n for x, n in chosen.items()) == max(sums) and all(n <= counts[x] for x, n in chosen.items())


@pytest.mark.parametrize("source", ["edges", "given"])
def test_packing_holds_every_id_once(spark, source):
    docs = table(spark, TEXTS) if source == "edges" else documents(spark, SF)
    encoder = slack_packing.ByteBpe(slack_packing.default_vocabulary())
    ids = {r["doc_id"]: np.append(encoder.ids(r["text"] or ""), np.array([1], "<u4")) for r in docs.collect()}
    rows = slack_packing.pack_documents(docs).collect()
    seen, filled = {d: 0 for d in ids}, {}
    for r in sorted(rows, key=lambda r: (r["doc_id"], r["start"])):
        assert r["start"] == seen[r["doc_id"]] and r["doc_tokens"] == len(ids[r["doc_id"]])
        seen[r["doc_id"]] += r["length"]
        assert r["ids_crc32"] == zlib.crc32(ids[r["doc_id"]][r["start"] : r["start"] + r["length"]].tobytes())
    assert seen == {d: len(x) for d, x in ids.items()}
    for r in sorted(rows, key=lambda r: (r["sequence_id"], r["offset"])):
        assert r["offset"] == filled.get(r["sequence_id"], 0)
        filled[r["sequence_id"]] = r["offset"] + r["length"]
    assert max(filled.values()) <= 2048
    if source == "given":
        assert sum(filled.values()) > 0.95 * 2048 * len(filled)


# --- mixing


def test_targets_are_cut_and_shared_again():
    assert slot_mixing.targets([100, 10, 10], [5, 2, 1], 180) == [140, 20, 20]
    assert slot_mixing.targets([0, 10], [5, 2], 15) == [0, 15]
    rng = random.Random(5)
    for _ in range(100):
        sizes = [rng.choice([0, 1, 50, 1000]) for _ in range(6)]
        got = slot_mixing.targets(sizes, [5, 2, 1, 5, 2, 1], 1.5 * sum(sizes))
        assert sum(got) == pytest.approx(1.5 * sum(sizes)) and all(t <= 2 * n + 1e-9 for t, n in zip(got, sizes, strict=True))


def test_permutations_and_shards():
    for n in (1, 2, 7, 1000):
        assert sorted(slot_mixing.permuted(np.arange(n), n, 11).tolist()) == list(range(n))
    slots = np.array([100, 3, 0, 57])
    parts = [slot_mixing.shard_counts(s, 16, slots, 10, 1) for s in range(16)]
    assert (sum(c for c, _ in parts) == slots).all() and all(c.sum() == 10 for c, _ in parts)
    assert all((b == sum((c for c, _ in parts[:i]), np.zeros(4, int))).all() for i, (_, b) in enumerate(parts))


@pytest.mark.parametrize("source", ["edges", "given"])
def test_mix_comes_near_its_targets_and_reruns_agree(spark, source):
    docs = table(spark, TEXTS + ["w " * 3000] * 5, sources=["b", "a", None, "", "b"] * 3) if source == "edges" else documents(spark, SF)
    rows = slot_mixing.mix(docs).collect()
    assert len(rows) == docs.count()
    where = {r["doc_id"]: r["source"] for r in docs.collect()}
    taken, target, sizes = {}, {}, {}
    for r in rows:
        assert r["taken"] <= 2 * r["size"]
        s = where[r["doc_id"]]
        taken[s], target[s], sizes[s] = taken.get(s, 0) + r["taken"], r["target"], r["source_size"]
    for s in taken:
        assert abs(taken[s] - target[s]) <= max(2 * slot_mixing.BLOCK_WORDS, 0.02 * target[s])
    assert sum(target.values()) == pytest.approx(1.5 * sum(sizes.values()))
    assert sorted(rows) == sorted(slot_mixing.mix(docs.repartition(7)).collect())


def test_mixed_documents_hold_the_words_taken(spark):
    docs = documents(spark, SF)
    taken = {r["doc_id"]: r["taken"] for r in slot_mixing.mix(docs).collect()}
    out = slot_mixing.mixed_documents(docs)
    assert out.columns == docs.columns
    words: dict[int, int] = {}
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    for r in out.collect():
        mine = r["text"].encode().split()
        words[r["doc_id"]] = words.get(r["doc_id"], 0) + len(mine)
        assert r["n_chars"] == len(r["text"]) and set(mine) <= set(texts[r["doc_id"]].encode().split())
    assert {d: n for d, n in taken.items() if n} == words


# --- quality


def test_linear_time_interactions_equal_the_pairs():
    rng = np.random.default_rng(0)
    n_stats = len(factor_classifier.STATISTICS)
    size = factor_classifier.SLOTS + n_stats
    model = factor_classifier.Model(0.1, rng.normal(size=size), rng.normal(size=(size, 3)), np.zeros(n_stats), np.ones(n_stats))
    slots, before, stats = factor_classifier.features(np.frombuffer(b"one two one", np.uint8), np.array([0, 11]))
    z = np.clip(stats[0], -6, 6)
    x = [(s, 1 / np.sqrt(3)) for s in slots] + [(factor_classifier.SLOTS + i, v) for i, v in enumerate(z)]
    raw = 0.1 + sum(model.weights[i] * v for i, v in x) + sum(float(model.vectors[i] @ model.vectors[j]) * v * u for a, (i, v) in enumerate(x) for j, u in x[:a])
    assert model.scores(slots, before, stats)[0] == pytest.approx(1 / (1 + np.exp(-np.clip(raw, -30, 30))))


def test_held_out_accuracy_and_clean_documents_stay(spark):
    sf = "/root/testdata/sf0.01"
    docs, labels = documents(spark, sf), spark.read.parquet(f"{sf}/labels.parquet")
    rows = factor_classifier.quality_scores(docs, labels).join(labels, "doc_id").filter("held_out").collect()
    assert rows and np.mean([r["predicted"] == r["quality"] for r in rows]) > 0.93
    assert np.mean([r["predicted"] for r in rows if r["quality"] == 1]) > 0.97
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 4 == 2) for r in rows)


def test_scores_of_odd_texts_and_missing_labels(spark):
    docs, sf = table(spark, TEXTS), "/root/testdata/sf0.01"
    labels = spark.read.parquet(f"{sf}/labels.parquet")
    model = factor_classifier.train(documents(spark, sf), labels)
    rows = factor_classifier.quality_scores(docs, labels, model).collect()
    assert len(rows) == len(TEXTS) and all(0 <= r["score"] <= 1 for r in rows)
    none = factor_classifier.quality_scores(docs, labels.filter("false")).collect()
    assert {r["score"] for r in none} == {1.0} and factor_classifier.accepted(docs, labels.filter("false")).count() == len(TEXTS)


# --- the pipeline


def test_stages_keep_columns_and_work_on_each_other(spark):
    docs = documents(spark, SF)
    for name, stage in corpus_pipeline.STAGES[:-1]:
        after = stage(spark, docs, SF)
        assert after.columns == docs.columns, name
        docs = spark.createDataFrame(after.collect(), docs.schema)
        assert docs.count()
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality classifier", "exact dedup", "n-gram Jaccard join", "mixing sources to target weights", "packing"]
    assert corpus_pipeline.STAGES[-1][1](spark, docs, SF).count() > 0


def test_filtering_stages_against_brute_force(spark):
    docs = documents(spark, SF)
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    kept = {r["doc_id"] for r in grace_dedup.without_copies(docs).collect()}
    assert kept == {max(d for d, t in texts.items() if t == text) for text in set(texts.values())}
    groups = brute_groups(list(texts.items()))
    assert {r["doc_id"] for r in multi_order_join.one_of_each_group(docs).collect()} == {d for d, (_, c) in groups.items() if c == d}
    model = factor_classifier.train(docs, spark.read.parquet(f"{SF}/labels.parquet"))
    scores = {r["doc_id"]: r["score"] for r in factor_classifier.quality_scores(docs, spark.read.parquet(f"{SF}/labels.parquet"), model).collect()}
    assert {r["doc_id"] for r in factor_classifier.accepted(docs, spark.read.parquet(f"{SF}/labels.parquet")).collect()} == {d for d, s in scores.items() if s >= 0.7}


def test_stages_with_clashing_names(spark):
    docs = documents(spark, SF)
    for c in ("__sha", "__keep", "__digest", "__nth", "__id", "__source", "__size", "__taken", "__stay", "K1", "k2", "nth", "taken", "stay", "digest", "sha", "keep", "score", "label"):
        docs = docs.withColumn(c, F.lit(1))
    for name, stage in corpus_pipeline.STAGES[:-1]:
        after = stage(spark, docs, SF)
        assert after.columns == docs.columns, name
        docs = spark.createDataFrame(after.collect(), docs.schema)
    assert corpus_pipeline.STAGES[-1][1](spark, docs, SF).count() > 0


def test_rows_that_share_id_source_and_size_are_mixed_each(spark):
    rng = random.Random(8)
    texts = [" ".join(f"t{i}x{rng.randint(0, 9)}" for _ in range(300)) for i in range(8)] + ["same words here"] * 3
    docs = table(spark, texts, [7] * 4 + [None] * 4 + [9] * 3, ["a"] * 11)
    taken = sorted(r["taken"] for r in slot_mixing.mix(docs).collect())
    words: dict[str, int] = {}
    for r in slot_mixing.mixed_documents(docs).collect():
        mine = r["text"].split()
        head = mine[0].split("x")[0]
        assert {m.split("x")[0] for m in mine} == {head} or mine[0] in ("same", "words", "here")
        words[head] = words.get(head, 0) + len(mine)
    assert sum(words.values()) == sum(taken)
    assert [words.get(f"t{i}", 0) for i in range(8)] and all(n <= 600 for h, n in words.items() if h.startswith("t"))


def test_draws_beyond_the_exact_ones():
    rng = np.random.default_rng(1)
    counts = np.array([5 * 10**11, 3, 2 * 10**11, 0, 90_000, 10**8])
    for left in (0, 1, int(counts.sum()) // 2, int(counts.sum())):
        draws = np.array([slot_mixing._halves(counts, left, rng) for _ in range(50)])
        assert (draws.sum(1) == left).all() and (draws >= 0).all() and (draws <= counts).all()
    assert len({tuple(d) for d in np.array([slot_mixing._halves(counts, int(counts.sum()) // 2, rng) for _ in range(20)]).tolist()}) > 1


def test_pipeline_on_an_empty_table(spark):
    docs = documents(spark, SF).filter("false")
    for _, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, SF)
        assert docs.count() == 0
    assert corpus_pipeline.STAGES[-1][1](spark, docs, SF).count() == 0


@pytest.mark.parametrize("name", ["pack", "mix", "score"])
def test_missing_values_and_clashing_columns(spark, name):
    docs = table(spark, ["a b c d e f", None, "a b c d e f"], [3, None, 1])
    for c in ("group", "offset", "size", "taken", "part", "nth", "score", "label", "block", "times"):
        docs = docs.withColumn(c, F.lit(1))
    labels = spark.createDataFrame([(1, 1, None), (3, 0, 0), (None, None, None)], "doc_id long, quality int, toxic int")
    op = {"pack": slack_packing.pack_documents, "mix": slot_mixing.mix, "score": lambda d: factor_classifier.quality_scores(d, labels)}[name]
    assert sorted((r["doc_id"] for r in op(docs).collect()), key=str) == [1, 3, None]
    assert op(docs.filter("doc_id > 99")).count() == 0


def test_registered_names():
    assert sorted(int(n[2:].split("_")[0]) for n in queries.queries()) == list(range(1, 11))
    assert set(queries.oracle_sql()) <= set(queries.queries())
