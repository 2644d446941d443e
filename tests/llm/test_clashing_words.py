"""Words that weak hashes take for one another, hot passages and rows that share a doc_id, against brute force."""

from __future__ import annotations

import random

import pytest
from pyspark.sql import functions as F

from nbflow.llm import block_anchors, multi_order_join, suffix_bwt
from nbflow.llm.common import documents
from test_dedup import SF, brute_bytes, brute_groups, brute_words, table


def doubling(n: int, a: str = "a", b: str = "b") -> tuple[str, str]:
    """The sequence a, ab, abba, ... of ``n`` letters and its complement: equal under many sums modulo a power of two."""
    bits = [bin(i).count("1") % 2 for i in range(n)]
    return "".join((a, b)[x] for x in bits), "".join((b, a)[x] for x in bits)


@pytest.fixture(scope="module")
def clashing():
    out = []
    plain = [f"w{i}" for i in range(49)]
    for n in (1024, 2048):
        for word in doubling(n):
            out += [" ".join([*plain, word]), " ".join(plain[:4] + [word]), word]
    left, right = doubling(64, "x ", "y ")
    return [*out, left * 3, right * 3, left * 3]


def test_different_words_are_no_repeats_and_no_links(spark, clashing):
    df = table(spark, clashing)
    rows = list(enumerate(clashing))
    got = {r["doc_id"]: (r["n_words"], r["n_removed"], r["kept"].encode()) for r in block_anchors.remove_repeated_passages(df).collect()}
    assert got == brute_words(rows)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in multi_order_join.similar_groups(df).collect()}
    assert got == brute_groups(rows)


@pytest.fixture(scope="module")
def hot():
    """A third of the documents share a passage, in places of their own; a group of near copies; the rest is different."""
    rng = random.Random(7)
    word = lambda: f"v{rng.randint(0, 10**6)}"
    passage, base = " ".join(word() for _ in range(90)), [word() for _ in range(80)]
    texts = []
    for i in range(240):
        if i % 3 == 0:
            texts.append(" ".join([*(word() for _ in range(rng.randint(0, 40))), passage, *(word() for _ in range(rng.randint(0, 40)))]))
        elif i % 3 == 1:
            near = list(base)
            near[rng.randrange(80)] = word()
            texts.append(" ".join(near))
        else:
            texts.append(" ".join(word() for _ in range(60)))
    return texts


@pytest.mark.parametrize("parts", [1, 6])
def test_hot_passages_against_brute_force(spark, hot, parts):
    df, rows = table(spark, hot).repartition(parts), list(enumerate(hot))
    got = {r["doc_id"]: (r["n_words"], r["n_removed"], r["kept"].encode()) for r in block_anchors.remove_repeated_passages(df).collect()}
    assert got == brute_words(rows)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in multi_order_join.similar_groups(df).collect()}
    assert got == brute_groups(rows)


@pytest.mark.parametrize("limit", [1, 8, 4096])
def test_hot_minimizers_that_senders_split(spark, hot, limit):
    got = {r["doc_id"]: (r["n_bytes"], r["n_removed"], len(r["spans"]), bytes(r["kept"])) for r in suffix_bwt.remove_repeated_bytes(table(spark, hot).repartition(5), hot_segments=limit).collect()}
    assert got == brute_bytes(list(enumerate(hot)))


def test_many_blocks_of_candidates(spark, hot, monkeypatch):
    monkeypatch.setattr(multi_order_join, "BLOCK_ROWS", 3)
    rng, base = random.Random(3), [f"u{i}" for i in range(60)]
    texts = list(hot)
    for i in range(60):  # chains, of which the first round finds a part
        for _ in range(rng.randint(1, 3)):
            base[rng.randrange(60)] = f"c{rng.randint(0, 10**6)}"
        texts.append(" ".join(base))
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in multi_order_join.similar_groups(table(spark, texts)).collect()}
    assert got == brute_groups(list(enumerate(texts)))


def test_rows_that_share_a_doc_id_are_cut_each_for_itself(spark):
    rng = random.Random(1)
    passage = " ".join(f"p{i}" for i in range(60))
    other = " ".join(f"q{rng.randint(0, 10**6)}" for _ in range(100))
    df = table(spark, [passage, f"x {passage}", other, f"{passage} y"], [1, 5, 5, None])
    words = {r["kept"] for r in block_anchors.remove_repeated_passages(df).filter("doc_id is not null").collect()}
    assert words == {"", "x", other}
    kept = {bytes(r["kept"]) for r in suffix_bwt.remove_repeated_bytes(df).filter("doc_id = 5").collect()}
    assert kept == {b"x ", other.encode()} or kept == {b"x", other.encode()}


def test_given_documents_in_many_parts(spark):
    df = documents(spark, SF).withColumn("text", F.col("text")).repartition(13)
    rows = [tuple(r) for r in df.select("doc_id", "text").collect()]
    got = {r["doc_id"]: (r["n_bytes"], r["n_removed"]) for r in suffix_bwt.remove_repeated_bytes(df, hot_segments=2).select("doc_id", "n_bytes", "n_removed").collect()}
    assert got == {d: v[:2] for d, v in brute_bytes(rows).items()}
