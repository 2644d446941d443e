"""Exact, near, passage, byte and line deduplication against brute force, and their edge cases."""

from __future__ import annotations

import hashlib
import random
import re
import tempfile

import numpy as np
import pytest
from pyspark import cloudpickle
from pyspark.sql import functions as F

from nbflow.llm import block_anchors, common, components, deletion_lines, digest_fingerprint, grace_dedup, multi_order_join, suffix_bwt
from nbflow.llm.common import documents

SF = "/root/testdata/sf0.001"
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
WORD = re.compile(r"[^\x20\x09-\x0D]+")


def table(spark, texts, ids=None):
    rows = [(i, t, None, None, None) for i, t in zip(ids or range(len(texts)), texts, strict=True)]
    return spark.createDataFrame(rows, SCHEMA)


def edge_texts():
    """Null, empty, white space, ties, repeats, signs of many bytes, a very long text and a text of one long word."""
    rng = random.Random(5)
    words = ["alpha", "beta", "gamma", "delta", "éa", "ñu", "中文", "x"]
    base = [" ".join(rng.choice(words) + str(rng.randint(0, 999)) for _ in range(rng.choice([3, 60, 200]))) for _ in range(12)]
    near = [b.replace("alpha", "omega", 1) for b in base[:6]]
    passage = " ".join(f"p{i}" for i in range(70))
    mixed = [f"{base[7]} {passage} {base[8]}", f"{base[9]}\t{passage}\n{base[10]}", passage]
    return [None, "", " ", "\n\t", "a", "a", "A", "b c", *base, *near, *base[:3], *mixed, "long " * 30_000, "w" * 50_000, "ab" * 400, "ab" * 400 + "c", "line one of some length\nline one of some length\nline one of some lengthy", "\x00 zero\x00"]


@pytest.fixture(scope="module")
def edges(spark):
    texts = edge_texts()
    return texts, table(spark, texts)


def brute_bytes(rows, length=100):
    seen, out = set(), {}
    for doc, text in sorted(rows):
        body = (text or "").encode()
        gone = np.zeros(len(body), bool)
        for i in range(len(body) - length + 1):
            w = body[i : i + length]
            if w in seen:
                gone[i : i + length] = True
            seen.add(w)
        out[doc] = (len(body), int(gone.sum()), int((np.diff(np.concatenate(([0], gone.astype(int)))) == 1).sum()), np.frombuffer(body, np.uint8)[~gone].tobytes())
    return out


def brute_words(rows, window=50):
    first, out = {}, {}
    split = {d: (t or "").encode().split() for d, t in rows}
    for d in sorted(split):
        for i in range(len(split[d]) - window + 1):
            first.setdefault(tuple(split[d][i : i + window]), d)
    for d, w in split.items():
        gone = [False] * len(w)
        for i in range(len(w) - window + 1):
            if first[tuple(w[i : i + window])] < d:
                gone[i : i + window] = [True] * window
        out[d] = (len(w), sum(gone), b" ".join(x for x, g in zip(w, gone, strict=True) if not g))
    return out


def brute_groups(rows, k=5):
    lower = lambda t: "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t)
    sets = {}
    for d, t in rows:
        w = WORD.findall(lower(t or ""))
        sets[d] = {tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if len(w) >= k else {tuple(w)} if w else set()
    top = {d: d for d in sets}

    def find(x):
        while top[x] != x:
            x = top[x]
        return x

    ids = sorted(sets)
    for i, a in enumerate(ids):
        for b in ids[i + 1 :]:
            both = len(sets[a] & sets[b])
            if both and 100 * both >= 80 * (len(sets[a]) + len(sets[b]) - both):
                x, y = sorted((find(a), find(b)))
                top[y] = x
    return {d: (len(s), find(d)) for d, s in sets.items()}


@pytest.mark.parametrize("source", ["edges", "given"])
def test_suffix_construction(spark, edges, source):
    rows = list(enumerate(edges[0])) if source == "edges" else [tuple(r) for r in documents(spark, SF).select("doc_id", "text").collect()]
    df = edges[1] if source == "edges" else documents(spark, SF)
    got = {r["doc_id"]: (r["n_bytes"], r["n_removed"], len(r["spans"]), bytes(r["kept"])) for r in suffix_bwt.remove_repeated_bytes(df).collect()}
    assert got == brute_bytes(rows)


def test_suffix_order_and_common_prefixes_are_exact():
    rng = random.Random(1)
    for _ in range(20):
        texts = [bytes(rng.choice(b"ab\xff") for _ in range(rng.randint(1, 25))) for _ in range(rng.randint(1, 15))]
        body = np.frombuffer(b"".join(texts), np.uint8).astype(np.uint16) + np.uint16(1)
        with tempfile.TemporaryDirectory() as folder:
            bwt, lcp, text, size = suffix_bwt.sorted_suffixes(body, np.array([len(t) for t in texts]), folder, 100)
        expected = sorted((t[i:], k) for k, t in enumerate(texts) for i in range(len(t) + 1))
        assert [(texts[k][len(texts[k]) - n :], k) for k, n in zip(text.tolist(), size.tolist(), strict=True)] == expected
        assert [0 if n == len(texts[k]) else texts[k][len(texts[k]) - n - 1] + 1 for k, n in zip(text.tolist(), size.tolist(), strict=True)] == bwt.tolist()
        common = lambda a, b: next((i for i, (x, y) in enumerate(zip(a, b, strict=False)) if x != y), min(len(a), len(b)))
        assert lcp.tolist() == [0, *(common(a[0], b[0]) for a, b in zip(expected, expected[1:], strict=False))]


def test_hot_minimizers_are_split(spark, monkeypatch):
    rng = random.Random(2)
    mid = "".join(rng.choice("abcdef") for _ in range(90))
    texts = ["".join(rng.choice("xyz") for _ in range(rng.randint(0, 80))) + mid + "".join(rng.choice("xyz") for _ in range(rng.randint(5, 60))) for _ in range(60)]
    parts = [(i, 0, t.encode().index(mid.encode()), t.encode()) for i, t in enumerate(texts)]
    pieces = [p for some, a, b in suffix_bwt.split_by_place([(d, s, min(p, 60), t[p - min(p, 60) : p + 100]) for d, s, p, t in parts], 0, 60, 100) for p in some]
    assert pieces and all(len(t) >= 100 for *_, t in pieces)


@pytest.mark.parametrize("source", ["edges", "given"])
def test_block_anchors(spark, edges, source):
    rows = list(enumerate(edges[0])) if source == "edges" else [tuple(r) for r in documents(spark, SF).select("doc_id", "text").collect()]
    df = edges[1] if source == "edges" else documents(spark, SF)
    got = {r["doc_id"]: (r["n_words"], r["n_removed"], r["kept"].encode()) for r in block_anchors.remove_repeated_passages(df).collect()}
    assert got == brute_words(rows)


@pytest.mark.parametrize("source", ["edges", "given"])
def test_multi_order_join(spark, edges, source):
    rows = list(enumerate(edges[0])) if source == "edges" else [tuple(r) for r in documents(spark, SF).select("doc_id", "text").collect()]
    df = edges[1] if source == "edges" else documents(spark, SF)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in multi_order_join.similar_groups(df).collect()}
    assert got == brute_groups(rows)


def test_chains_of_near_copies_are_one_group(spark):
    rng = random.Random(9)
    words = [f"w{rng.randint(0, 10**6)}" for _ in range(150)]
    texts = []
    for i in range(40):
        texts.append(" ".join(words))
        words[rng.randrange(150)] = f"n{i}"
        words[rng.randrange(150)] = f"m{i}"
    rng.shuffle(texts)
    rows = list(enumerate(texts))
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in multi_order_join.similar_groups(table(spark, texts)).collect()}
    assert got == brute_groups(rows)


def test_hot_classes(spark, monkeypatch):
    monkeypatch.setattr(common, "HOT_ROWS", 3)
    texts = ["one two three four five six seven"] * 30 + ["one two three four five six seven eight"] + [f"text {i % 8} of some other words" for i in range(40)] + ["", None]
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in multi_order_join.similar_groups(table(spark, texts).repartition(4)).collect()}
    assert got == brute_groups(list(enumerate(texts)))


def test_one_of_each_group_keeps_columns(spark, edges):
    kept = multi_order_join.one_of_each_group(edges[1])
    groups = brute_groups(list(enumerate(edges[0])))
    assert kept.columns == edges[1].columns
    assert sorted(r["doc_id"] for r in kept.collect()) == sorted(d for d, (_, c) in groups.items() if d == c)


def test_components(spark):
    links = spark.createDataFrame([(5, 4), (4, 3), (3, 9), (9, 1), (20, 21)], "a long, b long")
    assert {r["key"]: r["root"] for r in components.components(links).collect()} == {1: 1, 3: 1, 4: 1, 5: 1, 9: 1, 20: 20, 21: 20}
    assert components.components(links.filter("a < 0")).count() == 0


@pytest.mark.parametrize("budget", [1 << 20, 500])
def test_grace_table_and_spill(budget):
    rng = random.Random(3)
    texts = [b"t%d" % rng.randint(0, 60) * rng.choice([1, 1, 9]) for _ in range(800)]
    hashed = {t: hash(t) % 7 for t in texts}  # many different texts of one hash
    with tempfile.TemporaryDirectory() as folder:
        got = {t: (largest, n) for _, t, largest, n in grace_dedup.resolved(((hashed[t], t, i, 1) for i, t in enumerate(texts)), folder, budget, 4)}
    assert got == {t: (max(i for i, x in enumerate(texts) if x == t), texts.count(t)) for t in set(texts)}


def test_exact_dedup(spark, edges):
    texts = [t or "" for t in edges[0]]
    for r in grace_dedup.exact_dedup(edges[1]).collect():
        mine = [i for i, t in enumerate(texts) if t == texts[r["doc_id"]]]
        assert (r["keep_id"], r["group_size"], r["kept"]) == (max(mine), len(mine), r["doc_id"] == max(mine))
        assert r["text_sha256"] == hashlib.sha256(texts[r["doc_id"]].encode()).hexdigest()
    kept = grace_dedup.without_copies(edges[1])
    assert kept.columns == edges[1].columns and kept.count() == len(set(texts))


def test_exact_dedup_of_repeated_rows_and_missing_ids(spark):
    df = table(spark, ["x", "x", "x", None, "y"], [1, 1, None, None, None])
    rows = grace_dedup.exact_dedup(df).collect()
    assert len(rows) == 5 and sum(r["kept"] for r in rows) == 3
    assert {r["keep_id"] for r in rows if r["group_size"] == 3} == {1}
    assert grace_dedup.without_copies(df).count() == 3


def test_fingerprints(spark, edges):
    texts = [t or "" for t in edges[0]]
    rows = {r["doc_id"]: r for r in digest_fingerprint.fingerprints(edges[1]).collect()}
    for i, text in enumerate(texts):
        after = texts[(i - 1) % len(texts)]
        take = len(text) // 3
        edited = text[: len(text) - take] + after[:take]
        assert rows[i]["n_chars"] == len(text)
        assert rows[i]["edited_sha256"] == hashlib.sha256(edited.encode()).hexdigest()
        assert rows[i]["near_edited"] == float(digest_fingerprint.canonical(text) == digest_fingerprint.canonical(edited))
        assert rows[i]["near_next"] == float(digest_fingerprint.canonical(text) == digest_fingerprint.canonical(after))
    forms = [digest_fingerprint.canonical(t) for t in texts]
    assert all((rows[i]["fingerprint"] == rows[j]["fingerprint"]) == (forms[i] == forms[j]) for i in range(len(texts)) for j in range(i))


def test_digest_collisions_are_told_apart(spark, monkeypatch):
    df = table(spark, ["one", "two", "one", "three"])
    monkeypatch.setattr(digest_fingerprint, "digest", lambda form: "same")
    cloudpickle.register_pickle_by_value(digest_fingerprint)  # so that workers get the changed module
    try:
        prints = [r["fingerprint"] for r in digest_fingerprint.fingerprints(df).orderBy("doc_id").collect()]
    finally:
        cloudpickle.unregister_pickle_by_value(digest_fingerprint)
    assert prints == ["same", "same-2", "same", "same-1"]


def test_hot_digests_and_small_buckets(spark, monkeypatch):
    rng = random.Random(6)
    texts = ["Hot  text"] * 40 + [f"text {rng.randint(0, 30)}" for _ in range(60)] + [None, "hot text"]
    for module, name, value in ((common, "HOT_ROWS", 3), (digest_fingerprint, "BUCKET_BYTES", 64), (digest_fingerprint, "FORM_BYTES", 200)):
        monkeypatch.setattr(module, name, value)
    rows = {r["doc_id"]: r for r in digest_fingerprint.fingerprints(table(spark, texts)).collect()}
    forms = [digest_fingerprint.canonical(t or "") for t in texts]
    assert len(rows) == len(texts)
    for i in range(len(texts)):
        assert rows[i]["fingerprint"] == digest_fingerprint.digest(forms[i].encode())
        assert rows[i]["near_next"] == float(forms[i] == forms[i - 1])


def test_canonical_forms():
    c = digest_fingerprint.canonical
    assert c("Ａ  b C\n") == "a b c" and c("Straße") == c("STRASSE") and c("é") == c("é") and c("ﬁ") == "fi"


def brute_lines(rows, least=1):
    split = [(d, i, line, line.strip(" \t\r")) for d, t in rows for i, line in enumerate((t or "").split("\n"))]
    first = {}
    for d, i, _, s in sorted(split):
        if s:
            first.setdefault(s, (d, i))

    def one_edit(a, b):
        if len(a) < len(b):
            a, b = b, a
        if len(a) == len(b):
            return sum(x != y for x, y in zip(a, b, strict=True)) == 1
        return len(a) == len(b) + 1 and (i := next((i for i, (x, y) in enumerate(zip(a, b, strict=False)) if x != y), len(b))) >= 0 and a[:i] + a[i + 1 :] == b

    names = list(first)
    near = {a for a in names for b in names if abs(len(a) - len(b)) <= 1 and max(len(a), len(b)) >= least and min(len(a), len(b)) >= least - 1 and first[b] < first[a] and one_edit(a, b)}
    out = {}
    for d, t in rows:
        lines = (t or "").split("\n")
        stay = [x for i, x in enumerate(lines) if not (s := x.strip(" \t\r")) or (s not in near and first[s] == (d, i))]
        out[d] = (len(lines), len(lines) - len(stay), "\n".join(stay))
    return out


def test_line_dedup(spark, edges):
    texts = [*edges[0], "the quick brown fox jumps", "the quick brown fox jump", "the quick brown fax jumps  \nthe quick brown fax jumps", "short a\nshort b", "abcdefghijklmno", "abcdefghijklmnop", "the quick brown fax jumpz", "ab" * 400 + "\n" + "ab" * 399 + "ac"]
    got = {r["doc_id"]: (r["n_lines"], r["n_removed"], r["kept"]) for r in deletion_lines.remove_repeated_lines(table(spark, texts)).collect()}
    assert got == brute_lines(list(enumerate(texts)))
    longer = {r["doc_id"]: (r["n_lines"], r["n_removed"], r["kept"]) for r in deletion_lines.remove_repeated_lines(table(spark, texts), least_chars=16).collect()}
    assert longer == brute_lines(list(enumerate(texts)), 16)


def test_short_lines_and_many_lines_that_go(spark):
    rng = random.Random(4)
    texts = ["\n".join("".join(rng.choice("abc{}") for _ in range(rng.randint(0, 6))) for _ in range(40)) for _ in range(12)] + ["\n".join(["repeated line of words"] * 3000 + ["the last one is new"])]
    got = {r["doc_id"]: (r["n_lines"], r["n_removed"], r["kept"]) for r in deletion_lines.remove_repeated_lines(table(spark, texts)).collect()}
    assert got == brute_lines(list(enumerate(texts)))


def test_lines_of_rows_that_share_a_doc_id(spark):
    rows = deletion_lines.remove_repeated_lines(table(spark, ["first line here", "other words\nfirst line here", "kept as it is\nnothing like it"], [1, None, None])).collect()
    assert sorted(r["kept"] for r in rows) == ["", "kept as it is\nnothing like it", "other words\nfirst line here"]


OPERATORS = {
    "suffix": suffix_bwt.remove_repeated_bytes,
    "anchors": block_anchors.remove_repeated_passages,
    "join": multi_order_join.similar_groups,
    "grace": grace_dedup.exact_dedup,
    "digest": digest_fingerprint.fingerprints,
    "lines": deletion_lines.remove_repeated_lines,
}


@pytest.mark.parametrize("name", OPERATORS)
def test_empty_tables_missing_values_and_clashing_columns(spark, name):
    op = OPERATORS[name]
    clash = table(spark, ["same text of a few words here", None, "same text of a few words here"], [3, None, 1])
    for c in ("key", "size", "values", "bucket", "block", "digest", "root", "place", "h1", "body", "gone", "kept", "spans", "__sha", "token", "line"):
        clash = clash.withColumn(c, F.lit(1))
    rows = op(clash).collect()
    assert sorted((r["doc_id"] for r in rows), key=str) == [1, 3, None]
    assert op(clash.filter("doc_id > 99")).count() == 0
