"""Similarity join on word shingles, filtered under several global orders of the shingles.

Two sets whose Jaccard similarity reaches the threshold must share a member among the first few of each,
under any order of all shingles; the rarer the first ones, the fewer candidates. The first order puts
shingles that only one document has in front, then the others by how many documents have them; a pair
that shares a prefix there must also share one under two further orders (own hash orders behind the
same front) before its sets are compared. As links only matter through what they connect, pairs of
documents already connected are not compared: a first round links each document with one leader per
shared shingle, the one with the fewest shingles of its own; the last round compares all remaining
candidates of different components, behind a bitmap filter (the bits in which the parity bitmaps of two
sets differ are at most the members in which the sets do), so that a large group of near copies does not
become pairs of rows. The rows of a shingle meet block by block, each two blocks on a key of their own, and rows of its
most frequent component never meet one another.

Filters work on 48-bit hashes of shingles. A document with two shingles of one hash, or two sets with equal digests
and different check digests, make the join start again under another seed, so sizes and classes are exact; and of
pairs that link by their hashes, the texts are fetched and their shingles compared word by word. Hashes that clash
between documents can thus only make candidates, and lose none.

A shingle that ``HOT`` classes of one piece of the input hold is last in the first order, and known to be shared
without asking: a piece sends one entry for it, however many of its documents hold it.

Defined cases: words are runs of bytes other than space and 9 to 13, A-Z lower-cased; a document with
fewer words than a shingle is its whole sequence; one without words (or a null text) has an empty set
and links with nothing; equal sets are one class, however many copies; rows that share a doc_id count as
one document; a missing doc_id counts as the smallest and comes back missing; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from nbflow.llm.common import NO_ID, P_CHECK, P_WORD, Rolling, buckets_for, discard, fresh, joined_with_hot_keys, lowered, mixed, pieces_of, settle, small_batches, text_or_empty, with_both, word_hashes, word_spans
from nbflow.llm.components import components
from nbflow.llm.packed import BITS, MASK, Holders, spread, told

CHUNK = 1 << 20
_OWN = np.uint64(BITS)
#: Classes of a piece from which a shingle is last in the first order, that place, and rows of a block of candidates.
HOT, LAST, BLOCK_ROWS = 16, 65535, 512


def shingle_sets(data: np.ndarray, offsets: np.ndarray, k: int, seed: int, checked: bool = False):
    """(48-bit hashes, document of each, set sizes, checks, clash): distinct shingles of each document, sorted. If
    ``checked``: 64 more bits of each, and whether some document has two shingles of one hash."""
    data = lowered(data)
    starts, ends, before = word_spans(data, offsets)
    words = np.diff(before)
    first, second = word_hashes(data, starts, ends, seed)
    per_doc = np.where(words >= k, words - k + 1, np.minimum(words, 1))
    doc = np.repeat(np.arange(len(words)), per_doc)
    nth = np.arange(len(doc)) - np.repeat(np.cumsum(per_doc) - per_doc, per_doc)
    a = before[:-1][doc] + nth
    b = np.where(words[doc] >= k, a + k, before[1:][doc])
    both = (doc.astype(np.uint64) << _OWN) | (Rolling(first, P_WORD).of(a, b) >> np.uint64(64 - BITS))
    checks, clash = None, False
    if checked:
        checks = Rolling(second, P_CHECK).of(a, b)
        order = np.argsort(both, kind="stable")
        both, checks = both[order], checks[order]
        new = np.concatenate(([len(both) > 0], both[1:] != both[:-1]))[: len(both)]
        clash = bool((~new[1:] & (checks[1:] != checks[:-1])).any())
        both, checks = both[new], checks[new]
    else:
        both = np.unique(both)
    doc = (both >> _OWN).astype(np.int64)
    return both & MASK, doc, np.bincount(doc, minlength=len(words)), checks, clash


def set_digests(hashes: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """A 64-bit digest of each set, whatever its order; of the empty set a number that no caller uses."""
    sums = np.concatenate(([np.uint64(0)], np.cumsum(mixed(hashes + np.uint64(0x51ED)), dtype=np.uint64)))
    ends = np.cumsum(sizes)
    return mixed(sums[ends] - sums[ends - sizes] + sizes.astype(np.uint64)).view(np.int64)


_SETS = pa.schema([("doc_id", pa.int64()), ("key", pa.int64()), ("check", pa.int64()), ("n_shingles", pa.int64()), ("clash", pa.bool_())])


def _set_keys(k: int, seed: int):
    def run(batches):
        for ids, data, offsets in pieces_of(batches, CHUNK):
            hashes, _, sizes, checks, clash = shingle_sets(data, offsets, k, seed, True)
            columns = [pa.array(x, pa.int64()) for x in (ids, set_digests(hashes, sizes), set_digests(checks, sizes), sizes)]
            yield pa.RecordBatch.from_arrays([*columns, pa.array(np.full(len(ids), clash))], schema=_SETS)

    return run


def _holders(k: int, seed: int):
    def run(batches):
        for _, data, offsets in pieces_of(batches, CHUNK):
            hashes, doc, sizes, _, _ = shingle_sets(data, offsets, k, seed)
            keys = set_digests(hashes, sizes)
            _, first = np.unique(keys, return_index=True)
            once = np.zeros(len(keys), bool)
            once[first] = True
            use = once[doc]
            yield Holders(hashes[use], doc[use], keys, sizes, np.zeros(int(use.sum()), bool))

    return run


def _ranked(rank, hashes: np.ndarray) -> np.ndarray:
    return (np.uint64(rank) if np.isscalar(rank) else rank.astype(np.uint64)) << np.uint64(BITS) | hashes


def _hot_here(h: Holders, starts: np.ndarray):
    """Within a piece: a shingle that ``HOT`` of its classes hold is shared, and last in order; one entry says so."""
    keys, group = h.holder(), spread(starts, len(h.hashes))
    many = np.flatnonzero((np.diff(np.append(starts, len(keys))) >= HOT)[group])
    order = many[np.lexsort((keys[many], group[many]))]
    new = np.ones(len(order), bool)
    new[1:] = (group[order][1:] != group[order][:-1]) | (keys[order][1:] != keys[order][:-1])
    hot = np.bincount(group[order[new]], minlength=len(starts)) >= HOT
    keep, flags = ~hot[group], h.flags.copy()
    keep[starts] = True
    flags[starts[hot]] = True
    places = np.flatnonzero(hot[group])
    return Holders(h.hashes, h.owner, h.keys, h.sizes, flags).at(keep), places, _ranked(LAST, h.hashes[places])


def _shared(h: Holders, starts: np.ndarray):
    """Entries of hashes that several classes hold; the value has their number in front, so it sorts rare ones first."""
    group, keys = spread(starts, len(h.hashes)), h.holder()
    order = np.lexsort((keys, group))
    new = np.concatenate(([True], (group[order][1:] != group[order][:-1]) | (keys[order][1:] != keys[order][:-1])))
    places = np.sort(order[new])
    held = np.bincount(group[places], minlength=len(starts))
    hot = np.logical_or.reduceat(h.flags, starts)
    places = places[(held > 1)[group[places]] | hot[group[places]]]
    rank = np.where(hot, LAST, np.minimum(held, LAST - 1))[group[places]]
    return places, _ranked(rank, h.hashes[places])


def _least_overlap(n: np.ndarray, percent: int) -> np.ndarray:
    return -(-n * percent // 100)


def _prefixes(percent: int):
    """Rows (token, key, n, own, place): the shared shingles of a set's prefix under the first order; own: the
    number of shingles that no other class has, which come before them."""
    schema = pa.schema([("token", pa.int64()), ("key", pa.int64()), ("n", pa.int32()), ("own", pa.int32()), ("place", pa.int32())])

    def run(batches):
        for batch in batches:
            keys, sizes = batch.column(0).to_numpy(), batch.column(1).to_numpy()
            parts = []
            for key, n, values in zip(keys, sizes, batch.column(2).to_pylist(), strict=True):
                v = np.frombuffer(values, "<u8")
                own = int(n) - len(v)
                take = int(n) - int(_least_overlap(int(n), percent)) + 1 - own
                if take > 0:
                    v = np.sort(v)[:take]
                    parts.append((v.view(np.int64), np.full(len(v), key), np.full(len(v), n), np.full(len(v), own), own + np.arange(len(v))))
            if parts:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c), t.type) for c, t in zip(zip(*parts, strict=True), schema, strict=True)], schema=schema)

    return run


def _possible(n1, p1, n2, p2, percent: int):
    """Columns or arrays: sizes allow the similarity, and so do the places of a shared shingle in both orders."""
    small = (n1 * 100 >= n2 * percent) & (n2 * 100 >= n1 * percent)
    return small & ((1 + n1 - 1 - p1) * (100 + percent) >= percent * (n1 + n2)) & ((1 + n2 - 1 - p2) * (100 + percent) >= percent * (n1 + n2))


def _orders(values: np.ndarray, take: int):
    """The prefixes under the two further orders."""
    for salt in (0x2545F4914F6CDD1D, 0x5851F42D4C957F2D):
        rank = mixed(values ^ np.uint64(salt))
        yield rank if take >= len(rank) else np.partition(rank, take - 1)[:take]


def linked(a: np.ndarray, n_a: int, b: np.ndarray, n_b: int, percent: int) -> bool:
    """a, b: shingles of two sets that other sets hold too, without repeats."""
    takes = [n - int(_least_overlap(n, percent)) + 1 - (n - len(x)) for n, x in ((n_a, a), (n_b, b))]
    if min(takes) < 1:
        return False
    for x, y in zip(_orders(a, takes[0]), _orders(b, takes[1]), strict=True):
        if not len(np.intersect1d(x, y, assume_unique=True)):
            return False
    both = len(np.intersect1d(a, b, assume_unique=True))
    return 100 * both >= percent * (n_a + n_b - both)


def _verify(percent: int):
    schema = pa.schema([("a", pa.int64()), ("b", pa.int64())])

    def run(batches):
        last, mine = None, None
        for batch in batches:
            a, n_a, v_a, b, n_b, v_b = batch.columns
            keep = []
            for i in range(batch.num_rows):
                key = a[i].as_py()
                if key != last:
                    last, mine = key, np.frombuffer(v_a[i].as_py(), "<u8") & MASK
                if linked(mine, n_a[i].as_py(), np.frombuffer(v_b[i].as_py(), "<u8") & MASK, n_b[i].as_py(), percent):
                    keep.append(i)
            if keep:
                at = pa.array(keep)
                yield pa.RecordBatch.from_arrays([a.take(at), b.take(at)], schema=schema)

    return run


def _verified(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Those of ``pairs`` (a, b) that link."""
    both = with_both(pairs, sets.select("key", F.struct("size", "values").alias("set")), "set")
    return both.select("a", F.col("v_a.size").alias("n_a"), F.col("v_a.values").alias("v_a"), "b", F.col("v_b.size").alias("n_b"), F.col("v_b.values").alias("v_b")).mapInArrow(_verify(percent), "a long, b long")


def word_shingles(text: str, k: int) -> set[tuple[bytes, ...]]:
    words = text.encode().lower().split()
    return set(zip(*(words[i:] for i in range(k)), strict=False)) if len(words) >= k else {tuple(words)} if words else set()


def _own_texts(k: int, seed: int):
    """Rows (key, text) of (doc_id, text, key): those whose text has the key, as rows may share a doc_id."""
    schema = pa.schema([("key", pa.int64()), ("text", pa.string())])

    def run(batches):
        for batch in batches:
            at = 0
            for ids, data, offsets in pieces_of([batch], CHUNK):
                hashes, _, sizes, _, _ = shingle_sets(data, offsets, k, seed)
                keys, mine = batch.column(2).slice(at, len(ids)), batch.column(1).slice(at, len(ids))
                at += len(ids)
                same = pa.array(set_digests(hashes, sizes) == keys.to_numpy())
                yield pa.RecordBatch.from_arrays([keys.filter(same), mine.filter(same).cast(pa.string())], schema=schema)

    return run


def _compared(k: int, percent: int):
    schema = pa.schema([("a", pa.int64()), ("b", pa.int64())])

    def run(batches):
        last, mine = None, set()
        for batch in batches:
            a, t_a, b, t_b = batch.columns
            keep = []
            for i in range(batch.num_rows):
                key = a[i].as_py()
                if key != last:
                    last, mine = key, word_shingles(t_a[i].as_py(), k)
                theirs = word_shingles(t_b[i].as_py(), k)
                both = len(mine & theirs)
                if 100 * both >= percent * (len(mine) + len(theirs) - both):
                    keep.append(i)
            if keep:
                at = pa.array(keep)
                yield pa.RecordBatch.from_arrays([a.take(at), b.take(at)], schema=schema)

    return run


def word_by_word(links: DataFrame, rows: DataFrame, classes: DataFrame, k: int, seed: int, percent: int) -> DataFrame:
    """Those of ``links`` (a, b: classes) whose documents' shingles, as words, are similar enough."""
    wanted = links.select(F.explode(F.array("a", "b")).alias("key")).distinct().join(classes, "key").select(F.col("least").alias("doc_id"), "key")
    texts = settle(rows.join(wanted, "doc_id").select("doc_id", "text", "key").mapInArrow(_own_texts(k, seed), "key long, text string"), "linked-texts")
    both = with_both(links, texts, "text").select("a", F.col("v_a").alias("t_a"), "b", F.col("v_b").alias("t_b"))
    out = settle(both.mapInArrow(_compared(k, percent), "a long, b long").distinct(), "links")
    discard(texts)
    return out


def _bitmaps(batches):
    """Rows (key, bitmap): the parity, for each of 256 to 4096 bits, of the shared shingles that fall on it."""
    schema = pa.schema([("key", pa.int64()), ("bitmap", pa.binary())])
    for batch in batches:
        out = []
        for n, values in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True):
            bits = min(4096, max(256, 1 << (2 * n - 1).bit_length()))
            hashes = mixed(np.frombuffer(values, "<u8") & MASK) & np.uint64(bits - 1)
            out.append(np.packbits(np.bincount(hashes.astype(np.int64), minlength=bits) & 1).tobytes())
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.binary())], schema=schema)


def _folded_bitmaps(bitmaps: list[bytes], size: int) -> np.ndarray:
    """Bitmaps of ``size`` bytes: larger ones halved by parity, smaller ones all zero (never asked for)."""
    out = np.zeros((len(bitmaps), size), np.uint8)
    for i, b in enumerate(bitmaps):
        if len(b) >= size:
            out[i] = np.bitwise_xor.reduce(np.frombuffer(b, np.uint8).reshape(-1, size), axis=0)
    return out.view(np.uint64)


def _across(percent: int):
    """All candidates (a, b) of different components among the rows of a token that are of two blocks, or of one
    (rows sorted by token and blocks).

    A bitmap's bit is a shingle's hash modulo its length, and bits are numbered in order, so halving by
    parity gives the bitmap of half the length."""
    schema = pa.schema([("a", pa.int64()), ("b", pa.int64())])

    def pairs(rows: dict[str, np.ndarray], bitmaps: list[bytes]):
        order = np.argsort(rows["n"], kind="stable")
        key, n, own, place, root, block = (rows[c][order] for c in ("key", "n", "own", "place", "root", "block"))
        one = rows["i"][0] == rows["j"][0]
        bitmaps = [bitmaps[i] for i in order.tolist()]
        size = np.array([len(b) for b in bitmaps])
        maps = {int(x): _folded_bitmaps(bitmaps, int(x)) for x in np.unique(size)}
        reach = np.searchsorted(n, n * 100 // percent, side="right")
        for i in range(len(key) - 1):
            j = np.arange(i + 1, reach[i])
            j = j[(root[j] != root[i]) & (one | (block[j] != block[i]))]
            j = j[_possible(n[i], place[i], n[j], place[j], percent)]
            if len(j):
                mine = maps[int(size[i])]
                differ = own[i] + own[j] + np.bitwise_count(mine[j] ^ mine[i]).sum(axis=1)
                total = n[i] + n[j]
                j = j[(total - differ) * (100 + percent) >= 2 * percent * total]  # twice the overlap is at most total - differ
                if len(j):
                    yield np.minimum(key[j], key[i]), np.maximum(key[j], key[i])

    def run(batches):
        seen: set[tuple[int, int]] = set()

        def fresh(rows: dict[str, np.ndarray], bitmaps: list[bytes]):
            out = []
            for a, b in pairs(rows, bitmaps):
                for pair in zip(a.tolist(), b.tolist(), strict=True):
                    if pair not in seen:
                        seen.add(pair)
                        out.append(pair)
            if len(seen) > 100_000:
                seen.clear()  # repeats are dropped later; here they only cost
            if out:
                yield pa.RecordBatch.from_arrays([pa.array([p[0] for p in out]), pa.array([p[1] for p in out])], schema=schema)

        held, bits, last = [], [], None
        names = ("token", "i", "j", "key", "n", "own", "place", "root", "block")
        for batch in batches:
            columns = {c: batch.column(batch.schema.get_field_index(c)).to_numpy().astype(np.int64) for c in names}
            met = np.stack([columns[c] for c in names[:3]], axis=1)
            maps = batch.column(batch.schema.get_field_index("bitmap"))
            cut = [0, *(np.flatnonzero((met[1:] != met[:-1]).any(axis=1)) + 1).tolist(), len(met)]
            for s, e in zip(cut[:-1], cut[1:], strict=True):
                if s == e:
                    continue
                if (here := tuple(met[s].tolist())) != last and held:
                    yield from fresh({c: np.concatenate([h[c] for h in held]) for c in names}, bits)
                    held, bits = [], []
                last = here
                held.append({c: v[s:e] for c, v in columns.items()})
                bits += maps.slice(s, e - s).to_pylist()
        if held:
            yield from fresh({c: np.concatenate([h[c] for h in held]) for c in names}, bits)

    return run


def _in_blocks(rows: DataFrame) -> DataFrame:
    """Rows of tokens with block, i and j: once for each two blocks (i <= j) in which they meet. Rows of the token's most
    frequent component are blocks of their own, which meet only the others' blocks."""
    by_root = rows.groupBy("token", "root").agg(F.count("*").alias("c"))
    sizes = by_root.groupBy("token").agg(F.max(F.struct("c", "root")).alias("m"), F.sum("c").alias("c")).select("token", "c", F.col("m.root").alias("main"), F.ceil((F.col("c") - F.col("m.c")) / BLOCK_ROWS).cast("int").alias("few"), F.ceil(F.col("m.c") / BLOCK_ROWS).cast("int").alias("most"))
    placed = joined_with_hot_keys(rows, sizes, "token", "c", rows.count()).withColumn("h", F.xxhash64("key"))
    is_main = F.col("root") == F.col("main")
    placed = placed.withColumn("block", F.when(is_main, F.col("few") + F.pmod("h", "most")).otherwise(F.pmod("h", "few")).cast("int"))
    others = F.sequence(F.lit(0), F.when(is_main, F.col("few")).otherwise(F.col("few") + F.col("most")) - 1)
    met = placed.withColumn("other", F.explode(others))
    return met.select("token", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "block", "key", "n", "own", "place", "root")


def similar_groups(docs: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """One row per document: doc_id, n_shingles, component_id (the smallest doc_id that links reach)."""
    spark = docs.sparkSession
    small_batches(spark)
    rows = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID)).alias("doc_id"), text_or_empty().alias("text"))
    seed = 0
    while True:  # until no two shingles of a document and no two different sets share a hash: the first time, but for luck
        known = settle(rows.mapInArrow(_set_keys(k, seed), "doc_id long, key long, check long, n_shingles long, clash boolean"), "sets")
        clash = (F.min("check") != F.max("check")) | F.max("clash")
        classes = known.filter("n_shingles > 0").groupBy("key").agg(F.min("doc_id").alias("least"), F.count("*").alias("n"), clash.alias("clash"))
        if not classes.filter("clash").limit(1).count():
            break
        discard(known)
        seed += 1
    sized = settle(classes.select("key", "least", "n"), "classes")
    classes = sized.select("key", "least")
    buckets = buckets_for(rows)
    told_sets = told(rows, _holders(k, seed), _shared, buckets, fold=_hot_here)
    sets = settle(told_sets.filter(F.octet_length("values") * 100 >= F.col("size") * 8 * percent), "shared")

    prefix = settle(sets.mapInArrow(_prefixes(percent), "token long, key long, n int, own int, place int"), "prefixes")
    n_prefix, times = prefix.count(), F.count("*").alias("times")
    lead = F.min_by(F.struct("key", "n", "place"), F.struct("own", "key")).alias("lead")
    starred = joined_with_hot_keys(prefix, prefix.groupBy("token").agg(lead, times), "token", "times", n_prefix).filter(F.col("lead.key") != F.col("key"))
    fit = _possible(F.col("n").cast("long"), F.col("place"), F.col("lead.n").cast("long"), F.col("lead.place"), percent)
    tried = settle(starred.filter(fit).select(F.least("key", "lead.key").alias("a"), F.greatest("key", "lead.key").alias("b")).distinct(), "pairs")
    links = word_by_word(settle(_verified(tried, sets, percent), "hash-links"), rows, classes, k, seed, percent)
    roots = components(links)

    here = prefix.join(roots, "key", "left").withColumn("root", F.coalesce("root", "key"))
    mixed_tokens = here.groupBy("token").agg(F.min("root").alias("low"), F.max("root").alias("high"), times).filter("low < high").select("token", "times")
    cross = settle(joined_with_hot_keys(here, mixed_tokens, "token", "times", n_prefix), "candidates")
    maps = sets.mapInArrow(_bitmaps, "key long, bitmap binary")
    met = _in_blocks(cross).join(maps, "key").select("token", "i", "j", "block", "key", "n", "own", "place", "root", "bitmap")
    pairs = met.repartition("token", "i", "j").sortWithinPartitions("token", "i", "j").mapInArrow(_across(percent), "a long, b long").distinct()
    pairs = settle(pairs.join(tried, ["a", "b"], "left_anti"), "pairs")
    more = word_by_word(settle(_verified(pairs, sets, percent), "hash-links"), rows, classes, k, seed, percent)
    roots = components(links.unionByName(more))
    discard(prefix, cross, tried, pairs, sets)

    tops = roots.join(classes, "key")
    tops = tops.select("key", "root").join(tops.groupBy("root").agg(F.min("least").alias("top")), "root").select("key", "top")
    answers = settle(sized.join(tops, "key", "left").select("key", F.coalesce("top", "least").alias("component_id"), "n"), "answers")
    ids = known.select("doc_id", "key", "n_shingles")
    found = joined_with_hot_keys(ids.filter("n_shingles > 0"), answers, "key", "n", known.count())
    out = found.select("doc_id", "n_shingles", "component_id").unionByName(ids.filter("n_shingles = 0").select("doc_id", "n_shingles", F.col("doc_id").alias("component_id")))
    return out.select(F.nullif("doc_id", F.lit(NO_ID)).alias("doc_id"), "n_shingles", F.nullif("component_id", F.lit(NO_ID)).alias("component_id"))


def one_of_each_group(docs: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """The rows of ``docs``, with all their columns, whose doc_id is the smallest of its group."""
    groups = similar_groups(docs, k, percent)
    (stay,) = fresh(docs.columns, "stay")
    kept = groups.filter(F.col("doc_id").eqNullSafe(F.col("component_id"))).select(F.col("doc_id").alias(stay)).distinct()
    return docs.join(kept, F.col("doc_id").eqNullSafe(F.col(stay)), "left_semi")
