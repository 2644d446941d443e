"""Collection filters: which crawled notebooks and data files the miner takes in."""

from __future__ import annotations

import re
from collections.abc import Sequence
from hashlib import blake2b

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType

from nbflow.functions.parsing import _PATH
from nbflow.session import settle
from nbflow.sources.render import license_of

#: Licences that allow redistribution (fixed values).
ALLOWED = ("Apache-2.0", "MIT", "GPL-3")


def filter_extension(files: DataFrame, column: str, extension: str = ".ipynb") -> DataFrame:
    return files.filter(F.col(column).endswith(extension))


def filter_license(files: DataFrame, column: str = "license", allow: Sequence[str] = ALLOWED) -> DataFrame:
    return files.filter(F.col(column).isin(*allow))


def with_license(files: DataFrame, text: str) -> DataFrame:
    return files.withColumn("license", license_of(text))


def dedup_exact(files: DataFrame, content: str, key: str) -> DataFrame:
    """Of rows with equal content the one with the smallest key: digests are grouped, contents don't travel twice."""
    keep = files.groupBy(F.md5(content).alias("__d"), F.length(content).alias("__n")).agg(F.min(key).alias(key)).select(key)
    return files.join(keep, key, "left_semi")


def drop_forks(files: DataFrame, content: str, repo: str, key: str) -> DataFrame:
    """Without a fork flag: a file is a fork's if another repository has its content under a smaller key."""
    first = files.groupBy(F.md5(content).alias("__d")).agg(F.min_by(repo, key).alias("__repo"))
    return files.withColumn("__d", F.md5(content)).join(first, "__d").filter(F.col(repo) == F.col("__repo")).drop("__d", "__repo")


def filter_language(files: DataFrame, column: str = "lang_major", major: int = 3) -> DataFrame:
    return files.filter(F.col(column) == major)


def filter_has_call(files: DataFrame, stmts: DataFrame, api: str = "read_csv") -> DataFrame:
    """Files whose statements call ``api``."""
    calls = stmts.filter(F.exists("calls", lambda c: c["api"] == api)).select("nb_id")
    return files.join(calls, "nb_id", "left_semi")


def path_literals(stmts: DataFrame) -> DataFrame:
    """(nb_id, pos, raw): string literals that look like paths of data files."""
    return stmts.select("nb_id", "pos", F.explode("literals").alias("raw")).filter(F.col("raw").rlike(_PATH.pattern))


def basename(path: str | Column) -> Column:
    return F.element_at(F.split(path, "/"), -1)


def resolve_paths(refs: DataFrame, files: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """Path references with ``name``, the file they mean (null: none has it). ``by``: columns that a reference and its
    file share, as the repository; a file matches by its whole path, or by its base name where it has no other."""
    keys = list(by)
    exact = files.select(*keys, F.col("name").alias("raw"), F.col("name").alias("__exact")).distinct()
    based = files.select(*keys, basename("name").alias("__b"), "name").distinct().groupBy(*keys, "__b").agg(F.min("name").alias("__based"), F.count("*").alias("__n"))
    found = refs.withColumn("__b", basename("raw")).join(exact, [*keys, "raw"], "left").join(based, [*keys, "__b"], "left")
    return found.withColumn("name", F.coalesce("__exact", F.when(F.col("__n") == 1, F.col("__based")))).select(*refs.columns, "name")


def drop_unresolved(files: DataFrame, refs: DataFrame) -> DataFrame:
    return files.join(refs.filter("name is null").select("nb_id"), "nb_id", "left_anti")


def flat_names(paths: DataFrame, column: str) -> DataFrame:
    """Paths with ``flat``, their name in one directory: the file's own, or with a digest in front where different
    paths share it."""
    unique = paths.select(column).distinct().withColumn("__b", basename(column))
    shared = F.count("*").over(Window.partitionBy("__b")) > 1
    named = unique.withColumn("flat", F.when(shared, F.concat(F.substring(F.md5(column), 1, 8), F.lit("_"), "__b")).otherwise(F.col("__b"))).drop("__b")
    return paths.join(named, column)


def flatten_paths(cells: DataFrame, refs: DataFrame) -> DataFrame:
    """Cells whose path literals, in quotes of either kind, are replaced by flat names; each notebook's references are one
    small map. A path within another is left alone, as literals are replaced whole."""
    flat = flat_names(refs.select("nb_id", "raw").distinct(), "raw")
    maps = flat.groupBy("nb_id").agg(F.array_sort(F.collect_list(F.struct("raw", "flat"))).alias("__m"))
    quoted = lambda q, x: F.concat(F.lit(q), x, F.lit(q))
    fixed = F.aggregate("__m", F.col("source"), lambda text, m: F.replace(F.replace(text, quoted("'", m["raw"]), quoted("'", m["flat"])), quoted('"', m["raw"]), quoted('"', m["flat"])))
    return cells.join(maps, "nb_id", "left").withColumn("source", F.when(F.col("__m").isNull() | (F.col("kind") != "code"), F.col("source")).otherwise(fixed)).drop("__m")


def funnel(rows: DataFrame, steps: dict[str, Column]) -> DataFrame:
    """Rows (step, kept): how many rows pass each filter and all before it, in one scan."""
    so_far, measures = F.lit(True), [F.count("*").alias("all")]
    for name, condition in steps.items():
        so_far = so_far & F.coalesce(condition, F.lit(False))
        measures.append(F.count_if(so_far).alias(name))
    return rows.agg(*measures).unpivot([], ["all", *steps], "step", "kept")


def contained_items(documents: DataFrame, items: DataFrame) -> DataFrame:
    """(doc_id, item_id): items whose whole text a document contains.

    Each item gives one probe, the digest of the ``width`` words after its first; its outermost words are no part
    of it, as other characters may be glued to them in a document. Documents are scanned once, and the texts of
    candidates are then compared. Items too short for that are compared with every document."""
    width = 8
    words = lambda c: F.regexp_extract_all(c, F.lit(r"(\S+)"), 1)
    probe = items.withColumn("__w", words("text")).filter(F.size("__w") >= width + 2).select("item_id", F.xxhash64(F.array_join(F.slice("__w", 2, width), " ")).alias("__h"))
    short = items.withColumn("__w", words("text")).filter(F.size("__w") < width + 2).select("item_id", F.col("text").alias("item_text"))
    ids = documents.select("doc_id", words("text").alias("__w"))
    grams = F.array_distinct(F.transform(F.sequence(F.lit(1), F.greatest(F.size("__w") - width + 1, F.lit(1))), lambda i: F.xxhash64(F.array_join(F.slice("__w", i, width), " "))))
    met = ids.select("doc_id", F.explode(grams).alias("__h")).join(probe, "__h").select("doc_id", "item_id").distinct()
    texts = items.select("item_id", F.col("text").alias("item_text"))
    long = documents.select("doc_id", "text").join(met, "doc_id").join(texts, "item_id").filter(F.contains("text", "item_text")).select("doc_id", "item_id")
    rest = documents.select("doc_id", "text").join(short, F.contains("text", "item_text")).select("doc_id", "item_id")
    return long.unionByName(rest).distinct()


#: Classes of a bucket that meet in one block of candidates.
BLOCK = 64
_MIX = (np.uint64(0x9E3779B97F4A7C15), np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB))
_SKETCH = "doc_id long, s array<long>, x long, y long, bands array<long>"


def _mixed(v: np.ndarray) -> np.ndarray:
    v = (v ^ (v >> np.uint64(30))) * _MIX[1]
    v = (v ^ (v >> np.uint64(27))) * _MIX[2]
    return v ^ (v >> np.uint64(31))


def _sketches(k: int, hashes: int, rows: int):
    """Rows of (doc_id, text): the hashes of a document's different shingles in order, two digests of them all, and its
    min-hash bands (none, if no bands are asked for). Documents without words have no row."""
    seeds = _mixed(np.arange(1, hashes + 1, dtype=np.uint64) * _MIX[0])[:, None]
    space = re.compile(r"[^ \t\n\r\f\v]+")
    schema = to_arrow_schema(StructType.fromDDL(_SKETCH))

    def run(batches):
        known: dict[str, int] = {}
        for batch in batches:
            out = []
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                words = space.findall((text or "").lower())
                if not words:
                    continue
                if len(known) > 1_000_000:
                    known.clear()
                w = np.array([known.get(x) or known.setdefault(x, int.from_bytes(blake2b(x.encode(), digest_size=8).digest(), "little")) for x in words], np.uint64)
                v = np.zeros(max(len(w) - k + 1, 1), np.uint64)
                for i in range(min(k, len(w))):
                    v = _mixed(v * _MIX[0] + w[i : i + len(v)] + np.uint64(i + 1))
                v = np.unique(v)
                digest = blake2b(v.tobytes(), digest_size=16).digest()
                least = [_mixed(v[None, :] ^ seeds[i : i + 8]).min(axis=1) for i in range(0, hashes, 8)]
                bands = [int.from_bytes(blake2b(m.tobytes(), digest_size=8, salt=bytes([n])).digest(), "little", signed=True) for n, m in enumerate(np.concatenate(least).reshape(-1, rows))] if hashes else []
                out.append((doc, v.view(np.int64), int.from_bytes(digest[:8], "little", signed=True), int.from_bytes(digest[8:], "little", signed=True), bands))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*out, strict=True), schema, strict=True)], schema=schema)

    return run


def near_duplicates(documents: DataFrame, threshold: float = 0.8, k: int = 5, hashes: int = 80, rows: int = 4) -> DataFrame:
    """(a, b, similarity): pairs of documents that share a min-hash band and whose k-word shingle sets are similar, verified
    on the sets. Copies are not paired with one another: of equal sets, the smallest doc_id stands for all and is paired
    with each of them, at 1, and with other sets' smallest.

    Equal sets (128 bits of digest) are one class. Any two classes of a band's bucket are a candidate, taken in the first
    band that they share; large buckets are cut into blocks of about ``BLOCK`` classes, and each two blocks meet on a
    key of their own. Sizes that rule the threshold out are left before sets travel, and only the sets of candidates do."""

    def sketched(docs: DataFrame, n: int) -> DataFrame:
        return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(_sketches(k, n, rows), _SKETCH).withColumn("c", F.struct("x", "y"))

    sketch = settle(sketched(documents, hashes).select("doc_id", "c", F.size("s").alias("n"), "bands"), "sketch")
    classes = sketch.groupBy("c").agg(F.min("doc_id").alias("rep"), F.first("n").alias("n"), F.first("bands").alias("bands"))
    buckets = classes.select("*", F.posexplode("bands").alias("no", "band"))
    blocks = buckets.groupBy("no", "band").agg(F.ceil(F.count("*") / BLOCK).cast("int").alias("g"), F.count("*").alias("in_band")).filter("in_band > 1").drop("in_band")
    placed = buckets.join(blocks, ["no", "band"]).withColumn("own", F.pmod(F.xxhash64("c"), "g").cast("int"))
    one = placed.select("no", "band", F.col("own").alias("i"), F.explode(F.sequence("own", F.col("g") - 1)).alias("j"), F.struct("c", "rep", "n", "bands").alias("l"))
    two = placed.select("no", "band", F.explode(F.sequence(F.lit(0), "own")).alias("i"), F.col("own").alias("j"), F.struct("c", "rep", "n", "bands").alias("r"))
    shared = F.array_position(F.zip_with("l.bands", "r.bands", lambda x, y: x == y), F.lit(True)) == F.col("no") + 1
    fits = F.least("l.n", "r.n") >= F.greatest("l.n", "r.n") * (threshold - 1e-9)
    meet = one.join(two, ["no", "band", "i", "j"]).filter(((F.col("i") < F.col("j")) | (F.col("l.c") < F.col("r.c"))) & fits & shared)
    pairs = settle(meet.select(F.col("l.rep").alias("ra"), F.col("r.rep").alias("rb")), "candidates")
    needed = pairs.select(F.explode(F.array("ra", "rb")).alias("doc_id")).distinct()
    sets = settle(sketched(documents.join(needed, "doc_id", "left_semi"), 0).select("doc_id", "s"), "sets")
    both = pairs.join(sets.select(F.col("doc_id").alias("ra"), F.col("s").alias("sa")), "ra").join(sets.select(F.col("doc_id").alias("rb"), F.col("s").alias("sb")), "rb")
    common = F.size(F.array_intersect("sa", "sb"))
    near = both.withColumn("similarity", common / (F.size("sa") + F.size("sb") - common)).filter(F.col("similarity") >= threshold)
    copies = sketch.join(classes.select("c", "rep"), "c").filter("doc_id <> rep").select(F.col("rep").alias("a"), F.col("doc_id").alias("b"), F.lit(1.0).alias("similarity"))
    return near.select(F.least("ra", "rb").alias("a"), F.greatest("ra", "rb").alias("b"), "similarity").unionByName(copies)
