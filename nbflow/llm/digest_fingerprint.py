"""Canonical exact digests of documents.

A text is put in canonical form (compatibility composition, full case folding, runs of white space as one
space), and the 128-bit xxhash of that form is its fingerprint. Documents whose digests are equal are
compared byte by byte: should two forms share a digest, their order among the forms of that digest is
appended, so that fingerprints are equal exactly when forms are. Only forms whose digest occurs more than
once travel for the comparison, folded per task first. The likeness of two exact fingerprints is 1 or 0.

Digests that many documents have are marked without a shuffle. Documents are read in order in buckets of bounded size,
however many there are.

Defined cases: a null text counts as empty; the next document is the one before in ascending doc_id, the
first after the last; rows that share a doc_id follow one another by text; a missing doc_id counts as the
smallest; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import unicodedata

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from nbflow.llm.common import NO_ID, joined_with_hot_keys, partitions, settle, small_batches, text_or_empty, text_views


def canonical(text: str) -> str:
    """Composition, case folding, composition again (folding may undo it), and white space as single spaces."""
    if not text.isascii():
        text = unicodedata.normalize("NFKC", unicodedata.normalize("NFKC", text).casefold())
    else:
        text = text.lower()
    return " ".join(text.split())


def digest(form: bytes) -> str:
    return xxhash.xxh3_128_hexdigest(form)


def _texts(batch) -> list[str]:
    data, offsets = text_views(batch.column(1))
    body, at = data.tobytes(), offsets.tolist()
    return [body[a:b].decode("utf-8", "replace") for a, b in zip(at[:-1], at[1:], strict=True)]


#: Bytes of a bucket, and of the forms that a task keeps.
BUCKET_BYTES, FORM_BYTES = 32 << 20, 32 << 20
_DIGESTS = pa.schema([("doc_id", pa.int64()), ("digest", pa.string()), ("size", pa.int64())])


def _digests(batches):
    for batch in batches:
        found = [digest(canonical(t).encode("utf-8", "surrogatepass")) for t in _texts(batch)]
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(found, pa.string()), pa.array(np.diff(text_views(batch.column(1))[1]))], schema=_DIGESTS)


def _lasts(bounds: np.ndarray):
    """Rows (bucket, last): the largest doc_id that each batch has of each bucket."""

    def run(batches):
        for batch in batches:
            ids = np.sort(batch.column(0).to_numpy())
            bucket = np.searchsorted(bounds, ids, side="right")
            end = np.flatnonzero(np.diff(bucket, append=-1))
            yield pa.RecordBatch.from_arrays([pa.array(bucket[end], pa.int32()), pa.array(ids[end])], names=["bucket", "last"])

    return run


_DEALT = pa.schema([("bucket", pa.int32()), ("doc_id", pa.int64()), ("text", pa.string()), ("kind", pa.int32())])
#: Kinds of dealt rows: a mark that the document's digest is not unique, the document, a document of the next bucket.
_MARK, _OWN, _AHEAD = 0, 1, 2


def _dealt_out(bounds: np.ndarray, above: dict[int, list[int]], kind: int):
    """above: for a document that is the last of its bucket, the buckets that look ahead to it."""

    def run(batches):
        for batch in batches:
            ids = batch.column(0).to_numpy()
            bucket = np.searchsorted(bounds, ids, side="right")
            text = batch.column(1).cast(pa.string()) if kind == _OWN else pa.nulls(len(ids), pa.string())
            yield pa.RecordBatch.from_arrays([pa.array(bucket, pa.int32()), pa.array(ids), text, pa.array(np.full(len(ids), kind), pa.int32())], schema=_DEALT)
            ahead = [(i, b) for i, x in enumerate(ids.tolist()) for b in above.get(x, ())] if kind == _OWN else []
            if ahead:
                at = pa.array([i for i, _ in ahead])
                yield pa.RecordBatch.from_arrays([pa.array([b for _, b in ahead], pa.int32()), pa.array(ids).take(at), text.take(at), pa.array([_AHEAD] * len(ahead), pa.int32())], schema=_DEALT)

    return run


_OUT = pa.schema(
    [("doc_id", pa.int64()), ("n_chars", pa.int64()), ("edited_sha256", pa.string()), ("fingerprint", pa.string()), ("edited_fingerprint", pa.string()), ("near_edited", pa.float64()), ("near_next", pa.float64()), ("form", pa.binary())]
)
_OUT_SQL = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double, form binary"


def _read_on(batches):
    """Rows in order (bucket, own before ahead, descending doc_id); each document is read with the one after it."""
    forms: dict[str, bytes] = {}
    kept = 0
    rows: list[tuple] = []
    held = None  # (doc_id, text, form, marked)
    marked, bucket = None, None

    def result(doc, text, form, mark, after_text, after_form):
        nonlocal kept
        n = len(text)
        take = n // 3
        edited = text[: n - take] + after_text[:take]
        edited_form = canonical(edited).encode("utf-8", "surrogatepass")
        own = digest(form)
        shown = None
        if mark and forms.get(own) != form:  # the first of its digest in this task goes to the comparison, and what differs from it
            shown = form
            if own not in forms:
                kept += len(form) + 100
                if kept > FORM_BYTES:  # begun anew: a form may then go twice
                    forms.clear()
                    kept = len(form) + 100
                forms[own] = form
        return (doc, n, hashlib.sha256(edited.encode("utf-8", "surrogatepass")).hexdigest(), own, digest(edited_form), float(edited_form == form), float(after_form == form), shown)

    def flushed():
        out = pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), _OUT, strict=True)], schema=_OUT)
        rows.clear()
        return out

    for batch in batches:
        kinds, buckets, ids = (batch.column(batch.schema.get_field_index(c)).to_pylist() for c in ("kind", "bucket", "doc_id"))
        texts = batch.column(batch.schema.get_field_index("text"))
        for i, kind in enumerate(kinds):
            if buckets[i] != bucket:
                bucket, held, marked = buckets[i], None, None
            if kind == _MARK:
                marked = ids[i]
                continue
            text = texts[i].as_py() or ""
            form = canonical(text).encode("utf-8", "surrogatepass")
            if held is not None:
                rows.append(result(*held, text, form))
                if len(rows) >= 500:
                    yield flushed()
            held = None if kind == _AHEAD else (ids[i], text, form, marked == ids[i])
    if rows:
        yield flushed()


def fingerprints(docs: DataFrame) -> DataFrame:
    """One row per document: doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next."""
    small_batches(docs.sparkSession)
    spark = docs.sparkSession
    rows = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID)).alias("doc_id"), text_or_empty().alias("text"))
    found = settle(rows.mapInArrow(_digests, "doc_id long, digest string, size long"), "digests")
    n_docs, n_bytes = found.agg(F.count("*"), F.coalesce(F.sum("size"), F.lit(0))).first()
    again = settle(found.groupBy("digest").agg(F.count("*").alias("n")).filter("n > 1"), "again")
    marked = joined_with_hot_keys(found.select("doc_id", "digest"), again, "digest", "n", n_docs, "left_semi").select("doc_id").distinct()

    # cuts of the order of doc_ids, one per bucket, and the last document of each part: as many numbers as buckets
    parts = max(partitions(spark), -(-n_bytes // BUCKET_BYTES))
    shares = [i / parts for i in range(1, parts)] or [0.5]
    cuts = found.agg(F.percentile_approx("doc_id", F.array(*map(F.lit, shares)), F.lit(20 * parts))).first()[0]
    bounds = np.unique(np.array(cuts or [], np.int64))
    ends = found.select("doc_id").mapInArrow(_lasts(bounds), "bucket int, last long").groupBy("bucket").agg(F.max("last").alias("last")).orderBy("bucket").collect()
    above: dict[int, list[int]] = {}
    for lower, upper in zip(ends, ends[1:] + ends[:1], strict=True):
        above.setdefault(lower["last"], []).append(upper["bucket"])

    kinds = "bucket int, doc_id long, text string, kind int"
    own = rows.mapInArrow(_dealt_out(bounds, above, _OWN), kinds)
    marks = marked.select("doc_id", F.lit(None).cast("string").alias("text")).mapInArrow(_dealt_out(bounds, above, _MARK), kinds)
    order = [F.col("bucket"), (F.col("kind") == _AHEAD), F.col("doc_id").desc(), F.col("kind"), F.col("text")]
    read = own.unionByName(marks).repartition(max(len(ends), 1), "bucket").sortWithinPartitions(*order).mapInArrow(_read_on, _OUT_SQL)
    read = settle(read, "fingerprints")

    # byte comparison inside equal digests: grouping by digest and form compares whole forms
    forms = read.filter("form is not null").groupBy("fingerprint", "form").agg(F.count("*").alias("n"))
    shared = forms.groupBy("fingerprint").agg(F.count("*").alias("forms")).filter("forms > 1").select("fingerprint")
    out = read.drop("form")
    if shared.limit(1).count():
        nth = F.row_number().over(Window.partitionBy("fingerprint").orderBy("form")) - 1
        places = forms.join(shared, "fingerprint").withColumn("nth", nth)
        texts = rows.join(found.join(shared, found["digest"] == shared["fingerprint"], "left_semi").select("doc_id").distinct(), "doc_id")
        named = texts.mapInArrow(_forms, "doc_id long, fingerprint string, form binary").join(places, ["fingerprint", "form"]).select("doc_id", "fingerprint", "nth").distinct()
        suffix = F.when(F.coalesce("nth", F.lit(0)) > 0, F.concat(F.lit("-"), F.col("nth").cast("string"))).otherwise(F.lit(""))
        out = out.join(named, ["doc_id", "fingerprint"], "left").withColumn("fingerprint", F.concat("fingerprint", suffix)).drop("nth")
    return out.withColumn("doc_id", F.nullif("doc_id", F.lit(NO_ID)))


def _forms(batches):
    for batch in batches:
        forms = [canonical(t).encode("utf-8", "surrogatepass") for t in _texts(batch)]
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([digest(f) for f in forms], pa.string()), pa.array(forms, pa.binary())], names=["doc_id", "fingerprint", "form"])
