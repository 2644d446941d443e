"""Line deduplication by deletion neighbourhoods, in DataFrame functions only.

Two lines are within one edit exactly if deleting a character of each at the same place makes them equal
(one replaced), or deleting one of the longer gives the shorter. So each line emits all its variants with
one character deleted, as hashed keys, and equal variants meet: within such a group the earliest line is
known at once, without pairs. The edit distance of what met is then verified on the lines themselves.

A line emits variants only if it can have a partner at all: of any equal parts that a line is cut into, an
edit changes one, so a line must share all parts but one, under the length of the shorter, with a different
line. Two parts are tried on all lines, sixteen on those left, and only characters of a part that may differ are
deleted: no other deletion can meet a partner's. Equal lines are folded first, to one row with their earliest
place.

Defined cases: lines end at line feeds and are compared without spaces, tabs and carriage returns at
their ends; blank lines stay and match nothing; a caller may ask that two lines of fewer than ``least_chars``
characters match only if equal; a line goes if an equal or near one begins earlier (smaller doc_id, then line), judged on the
input; a null text is one blank line; rows that share a doc_id count as one document; a missing doc_id
counts as the smallest; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from nbflow.llm.common import NO_ID, settle, text_or_empty

#: Shortest line, in characters, for which one edit still means the same line: any.
LEAST_CHARS = 1
_LINE = ["h1", "h2"]


def _place(doc_id: Column, line_no: Column) -> Column:
    """The order of lines: document, then line, as one number that hash aggregation can hold."""
    return (doc_id.cast("decimal(20,0)") * F.lit(1 << 32).cast("decimal(11,0)") + line_no.cast("decimal(11,0)")).cast("decimal(38,0)")


def _trimmed(line: Column) -> Column:
    return F.btrim(line, F.lit(" \t\r"))


def _without(line: Column, k: Column, parts: int) -> Column:
    """(key, first, last): the hash of a line without one of its parts, and the places of the characters left out.
    The first ``parts`` numbers k are the parts as a partner of the same or a larger length sees them, the others as one
    that lacks a character does."""
    n = F.length(line)
    shorter, i = n - F.floor(k / parts).cast("int"), F.pmod(k, F.lit(parts))
    ahead, behind = F.floor(shorter * i / parts).cast("int"), (shorter - F.floor(shorter * (i + 1) / parts)).cast("int")
    key = F.xxhash64(shorter, i, F.substring(line, F.lit(1), ahead), F.substring(line, n - behind + 1, behind))
    return F.struct(key.alias("key"), (ahead + 1).alias("first"), (n - behind).alias("last"))


def _met(keyed: DataFrame) -> DataFrame:
    """Keys that several lines have."""
    return keyed.groupBy("key").agg(F.count("*").alias("n")).filter("n > 1").select("key")


def _lines(rows: DataFrame) -> DataFrame:
    """Rows (doc_id, row, place, line, h1, h2) of the lines that aren't blank."""
    found = rows.select("doc_id", "row", F.posexplode(F.split("text", "\n", -1)).alias("line_no", "raw")).withColumn("line", _trimmed(F.col("raw"))).filter("line <> ''")
    return found.select("doc_id", "row", "line_no", _place(F.col("doc_id"), F.col("line_no")).alias("place"), "line", F.xxhash64("line").alias("h1"), F.xxhash64(F.lit("second"), "line").alias("h2"))


def near_lines(rows: DataFrame, distinct: DataFrame, least_chars: int) -> DataFrame:
    """Rows (h1, h2): the distinct lines that are one edit from an earlier one.

    Joins with all documents or lines are merge joins at every size: their other side grows with the input."""
    able = distinct.filter(F.col("chars") >= least_chars - 1)
    halves = able.select(*_LINE, F.explode(F.array_distinct(F.array("k0", "k1", "k2", "k3"))).alias("key"))
    partnered = halves.join(_met(halves), "key", "left_semi").select(*_LINE).distinct()
    able = settle(able.join(partnered, _LINE).select(*_LINE, "place", "doc_id", "line_no"), "able")

    wanted = able.groupBy("doc_id").agg(F.collect_list(F.struct("line_no", "place", *_LINE)).alias("wanted"))
    picked = F.transform("wanted", lambda x: F.struct(x["h1"].alias("h1"), x["h2"].alias("h2"), x["place"].alias("place"), _trimmed(F.get(F.col("lines"), x["line_no"])).alias("line")))
    texts = rows.join(wanted.hint("merge"), "doc_id").withColumn("lines", F.split("text", "\n", -1)).select(F.explode(picked).alias("x")).select("x.*")
    texts = settle(texts.filter((F.xxhash64("line") == F.col("h1")) & (F.length("line") >= least_chars - 1)), "able-lines")

    parts = F.transform(F.sequence(F.lit(0), F.lit(31)), lambda k: _without(F.col("line"), k, 16))
    keyed = settle(texts.select(*_LINE, F.explode(parts).alias("p")).select(*_LINE, "p.*"), "keys")
    lone = keyed.select(*_LINE, "key").distinct()  # a line may have a key twice; it meets itself no partner
    spans = keyed.filter("first <= last").join(_met(lone), "key", "left_semi").groupBy(*_LINE).agg(F.collect_set(F.struct("first", "last")).alias("spans"))
    met = lone.join(_met(lone), "key", "left_semi").select(*_LINE).distinct()
    texts = settle(texts.join(met, _LINE).join(spans, _LINE, "left"), "near-able-lines")
    n = F.length("line")
    places = F.array_distinct(F.flatten(F.transform(F.coalesce("spans", F.array()), lambda s: F.sequence(s["first"], s["last"]))))
    cut = F.transform(places, lambda i: F.struct(F.xxhash64(F.concat(F.substring(F.col("line"), F.lit(1), i - 1), F.substring(F.col("line"), i + 1, n))).alias("key"), i.alias("at")))
    whole = F.array(F.struct(F.xxhash64("line").alias("key"), F.lit(0).alias("at")))
    emitted = texts.select(*_LINE, "place", F.explode(F.concat(whole, cut)).alias("v")).select(*_LINE, "place", "v.key", "v.at")
    me = F.struct("place", *_LINE)
    same_place, same_key = Window.partitionBy("key", "at"), Window.partitionBy("key")
    emitted = emitted.withColumn("replaced", F.min(F.when(F.col("at") > 0, me)).over(same_place))
    emitted = emitted.withColumn("longer", F.min(F.when(F.col("at") > 0, me)).over(same_key)).withColumn("shorter", F.min(F.when(F.col("at") == 0, me)).over(same_key))
    others = F.array(F.when(F.col("at") > 0, F.col("replaced")), F.when(F.col("at") > 0, F.col("shorter")), F.when(F.col("at") == 0, F.col("longer")))
    pairs = emitted.select(*_LINE, "place", F.explode(others).alias("other")).filter("other is not null and other.place < place").select(*_LINE, F.col("other.h1").alias("o1"), F.col("other.h2").alias("o2")).distinct()

    mine, theirs = texts.select(*_LINE, "line"), texts.select(F.col("h1").alias("o1"), F.col("h2").alias("o2"), F.col("line").alias("other"))
    both = pairs.join(mine, _LINE).join(theirs, ["o1", "o2"])
    long_enough = F.least(F.length("line"), F.length("other")) >= least_chars - 1
    near = (F.levenshtein("line", "other", 1) >= 0) & long_enough & (F.greatest(F.length("line"), F.length("other")) >= least_chars)
    return both.filter(near).select(*_LINE).distinct()


def remove_repeated_lines(docs: DataFrame, least_chars: int = LEAST_CHARS) -> DataFrame:
    """One row per document: doc_id, n_lines, n_removed, kept (its other lines, unchanged, in order)."""
    spark = docs.sparkSession
    rows = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID)).alias("doc_id"), text_or_empty().alias("text")).withColumn("row", F.xxhash64("text"))  # rows may share a doc_id
    lines = _lines(rows)
    shape = lines.select(*_LINE, "place", F.length("line").alias("chars"), *[_without(F.col("line"), F.lit(k), 2)["key"].alias(f"k{k}") for k in range(4)])
    distinct = shape.groupBy(*_LINE).agg(F.min("place").alias("place"), F.count("*").alias("n"), F.min("chars").alias("chars"), *[F.min(f"k{i}").alias(f"k{i}") for i in range(4)])
    two32 = F.lit(1 << 32).cast("decimal(11,0)")
    line_no = F.pmod(F.col("place"), two32).cast("int")
    distinct = distinct.withColumn("line_no", line_no).withColumn("doc_id", ((F.col("place") - F.col("line_no")) / two32).cast("long"))
    distinct = settle(distinct, "lines")
    near = settle(near_lines(rows, distinct, least_chars), "near-lines")

    marked = distinct.join(near.withColumn("near", F.lit(True)), _LINE, "left").select(*_LINE, F.col("place").alias("first"), "n", F.coalesce("near", F.lit(False)).alias("near")).filter("n > 1 or near")
    gone = lines.select(*_LINE, "doc_id", "row", "line_no", "place").join(marked.hint("merge"), _LINE).filter("near or place > first")
    gone = settle(gone.groupBy("doc_id", "row").agg(F.array_sort(F.collect_set("line_no")).alias("gone")), "gone-lines")
    cut = rows.join(gone.hint("merge"), ["doc_id", "row"], "left").withColumn("lines", F.split("text", "\n", -1)).withColumn("gone", F.coalesce("gone", F.array().cast("array<int>")))
    # a sign for each line up to the last that goes: linear in the lines, however many go
    ahead = lambda i: F.coalesce(F.get("gone", i - 1), F.lit(-1))
    signs = F.split(F.array_join(F.transform("gone", lambda g, i: F.concat(F.repeat(F.lit("s"), g - ahead(i) - 1), F.lit("g"))), ""), "")
    kept = F.array_join(F.zip_with("lines", signs, lambda line, sign: F.when(F.coalesce(sign != "g", F.lit(True)), line)), "\n")
    n_lines, n_gone = F.size("lines").cast("long"), F.size("gone").cast("long")
    return cut.select(F.nullif("doc_id", F.lit(NO_ID)).alias("doc_id"), n_lines.alias("n_lines"), n_gone.alias("n_removed"), F.when(n_gone == 0, F.col("text")).otherwise(kept).alias("kept"))
