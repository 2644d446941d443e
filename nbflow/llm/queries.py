"""The registered queries of the training-data operators, each over its whole table, and their SQL."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from nbflow.llm import block_anchors, deletion_lines, digest_fingerprint, factor_classifier, grace_dedup, multi_order_join, slack_packing, slot_mixing, suffix_bwt
from nbflow.llm import token_rollup as rollup
from nbflow.llm.common import documents, settle, work_dir

Query = Callable[[SparkSession, str], DataFrame]


def token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Totals after four commits: all documents come, counted by the first vocabulary and estimated for the second;
    those labelled toxic go; the estimates of those left are revised to counts; and the second batch comes again,
    which changes nothing. The batches are compacted before the totals are read."""
    import public_tokenizers

    first, second = map(rollup.version, rollup.VERSIONS)
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg((F.max("toxic") == 1).alias("toxic"))
    docs = documents(spark, sf_dir).select("doc_id", "source", "lang", "text")
    found = settle(rollup.counted(docs, {rollup.version(f): public_tokenizers.path(f) for f in rollup.VERSIONS}), "counts")
    guessed = settle(docs.select("doc_id", "source", "lang", rollup.estimate().alias("guess")), "estimates")
    totals = rollup.TokenRollup(spark, f"{work_dir(spark)}/rollup-{uuid.uuid4().hex}")

    def marked(rows: DataFrame) -> DataFrame:
        return rows.join(labels, "doc_id", "left").withColumn("toxic", F.coalesce("toxic", F.lit(False)))

    def moved(keep, sign: int) -> DataFrame:
        return rollup.changes(keep(found), first, F.col(first), sign).unionByName(rollup.changes(keep(guessed), second, F.col("guess"), sign))

    def toxic(rows: DataFrame) -> DataFrame:
        return marked(rows).filter("toxic")

    totals.commit(0, moved(lambda rows: rows, 1))
    totals.commit(1, moved(toxic, -1))
    stay = rollup.revisions(marked(found).filter("not toxic"), second, F.lit(0), F.col(second)).unionByName(rollup.revisions(marked(guessed).filter("not toxic"), second, F.col("guess"), F.lit(0)))
    totals.commit(2, stay)
    totals.commit(1, moved(toxic, -1))
    totals.compact()
    return totals.totals()


def line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    cut = deletion_lines.remove_repeated_lines(documents(spark, sf_dir))
    return cut.select("doc_id", "n_lines", "n_removed", F.sha2("kept", 256).alias("kept_sha256"))


def quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return factor_classifier.quality_scores(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet"))


def repeated_bytes(spark: SparkSession, sf_dir: str) -> DataFrame:
    cut = suffix_bwt.remove_repeated_bytes(documents(spark, sf_dir))
    return cut.select("doc_id", "n_bytes", "n_removed", F.size("spans").cast("long").alias("n_spans"), F.sha2("kept", 256).alias("kept_sha256"))


def repeated_passages(spark: SparkSession, sf_dir: str) -> DataFrame:
    cut = block_anchors.remove_repeated_passages(documents(spark, sf_dir))
    return cut.select("doc_id", "n_words", "n_removed", F.sha2("kept", 256).alias("kept_sha256"))


def queries() -> dict[str, Query]:
    return {
        "op1_delta_token_rollup": token_counts,
        "op2_suffix_dedup": repeated_bytes,
        "op3_block_anchor_dedup": repeated_passages,
        "op4_canonical_digest": lambda spark, d: digest_fingerprint.fingerprints(documents(spark, d)),
        "op5_multi_order_jaccard": lambda spark, d: multi_order_join.similar_groups(documents(spark, d)),
        "op6_min_slack_packing": lambda spark, d: slack_packing.pack_documents(documents(spark, d)),
        "op7_grace_exact_dedup": lambda spark, d: grace_dedup.exact_dedup(documents(spark, d)),
        "op8_factor_quality": quality,
        "op9_slot_mixing": lambda spark, d: slot_mixing.mix(documents(spark, d)),
        "op10_deletion_line_dedup": line_dedup,
    }


#: Candidates by a shared half and at most one character of difference in length; then a deletion at one place.
_LINES = """
    WITH split AS (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS lines FROM documents),
    every AS (SELECT doc_id, unnest(range(len(lines))) AS line_no, unnest(lines) AS raw FROM split),
    filled AS (SELECT doc_id, line_no, trim(raw, ' ' || chr(9) || chr(13)) AS line FROM every),
    firsts AS (SELECT line, min(doc_id * 4294967296 + line_no) AS place, length(line) AS n FROM filled WHERE line <> '' GROUP BY line),
    halves AS (
      SELECT line, place, n, m, left(line, CAST(floor(m / 2) AS BIGINT)) AS half, 0 AS side FROM (SELECT *, unnest([n, n - 1]) AS m FROM firsts)
      UNION ALL
      SELECT line, place, n, m, substr(line, n - CAST(floor(m / 2) AS BIGINT) + 1), 1 FROM (SELECT *, unnest([n, n - 1]) AS m FROM firsts)),
    pairs AS (
      SELECT DISTINCT a.line AS line, b.line AS other, a.n AS n, b.n AS k
      FROM halves a JOIN halves b ON a.m = b.m AND a.side = b.side AND a.half = b.half AND a.line <> b.line AND b.place < a.place
      WHERE abs(a.n - b.n) <= 1),
    near AS (
      SELECT DISTINCT line FROM pairs
      WHERE len(list_filter(range(1, greatest(n, k) + 1), lambda i:
        CASE WHEN n = k THEN left(line, i - 1) || substr(line, i + 1) = left(other, i - 1) || substr(other, i + 1)
             WHEN n > k THEN left(line, i - 1) || substr(line, i + 1) = other
             ELSE left(other, i - 1) || substr(other, i + 1) = line END)) > 0),
    judged AS (
      SELECT e.doc_id, e.line_no, e.raw, coalesce(f.line <> '' AND (near.line IS NOT NULL OR e.doc_id * 4294967296 + e.line_no > firsts.place), false) AS gone
      FROM every e JOIN filled f ON e.doc_id = f.doc_id AND e.line_no = f.line_no
      LEFT JOIN firsts ON f.line = firsts.line LEFT JOIN near ON f.line = near.line)
    SELECT doc_id, count(*) AS n_lines, count(*) FILTER (WHERE gone) AS n_removed,
           sha256(coalesce(string_agg(raw, chr(10) ORDER BY line_no) FILTER (WHERE NOT gone), '')) AS kept_sha256
    FROM judged GROUP BY doc_id"""


def oracle_sql() -> dict[str, str]:
    return {
        "op10_deletion_line_dedup": _LINES,
        "op7_grace_exact_dedup": """
            SELECT doc_id, keep_id, group_size, doc_id = keep_id AS kept, text_sha256
            FROM (SELECT doc_id, sha256(coalesce(text, '')) AS text_sha256,
                         max(doc_id) OVER (PARTITION BY coalesce(text, '')) AS keep_id,
                         count(*) OVER (PARTITION BY coalesce(text, '')) AS group_size
                  FROM documents)""",
    }
