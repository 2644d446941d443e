"""Mining queries: collection, lifecycle identification and context alignment over the stand-in corpus.

The oracle never parses code: it repeats the renderer's arithmetic and joins the templates' facts.
"""

from __future__ import annotations

from functools import cached_property

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from nbflow.functions import apidb
from nbflow.operators import collect, mining
from nbflow.session import kept, table
from nbflow.sources import render, templates

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
#: Variables that templates track; others are helpers.
TRACKED = "(var like 'data%' or var like 'df%')"


def query(name: str, sql: str | None = None):
    def keep(build):
        QUERIES[name] = build
        if sql:
            ORACLES[name] = sql
        return build

    return keep


def statements(spark: SparkSession, d: str) -> DataFrame:
    return mining.parse_cells(render.rendered_cells(spark, d))


def staged(spark: SparkSession, d: str, **options) -> DataFrame:
    return mining.label_stages(statements(spark, d), **options)


class Mined:
    """The miner's tables over one corpus. Each is made when it is first asked for; those that others read are written
    once and reread, so no plan holds the steps of another again."""

    def __init__(self, spark: SparkSession, d: str):
        self.spark, self.d = spark, d

    @cached_property
    def cells(self) -> DataFrame:
        return kept(render.rendered_cells(self.spark, self.d), "cells")

    @cached_property
    def stmts(self) -> DataFrame:
        return kept(mining.parse_cells(self.cells), "statements")

    @cached_property
    def staged(self) -> DataFrame:
        return kept(mining.label_stages(self.stmts, facts=False), "stages")

    @cached_property
    def lives(self) -> DataFrame:
        return kept(mining.lifecycles(self.staged), "lives")

    @cached_property
    def spans(self) -> DataFrame:
        return kept(mining.segment_targets(self.staged, self.lives), "spans")

    @cached_property
    def of_target(self) -> DataFrame:
        return kept(mining.target_statements(self.spans, self.staged, self.stmts, self.lives), "target-statements")

    @cached_property
    def targets(self) -> DataFrame:
        return kept(mining.with_code(self.spans, self.of_target), "targets")

    @cached_property
    def ctx(self) -> DataFrame:
        return kept(mining.context_cells(self.targets, self.lives), "context-cells")

    @cached_property
    def prelude(self) -> DataFrame:
        return mining.prelude(self.targets, self.of_target, self.ctx, self.stmts)

    def contexts(self) -> DataFrame:
        return mining.contexts(self.targets, self.ctx, self.prelude, self.cells, self.stmts)


def _values(rows: list[tuple]) -> str:
    return ", ".join("(" + ", ".join("'" + str(x).replace("'", "''") + "'" if isinstance(x, str) else str(x) for x in r) + ")" for r in rows)


FACTS = f"""facts(template, j, s, stage) AS (VALUES {_values(templates.facts())}),
turns AS (
  SELECT conv_id AS nb_id, turn, role, (conv_id * 31 + turn * 7) % 16 AS template, row_number() OVER (PARTITION BY conv_id, role ORDER BY turn) - 1 AS nth FROM conversations),
placed AS (
  SELECT *, CASE WHEN role = 'assistant' AND nb_id % 2 = 1 THEN min(turn) OVER (PARTITION BY nb_id, role, nth - nth % 2) ELSE turn END AS base_turn,
         CASE WHEN role = 'assistant' AND nb_id % 2 = 1 THEN nth % 2 END AS odd FROM turns),
rows_ AS (
  SELECT nb_id, template, CASE WHEN template % 2 = 0 THEN 'df' || turn WHEN odd IS NOT NULL THEN 'data' || turn ELSE 'data' END AS var, stage,
         CAST((base_turn * 20 + CASE WHEN odd IS NULL THEN j ELSE 2 * j + odd END)::BIGINT * 4294967296 + s AS BIGINT) AS pos
  FROM placed JOIN facts USING (template) WHERE role = 'assistant'),
numbered AS (
  SELECT *, count(CASE WHEN stage = 'init' THEN 1 END) OVER (PARTITION BY nb_id, var ORDER BY pos) AS life_no FROM rows_ WHERE stage <> 'other'),
first_ AS (
  SELECT *, min(CASE WHEN stage = 'init' THEN pos END) OVER (PARTITION BY nb_id, var, life_no) AS init_pos,
         min(CASE WHEN stage = 'wrangle' THEN pos END) OVER (PARTITION BY nb_id, var, life_no) AS first_wrangle_pos FROM numbered WHERE life_no > 0),
ended AS (
  SELECT *, min(CASE WHEN stage = 'utilize' AND pos > first_wrangle_pos THEN pos END) OVER (PARTITION BY nb_id, var, life_no) AS end_pos FROM first_),
lives AS (
  SELECT nb_id, var, life_no, min(init_pos) AS init_pos, min(first_wrangle_pos) AS first_wrangle_pos, min(end_pos) AS end_pos,
         count(CASE WHEN stage = 'wrangle' AND (end_pos IS NULL OR pos <= end_pos) THEN 1 END) AS n_wrangle FROM ended GROUP BY ALL),
looks AS (
  SELECT nb_id, var, life_no, pos AS begin_pos, lead(pos) OVER (PARTITION BY nb_id, var, life_no ORDER BY pos) AS end_pos
  FROM ended WHERE stage = 'inspect' AND pos > init_pos AND pos < end_pos),
targets AS (
  SELECT k.nb_id, k.var, k.life_no, k.begin_pos, k.end_pos, count(*) AS n_wrangle
  FROM looks k JOIN ended e ON e.nb_id = k.nb_id AND e.var = k.var AND e.life_no = k.life_no AND e.stage = 'wrangle' AND e.pos > k.begin_pos AND e.pos < k.end_pos
  GROUP BY ALL)"""


def _sql(tail: str) -> str:
    return f"WITH {FACTS} {tail}"


# --- collection
query("a1_extension", "SELECT page_id, url FROM pages WHERE url LIKE '%.html'")(lambda s, d: collect.filter_extension(table(s, d, "pages").select("page_id", "url"), "url", ".html"))
_LICENSE = "CASE WHEN contains(text, 'Apache License, Version 2.0') THEN 'Apache-2.0' WHEN contains(text, 'MIT License') THEN 'MIT' WHEN contains(text, 'GNU General Public License, version 3') THEN 'GPL-3' WHEN contains(text, 'CC BY-NC 4.0') THEN 'CC-BY-NC' ELSE 'none' END"
query("a2_license", f"SELECT doc_id, license FROM (SELECT doc_id, {_LICENSE} AS license FROM documents) WHERE license IN ('Apache-2.0', 'MIT', 'GPL-3')")(lambda s, d: collect.filter_license(collect.with_license(table(s, d, "documents"), "text")).select("doc_id", "license"))
query("a3_dedup_exact", "SELECT min(doc_id) AS doc_id FROM documents GROUP BY text")(lambda s, d: collect.dedup_exact(table(s, d, "documents"), "text", "doc_id").select("doc_id"))
query("a4_forks", "SELECT doc_id FROM documents d WHERE source = (SELECT arg_min(source, doc_id) FROM documents e WHERE e.text = d.text)")(lambda s, d: collect.drop_forks(table(s, d, "documents"), "text", "source", "doc_id").select("doc_id"))
_NEAR = """
    WITH w AS (SELECT doc_id, regexp_extract_all(lower(text), '[^ \\t\\n\\r\\f\\v]+') AS w FROM documents),
    s AS (SELECT DISTINCT doc_id, array_to_string(w[i:i + 4], ' ') AS s FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 4, 1) + 1)) AS i FROM w WHERE len(w) > 0)),
    classes AS (SELECT doc_id, min(doc_id) OVER (PARTITION BY d) AS rep, n FROM (SELECT doc_id, md5(string_agg(s, chr(10) ORDER BY s)) AS d, count(*) AS n FROM s GROUP BY 1)),
    r AS (SELECT s.* FROM s JOIN classes USING (doc_id) WHERE doc_id = rep),
    met AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS c FROM r x JOIN r y ON x.s = y.s AND x.doc_id < y.doc_id GROUP BY ALL)
    SELECT a, b, c / (p.n + q.n - c) AS similarity FROM met JOIN classes p ON p.doc_id = a JOIN classes q ON q.doc_id = b WHERE c / (p.n + q.n - c) >= 0.8
    UNION ALL SELECT rep, doc_id, 1.0 FROM classes WHERE doc_id <> rep"""
query("a4b_near_dup", _NEAR)(lambda s, d: collect.near_duplicates(table(s, d, "documents")))
query("a5_language", "SELECT DISTINCT conv_id AS nb_id FROM conversations WHERE conv_id % 17 <> 0")(lambda s, d: collect.filter_language(render.notebook_facts(s, d)).select("nb_id"))
_HAS = sorted(t for t, cells in enumerate(templates.TEMPLATES) if any("read_csv" in line for cell in cells for line, _ in cell))
query("a6_has_loader", f"SELECT DISTINCT conv_id AS nb_id FROM conversations WHERE role = 'assistant' AND (conv_id * 31 + turn * 7) % 16 IN ({', '.join(map(str, _HAS))})")(lambda s, d: collect.filter_has_call(render.notebook_facts(s, d), statements(s, d)).select("nb_id"))
_FILES = [(t, f"data/raw/{name}_") for t in range(16) for name in ([templates.TABLES[t]] if t != 6 else []) + ([templates.SECOND[t]] if t in templates.SECOND else [])]
query("a7_path_literals", f"WITH files(template, head) AS (VALUES {_values(_FILES)}) SELECT conv_id AS nb_id, head || (conv_id % 4) || '.csv' AS raw, count(*) AS n FROM conversations JOIN files ON template = (conv_id * 31 + turn * 7) % 16 WHERE role = 'assistant' GROUP BY ALL")(
    lambda s, d: collect.path_literals(statements(s, d)).groupBy("nb_id", "raw").agg(F.count("*").alias("n"))
)


@query("a8_unresolved", "SELECT DISTINCT conv_id AS nb_id FROM conversations WHERE conv_id NOT IN (SELECT conv_id FROM conversations WHERE role = 'assistant' AND (conv_id * 31 + turn * 7) % 16 = 13)")
def _available(spark, d):
    books = render.notebook_facts(spark, d).withColumn("repo", F.coalesce("repo", F.lit("none")))
    refs = collect.path_literals(statements(spark, d)).join(books.select("nb_id", "repo"), "nb_id")
    return collect.drop_unresolved(books, collect.resolve_paths(refs, render.repo_files(spark, d), ("repo",))).select("nb_id")


_HREFS = "(SELECT DISTINCT unnest(regexp_extract_all(html, 'href=\"([^\"]+)\"', 1)) AS raw FROM pages)"


@query("a9_flatten", f"SELECT raw, CASE WHEN count(*) OVER (PARTITION BY b) > 1 THEN left(md5(raw), 8) || '_' || b ELSE b END AS flat FROM (SELECT raw, string_split(raw, '/')[-1] AS b FROM {_HREFS})")
def _flat(spark, d):
    hrefs = table(spark, d, "pages").select(F.explode(F.regexp_extract_all("html", F.lit('href="([^"]+)"'), 1)).alias("raw")).distinct()
    return collect.flat_names(hrefs, "raw")


query("w10_paths", f"SELECT raw, string_split(raw, '/')[-1] AS name, regexp_extract(raw, '\\.([a-z0-9]+)$', 1) AS ext FROM {_HREFS}")(
    lambda s, d: table(s, d, "pages").select(F.explode(F.regexp_extract_all("html", F.lit('href="([^"]+)"'), 1)).alias("raw")).distinct().select("raw", collect.basename("raw").alias("name"), F.regexp_extract("raw", r"\.([a-z0-9]+)$", 1).alias("ext"))
)
query(
    "a10_funnel",
    f"WITH f AS (SELECT conv_id, {_LICENSE} AS license FROM (SELECT DISTINCT conv_id FROM conversations) c LEFT JOIN documents ON doc_id = conv_id) SELECT 'all' AS step, count(*) AS kept FROM f UNION ALL SELECT 'extension', count(*) FROM f WHERE conv_id % 23 <> 0 UNION ALL SELECT 'license', count(*) FROM f WHERE conv_id % 23 <> 0 AND license <> 'CC-BY-NC' UNION ALL SELECT 'language', count(*) FROM f WHERE conv_id % 23 <> 0 AND license <> 'CC-BY-NC' AND conv_id % 17 <> 0",
)(lambda s, d: collect.funnel(render.notebook_facts(s, d), {"extension": F.col("path").endswith(".ipynb"), "license": F.coalesce("license", F.lit("none")) != "CC-BY-NC", "language": F.col("lang_major") == 3}))
query("c13_leak_benchmark", "SELECT doc_id, item_id FROM documents d JOIN benchmark b ON contains(d.text, b.text)")(lambda s, d: collect.contained_items(table(s, d, "documents"), table(s, d, "benchmark")))

# --- identification
query("b1_stmts", _sql("SELECT nb_id, count(*) AS n FROM rows_ GROUP BY 1"))(lambda s, d: statements(s, d).filter("parse_ok").groupBy("nb_id").agg(F.count("*").alias("n")))
query("b2_api_seq")(lambda s, d: mining.api_calls(statements(s, d)))
query("b3_alias")(lambda s, d: mining.resolve_aliases(statements(s, d)))
query("b4_api_db", f"SELECT stage, category, library, api, count(doc_id) AS documents FROM (VALUES {_values(apidb.rows())}) AS t(stage, category, library, api) LEFT JOIN documents ON contains(text, api) GROUP BY ALL")(lambda s, d: apidb.named_in(table(s, d, "documents"), "text"))
query("b5_api_freq")(lambda s, d: mining.api_frequency(statements(s, d)))
_KIND = "CASE WHEN template IN (5, 7) THEN 'manipulation' WHEN template = 6 THEN 'definition' WHEN template = 9 THEN 'operation' ELSE 'loading' END"
query("b6_init_kinds", _sql(f"SELECT nb_id, var, pos, {_KIND} AS init_kind FROM rows_ WHERE stage = 'init'"))(lambda s, d: staged(s, d).filter(f"stage = 'init' and {TRACKED}").select("nb_id", "var", "pos", "init_kind"))
for _name, _stage in (("b7_wrangle", "wrangle"), ("b8_utilize", "utilize"), ("b8b_inspect", "inspect")):
    query(_name, _sql(f"SELECT nb_id, var, pos FROM rows_ WHERE stage = '{_stage}'"))(lambda s, d, stage=_stage: staged(s, d).filter(f"stage = '{stage}' and {TRACKED}").select("nb_id", "var", "pos"))
query("b7n_new_var", _sql("SELECT count(*) AS n FROM rows_ WHERE template = 11 AND stage = 'wrangle'"))(lambda s, d: staged(s, d).filter("stage = 'wrangle' and array_contains(defs, 'other')").agg(F.count("*").alias("n")))
query("b9_stages", _sql("SELECT nb_id, var, pos, stage, life_no FROM numbered"))(lambda s, d: staged(s, d).filter(f"stage <> 'other' and {TRACKED}").select("nb_id", "var", "pos", "stage", "life_no"))
query("b10_lifecycles", _sql("SELECT * FROM lives"))(lambda s, d: mining.lifecycles(staged(s, d)).filter(TRACKED).drop("cell_idxs"))
query("b11_life_cells")(lambda s, d: mining.lifecycles(staged(s, d)).filter("end_pos is not null").select("nb_id", "var", "life_no", F.array_join(F.col("cell_idxs").cast("array<string>"), ",").alias("cells")))
query("b12_complete", _sql("SELECT DISTINCT nb_id FROM lives WHERE end_pos IS NOT NULL"))(lambda s, d: mining.drop_incomplete(render.notebook_facts(s, d), mining.lifecycles(staged(s, d)).filter(TRACKED)).select("nb_id"))
query("b13_def_use")(lambda s, d: mining.def_use(statements(s, d)))


@query("b14_slice")
def _slice(spark, d):
    edges = mining.def_use(statements(spark, d))
    return mining.slice_back(edges, staged(spark, d).filter("stage = 'utilize'").select("nb_id", "pos"), 2)


# --- alignment
query("c1_targets", _sql("SELECT * FROM targets"))(lambda s, d: Mined(s, d).targets.filter(TRACKED).select("nb_id", "var", "life_no", "begin_pos", "end_pos", "n_wrangle"))
query("c2_target_comments")(lambda s, d: Mined(s, d).targets.select("target_id", F.explode("inline_comments").alias("comment")))
query("c3_ctx_cells")(lambda s, d: Mined(s, d).ctx)
query("c4_prelude")(lambda s, d: Mined(s, d).prelude)


@query("c5_text_ctx")
def _text(spark, d):
    m = Mined(spark, d)
    return mining.text_context(m.targets, m.ctx, m.cells, m.stmts)


query("c6_merged")(lambda s, d: Mined(s, d).contexts().select("target_id", "merged_ctx", "n_code_cells"))
