"""Queries of examples, model inputs, generators, measures and experiments, with SQL where SQL can say them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from nbflow import experiments as w
from nbflow.functions.metrics import corpus_bleu_udaf, subtrees_udf
from nbflow.operators import examples as ex
from nbflow.operators import generators as g
from nbflow.operators import inputs, mining, scoring
from nbflow.plans.mine import _values
from nbflow.session import kept, table

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def keep(build):
        QUERIES[name] = build
        if sql:
            ORACLES[name] = sql
        return build

    return keep


# --- examples
query("c7_replay")(lambda s, d: w.corpus(s, d).frames.select("target_id", "outcome"))
query("c8_snapshot")(lambda s, d: w.corpus(s, d).all.select("example_id", F.col("in_frame.n_rows").alias("n_rows"), F.size("in_frame.rows").alias("stored"), F.array_join("in_frame.columns", ",").alias("columns")))
query("c9_cap")(lambda s, d: ex.cap_context(w.corpus(s, d).all).select("example_id", "n_code_cells"))
query("c10_noop")(lambda s, d: ex.drop_noop(w.corpus(s, d).all).select("example_id"))
query("c11_dedup_target")(lambda s, d: ex.dedup_examples(w.corpus(s, d).all).select("example_id"))
query("c12_split", "SELECT conv_id AS nb_id, CASE WHEN (conv_id * 7919 + 13) % 1000 < 937 THEN 'train' WHEN (conv_id * 7919 + 13) % 1000 < 972 THEN 'dev' ELSE 'test' END AS split FROM (SELECT DISTINCT conv_id FROM conversations)")(
    lambda s, d: table(s, d, "conversations").select(F.col("conv_id").alias("nb_id")).distinct().withColumn("split", ex.split_of(F.col("nb_id")))
)
query("c13_leak_examples")(lambda s, d: ex.remove_leakage(w.corpus(s, d).all).select("example_id", "split"))
_COMBOS = "(VALUES ('CT', 34), ('CTI', 40), ('CTO', 42), ('CTIO', 76)) AS c(ctx, thr)"
_VOTES = f"(SELECT doc_id, a AS annotator, ctx, (doc_id * 37) % 100 + (a * 17 + doc_id * 11) % 21 - 10 + 10 * toxic - 5 * quality < thr AS solvable FROM labels, range(5) r(a), {_COMBOS})"
query("c14_votes", f"SELECT doc_id, CAST(annotator AS INT) AS annotator, ctx, solvable FROM {_VOTES}")(lambda s, d: ex.votes(table(s, d, "labels")))
query("c14_majority", f"SELECT doc_id, ctx, count(*) FILTER (WHERE solvable) >= 3 AS solvable FROM {_VOTES} GROUP BY ALL")(lambda s, d: ex.majority(ex.votes(table(s, d, "labels"))))
query("c14_solvable", f"SELECT ctx, count(*) FILTER (WHERE m) AS solvable, count(*) AS n FROM (SELECT doc_id, ctx, count(*) FILTER (WHERE solvable) >= 3 AS m FROM {_VOTES} GROUP BY ALL) GROUP BY ctx")(lambda s, d: ex.solvable_rate(ex.majority(ex.votes(table(s, d, "labels")))))
query("c14_sample", "SELECT doc_id FROM labels ORDER BY md5('50' || CAST(doc_id AS VARCHAR)), doc_id LIMIT 50")(lambda s, d: ex.sample_fixed(table(s, d, "labels").select("doc_id"), 50, "doc_id", "50"))
query("c15_stats")(lambda s, d: ex.corpus_stats(w.corpus(s, d).examples))


def _used(spark, d, kind):
    c = w.corpus(spark, d)
    return c.of_target.select("target_id").distinct(), ex.used_names(c.of_target, c.mined.stmts, mining.named_rows(c.mined.stmts), kind)


for _short, _kind in (("mod", "module"), ("api", "api")):
    query(f"c16_{_short}_hist")(lambda s, d, k=_kind: ex.usage_histogram(*_used(s, d, k)))
    query(f"c16_{_short}_freq")(lambda s, d, k=_kind: ex.usage_frequency(_used(s, d, k)[1]))
query("c16_share")(lambda s, d: ex.share_below(ex.usage_histogram(*_used(s, d, "api")), 3))

# --- inputs
query("d1_flatten")(lambda s, d: w.corpus(s, d).examples.select("example_id", inputs.data_text().alias("text")))
query("d2_joint")(lambda s, d: inputs.serialize_joint(w.corpus(s, d).examples).select("example_id", F.size("ctx_tokens").alias("ctx"), F.size("data_tokens").alias("data"), "truncated"))
query("d3_dual")(lambda s, d: inputs.serialize_dual(w.corpus(s, d).examples).select("example_id", F.size("ctx_tokens").alias("ctx"), F.size("data_tokens").alias("data"), "truncated"))


@query("d4_trunc")
def _truncated(spark, d):
    rows = w.corpus(spark, d).examples
    joint, dual = (inputs.truncation_rate(f(rows)).select(F.lit(n).alias("preset"), "share") for n, f in (("joint", inputs.serialize_joint), ("dual", inputs.serialize_dual)))
    return joint.unionByName(dual)


query("d6_cap")(lambda s, d: inputs.cap_target(w.corpus(s, d).examples).select("example_id", F.size("target_tokens").alias("n")))
query("d9_prompt")(lambda s, d: inputs.build_prompt(w.corpus(s, d).test, inputs.ring_demos(w.corpus(s, d).train, w.corpus(s, d).test), pool=w.corpus(s, d).train))
query("d9_zero_shot")(lambda s, d: inputs.build_prompt(w.corpus(s, d).test))
_RING = "(SELECT doc_id, row_number() OVER (ORDER BY md5(CAST(doc_id AS VARCHAR)), CAST(doc_id AS VARCHAR)) - 1 AS place FROM documents WHERE doc_id % 10 {})"
query("d9_few_shot", f"SELECT CAST(t.doc_id AS VARCHAR) AS example_id, CAST(k AS INT) AS demo_rank, CAST(p.doc_id AS VARCHAR) AS demo_id FROM {_RING.format('= 0')} t, range(2) r(k), {_RING.format('<> 0')} p WHERE p.place = (t.place * 2 + k) % (SELECT count(*) FROM documents WHERE doc_id % 10 <> 0)")(
    lambda s, d: inputs.ring_demos(table(s, d, "documents").filter("doc_id % 10 <> 0").select(F.col("doc_id").cast("string").alias("example_id")), table(s, d, "documents").filter("doc_id % 10 = 0").select(F.col("doc_id").cast("string").alias("example_id")))
)
query("d10_fit")(lambda s, d: inputs.fits_window(inputs.build_prompt(w.corpus(s, d).test), s.createDataFrame(list(g.LLM_CONFIGS), "model string, window int")))
query("d12_schema_diff")(lambda s, d: inputs.schema_diff(w.corpus(s, d).examples).select("example_id", F.array_join("added", ",").alias("added"), F.array_join("dropped", ",").alias("dropped"), "rows_changed"))

# --- vectors: two towers against one, on the given embeddings
_COSINE = "coalesce(nullif(list_cosine_similarity(q.embedding[{0}:{1}]::DOUBLE[], p.embedding[{0}:{1}]::DOUBLE[]), 'nan'::DOUBLE), 0)"
_SCORE = {"d7_embed_two_tower": f"{_COSINE.format(1, 32)} + {_COSINE.format(33, 64)}", "d8_embed_joint": _COSINE.format(1, 32), "d9_knn": _COSINE.format(1, 64)}


def _towers(rows: DataFrame, parts: list[tuple[int, int]]) -> DataFrame:
    unit = []
    for a, b in parts:
        x = F.transform(F.slice("embedding", a, b - a + 1), lambda v: v.cast("double"))
        norm = F.sqrt(F.aggregate(x, F.lit(0.0), lambda acc, v: acc + v * v))
        unit.append(F.zip_with(x, F.array_repeat(norm, b - a + 1), lambda v, size: F.coalesce(F.try_divide(v, size), F.lit(0.0))))
    return rows.select(F.col("vec_id").cast("string").alias("id"), "label", F.concat(*unit).alias("vec"))


def _neighbours(spark: SparkSession, d: str, parts: list[tuple[int, int]]) -> DataFrame:
    rows = _towers(table(spark, d, "embeddings"), parts)
    queries = rows.filter(F.pmod(F.col("id").cast("long"), F.lit(20)) == 0).select(F.col("id").alias("example_id"), "vec")
    found = g.nearest(queries, rows.select("id", "vec"), 2).filter("id <> example_id")
    found = found.groupBy("example_id").agg(F.min_by("id", F.struct(-F.col("score"), F.col("id"))).alias("id"))
    return found.select(F.col("example_id").cast("long").alias("vec_id"), F.col("id").cast("long").alias("near_id"))


_PARTS = {"d7_embed_two_tower": [(1, 32), (33, 64)], "d8_embed_joint": [(1, 32)], "d9_knn": [(1, 64)]}
#: Equal scores go by the text of the number; a vector of zeros is like nothing.
_NEAR = "SELECT vec_id, near_id FROM (SELECT q.vec_id, p.vec_id AS near_id, row_number() OVER (PARTITION BY q.vec_id ORDER BY round({}, 9) DESC, CAST(p.vec_id AS VARCHAR)) AS nth FROM embeddings q, embeddings p WHERE q.vec_id % 20 = 0 AND p.vec_id <> q.vec_id) WHERE nth = 1"
for _name, _parts in _PARTS.items():
    query(_name, _NEAR.format(_SCORE[_name]))(lambda s, d, p=_parts: _neighbours(s, d, p))


@query("w5e_nn_accuracy", " UNION ALL ".join(f"SELECT '{n}' AS model, count(*) FILTER (WHERE a.label = b.label) AS hits, count(*) AS n FROM ({_NEAR.format(_SCORE[n])}) x JOIN embeddings a ON a.vec_id = x.vec_id JOIN embeddings b ON b.vec_id = x.near_id" for n in ("d7_embed_two_tower", "d8_embed_joint")))
def _nn_accuracy(spark, d):
    labels = table(spark, d, "embeddings").select("vec_id", "label")
    out = None
    for name in ("d7_embed_two_tower", "d8_embed_joint"):
        rows = _neighbours(spark, d, _PARTS[name]).join(labels, "vec_id").join(labels.select(F.col("vec_id").alias("near_id"), F.col("label").alias("theirs")), "near_id")
        one = rows.agg(F.count_if(F.col("label") == F.col("theirs")).alias("hits"), F.count("*").alias("n")).select(F.lit(name).alias("model"), "hits", "n")
        out = one if out is None else out.unionByName(one)
    return out


# --- sizes
#: Twelve layers as wide as the given vectors, blocks four times as wide, one embedding of each vector.
query("d7p_params", "SELECT towers, towers * 12 * (4 * d * d + 2 * d * 4 * d) + 12 * (8 * d * d + 2 * d * 4 * d) + n * d AS weights FROM (SELECT max(len(embedding)) AS d, count(*) AS n FROM embeddings), range(1, 3) r(towers)")(
    lambda s, d: table(s, d, "embeddings").agg(F.max(F.size("embedding")).cast("long").alias("d"), F.count("*").alias("n")).select("d", "n", F.explode(F.array(F.lit(1).cast("long"), F.lit(2).cast("long"))).alias("towers")).select("towers", g.parameter_count(12, F.col("d"), F.col("d") * 4, F.col("n"), F.col("towers")).alias("weights"))
)
query("d11_params", "SELECT label, count(*) * 2 * 2 * max(len(embedding)) * 8 AS weights FROM embeddings GROUP BY label")(
    lambda s, d: table(s, d, "embeddings").groupBy("label").agg(F.count("*").alias("layers"), F.max(F.size("embedding")).alias("d")).select("label", g.lora_param_count(F.col("layers"), F.col("d"), 8, 2).alias("weights"))
)

# --- generators: exact match and CodeBLEU on the test split; of those that SQL can follow, exact match


def _exact(spark, d, model) -> DataFrame:
    c = w.corpus(spark, d)
    return scoring.exact_match(w.predictions([("model", "full", model(c))]), c.test).select("example_id", "code", "em")


def _surface(spark, d, model) -> DataFrame:
    c = w.corpus(spark, d)
    rows = kept(w.predictions([("model", "full", model(c))]), "predictions")  # read twice: by row and by pair
    return scoring.code_bleu(scoring.exact_match(rows, c.test).drop("target_code"), c.test).select("example_id", "code", "em", "cb")


for _name, _make in {
    "d7_two_tower": lambda c: g.TwoTowerRetriever().fit(c.train, c.dev),
    "d8_joint": lambda c: g.JointRetriever().fit(c.train),
    "d8g": lambda c: g.JointRetriever("dataflow").fit(c.train),
    "d8u": lambda c: g.JointRetriever("ast").fit(c.train),
    "d8i": lambda c: g.JointRetriever("identifier").fit(c.train),
    "d8d": lambda c: g.JointRetriever("denoise").fit(c.train),
    "d11_lowrank": lambda c: g.LowRankHead().fit(c.train, c.dev),
    "d12_pbe": lambda c: g.ByExample().fit(c.train),
}.items():
    query(_name)(lambda s, d, make=_make: _surface(s, d, lambda c: make(c).generate(c.test)))
query("d10_prompt_copy")(lambda s, d: _exact(s, d, lambda c: g.PromptCopy(2).fit(c.train).generate(c.test)))
query("d13_copy_last")(lambda s, d: _exact(s, d, lambda c: g.CopyLast().generate(c.test)))
query("d13_mode")(lambda s, d: _exact(s, d, lambda c: g.ModeTarget().fit(c.train).generate(c.test)))
query("d14_corrupt")(lambda s, d: _exact(s, d, lambda c: g.corrupt(c.test, 100, "rename_col")))

# --- measures
query("e1_em")(lambda s, d: scoring.exact_match(w.predictions([("truth", "full", g.corrupt(w.corpus(s, d).test, 0)), ("half", "full", g.corrupt(w.corpus(s, d).test, 50))]), w.corpus(s, d).test).groupBy("model").agg(F.avg(F.col("em").cast("double")).alias("em")))
query("e2_codebleu")(lambda s, d: _surface(s, d, lambda c: g.corrupt(c.test, 50)).agg(F.avg("cb").alias("cb")))


def _parts(spark, d):
    c = w.corpus(spark, d)
    return scoring.code_bleu(w.predictions([("half", "full", g.corrupt(c.test, 50))]), c.test)


for _name, _part in (("e2a_ngram", "ngram"), ("e2b_wngram", "weighted"), ("e2c_ast", "syntax"), ("e2d_dataflow", "dataflow")):
    query(_name)(lambda s, d, p=_part: _parts(s, d).select("example_id", p))
query("udf_ast")(lambda s, d: w.corpus(s, d).examples.select("example_id", F.size(subtrees_udf("target_code")).alias("subtrees")))
query("udaf_bleu")(lambda s, d: _parts(s, d).groupBy("model").agg(corpus_bleu_udaf("target_code", "code").alias("bleu")))
query("e3_ea")(lambda s, d: w.scored(w.corpus(s, d), [("truth", "full", g.corrupt(w.corpus(s, d).test, 0))]).agg(F.avg(F.col("ea").cast("double")).alias("ea")))
query("e3_bag_equal", "SELECT true AS equal UNION ALL SELECT false")(
    lambda s, d: scoring.frames_equal(table(s, d, "orders"), table(s, d, "orders").repartition(5)).unionByName(scoring.frames_equal(table(s, d, "orders"), table(s, d, "orders").filter("o_orderkey > 0")))
)
query("e3_except_all", "SELECT o_orderkey FROM orders EXCEPT ALL SELECT o_orderkey FROM orders WHERE o_orderkey > 3")(lambda s, d: table(s, d, "orders").select("o_orderkey").exceptAll(table(s, d, "orders").filter("o_orderkey > 3").select("o_orderkey")))
query("e4_outcomes", "SELECT CASE WHEN event_type = 'error' THEN 'exception' ELSE 'ok' END AS outcome, count(*) AS n FROM events GROUP BY 1")(lambda s, d: table(s, d, "events").groupBy(F.when(F.col("event_type") == "error", "exception").otherwise("ok").alias("outcome")).agg(F.count("*").alias("n")))
_SOLVED = f"(SELECT ctx AS model, CAST(count(*) FILTER (WHERE solvable) AS DOUBLE) AS em, CAST(count(DISTINCT CASE WHEN solvable THEN doc_id END) AS DOUBLE) AS cb, CAST(count(*) FILTER (WHERE solvable AND annotator = 0) AS DOUBLE) AS ea FROM {_VOTES} GROUP BY 1)"


def _solved(votes: DataFrame) -> DataFrame:
    """Votes by context as a table of scores: solvable ones, documents with one, those of the first annotator."""
    return votes.groupBy(F.col("ctx").alias("model")).agg(F.count_if("solvable").cast("double").alias("em"), F.count_distinct(F.when(F.col("solvable"), F.col("doc_id"))).cast("double").alias("cb"), F.count_if(F.col("solvable") & (F.col("annotator") == 0)).cast("double").alias("ea"))


query("e5_delta", f"SELECT p.model, round(p.em - b.em, 1) AS d_em, round(p.cb - b.cb, 1) AS d_cb, round(p.ea - b.ea, 1) AS d_ea FROM {_SOLVED} p, (SELECT * FROM {_SOLVED} WHERE model = 'CTIO') b")(lambda s, d: scoring.delta(_solved(ex.votes(table(s, d, "labels"))), "CTIO"))
_RATES = f"(SELECT CAST(annotator AS INT) AS annotator, ctx, CAST(count(*) FILTER (WHERE solvable) AS DOUBLE) AS ea FROM {_VOTES} GROUP BY ALL)"
query("w6_published_delta", f"SELECT p.annotator, p.ctx, round(p.ea - b.ea, 1) AS d_ea FROM {_RATES} p JOIN {_RATES} b ON b.annotator = p.annotator AND b.ctx = 'CTIO'")(
    lambda s, d: (lambda rows: rows.join(rows.filter("ctx = 'CTIO'").select("annotator", F.col("ea").alias("base")), "annotator").select("annotator", "ctx", F.round(F.col("ea") - F.col("base"), 1).alias("d_ea")))(ex.votes(table(s, d, "labels")).groupBy("annotator", "ctx").agg(F.count_if("solvable").cast("double").alias("ea")))
)
query("e8_boot")(lambda s, d: scoring.bootstrap_ci(_surface(s, d, lambda c: g.corrupt(c.test, 50)).select("example_id", F.lit("half").alias("model"), F.lit("full").alias("ctx"), F.col("cb").alias("ea"))))

# --- experiments
query("w1_mine")(w.mining_run)
query("w5_rq1")(w.model_comparison)


@query("w6_masks")
def _masks(spark, d):
    rows, out = w.corpus(spark, d).examples, None
    for mask in inputs.MASKS:
        one = inputs.serialize_dual(rows, mask=mask).select("example_id", F.lit(mask[0]).alias("ctx"), "n_ctx", "n_data")
        out = one if out is None else out.unionByName(one)
    return out


query("w6_rq2")(w.context_ablation)


@query("w7_inputs")
def _components(spark, d):
    rows, out = w.corpus(spark, d).examples, None
    for name, values, columns in inputs.COMPONENTS:
        one = inputs.serialize_dual(rows, with_values=values, with_columns=columns).select("example_id", F.lit(name).alias("component"), "n_data")
        out = one if out is None else out.unionByName(one)
    return out


query("w7_rq3")(w.component_ablation)
query("w7r_rows")(w.rows_sweep)
query("w8_corruption")(w.corruption_study)
query("w8_contexts")(lambda s, d: w.case_study(s, d).select("example_id", "ctx", "em", "ea"))
