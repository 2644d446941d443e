"""The lifecycle miner: statements, stages, lifecycles, targets and their code and text contexts.

Only ``parse_cells`` runs Python; all else are windows and equi joins keyed by notebook. Rows are dealt
by ``nb_id``, once more after the pass that follows chains of frames: windows over (nb_id, variable) and
(nb_id, statement) are served by that dealing.
"""

from __future__ import annotations

from dataclasses import asdict

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import BooleanType, IntegerType, StringType, StructField, StructType

from nbflow.functions import apidb
from nbflow.functions.parsing import parse_cell
from nbflow.functions.sandbox import CELL_STEP
from nbflow.session import many_tasks

STATEMENTS = (
    "nb_id long, cell_idx int, stmt_idx int, pos long, kind string, defs array<string>, uses array<string>, base string, receiver string, api string,"
    " calls array<struct<receiver: string, api: string, uses: array<string>>>, inplace boolean, store string, rhs_op string, rhs_names array<string>,"
    " imports array<struct<alias: string, module: string>>, literals array<string>, comments array<string>, src string, parse_ok boolean"
)


def _facts(source: str) -> list[dict]:
    """The statements of a cell's source, without their place."""
    found = parse_cell(source)
    if found is None:
        return [{"stmt_idx": 0, "kind": "error", "inplace": False, "store": "none", "src": source, "parse_ok": False} | {k: [] for k in ("defs", "uses", "calls", "rhs_names", "imports", "literals", "comments")}]
    rows = []
    for i, s in enumerate(found):
        row = asdict(s) | {"stmt_idx": i, "parse_ok": True}
        row["calls"] = [{"receiver": r, "api": a, "uses": u} for r, a, u in s.calls]
        row["imports"] = [{"alias": a, "module": m} for a, m in s.imports]
        rows.append(row)
    return rows


def _parsed(batches, schema):
    """Statements of batches (nb_id, cell_idx, source). Equal sources of a batch are parsed once."""
    facts = pa.schema([f for f in schema if f.name not in ("nb_id", "cell_idx", "pos")])
    for batch in batches:
        nb, cell, source = batch.columns
        coded = source.fill_null("").dictionary_encode()
        rows, begins = [], [0]
        for text in coded.dictionary.to_pylist():
            rows += _facts(text)
            begins.append(len(rows))
        code, begins = coded.indices.to_numpy(), np.array(begins)
        n = np.diff(begins)[code]
        if n.sum():
            nth = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
            at = pa.array(np.repeat(np.arange(len(code)), n))
            made = pa.RecordBatch.from_pylist(rows, schema=facts).take(pa.array(np.repeat(begins[code], n) + nth))
            place = cell.take(at)
            columns = {"nb_id": nb.take(at), "cell_idx": place, "pos": pa.array(place.to_numpy().astype(np.int64) * CELL_STEP + nth)}
            columns |= dict(zip(made.schema.names, made.columns, strict=True))
            yield pa.RecordBatch.from_arrays([columns[f.name] for f in schema], schema=schema)


def parse_cells(cells: DataFrame) -> DataFrame:
    """One row per statement of each code cell; a cell that isn't Python gives one row with parse_ok false."""
    code = cells.filter("kind = 'code'").select(F.col("nb_id").cast("long"), F.col("cell_idx").cast("int"), "source")
    schema = to_arrow_schema(StructType.fromDDL(STATEMENTS))
    return code.repartition(many_tasks(cells.sparkSession), "nb_id").mapInArrow(lambda batches: _parsed(batches, schema), STATEMENTS)


def api_calls(stmts: DataFrame) -> DataFrame:
    """Calls in time: nb_id, pos, nth, receiver, api."""
    return stmts.select("nb_id", "pos", F.posexplode("calls").alias("nth", "call")).select("nb_id", "pos", "nth", "call.receiver", "call.api")


def api_frequency(stmts: DataFrame) -> DataFrame:
    return api_calls(stmts).groupBy("api").agg(F.count("*").alias("n"))


def named_rows(stmts: DataFrame) -> DataFrame:
    """One row per statement and name that it defines, uses, stores into or imports, with the module that the name
    stands for there: that of the latest import before."""
    aliases = F.transform("imports", lambda x: x["alias"])
    names = F.array_compact(F.array_distinct(F.concat("defs", "uses", F.array("base"), aliases)))
    rows = stmts.repartition("nb_id").withColumn("var", F.explode(names))
    module = F.get(F.filter("imports", lambda x: x["alias"] == F.col("var")), F.lit(0))["module"]
    until = Window.partitionBy("nb_id", "var").orderBy("pos").rowsBetween(Window.unboundedPreceding, 0)
    return rows.withColumn("module", F.last(module, ignorenulls=True).over(until))


def resolve_aliases(stmts: DataFrame) -> DataFrame:
    """Calls with the dotted name of the module that their receiver stands for (null: none)."""
    names = named_rows(stmts).select("nb_id", "pos", F.col("var").alias("receiver"), "module")
    return api_calls(stmts).join(names, ["nb_id", "pos", "receiver"], "left").select("nb_id", "pos", "nth", "receiver", "api", "module")


def _begun(batches):
    """Rows in order of notebook and place with ``starts``: whether an operation on a live frame begins this one. What
    a statement changes holds from the next on."""
    book, place, live, changes = None, None, set(), {}
    for batch in batches:
        starts = []
        for nb, pos, var, event, may, bases in zip(*(batch.column(batch.schema.names.index(c)).to_pylist() for c in ("nb_id", "pos", "var", "event", "may", "bases")), strict=True):
            if nb != book:
                book, place, live, changes = nb, pos, set(), {}
            elif pos != place:
                for name, on in changes.items():
                    (live.add if on else live.discard)(name)
                place, changes = pos, {}
            starts.append(may and any(b in live for b in bases))
            if starts[-1] or event is not None:
                changes[var] = starts[-1] or event == 1
        yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(starts, pa.bool_())], names=[*batch.schema.names, "starts"])


def label_stages(stmts: DataFrame, extra: list | None = None, subscript_store: bool = True, inspect_position: str = "any", facts: bool = True) -> DataFrame:
    """Rows (nb_id, pos, cell_idx, var, stage, life_no, init_kind and, if asked for, the statement's facts).

    A frame that an operation on a live frame begins may be the base of another such frame: ``_begun`` follows
    such chains of any length in one pass over each notebook's statements in order. Rows take to it only what is read
    after it."""
    used_by = F.filter("calls", lambda c: c["api"].isin(apidb.names("utilize", extra=extra)))
    utilized = F.flatten(F.transform(used_by, lambda c: F.concat(F.coalesce(c["uses"], F.array().cast("array<string>")), F.array(c["receiver"]))))
    rows = named_rows(stmts.withColumn("utilized", utilized))
    by_name, at = Window.partitionBy("nb_id", "var").orderBy("pos"), Window.partitionBy("nb_id", "pos")
    var, hard_names = F.col("var"), apidb.names("init", "definition", "loading", "manipulation", extra=extra)
    is_def = F.array_contains("defs", var) & (F.col("kind") != "import")
    self_use = is_def & (F.array_contains("uses", var) | (F.col("kind") == "augassign"))
    of_pandas = F.max(F.when(var == F.col("receiver"), F.col("module"))).over(at).rlike(r"^pandas(\.|$)")
    assigned = F.col("kind").isin("assign", "augassign")
    hard = assigned & F.col("api").isin(hard_names) & F.coalesce(of_pandas, F.lit(False))
    method = F.col("api").isin(apidb.names("init", "manipulation", extra=extra))
    base = (F.array_contains("rhs_names", var) | (method & (var == F.col("receiver")))) & ~F.array_contains("defs", var)
    rows = rows.withColumns({"is_def": is_def, "self_use": self_use, "hard": hard, "is_base": base, "op": assigned & (F.col("rhs_op").isNotNull() | method)})
    event = F.when(F.col("is_def") & F.col("hard"), 1).when(F.col("is_def") & ~F.col("self_use"), 0)
    may = F.coalesce(F.col("is_def") & ~F.col("hard") & ~F.col("self_use") & F.col("op"), F.lit(False))
    rows = rows.withColumns({"event": event, "may": may, "bases": F.collect_set(F.when(F.col("is_base"), var)).over(at)})
    mine = F.col("base") == var
    stores = mine & F.col("store").isin("subscript", "attr") & F.lit(subscript_store)
    changed = F.col("self_use") | (mine & F.col("inplace")) | stores
    looked = (F.col("kind") == "expr") & mine & F.col("api").isin(apidb.INSPECTIONS)
    keep = ["nb_id", "pos", "cell_idx", "stmt_idx", "var", "kind", "api", *(["receiver", "src", "defs", "uses", "comments"] if facts else [])]
    rows = rows.select(*keep, "is_def", "hard", "event", "may", "bases", changed.alias("changed"), looked.alias("looked"), F.array_contains("utilized", var).alias("utilized"))
    schema = StructType([*(StructField(f.name, f.dataType) for f in rows.schema), StructField("starts", BooleanType())])
    rows = rows.sortWithinPartitions("nb_id", "pos").mapInArrow(_begun, schema).repartition("nb_id")
    begun = F.when(F.col("starts"), F.lit("operation")).when(F.col("is_def") & F.col("hard"), F.lit("api"))
    rows = rows.withColumns({"event": F.when(F.col("starts"), 1).otherwise(F.col("event")), "begun": begun})
    before = by_name.rowsBetween(Window.unboundedPreceding, -1)
    rows = rows.withColumn("live", F.coalesce(F.last("event", ignorenulls=True).over(before), F.lit(0)) == 1)
    wrangle, looks = F.col("live") & F.col("changed"), F.col("live") & F.col("looked")
    if inspect_position == "last_line":
        looks = looks & (F.col("stmt_idx") == F.max("stmt_idx").over(Window.partitionBy("nb_id", "cell_idx")))
    stage = F.when(wrangle, "wrangle").when(F.col("begun").isNotNull(), "init").when(F.col("is_def"), "kill").when(looks, "inspect").when(F.col("live") & F.col("utilized"), "utilize").otherwise("other")
    rows = rows.withColumn("stage", stage)
    kind = F.when(F.col("stage") == "init", F.when(F.col("begun") == "operation", "operation").when(F.col("api").isin(apidb.CONSTRUCTORS), "definition").when(F.col("api").isin(apidb.LOADERS), "loading").otherwise("manipulation"))
    count = F.count_if(F.col("stage") == "init").over(by_name.rowsBetween(Window.unboundedPreceding, 0))
    keep = ["nb_id", "pos", "cell_idx", "stmt_idx", "var", "stage", *(["kind", "api", "receiver", "src", "defs", "uses", "comments"] if facts else []), "live"]
    return rows.withColumns({"life_no": count, "init_kind": kind}).select(*keep, "life_no", "init_kind")


def lifecycles(staged: DataFrame, close_on: str = "first_after_wrangle") -> DataFrame:
    """One row per life of a variable: nb_id, var, life_no, init_pos, first_wrangle_pos, end_pos (null: never
    complete), n_wrangle, cell_idxs (the cells that touch it from begin to end, in order)."""
    life = Window.partitionBy("nb_id", "var", "life_no")
    rows = staged.filter("life_no > 0").withColumn("init_pos", F.min(F.when(F.col("stage") == "init", F.col("pos"))).over(life))
    rows = rows.withColumn("first_wrangle_pos", F.min(F.when(F.col("stage") == "wrangle", F.col("pos"))).over(life))
    close = F.when((F.col("stage") == "utilize") & (F.col("pos") > F.col("first_wrangle_pos")), F.col("pos"))
    rows = rows.withColumn("end_pos", (F.min(close) if close_on == "first_after_wrangle" else F.max(close)).over(life))
    inside = F.col("end_pos").isNull() | (F.col("pos") <= F.col("end_pos"))
    return rows.groupBy("nb_id", "var", "life_no").agg(
        F.min("init_pos").alias("init_pos"),
        F.min("first_wrangle_pos").alias("first_wrangle_pos"),
        F.min("end_pos").alias("end_pos"),
        F.count_if((F.col("stage") == "wrangle") & inside).alias("n_wrangle"),
        F.array_sort(F.collect_set(F.when(inside & ~F.col("stage").isin("kill"), F.col("cell_idx")))).alias("cell_idxs"),
    )


def drop_incomplete(notebooks: DataFrame, lives: DataFrame) -> DataFrame:
    return notebooks.join(lives.filter("end_pos is not null").select("nb_id"), "nb_id", "left_semi")


def def_use(stmts: DataFrame) -> DataFrame:
    """Edges (nb_id, name, use_pos, def_pos): the latest definition or import before each use; null if there is none."""
    rows = named_rows(stmts)
    defines = F.array_contains("defs", F.col("var")) | (F.col("kind") == "import") | ((F.col("base") == F.col("var")) & F.col("store").isin("subscript", "attr"))
    before = Window.partitionBy("nb_id", "var").orderBy("pos").rowsBetween(Window.unboundedPreceding, -1)
    latest = F.last(F.when(defines, F.col("pos")), ignorenulls=True).over(before)
    return rows.withColumn("def_pos", latest).filter(F.array_contains("uses", F.col("var"))).select("nb_id", F.col("var").alias("name"), F.col("pos").alias("use_pos"), "def_pos")


def slice_back(edges: DataFrame, seeds: DataFrame, max_hops: int = 1) -> DataFrame:
    """Statements (nb_id, pos, hops) that the seeds (nb_id, pos) depend on, up to ``max_hops`` edges away."""
    step = edges.filter("def_pos is not null").select("nb_id", F.col("use_pos").alias("pos"), "def_pos").distinct()
    reached, last = None, seeds.select("nb_id", "pos")
    for hop in range(1, max_hops + 1):
        last = last.join(step, ["nb_id", "pos"]).select("nb_id", F.col("def_pos").alias("pos")).distinct()
        found = last.withColumn("hops", F.lit(hop))
        reached = found if reached is None else reached.unionByName(found)
    return reached.groupBy("nb_id", "pos").agg(F.min("hops").alias("hops"))


def segment_targets(staged: DataFrame, lives: DataFrame) -> DataFrame:
    """Spans between successive inspections of a complete life that hold a wrangling step: target_id, nb_id, var,
    life_no, begin_pos, end_pos, n_wrangle, cell_from, cell_to."""
    key = ["nb_id", "var", "life_no"]
    whole = lives.filter("end_pos is not null").select(*key, "init_pos", F.col("end_pos").alias("life_end"))
    rows = staged.join(whole, key).filter("pos > init_pos and pos < life_end")
    order = Window.partitionBy(*key).orderBy("pos")
    done = F.count_if(F.col("stage") == "wrangle").over(order.rowsBetween(Window.unboundedPreceding, 0))
    looks = rows.withColumn("done", done).filter("stage = 'inspect'")
    spans = looks.withColumn("until", F.lead(F.struct("pos", "cell_idx", "done")).over(order)).filter("until is not null")
    spans = spans.withColumn("n_wrangle", F.col("until.done") - F.col("done")).filter("n_wrangle > 0")
    same_cell = F.col("until.cell_idx") == F.col("cell_idx")
    return spans.select(
        F.concat_ws("/", F.col("nb_id").cast("string"), "var", F.col("life_no").cast("string"), F.col("pos").cast("string")).alias("target_id"),
        *key,
        F.col("pos").alias("begin_pos"),
        F.col("until.pos").alias("end_pos"),
        "n_wrangle",
        F.when(same_cell, F.col("cell_idx")).otherwise(F.col("cell_idx") + 1).alias("cell_from"),
        F.col("until.cell_idx").alias("cell_to"),
    )


def _listed(order: str, value) -> F.Column:
    """Values of a group in order, as an array."""
    return F.transform(F.array_sort(F.collect_list(F.struct(order, value.alias("__v")))), lambda x: x["__v"])


def target_statements(targets: DataFrame, staged: DataFrame, stmts: DataFrame, lives: DataFrame) -> DataFrame:
    """Statements (target_id, pos, src, comments, uses, defs) of each target: those of the life's cells within the
    span, without looks at the variable."""
    looks = staged.filter("stage = 'inspect'").select("nb_id", "pos", "var", F.lit(True).alias("look"))
    spans = targets.join(lives.select("nb_id", "var", "life_no", "cell_idxs"), ["nb_id", "var", "life_no"])
    rows = stmts.select("nb_id", "pos", "cell_idx", "src", "comments", "uses", "defs").join(spans, "nb_id")
    rows = rows.filter((F.col("pos") > F.col("begin_pos")) & (F.col("pos") < F.col("end_pos")) & F.col("cell_idx").between(F.col("cell_from"), F.col("cell_to")) & F.array_contains("cell_idxs", F.col("cell_idx")))
    return rows.join(looks, ["nb_id", "pos", "var"], "left").filter("look is null").select("target_id", "nb_id", "pos", "cell_idx", "src", "comments", "uses", "defs")


def with_code(targets: DataFrame, of_target: DataFrame) -> DataFrame:
    """Targets with target_code and inline_comments (of the target's statements)."""
    line = F.concat(F.array_join(F.transform("comments", lambda c: F.concat(F.lit("# "), c, F.lit("\n"))), ""), "src")
    code = of_target.groupBy("target_id").agg(F.array_join(_listed("pos", line), "\n").alias("target_code"), F.flatten(_listed("pos", F.col("comments"))).alias("inline_comments"))
    return targets.join(code, "target_id")


def context_cells(targets: DataFrame, lives: DataFrame) -> DataFrame:
    """(target_id, nb_id, cell_idx) of the life's cells before the target's first cell."""
    rows = targets.join(lives.select("nb_id", "var", "life_no", "cell_idxs"), ["nb_id", "var", "life_no"])
    rows = rows.select("target_id", "nb_id", "cell_from", "begin_pos", F.explode("cell_idxs").alias("cell_idx"))
    return rows.filter((F.col("cell_idx") < F.col("cell_from")) & (F.col("cell_idx").cast("long") * CELL_STEP <= F.col("begin_pos"))).select("target_id", "nb_id", "cell_idx")


def prelude(targets: DataFrame, of_target: DataFrame, ctx: DataFrame, stmts: DataFrame) -> DataFrame:
    """(target_id, prelude): the latest definitions of names that the target or its context reads, and the imports
    behind them, unless they lie in a context cell; in the order of the notebook, as one cell."""
    spans = targets.select("target_id", "nb_id", "begin_pos")
    reads = of_target.select("target_id", F.explode("uses").alias("name"))
    context = ctx.join(stmts.select("nb_id", "cell_idx", F.explode("uses").alias("name")), ["nb_id", "cell_idx"]).select("target_id", "name")
    reads = reads.unionByName(context).distinct().join(spans, "target_id")
    gives = F.array_distinct(F.concat("defs", F.transform("imports", lambda x: x["alias"])))
    defs = stmts.select("nb_id", F.explode(gives).alias("name"), F.col("pos").alias("def_pos"), F.col("cell_idx").alias("def_cell"), F.col("src").alias("def_src"))
    found = reads.join(defs, ["nb_id", "name"]).filter("def_pos < begin_pos").groupBy("target_id", "name").agg(F.max_by(F.struct("def_pos", "def_cell", "def_src"), "def_pos").alias("d"))
    found = found.select("target_id", "d.*").distinct().join(ctx.select("target_id", F.col("cell_idx").alias("def_cell")), ["target_id", "def_cell"], "left_anti")
    return found.groupBy("target_id").agg(F.array_join(_listed("def_pos", F.col("def_src")), "\n").alias("prelude"))


def markdown_before(cells: DataFrame) -> DataFrame:
    """(nb_id, cell_idx of a code cell, text_idx, text): the run of non-blank markdown cells right before it."""
    order = Window.partitionBy("nb_id").orderBy("cell_idx")
    next_code = F.first(F.when(F.col("kind") == "code", F.col("cell_idx")), ignorenulls=True).over(order.rowsBetween(1, Window.unboundedFollowing))
    rows = cells.withColumn("before", next_code).filter("kind = 'markdown' and before is not null and trim(source) <> ''")
    return rows.select("nb_id", F.col("before").alias("cell_idx"), F.col("cell_idx").alias("text_idx"), F.col("source").alias("text"))


def text_context(targets: DataFrame, ctx: DataFrame, cells: DataFrame, stmts: DataFrame, origins: tuple[str, ...] = ("markdown", "ctx_comment", "inline")) -> DataFrame:
    """(target_id, place, origin, text): markdown before the target's and each context cell, comments of context
    cells, and the target's own comments."""
    parts = []
    if "markdown" in origins:
        first = targets.select("target_id", "nb_id", F.col("cell_from").alias("cell_idx"))
        near = ctx.select("target_id", "nb_id", "cell_idx").unionByName(first).join(markdown_before(cells), ["nb_id", "cell_idx"])
        parts.append(near.select("target_id", (F.col("text_idx").cast("long") * CELL_STEP).alias("place"), F.lit("markdown").alias("origin"), "text").distinct())
    if "ctx_comment" in origins:
        notes = ctx.join(stmts.select("nb_id", "cell_idx", "pos", F.explode("comments").alias("text")), ["nb_id", "cell_idx"])
        parts.append(notes.select("target_id", F.col("pos").alias("place"), F.lit("ctx_comment").alias("origin"), "text"))
    if "inline" in origins:
        parts.append(targets.select("target_id", F.col("begin_pos").alias("place"), F.lit("inline").alias("origin"), F.explode("inline_comments").alias("text")))
    out = parts[0]
    for part in parts[1:]:
        out = out.unionByName(part)
    return out


def wrap_text(text: F.Column) -> F.Column:
    """Prose as a triple-quoted string, so that a merged context is code throughout."""
    return F.concat(F.lit('"""'), F.replace(F.replace(text, F.lit("\\"), F.lit("\\\\")), F.lit('"""'), F.lit("'''")), F.lit('\n"""'))


def contexts(targets: DataFrame, ctx: DataFrame, first: DataFrame, cells: DataFrame, stmts: DataFrame) -> DataFrame:
    """(target_id, prelude, code_ctx, text_ctx, merged_ctx, n_code_cells, n_text): contexts in the notebook's order,
    the prelude in front."""
    code = ctx.join(cells.filter("kind = 'code'").select("nb_id", "cell_idx", "source"), ["nb_id", "cell_idx"])
    code = code.select("target_id", (F.col("cell_idx").cast("long") * CELL_STEP + 1).alias("place"), F.lit("code").alias("origin"), F.col("source").alias("text"))
    marks = text_context(targets, ctx, cells, stmts, ("markdown",))
    notes = text_context(targets, ctx, cells, stmts, ("ctx_comment", "inline"))
    rows = code.unionByName(marks).unionByName(notes)
    in_order = lambda keep, value: F.transform(F.filter(F.array_sort(F.collect_list(F.struct("place", "origin", "text"))), keep), value)
    made = rows.groupBy("target_id").agg(
        F.array_join(in_order(lambda x: x["origin"] == "code", lambda x: x["text"]), "\n").alias("code_ctx"),
        F.array_join(in_order(lambda x: x["origin"] != "code", lambda x: x["text"]), "\n").alias("text_ctx"),
        F.array_join(in_order(lambda x: x["origin"].isin("code", "markdown"), lambda x: F.when(x["origin"] == "code", x["text"]).otherwise(wrap_text(x["text"]))), "\n").alias("merged"),
        F.count_if(F.col("origin") == "code").alias("n_code_cells"),
        F.count_if(F.col("origin") != "code").alias("n_text"),
    )
    made = targets.select("target_id").join(made, "target_id", "left").join(first, "target_id", "left").na.fill({"prelude": "", "code_ctx": "", "text_ctx": "", "merged": "", "n_code_cells": 0, "n_text": 0})
    return made.withColumn("merged_ctx", F.concat_ws("\n", F.nullif("prelude", F.lit("")), F.nullif("merged", F.lit("")))).drop("merged")


@F.udtf(returnType=StructType([StructField("stmt_idx", IntegerType()), *(StructField(c, StringType()) for c in ("kind", "api", "src"))]))
class CELLS_UDTF:
    """The statements of one cell's source, as a table function for SQL."""

    def eval(self, source: str):
        for i, s in enumerate(parse_cell(source or "") or []):
            yield i, s.kind, s.api, s.src
