"""The oracle's side of the mined corpus, in SQL: statements, contexts, frames, examples and model inputs.

Nothing here parses or runs code. Statements come from what ``templates`` says about its lines by hand, places from the
renderer's arithmetic, and frames from the given tables: each step that a template's code takes is said again as SQL.
Each ``WITH`` list builds on the one before; a query takes the shortest that has its tables.
"""

from __future__ import annotations

from nbflow.operators import generators, inputs
from nbflow.operators.examples import SMALL_SPLIT, STORED_ROWS
from nbflow.plans.mine import FACTS, _values
from nbflow.sources import templates

STEP = "4294967296"
NL = "chr(10)"


def _names(column: str) -> str:
    return f"list_filter(string_split(replace({column}, '<v>', var), ' '), lambda x: x <> '')"


def _filled(column: str) -> str:
    return f"replace(replace({column}, '<v>', var), '<k>', CAST(nb_id % {templates.SLICES} AS VARCHAR))"


_CELL = "base_turn * 20 + CASE WHEN odd IS NULL THEN j ELSE 2 * j + odd END"

STATEMENTS = f"""{FACTS},
cf(template, j, s, src, note, defs, uses, calls, stores, tracks) AS (VALUES {_values(templates.code_facts())}),
tc(template, j, code) AS (VALUES {_values(templates.cells())}),
books AS (SELECT nb_id, template, turn, base_turn, odd, CASE WHEN template % 2 = 0 THEN 'df' || turn WHEN odd IS NOT NULL THEN 'data' || turn ELSE 'data' END AS var FROM placed WHERE role = 'assistant'),
stm AS MATERIALIZED (
  SELECT nb_id, template, var, {_CELL} AS cell_idx, ({_CELL})::BIGINT * {STEP} + s AS pos, {_filled('src')} AS src, note, {_names('defs')} AS defs, {_names('uses')} AS uses, {_names('calls')} AS calls, stores, tracks
  FROM books JOIN cf USING (template)),
modules(alias, module) AS (VALUES {_values(list(templates.MODULES.items()))})"""

CONTEXTS = f"""{STATEMENTS},
code_cells AS (SELECT nb_id, {_CELL} AS cell_idx, {_filled('code')} AS source FROM books JOIN tc USING (template)),
prose AS (SELECT nb_id, turn * 20 AS cell_idx, CASE WHEN (nb_id + turn) % 13 = 0 THEN ' ' ELSE text END AS source FROM (SELECT conv_id AS nb_id, turn, role, text FROM conversations) WHERE role <> 'assistant'),
touch AS (
  SELECT m.nb_id, m.var, m.cell_idx, m.pos, count(CASE WHEN r.stage = 'init' THEN 1 END) OVER (PARTITION BY m.nb_id, m.var ORDER BY m.pos) AS life_no
  FROM stm m JOIN rows_ r ON r.nb_id = m.nb_id AND r.var = m.var AND r.pos = m.pos WHERE tracks = 1),
life_cells AS MATERIALIZED (SELECT DISTINCT nb_id, var, life_no, cell_idx FROM touch JOIN lives USING (nb_id, var, life_no) WHERE end_pos IS NOT NULL AND pos <= end_pos),
spans AS MATERIALIZED (
  SELECT nb_id || '/' || var || '/' || life_no || '/' || begin_pos AS target_id, *, begin_pos // {STEP} + CASE WHEN begin_pos // {STEP} = end_pos // {STEP} THEN 0 ELSE 1 END AS cell_from, end_pos // {STEP} AS cell_to,
         row_number() OVER (PARTITION BY nb_id, var, life_no ORDER BY begin_pos) - 1 AS nth FROM targets),
target_stm AS MATERIALIZED (
  SELECT t.target_id, m.* FROM spans t JOIN life_cells c USING (nb_id, var, life_no) JOIN stm m ON m.nb_id = c.nb_id AND m.cell_idx = c.cell_idx
  WHERE m.pos > t.begin_pos AND m.pos < t.end_pos AND m.cell_idx BETWEEN cell_from AND cell_to
    AND NOT EXISTS (SELECT 1 FROM rows_ r WHERE r.nb_id = m.nb_id AND r.pos = m.pos AND r.var = t.var AND r.stage = 'inspect')),
coded AS (SELECT target_id, string_agg(CASE WHEN note <> '' THEN '# ' || note || {NL} ELSE '' END || src, {NL} ORDER BY pos) AS target_code FROM target_stm GROUP BY 1),
ctx AS MATERIALIZED (SELECT target_id, nb_id, cell_idx FROM spans JOIN life_cells USING (nb_id, var, life_no) WHERE cell_idx < cell_from AND cell_idx::BIGINT * {STEP} <= begin_pos),
reads AS (
  SELECT target_id, unnest(uses) AS name FROM target_stm
  UNION SELECT target_id, unnest(uses) FROM ctx JOIN stm USING (nb_id, cell_idx)),
gives AS (SELECT nb_id, unnest(defs) AS name, pos, cell_idx, src FROM stm),
latest AS (SELECT target_id, max(pos) AS pos FROM reads JOIN spans USING (target_id) JOIN gives g USING (nb_id, name) WHERE g.pos < begin_pos GROUP BY target_id, name),
first_cell AS (
  SELECT target_id, string_agg(src, {NL} ORDER BY pos) AS prelude
  FROM (SELECT DISTINCT l.target_id, l.pos, m.src, m.cell_idx FROM latest l JOIN spans s USING (target_id) JOIN stm m ON m.nb_id = s.nb_id AND m.pos = l.pos) d
  WHERE NOT EXISTS (SELECT 1 FROM ctx c WHERE c.target_id = d.target_id AND c.cell_idx = d.cell_idx) GROUP BY 1),
marks AS (SELECT p.nb_id, min(c.cell_idx) AS cell_idx, p.cell_idx AS text_idx, any_value(p.source) AS text FROM prose p JOIN code_cells c ON c.nb_id = p.nb_id AND c.cell_idx > p.cell_idx WHERE trim(p.source, ' ') <> '' GROUP BY p.nb_id, p.cell_idx),
texts AS MATERIALIZED (
  SELECT DISTINCT target_id, text_idx::BIGINT * {STEP} AS place, 'markdown' AS origin, text FROM (SELECT target_id, nb_id, cell_idx FROM ctx UNION ALL SELECT target_id, nb_id, cell_from FROM spans) JOIN marks USING (nb_id, cell_idx)
  UNION ALL SELECT target_id, pos, 'ctx_comment', note FROM ctx JOIN stm USING (nb_id, cell_idx) WHERE note <> ''
  UNION ALL SELECT target_id, begin_pos, 'inline', note FROM target_stm JOIN spans USING (target_id) WHERE note <> ''),
parts AS (SELECT target_id, cell_idx::BIGINT * {STEP} + 1 AS place, 'code' AS origin, source AS text FROM ctx JOIN code_cells USING (nb_id, cell_idx) UNION ALL SELECT * FROM texts),
made AS (
  SELECT target_id, string_agg(text, {NL} ORDER BY place, origin, text) FILTER (WHERE origin = 'code') AS code_ctx, string_agg(text, {NL} ORDER BY place, origin, text) FILTER (WHERE origin <> 'code') AS text_ctx,
         string_agg(CASE WHEN origin = 'code' THEN text ELSE '\"\"\"' || replace(replace(text, '\\', '\\\\'), '\"\"\"', '''''''') || {NL} || '\"\"\"' END, {NL} ORDER BY place, origin, text) FILTER (WHERE origin IN ('code', 'markdown')) AS merged,
         count(*) FILTER (WHERE origin = 'code') AS n_code_cells
  FROM parts GROUP BY 1),
contexts AS MATERIALIZED (
  SELECT target_id, coalesce(prelude, '') AS prelude, coalesce(code_ctx, '') AS code_ctx, coalesce(text_ctx, '') AS text_ctx, coalesce(n_code_cells, 0) AS n_code_cells, concat_ws({NL}, nullif(prelude, ''), nullif(merged, '')) AS merged_ctx
  FROM spans LEFT JOIN made USING (target_id) LEFT JOIN first_cell USING (target_id))"""


def _slice(name: str, table: str, columns: list[str]) -> str:
    key = templates.KEYS[table]
    order = ", ".join([key, *[c for c in columns if c != key]])
    return f"{name} AS (SELECT *, {key} % {templates.SLICES} AS k, row_number() OVER (PARTITION BY {key} % {templates.SLICES} ORDER BY {order}) AS r FROM {table} QUALIFY r <= {templates.SLICE_ROWS})"


def _num(x: str) -> str:
    return f"CAST(round({x}, 6) + 0.0 AS VARCHAR)"


def _time(x: str) -> str:
    return f"strftime({x}, '%Y-%m-%dT%H:%M:%S.%g')"


#: Columns of the given tables in order, as text.
_O = {"o_orderkey": "o_orderkey", "o_custkey": "o_custkey", "o_orderstatus": "o_orderstatus", "o_totalprice": _num("o_totalprice"), "o_orderdate": _time("o_orderdate"), "o_orderpriority": "o_orderpriority"}
_C = {"c_custkey": "c_custkey", "c_name": "c_name", "c_nationkey": "c_nationkey", "c_acctbal": _num("c_acctbal"), "c_mktsegment": "c_mktsegment"}
_L = {"l_orderkey": "l_orderkey", "l_partkey": "l_partkey", "l_suppkey": "l_suppkey", "l_linenumber": "l_linenumber"} | {c: _num(c) for c in ("l_quantity", "l_extendedprice", "l_discount", "l_tax")} | {"l_returnflag": "l_returnflag", "l_linestatus": "l_linestatus", "l_shipdate": _time("l_shipdate")}
_P = {"p_partkey": "p_partkey", "p_name": "p_name", "p_brand": "p_brand", "p_type": "p_type", "p_size": "p_size", "p_retailprice": _num("p_retailprice")}
_E = {"event_id": "event_id", "ts": _time("ts"), "user_id": "user_id", "event_type": "event_type", "value": _num("value"), "props": "props"}
_N = {c: c for c in ("n_nationkey", "n_name", "n_regionkey", "r_regionkey", "r_name")}
_S = {"s_suppkey": "s_suppkey", "s_acctbal": _num("s_acctbal")}
_REVENUE = _L | {"revenue": _num("l_extendedprice * (1 - l_discount)")}
_SEEN = "(SELECT * FROM l_ QUALIFY row_number() OVER (PARTITION BY k, l_orderkey, l_linenumber ORDER BY r) = 1)"
_ORDER_CUSTOMER = "(SELECT o_.*, c_.* EXCLUDE (k, r) FROM o_ JOIN c_ ON o_custkey = c_custkey AND o_.k = c_.k)"
_NATION_REGION = "(SELECT n_.*, g_.* EXCLUDE (k, r) FROM n_ JOIN g_ ON n_regionkey = r_regionkey AND n_.k = g_.k)"
_LITERAL = [(k, 10 * k, k * k) for k in (1, 2, 3)]
#: (template, target of the life, side, columns as text, rows): rows have k (the file's number) and r (their order).
_FRAMES = [
    (0, 0, "in", _O, "o_"),
    (0, 0, "out", _O | {"o_totalprice": _num("price")}, "(SELECT *, round_even(o_totalprice, 1) AS price FROM o_ WHERE price > 1000)"),
    (1, 0, "in", _C, "c_"),
    (1, 0, "out", _C | {"band": "len(list_filter(q, lambda e: e < c_acctbal))"}, "(SELECT * FROM c_ JOIN (SELECT k, quantile_cont(c_acctbal, [0.25, 0.5, 0.75]) AS q FROM c_ GROUP BY k) USING (k))"),
    (2, 0, "in", _L, "l_"),
    (2, 0, "out", _REVENUE, _SEEN),
    (2, 1, "in", _REVENUE, _SEEN),
    (2, 1, "out", {"l_returnflag": "l_returnflag", "revenue": _num("revenue")}, f"(SELECT k, l_returnflag, fsum(l_extendedprice * (1 - l_discount)) AS revenue, ascii(l_returnflag) AS r FROM {_SEEN} GROUP BY ALL)"),
    (3, 0, "in", _P, "p_"),
    (3, 0, "out", {("brand" if c == "p_brand" else c): ("upper(p_name)" if c == "p_name" else x) for c, x in _P.items()}, "p_"),
    (4, 0, "in", _E, "e_"),
    (4, 0, "out", _E, "(SELECT * REPLACE (-event_id AS r) FROM e_ WHERE value > 20)"),
    (5, 0, "in", _O | _C, _ORDER_CUSTOMER),
    (5, 0, "out", _O | {c: x for c, x in _C.items() if c not in ("c_custkey", "c_name")}, _ORDER_CUSTOMER),
    (6, 0, "in", {"key": "key", "a": "a", "b": "b"}, f"(SELECT *, key AS r FROM range({templates.SLICES}) s(k), (VALUES {_values(_LITERAL)}) v(key, a, b))"),
    (6, 0, "out", {"key": "key", "variable": "variable", "value": "value"}, f"(SELECT k, key, variable, value, key + CASE variable WHEN 'a' THEN 0 ELSE 9 END AS r FROM range({templates.SLICES}) s(k), (VALUES {_values([(k, n, x) for k, a, b in _LITERAL for n, x in (('a', a), ('b', b))])}) v(key, variable, value))"),
    (7, 0, "in", _N, _NATION_REGION),
    (7, 0, "out", {"r_name": "r_name", "n_nationkey": "n"}, f"(SELECT k, r_name, count(*) AS n, row_number() OVER (PARTITION BY k ORDER BY r_name) AS r FROM {_NATION_REGION} GROUP BY k, r_name)"),
    (8, 0, "in", _O, "o_"),
    (8, 0, "out", {c: x for c, x in _O.items() if c != "o_orderstatus"} | {"open": "(o_orderstatus = 'O')::INT"}, "o_"),
    (9, 0, "in", _S, "s_"),
    (9, 0, "out", {"s_suppkey": "s_suppkey * 2", "s_acctbal": _num("s_acctbal * 2")}, "s_"),
    (14, 0, "in", _O, "o_"),
    (14, 0, "out", _O, "o_"),
]


def _frame(t: int, nth: int, side: str, columns: dict[str, str], rows: str) -> str:
    cells = ", ".join(f"CAST({x} AS VARCHAR)" for x in columns.values())
    names = ", ".join(f"'{c}'" for c in columns)
    return f"SELECT {t} AS template, {nth} AS nth, '{side}' AS side, k, [{names}] AS columns, count(*) AS n_rows, list([{cells}] ORDER BY r)[1:{STORED_ROWS}] AS rows FROM {rows} GROUP BY k"


def _normal(code: str) -> str:
    return f"array_to_string(list_filter(list_transform(string_split({code}, {NL}), lambda x: rtrim(x, ' ')), lambda x: x <> '' AND NOT starts_with(ltrim(x, ' '), '#')), {NL})"


SPLIT = f"CASE WHEN (nb_id * 7919 + 13) % 1000 < {SMALL_SPLIT[0]} THEN 'train' WHEN (nb_id * 7919 + 13) % 1000 < {SMALL_SPLIT[0] + SMALL_SPLIT[1]} THEN 'dev' ELSE 'test' END"
_FAILS = _values([(t, j, e) for t, (j, e) in templates.FAILURES.items()])

EXAMPLES = f"""{CONTEXTS},
{_slice('o_', 'orders', list(_O))}, {_slice('c_', 'customer', list(_C))}, {_slice('l_', 'lineitem', list(_L))}, {_slice('p_', 'part', list(_P))}, {_slice('e_', 'events', list(_E))},
{_slice('n_', 'nation', ['n_nationkey', 'n_name', 'n_regionkey'])}, {_slice('g_', 'region', ['r_regionkey', 'r_name'])}, {_slice('s_', 'supplier', ['s_suppkey', 's_name', 's_nationkey', 's_acctbal'])},
frames AS MATERIALIZED ({' UNION ALL '.join(_frame(*f) for f in _FRAMES)}),
failed AS (SELECT nb_id, arg_min(error, {_CELL}) AS outcome FROM books JOIN (VALUES {_FAILS}) f(template, j, error) USING (template) GROUP BY 1),
replayed AS (SELECT target_id, coalesce(outcome, 'ok') AS outcome FROM spans LEFT JOIN failed USING (nb_id)),
begun AS (SELECT target_id, any_value(template) AS template FROM target_stm GROUP BY 1),
everything AS MATERIALIZED (
  SELECT target_id AS example_id, s.nb_id, s.var, begun.template, {SPLIT} AS split, target_code, {_normal('target_code')} AS norm, prelude, code_ctx, text_ctx, merged_ctx, n_code_cells,
         i.columns AS in_columns, i.rows AS in_rows, i.n_rows AS in_n, o.columns AS out_columns, o.rows AS out_rows, o.n_rows AS out_n
  FROM spans s JOIN replayed USING (target_id) JOIN begun USING (target_id) JOIN coded USING (target_id) JOIN contexts USING (target_id)
  JOIN frames i ON i.template = begun.template AND i.nth = s.nth AND i.side = 'in' AND i.k = s.nb_id % {templates.SLICES}
  JOIN frames o ON o.template = begun.template AND o.nth = s.nth AND o.side = 'out' AND o.k = s.nb_id % {templates.SLICES}
  WHERE outcome = 'ok'),
capped AS (SELECT * FROM everything WHERE n_code_cells <= 10),
changed AS (SELECT * FROM capped WHERE template <> 14),
one_each AS MATERIALIZED (SELECT * FROM changed WHERE example_id IN (SELECT min(example_id) FROM changed GROUP BY norm)),
examples AS MATERIALIZED (
  SELECT * FROM one_each e WHERE split <> 'test' OR NOT EXISTS (SELECT 1 FROM one_each o WHERE o.split <> 'test' AND contains({NL} || {_normal('o.merged_ctx')} || {NL}, {NL} || e.norm || {NL}))),
test AS (SELECT * FROM examples WHERE split = 'test')"""


def flat(side: str, rows: int = 5, columns: bool = True, values: bool = True) -> str:
    """A frame as text."""
    head = f"{side}_columns" if columns else f"list_transform({side}_columns, lambda c, i: 'c' || (i - 1))"
    lines = f"list_transform({side}_rows[1:{rows}], lambda r: array_to_string(list_transform(r, lambda x: coalesce(x, 'NaN')), ' | '))" if values and rows else "[]::VARCHAR[]"
    return f"array_to_string(list_concat([array_to_string({head}, ' | ')], {lines}), {NL})"


def data(a: int = 1, b: int = 1, **parts) -> str:
    used = [flat(side, **parts) for side, on in (("in", a), ("out", b)) if on]
    return f"concat_ws({NL}, {', '.join(used)})" if used else "''"


def context(code: int = 1, text: int = 1) -> str:
    return "merged_ctx" if code and text else f"concat_ws({NL}, nullif(prelude, ''), code_ctx)" if code else "text_ctx" if text else "''"


def count(text: str) -> str:
    """The number of words and single signs."""
    return f"len(regexp_extract_all({text}, '\\w+|[^\\w\\s]'))"


def wrapped(text: str) -> str:
    return f"'\"\"\"' || replace(replace({text}, '\\', '\\\\'), '\"\"\"', '''''''') || {NL} || '\"\"\"'"


_BODY = f"concat_ws({NL}, merged_ctx, {wrapped(f'concat_ws({NL}, ' + repr('Input:') + ', ' + flat('in') + ', ' + repr('Output:') + ', ' + flat('out') + ')')}, '# code:')"
_HEAD = wrapped("'" + inputs.INSTRUCTION.replace("'", "''") + "'")


def _ring(rows: str) -> str:
    return f"(SELECT example_id, row_number() OVER (ORDER BY md5(example_id), example_id) - 1 AS place FROM examples WHERE split = '{rows}')"


PROMPTS = f"""{EXAMPLES},
bodies AS (SELECT example_id, split, {_BODY} AS body, target_code FROM examples),
ring AS (SELECT t.example_id, r.n AS demo_rank, p.example_id AS demo_id FROM {_ring('test')} t, range(2) r(n), {_ring('train')} p, (SELECT count(*) AS size FROM {_ring('train')}) WHERE r.n < size AND p.place = (t.place * 2 + r.n) % size),
shown AS (SELECT ring.example_id, string_agg(concat_ws({NL}, body, target_code), {NL} || {NL} ORDER BY demo_rank) AS demos FROM ring JOIN bodies b ON b.example_id = demo_id GROUP BY 1),
zero AS (SELECT example_id, concat_ws({NL} || {NL}, {_HEAD}, body) AS prompt FROM bodies WHERE split = 'test')"""

_SHAPE = "regexp_replace(target_code, '\\b' || var || '\\b', '__frame__', 'g')"
_MODE = f"(SELECT shape FROM (SELECT {_SHAPE} AS shape, count(*) AS n FROM examples WHERE split = 'train' GROUP BY 1) ORDER BY n DESC, shape LIMIT 1)"


def corrupted(percent: int) -> str:
    """The code of a test example with a misspelt key, if chosen."""
    chosen = f"('0x' || left(md5('rename_col' || example_id), 8))::BIGINT % 100 < {percent}"
    return f"CASE WHEN {chosen} THEN CASE WHEN regexp_matches(target_code, '''\\w+''') THEN regexp_replace(target_code, '''(\\w+)''', '''\\1_x''', 'g') ELSE target_code || {NL} || '__missing__' END ELSE target_code END"


_USED_API = "SELECT DISTINCT target_id, string_split(c, '.')[2] AS name FROM (SELECT target_id, unnest(calls) AS c FROM target_stm)"
_USED_MODULE = "SELECT DISTINCT target_id, string_split(module, '.')[1] AS name FROM (SELECT target_id, unnest(uses) AS alias FROM target_stm) JOIN modules USING (alias)"
_DEFINES = "SELECT nb_id, name, pos AS def_pos FROM gives UNION SELECT nb_id, var, pos FROM stm WHERE stores = 1"
_EDGES = f"SELECT u.nb_id, u.name, u.pos AS use_pos, max(def_pos) AS def_pos FROM (SELECT DISTINCT nb_id, pos, unnest(uses) AS name FROM stm) u LEFT JOIN ({_DEFINES}) d ON d.nb_id = u.nb_id AND d.name = u.name AND def_pos < u.pos GROUP BY ALL"
_CALLS = "SELECT nb_id, pos, CAST(generate_subscripts(calls, 1) - 1 AS INT) AS nth, unnest(calls) AS c FROM stm"
_NAMED = "SELECT nb_id, pos, nth, string_split(c, '.')[1] AS receiver, string_split(c, '.')[2] AS api"
_HIST = "SELECT n, count(*) AS targets FROM (SELECT target_id, count(name) AS n FROM spans LEFT JOIN ({0}) u USING (target_id) GROUP BY 1) GROUP BY 1"
_STORED = f"CASE WHEN split = 'test' THEN {{0}}_n ELSE least({{0}}_n, {STORED_ROWS}) END"
_METRICS = {
    "examples": "count(*)::DOUBLE",
    "in_columns": "avg(len(in_columns))",
    "in_rows": f"avg({_STORED.format('in')})",
    "out_columns": "avg(len(out_columns))",
    "out_rows": f"avg({_STORED.format('out')})",
    "text_tokens": f"avg({count('text_ctx')})",
    "target_tokens": f"avg({count('target_code')})",
}
_SIZES = f"SELECT example_id, CAST(least(c, {{0}}) AS INT) AS ctx, CAST(least(d, {{0}}) AS INT) AS data, c > {{0}} OR d > {{0}} AS truncated FROM (SELECT example_id, {count(context())} AS c, {count(data())} AS d FROM examples)"


def _with(tables: str, query: str) -> str:
    return f"WITH {tables} {query}"


def _funnel() -> str:
    steps = [
        ("notebooks", "SELECT DISTINCT conv_id FROM conversations"),
        ("lifecycles", "SELECT * FROM lives WHERE end_pos IS NOT NULL"),
        ("targets", "SELECT * FROM spans"),
        ("replayed", "SELECT * FROM everything"),
        ("context cap", "SELECT * FROM capped"),
        ("changed frames", "SELECT * FROM changed"),
        ("unique targets", "SELECT * FROM one_each"),
        ("no leakage", "SELECT * FROM examples"),
    ]
    return " UNION ALL ".join(f"SELECT {i} AS nth, '{name}' AS step, count(*) AS kept FROM ({q})" for i, (name, q) in enumerate(steps))


_GUESSED = {"all": "true", "no column names": "false", "no values": "false", "no input frame": "false", "no output frame": "false"}

_SEEN_TOKENS = f"SELECT *, list_distinct(regexp_extract_all(concat_ws({NL}, {context()}, {data()}), '\\w+|[^\\w\\s]')) AS seen FROM examples"
_BEST_DEMO = f"""
    , seen AS ({_SEEN_TOKENS}),
    alike AS (SELECT r.example_id, r.demo_id, row_number() OVER (PARTITION BY r.example_id ORDER BY len(list_intersect(a.seen, b.seen)) / len(list_distinct(list_concat(a.seen, b.seen))) DESC, demo_rank) AS nth FROM ring r JOIN seen a ON a.example_id = r.example_id JOIN seen b ON b.example_id = r.demo_id)
    SELECT e.example_id, regexp_replace(p.target_code, '\\b' || p.var || '\\b', e.var, 'g') AS code, code = e.target_code AS em FROM alike JOIN examples e USING (example_id) JOIN examples p ON p.example_id = demo_id WHERE nth = 1"""
_KIND = "CASE WHEN starts_with(src, 'import ') OR starts_with(src, 'from ') THEN 'import' WHEN stores = 1 OR len(defs) > 0 THEN 'assign' ELSE 'expr' END"

SQL: dict[str, str] = {
    "udtf_parse": _with(STATEMENTS, f"SELECT nb_id, {_KIND} AS kind, count(*) AS n FROM stm GROUP BY ALL"),
    "d10_prompt_copy": _with(PROMPTS, _BEST_DEMO),
    "b2_api_seq": _with(STATEMENTS, f"{_NAMED} FROM ({_CALLS})"),
    "b3_alias": _with(STATEMENTS, f"SELECT c.*, module FROM ({_NAMED} FROM ({_CALLS})) c LEFT JOIN modules ON alias = receiver"),
    "b5_api_freq": _with(STATEMENTS, f"SELECT api, count(*) AS n FROM ({_NAMED} FROM ({_CALLS})) GROUP BY 1"),
    "topk_api": _with(STATEMENTS, f"SELECT api, count(*) AS n FROM ({_NAMED} FROM ({_CALLS})) GROUP BY 1 ORDER BY n DESC, api LIMIT 10"),
    "b11_life_cells": _with(CONTEXTS, "SELECT nb_id, var, life_no, string_agg(cell_idx, ',' ORDER BY cell_idx) AS cells FROM life_cells GROUP BY ALL"),
    "b13_def_use": _with(CONTEXTS, _EDGES),
    "b14_slice": _with(
        CONTEXTS,
        f""", edges AS (SELECT DISTINCT nb_id, use_pos, def_pos FROM ({_EDGES}) WHERE def_pos IS NOT NULL),
        one AS (SELECT DISTINCT e.nb_id, def_pos AS pos FROM rows_ r JOIN edges e ON e.nb_id = r.nb_id AND use_pos = r.pos JOIN numbered n ON n.nb_id = r.nb_id AND n.var = r.var AND n.pos = r.pos WHERE r.stage = 'utilize'),
        two AS (SELECT DISTINCT e.nb_id, def_pos AS pos FROM one JOIN edges e ON e.nb_id = one.nb_id AND use_pos = one.pos)
        SELECT nb_id, pos, CAST(min(hops) AS INT) AS hops FROM (SELECT *, 1 AS hops FROM one UNION ALL SELECT *, 2 FROM two) GROUP BY ALL""",
    ),
    "c2_target_comments": _with(CONTEXTS, "SELECT target_id, note AS comment FROM target_stm WHERE note <> ''"),
    "c3_ctx_cells": _with(CONTEXTS, "SELECT target_id, nb_id, CAST(cell_idx AS INT) AS cell_idx FROM ctx"),
    "c4_prelude": _with(CONTEXTS, "SELECT * FROM first_cell"),
    "c5_text_ctx": _with(CONTEXTS, "SELECT * FROM texts"),
    "c6_merged": _with(CONTEXTS, "SELECT target_id, merged_ctx, n_code_cells FROM contexts"),
    "c7_replay": _with(EXAMPLES, "SELECT * FROM replayed"),
    "c8_snapshot": _with(EXAMPLES, f"SELECT example_id, in_n AS n_rows, CAST({_STORED.format('in')} AS INT) AS stored, array_to_string(in_columns, ',') AS columns FROM everything"),
    "c9_cap": _with(EXAMPLES, "SELECT example_id, n_code_cells FROM capped"),
    "c10_noop": _with(EXAMPLES, "SELECT example_id FROM everything WHERE template <> 14"),
    "c11_dedup_target": _with(EXAMPLES, "SELECT min(example_id) AS example_id FROM everything GROUP BY norm"),
    "c13_leak_examples": _with(EXAMPLES, f"SELECT example_id, split FROM everything e WHERE split <> 'test' OR NOT EXISTS (SELECT 1 FROM everything o WHERE o.split <> 'test' AND contains({NL} || {_normal('o.merged_ctx')} || {NL}, {NL} || e.norm || {NL}))"),
    "c15_stats": _with(EXAMPLES, " UNION ALL ".join(f"SELECT split, '{m}' AS metric, {x} AS value FROM examples GROUP BY split" for m, x in _METRICS.items())),
    "c16_mod_hist": _with(CONTEXTS, _HIST.format(_USED_MODULE)),
    "c16_api_hist": _with(CONTEXTS, _HIST.format(_USED_API)),
    "c16_mod_freq": _with(CONTEXTS, f"SELECT name, count(*) AS targets FROM ({_USED_MODULE}) GROUP BY 1"),
    "c16_api_freq": _with(CONTEXTS, f"SELECT name, count(*) AS targets FROM ({_USED_API}) GROUP BY 1"),
    "c16_share": _with(CONTEXTS, f"SELECT sum(CASE WHEN n < 3 THEN targets ELSE 0 END) / sum(targets) AS share FROM ({_HIST.format(_USED_API)})"),
    "d1_flatten": _with(EXAMPLES, f"SELECT example_id, {data()} AS text FROM examples"),
    "d2_joint": _with(EXAMPLES, _SIZES.format(256)),
    "d3_dual": _with(EXAMPLES, _SIZES.format(512)),
    "d4_trunc": _with(EXAMPLES, " UNION ALL ".join(f"SELECT '{name}' AS preset, avg(truncated::INT::DOUBLE) AS share FROM ({_SIZES.format(n)})" for name, n in (("joint", 256), ("dual", 512)))),
    "d6_cap": _with(EXAMPLES, f"SELECT example_id, CAST(least({count('target_code')}, {inputs.TARGET_TOKENS}) AS INT) AS n FROM examples"),
    "d9_prompt": _with(PROMPTS, f"SELECT example_id, concat_ws({NL} || {NL}, {_HEAD}, demos, body) AS prompt FROM bodies LEFT JOIN shown USING (example_id) WHERE split = 'test'"),
    "d9_zero_shot": _with(PROMPTS, "SELECT * FROM zero"),
    "d10_fit": _with(PROMPTS, f"SELECT model, w AS window, count(*) FILTER (WHERE {count('prompt')} <= w) AS fits, count(*) AS n FROM zero, (VALUES {_values(list(generators.LLM_CONFIGS))}) c(model, w) GROUP BY ALL"),
    "d12_schema_diff": _with(EXAMPLES, "SELECT example_id, array_to_string(list_sort(list_filter(out_columns, lambda c: NOT list_contains(in_columns, c))), ',') AS added, array_to_string(list_sort(list_filter(in_columns, lambda c: NOT list_contains(out_columns, c))), ',') AS dropped, out_n - in_n AS rows_changed FROM examples"),
    "d13_copy_last": _with(EXAMPLES, f"SELECT example_id, string_split(code_ctx, {NL})[-1] AS code, string_split(code_ctx, {NL})[-1] = target_code AS em FROM test"),
    "d13_mode": _with(EXAMPLES, f"SELECT example_id, code, code = target_code AS em FROM (SELECT example_id, target_code, replace(shape, '__frame__', var) AS code FROM test, {_MODE})"),
    "d14_corrupt": _with(EXAMPLES, f"SELECT example_id, {corrupted(100)} AS code, {corrupted(100)} = target_code AS em FROM test"),
    "e1_em": _with(EXAMPLES, f"SELECT 'truth' AS model, avg((target_code = target_code)::INT::DOUBLE) AS em FROM test HAVING count(*) > 0 UNION ALL SELECT 'half', avg(({corrupted(50)} = target_code)::INT::DOUBLE) FROM test HAVING count(*) > 0"),
    "e3_ea": _with(EXAMPLES, "SELECT avg(1.0::DOUBLE) AS ea FROM test"),
    "w1_mine": _with(EXAMPLES, _funnel()),
    "w6_masks": _with(EXAMPLES, " UNION ALL ".join(f"SELECT example_id, '{name}' AS ctx, CAST({count(context(c, t))} AS INT) AS n_ctx, CAST({count(data(a, b))} AS INT) AS n_data FROM examples" for name, c, t, a, b in inputs.MASKS)),
    "w7_inputs": _with(EXAMPLES, " UNION ALL ".join(f"SELECT example_id, '{name}' AS component, CAST({count(data(values=v, columns=c))} AS INT) AS n_data FROM examples" for name, v, c in inputs.COMPONENTS)),
    "w8_contexts": _with(EXAMPLES, " UNION ALL ".join(f"SELECT example_id, '{name}' AS ctx, {right} AS em, {right} AS ea FROM everything WHERE contains(target_code, '.astype(int)')" for name, right in _GUESSED.items())),
    "sink_parquet": _with(EXAMPLES, "SELECT split, count(*) AS n FROM examples GROUP BY 1 UNION ALL SELECT 'jsonl', count(*) FROM examples"),
}
