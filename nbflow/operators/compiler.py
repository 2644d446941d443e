"""Wrangling code compiled to one Spark plan: the native path of replay, for frames of any size.

``compile_ops`` reads pandas statements on one variable and gives a list of operations; ``apply_ops`` turns them
into a lazy frame. Steps are not run one after another as a notebook would: Catalyst sees all of them, so
filters reach the scan and columns that nobody reads are not read. What isn't recognized raises
``Unsupported``, and the caller replays in the sandbox instead. A scalar given to ``fillna`` fills the columns of
its own type only, as a column has one type here. Order is kept by ``sort_values`` alone.
"""

from __future__ import annotations

import ast
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from nbflow.operators import native


class Unsupported(Exception):
    """A statement that has no native form here."""


@dataclass
class WrangleOp:
    name: str
    args: dict = field(default_factory=dict)


_COMPARE = {ast.Gt: lambda a, b: a > b, ast.GtE: lambda a, b: a >= b, ast.Lt: lambda a, b: a < b, ast.LtE: lambda a, b: a <= b, ast.Eq: lambda a, b: a == b, ast.NotEq: lambda a, b: a != b}
_ARITHMETIC = {ast.Add: lambda a, b: a + b, ast.Sub: lambda a, b: a - b, ast.Mult: lambda a, b: a * b, ast.Div: F.try_divide}
_CASTS = {"float": "double", "int": "long", "str": "string"}


def _constant(node: ast.AST, known: dict):
    if isinstance(node, ast.Name) and node.id in known:
        return known[node.id]
    if isinstance(node, ast.Name) and node.id in _CASTS:
        return node.id
    try:
        return ast.literal_eval(node)
    except (ValueError, SyntaxError, TypeError) as error:
        raise Unsupported(ast.dump(node)[:80]) from error


def _column_name(node: ast.AST, var: str) -> str | None:
    if isinstance(node, ast.Subscript) and isinstance(node.value, ast.Name) and node.value.id == var and isinstance(node.slice, ast.Constant) and isinstance(node.slice.value, str):
        return node.slice.value
    return None


def expression(node: ast.AST, var: str, known: dict) -> Column:
    """A column expression over the frame ``var``."""
    if (name := _column_name(node, var)) is not None:
        return F.col(f"`{name}`")
    if isinstance(node, ast.BinOp) and type(node.op) in _ARITHMETIC:
        return _ARITHMETIC[type(node.op)](expression(node.left, var, known), expression(node.right, var, known))
    if isinstance(node, ast.BinOp) and isinstance(node.op, (ast.BitAnd, ast.BitOr)):
        a, b = expression(node.left, var, known), expression(node.right, var, known)
        return a & b if isinstance(node.op, ast.BitAnd) else a | b
    if isinstance(node, ast.UnaryOp) and isinstance(node.op, ast.Invert):
        return ~expression(node.operand, var, known)
    if isinstance(node, ast.Compare) and len(node.ops) == 1 and type(node.ops[0]) in _COMPARE:
        compared = _COMPARE[type(node.ops[0])](expression(node.left, var, known), expression(node.comparators[0], var, known))
        return F.coalesce(compared, F.lit(isinstance(node.ops[0], ast.NotEq)))  # a missing value compares as False, and differs from all
    if isinstance(node, ast.Call) and isinstance(node.func, ast.Attribute):
        args = node.args
        if isinstance(node.func.value, ast.Attribute) and node.func.value.attr == "str":
            inner = expression(node.func.value.value, var, known)
            if node.func.attr in ("upper", "lower", "strip", "len"):
                return {"upper": F.upper, "lower": F.lower, "strip": F.trim, "len": F.length}[node.func.attr](inner)
            if node.func.attr == "contains" and len(args) == 1:
                return F.contains(inner, F.lit(_constant(args[0], known)))
            raise Unsupported(node.func.attr)
        inner = expression(node.func.value, var, known)
        if node.func.attr == "astype" and len(args) == 1:
            kind = _constant(args[0], known)
            return inner.cast(_CASTS.get(kind, kind))
        if node.func.attr == "round":
            return F.bround(inner, _constant(args[0], known) if args else 0)
        if node.func.attr == "fillna" and len(args) == 1:
            return F.coalesce(inner, F.lit(_constant(args[0], known)))
        if node.func.attr in ("isna", "isnull", "notna", "notnull") and not args:
            return inner.isNull() if node.func.attr in ("isna", "isnull") else inner.isNotNull()
        if node.func.attr == "isin" and len(args) == 1:
            return F.coalesce(inner.isin(list(_constant(args[0], known))), F.lit(False))
        if node.func.attr == "between" and len(args) == 2:
            return inner.between(*(_constant(a, known) for a in args))
        raise Unsupported(node.func.attr)
    return F.lit(_constant(node, known))


def _method(call: ast.Call, known: dict) -> WrangleOp:
    name = call.func.attr
    args, named = call.args, {k.arg: k.value for k in call.keywords if k.arg != "inplace"}
    value = lambda key, at, default=None: _constant(args[at], known) if len(args) > at else _constant(named[key], known) if key in named else default
    many = lambda x: [x] if isinstance(x, str) else x
    if name == "dropna":
        return WrangleOp("dropna", {"subset": many(value("subset", 9)), "how": value("how", 9, "any")})
    if name == "fillna":
        return WrangleOp("fillna", {"value": value("value", 0)})
    if name == "drop_duplicates":
        return WrangleOp("drop_duplicates", {"subset": many(value("subset", 0))})
    if name == "rename" and "columns" in named:
        return WrangleOp("rename", {"names": value("columns", 9)})
    if name == "drop" and ("columns" in named or (args and _constant(named.get("axis", ast.Constant(0)), known) in (1, "columns"))):
        return WrangleOp("drop", {"names": many(value("columns", 0))})
    if name == "sort_values":
        return WrangleOp("sort", {"by": many(value("by", 0)), "ascending": value("ascending", 9, True)})
    if name == "head":
        return WrangleOp("head", {"n": value("n", 0, 5)})
    if name == "reset_index":
        return WrangleOp("reset_index")
    if name == "astype":
        return WrangleOp("astype", {"kinds": value("dtype", 0)})
    if name == "melt":
        return WrangleOp("melt", {"ids": many(value("id_vars", 0)), "values": many(value("value_vars", 1))})
    if name == "query":
        return WrangleOp("query", {"text": value("expr", 0)})
    raise Unsupported(name)


def _chain(node: ast.AST, var: str, known: dict) -> list[WrangleOp]:
    """Operations of a chain that starts at the variable, in time."""
    if isinstance(node, ast.Name) and node.id == var:
        return []
    if isinstance(node, ast.Call) and isinstance(node.func, ast.Attribute):
        inner = node.func.value
        if node.func.attr in ("sum", "mean", "max", "min", "count") and isinstance(inner, ast.Subscript) and isinstance(inner.value, ast.Call) and isinstance(inner.value.func, ast.Attribute) and inner.value.func.attr == "groupby":
            group = inner.value
            keys, columns = _constant(group.args[0], known), _constant(inner.slice, known)
            many = lambda x: [x] if isinstance(x, str) else list(x)
            return [*_chain(group.func.value, var, known), WrangleOp("groupby", {"keys": many(keys), "columns": many(columns), "measure": node.func.attr})]
        return [*_chain(inner, var, known), _method(node, known)]
    if isinstance(node, ast.Subscript):
        before = _chain(node.value, var, known)
        if isinstance(node.slice, ast.List):
            return [*before, WrangleOp("select", {"names": _constant(node.slice, known)})]
        if before:
            raise Unsupported("filter after a step")
        return [WrangleOp("filter", {"condition": node.slice, "known": known, "var": var})]
    if isinstance(node, ast.BinOp) and type(node.op) in _ARITHMETIC:
        return [*_chain(node.left, var, known), WrangleOp("scale", {"op": type(node.op), "by": _constant(node.right, known)})]
    raise Unsupported(type(node).__name__)


def compile_ops(code: str, var: str, known: dict | None = None) -> list[WrangleOp]:
    """The operations of ``code`` on ``var``; ``known``: values of other names, to which assigned constants are added."""
    known, out = dict(known or {}), []
    for s in ast.parse(code).body:
        if isinstance(s, ast.Assign) and len(s.targets) == 1:
            target = s.targets[0]
            if isinstance(target, ast.Name) and target.id == var:
                out += _chain(s.value, var, known)
                continue
            if (name := _column_name(target, var)) is not None:
                if isinstance(s.value, ast.Call) and isinstance(s.value.func, ast.Attribute) and s.value.func.attr == "qcut" and (source := _column_name(s.value.args[0], var)):
                    out.append(WrangleOp("qcut", {"column": source, "q": _constant(s.value.args[1], known), "out": name}))
                else:
                    out.append(WrangleOp("assign", {"out": name, "value": s.value, "known": dict(known), "var": var}))
                continue
            if isinstance(target, ast.Name):
                known[target.id] = _constant(s.value, known)
                continue
        elif isinstance(s, ast.Expr) and isinstance(s.value, ast.Call) and isinstance(s.value.func, ast.Attribute) and any(k.arg == "inplace" for k in s.value.keywords):
            out += _chain(s.value, var, known)
            continue
        elif isinstance(s, ast.Delete) and (name := _column_name(s.targets[0], var)) is not None:
            out.append(WrangleOp("drop", {"names": [name]}))
            continue
        raise Unsupported(ast.unparse(s)[:80])
    return out


def _apply(df: DataFrame, op: WrangleOp) -> DataFrame:
    a = op.args
    if op.name == "dropna":
        return native.dropna(df, a["subset"], a["how"])
    if op.name == "fillna":
        return df.na.fill(a["value"])
    if op.name == "drop_duplicates":
        subset = a["subset"] or df.columns
        return native.drop_duplicates(df, subset, [c for c in df.columns if c not in subset] or subset)
    if op.name == "rename":
        return native.rename(df, a["names"])
    if op.name == "drop":
        missing = [c for c in a["names"] if c not in df.columns]
        if missing:
            raise KeyError(missing)
        return df.drop(*a["names"])
    if op.name == "select":
        return df.select(*a["names"])
    if op.name == "sort":
        ascending = a["ascending"] if isinstance(a["ascending"], list) else [a["ascending"]] * len(a["by"])
        return df.orderBy(*[F.col(c).asc_nulls_last() if up else F.col(c).desc_nulls_last() for c, up in zip(a["by"], ascending, strict=True)])
    if op.name == "head":
        return df.limit(a["n"])
    if op.name == "reset_index":
        return df
    if op.name == "astype":
        kinds = a["kinds"] if isinstance(a["kinds"], dict) else {c: a["kinds"] for c in df.columns}
        return df.withColumns({c: F.col(c).cast(_CASTS.get(k, k)) for c, k in kinds.items()})
    if op.name == "melt":
        return native.melt(df, a["ids"], a["values"])
    if op.name == "query":
        return df.filter(a["text"])
    if op.name == "filter":
        return df.filter(expression(a["condition"], a["var"], a["known"]))
    if op.name == "assign":
        return df.withColumn(a["out"], expression(a["value"], a["var"], a["known"]))
    if op.name == "qcut":
        return native.qcut(df, a["column"], a["q"], a["out"])
    if op.name == "scale":
        return df.select(*[_ARITHMETIC[a["op"]](F.col(c), F.lit(a["by"])).alias(c) for c in df.columns])
    if op.name == "groupby":
        measure = {"sum": F.sum, "mean": F.avg, "max": F.max, "min": F.min, "count": F.count}[a["measure"]]
        return df.groupBy(*a["keys"]).agg(*[measure(c).alias(c) for c in a["columns"]])
    raise Unsupported(op.name)


def apply_ops(df: DataFrame, ops: list[WrangleOp]) -> DataFrame:
    return reduce(_apply, ops, df)
