"""Statements of code cells and their facts, by the standard library's parser.

``parse_cell`` is plain Python and runs in Arrow batches (``parse_cells`` in ``nbflow.operators.mining``);
it is the one place where source text leaves the JVM. Everything after it is relational.
"""

from __future__ import annotations

import ast
import io
import re
import tokenize
from dataclasses import dataclass, field

_MAGIC = re.compile(r"^\s*[%!].*$", re.M)
_BINARY = {ast.Add: "+", ast.Sub: "-", ast.Mult: "*", ast.Div: "/"}
_PATH = re.compile(r"^[\w./~ -]+\.(csv|tsv|txt|json|xlsx?|parquet|pkl|h5|html?)$")


@dataclass
class Statement:
    kind: str
    defs: list[str] = field(default_factory=list)
    uses: list[str] = field(default_factory=list)
    base: str | None = None  # the variable that a store, deletion or expression starts from
    receiver: str | None = None  # first name of the outermost call's chain
    api: str | None = None  # last name of the outermost call's chain
    calls: list[tuple[str, str, list[str]]] = field(default_factory=list)  # (receiver, api, names used), in time
    inplace: bool = False
    store: str = "none"  # name, subscript, attr, none
    rhs_op: str | None = None  # operation on frames on the right: + - * / or []
    rhs_names: list[str] = field(default_factory=list)  # operands of that operation
    imports: list[tuple[str, str]] = field(default_factory=list)  # (alias, dotted name)
    literals: list[str] = field(default_factory=list)
    comments: list[str] = field(default_factory=list)
    src: str = ""


def stripped(source: str) -> str:
    """Magics and shell lines become blank, so line numbers stay."""
    return _MAGIC.sub("", source)


def comments_by_line(source: str) -> dict[int, str]:
    found = {}
    try:
        for token in tokenize.generate_tokens(io.StringIO(source).readline):
            if token.type == tokenize.COMMENT:
                found[token.start[0]] = token.string.lstrip("# ").rstrip()
    except (tokenize.TokenError, IndentationError, SyntaxError):
        pass
    return found


def _names(node: ast.AST, kind: type) -> list[str]:
    return list(dict.fromkeys(n.id for n in ast.walk(node) if isinstance(n, ast.Name) and isinstance(n.ctx, kind)))


def _root(node: ast.AST) -> str | None:
    """The first name of a chain of attributes, subscripts and calls."""
    while isinstance(node, (ast.Attribute, ast.Subscript, ast.Call)):
        node = node.func if isinstance(node, ast.Call) else node.value
    return node.id if isinstance(node, ast.Name) else None


def _api(func: ast.AST) -> str | None:
    return func.attr if isinstance(func, ast.Attribute) else func.id if isinstance(func, ast.Name) else None


def _calls(node: ast.AST) -> list[tuple[str, str, list[str]]]:
    """Calls in the order in which they run: arguments and receivers before the call itself."""
    out: list[tuple[str, str, list[str]]] = []

    def visit(n: ast.AST) -> None:
        for child in ast.iter_child_nodes(n):
            visit(child)
        if isinstance(n, ast.Call) and (api := _api(n.func)):
            out.append((_root(n.func) or "", api, _names(n, ast.Load)))

    visit(node)
    return out


def _inplace(node: ast.AST) -> bool:
    return any(isinstance(n, ast.keyword) and n.arg == "inplace" and isinstance(n.value, ast.Constant) and n.value.value is True for n in ast.walk(node))


def _operation(value: ast.AST) -> tuple[str | None, list[str]]:
    if isinstance(value, ast.BinOp) and type(value.op) in _BINARY:
        return _BINARY[type(value.op)], [x for x in (_root(value.left), _root(value.right)) if x]
    if isinstance(value, ast.Subscript):
        return "[]", [x for x in (_root(value.value),) if x]
    return None, []


def _statement(node: ast.stmt, source: str) -> Statement:
    s = Statement("other", src=ast.get_source_segment(source, node) or "")
    s.uses, s.calls, s.inplace = _names(node, ast.Load), _calls(node), _inplace(node)
    s.literals = [n.value for n in ast.walk(node) if isinstance(n, ast.Constant) and isinstance(n.value, str)]
    if isinstance(node, ast.Import):
        s.kind = "import"
        s.imports = [(a.asname or a.name.split(".")[0], a.name if a.asname else a.name.split(".")[0]) for a in node.names]
    elif isinstance(node, ast.ImportFrom):
        s.kind = "import"
        s.imports = [(a.asname or a.name, f"{node.module or ''}.{a.name}") for a in node.names]
    elif isinstance(node, (ast.Assign, ast.AnnAssign, ast.AugAssign)):
        s.kind = "augassign" if isinstance(node, ast.AugAssign) else "assign"
        targets = node.targets if isinstance(node, ast.Assign) else [node.target]
        s.defs = list(dict.fromkeys(n for t in targets for n in _names(t, ast.Store)))
        s.base = _root(targets[0])
        s.store = "subscript" if isinstance(targets[0], ast.Subscript) else "attr" if isinstance(targets[0], ast.Attribute) else "name"
        if isinstance(targets[0], ast.Attribute) and isinstance(targets[0].value, ast.Subscript):
            s.store = "subscript"
        if node.value is not None:
            s.rhs_op, s.rhs_names = _operation(node.value)
            s.uses = _names(node.value, ast.Load) + [n for t in targets for n in _names(t, ast.Load)]
            if isinstance(node.value, ast.Call):
                s.receiver, s.api = _root(node.value.func), _api(node.value.func)
        if isinstance(node, ast.AugAssign) and s.base:
            s.uses.append(s.base)
    elif isinstance(node, ast.Delete):
        s.kind, s.base = "del", _root(node.targets[0])
        s.store = "subscript" if isinstance(node.targets[0], ast.Subscript) else "attr" if isinstance(node.targets[0], ast.Attribute) else "name"
        s.defs = [n for t in node.targets for n in _names(t, ast.Del)]
    elif isinstance(node, ast.Expr):
        s.kind, s.base = "expr", _root(node.value)
        if isinstance(node.value, ast.Call):
            s.receiver, s.api = _root(node.value.func), _api(node.value.func)
        elif isinstance(node.value, ast.Name):
            s.api = "<bare>"
    else:  # a compound statement counts as one
        s.defs = _names(node, ast.Store)
    s.uses = list(dict.fromkeys(s.uses))
    return s


def parse_cell(source: str) -> list[Statement] | None:
    """The statements of a cell in order; None if it isn't Python."""
    source = stripped(source)
    try:
        tree = ast.parse(source)
    except (SyntaxError, ValueError, RecursionError):
        return None
    notes = comments_by_line(source)
    out, last = [], 0
    for node in tree.body:
        s = _statement(node, source)
        s.comments = [notes[line] for line in sorted(notes) if last < line <= (node.end_lineno or node.lineno)]
        last = node.end_lineno or node.lineno
        out.append(s)
    return out


def is_path(text: str) -> bool:
    """Whether a string literal looks like the path of a data file."""
    return bool(_PATH.match(text))


# --- structure of code, for the accuracy measures ------------------------------------------------------------


def subtrees(code: str) -> list[str] | None:
    """Every subtree of the syntax tree with names and constants left out; None if the code isn't Python."""
    try:
        tree = ast.parse(stripped(code))
    except (SyntaxError, ValueError, RecursionError):
        return None
    out: list[str] = []

    def shape(node: ast.AST) -> str:
        parts = [shape(c) for c in ast.iter_child_nodes(node) if not isinstance(c, (ast.Load, ast.Store, ast.Del))]
        text = type(node).__name__ + (f"({','.join(parts)})" if parts else "")
        if parts:
            out.append(text)
        return text

    shape(tree)
    return out


def dataflow(code: str) -> list[str] | None:
    """Edges 'definition<-source', with variables numbered by first appearance; None if the code isn't Python."""
    statements = parse_cell(code)
    if statements is None:
        return None
    number: dict[str, int] = {}
    edges = []
    for s in statements:
        for name in (*s.uses, *s.defs, *([s.base] if s.base else [])):
            number.setdefault(name, len(number))
        for d in s.defs or ([s.base] if s.store in ("subscript", "attr") and s.base else []):
            edges += [f"v{number[d]}<-v{number[u]}" for u in s.uses]
    return edges


def code_tokens(code: str) -> list[str]:
    """Python tokens without layout; of code that can't be tokenized, words and signs."""
    out = []
    try:
        for token in tokenize.generate_tokens(io.StringIO(code).readline):
            if token.type in (tokenize.NAME, tokenize.OP, tokenize.NUMBER, tokenize.STRING):
                out.append(token.string)
    except (tokenize.TokenError, IndentationError, SyntaxError):
        return re.findall(r"\w+|[^\w\s]", code)
    return out
