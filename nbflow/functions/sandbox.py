"""Running notebook code: one child process per notebook, with limits, inert plotting libraries and no files.

Only code that this engine rendered or generated runs here. The child may import an allow-listed set; data
files come from memory by their base name. Each cell has a time limit of its own. A candidate runs in a child of that
child, forked where its target begins, so it finds the notebook's state as it is there, and its failure, exit or endless
loop is no one else's.
"""

from __future__ import annotations

import ast
import hashlib
import io
import os
import pickle
import resource
import select
import signal
import sys
import time
import types

#: Libraries that answer every call with nothing (their names are fixed values).
INERT = ("matplotlib", "seaborn", "sklearn", "scipy", "nltk", "plotly", "statsmodels", "geopandas", "bokeh", "ggplot", "xgboost", "lightgbm", "patsy")
#: A statement's place is its cell's number times this, plus its number in the cell.
CELL_STEP = 1 << 32
ALLOWED = ("pandas", "numpy", "math", "re", "datetime", "json", "collections", "itertools", "functools", "statistics", "string", "random")


class _Inert(types.ModuleType):
    def __getattr__(self, name: str):
        if name.startswith("__"):
            raise AttributeError(name)
        return _Inert(name)

    def __call__(self, *args, **kwargs):
        return None


def _import(name, globals=None, locals=None, fromlist=(), level=0):
    top = name.split(".")[0]
    if top in INERT:
        return _Inert(name)
    if top in ALLOWED:
        return __import__(name, globals, locals, fromlist, level)
    raise ImportError(f"{name} is not in the sandbox")


def _namespace(files: dict[str, str]) -> dict:
    import builtins

    import pandas as pd

    def read_csv(path, *args, **kwargs):
        name = os.path.basename(str(path))
        if name not in files:
            raise FileNotFoundError(name)
        return _read(io.StringIO(files[name]), *args, **kwargs)

    for kind in (pd.DataFrame, pd.Series):  # plotting methods answer with nothing, as plotting libraries do
        kind.plot = _Inert("plot")
        kind.hist = lambda self, *args, **kwargs: None
    pd.DataFrame.boxplot = lambda self, *args, **kwargs: None
    _read = getattr(pd, "_plain_read_csv", pd.read_csv)
    pd._plain_read_csv, pd.read_csv = _read, read_csv
    blocked = {"open", "exec", "eval", "compile", "input", "breakpoint", "exit", "quit", "globals", "__import__"}
    safe = {k: v for k, v in vars(builtins).items() if k not in blocked} | {"__import__": _import, "print": lambda *a, **k: None}
    return {"__builtins__": safe, "__name__": "notebook"}


def snapshot(value, rows: int | None = 10) -> dict | None:
    """A frame as data: columns, types, number of rows, the first rows as text, and digests of all of it, in
    order (strict) and as a bag. None if the value is no frame."""
    import pandas as pd

    if isinstance(value, pd.Series):
        value = value.to_frame(value.name if value.name is not None else "0")
    if not isinstance(value, pd.DataFrame):
        return None
    text = [[_cell(x) for x in row] for row in value.itertuples(index=False, name=None)]
    columns, kinds = [str(c) for c in value.columns], [_kind(str(t)) for t in value.dtypes]
    head = "\x1f".join(columns) + "\x1e" + "\x1f".join(kinds)
    lines = ["\x1f".join("\x00" if x is None else x for x in row) for row in text]
    bag = sum(int.from_bytes(hashlib.md5(x.encode()).digest()[:7], "big") for x in lines) % (1 << 61)
    return {
        "columns": columns,
        "dtypes": kinds,
        "n_rows": len(text),
        "rows": text if rows is None else text[:rows],
        "strict": hashlib.md5((head + "\x1e" + "\x1e".join(lines)).encode()).hexdigest(),
        "bag": hashlib.md5((head + f"\x1e{bag}").encode()).hexdigest(),
    }


def _kind(dtype: str) -> str:
    return {"object": "string", "str": "string", "category": "string"}.get(dtype, dtype.rstrip("0123456789").replace("uint", "int"))


def _cell(x) -> str | None:
    if x is None or x != x:
        return None
    if isinstance(x, float):
        return repr(round(x, 6) + 0.0)
    return str(x)


def _statements(cells: list[tuple[int, str]], step: int):
    from nbflow.functions.parsing import stripped

    for idx, source in cells:
        tree = ast.parse(stripped(source))
        for i, node in enumerate(tree.body):
            yield idx * step + i, compile(ast.Module([node], []), f"cell {idx}", "exec")


class _OutOfTime(BaseException):
    """Raised in a cell whose time is up; no base class that notebook code would catch."""


def _timed(run, seconds: float):
    """Run a cell's statement with what is left of the cell's time."""

    def stop(*_):
        raise _OutOfTime

    before = signal.signal(signal.SIGALRM, stop)
    signal.setitimer(signal.ITIMER_REAL, max(seconds, 1e-3))
    try:
        run()
    finally:
        signal.setitimer(signal.ITIMER_REAL, 0)
        signal.signal(signal.SIGALRM, before)


def replay(cells, spans, files, seconds: float = 300, rows: int | None = 10) -> dict:
    """Run cells top to bottom, each for ``seconds`` at most. spans: (id, variable, begin, end, candidate or None). Result:
    per id the frames before and after; with a candidate, the frame after running it in place of the span. Raises on
    failure of the notebook; a candidate's failure is that span's error. After the last span the notebook runs on only
    if some span has no candidate, as then its failure matters."""
    space, out = _namespace(files), {}
    starts: dict[int, list] = {}
    for span in spans:
        starts.setdefault(span[2], []).append(span)
    open_: dict = {}
    last = max((s[2] for s in spans), default=-1) if all(s[4] is not None for s in spans) else None
    cell, left = None, seconds
    try:
        for pos, code in _statements(cells, CELL_STEP):
            if pos // CELL_STEP != cell:
                cell, left = pos // CELL_STEP, seconds
            for key in [k for k, (span, _) in open_.items() if pos == span[3]]:
                span, before = open_.pop(key)
                out[key] = {"before": before, "after": snapshot(space.get(span[1]), rows), "error": None}
            began = time.monotonic()
            _timed(lambda code=code: exec(code, space), left)
            left -= time.monotonic() - began
            for span in starts.get(pos, ()):
                key, name, _, _, candidate = span
                if candidate is None:
                    open_[key] = (span, snapshot(space.get(name), rows))
                else:
                    after, error = limited(lambda candidate=candidate, name=name: _after(candidate, name, space, rows), seconds, nested=True)
                    out[key] = {"before": None, "after": after, "error": error}
            if pos == last:
                break
    except _OutOfTime:
        raise TimeoutError from None
    return out


def _after(candidate: str, name: str, space: dict, rows: int | None):
    exec(compile(candidate, "candidate", "exec"), space)
    return snapshot(space.get(name), rows)


def limited(call, seconds: float, memory_mb: int = 4096, nested: bool = False):
    """(result, error name) of a call in a child process that is killed when its time is up. A nested one stays in its
    parent's group, so it goes when that goes."""
    read, write = os.pipe()
    pid = os.fork()
    if pid == 0:  # the child
        try:
            os.close(read)
            if not nested:
                os.setsid()
            soft, hard = resource.getrlimit(resource.RLIMIT_CPU)
            more = int(time.process_time() if nested else 0) + int(seconds) + 1
            resource.setrlimit(resource.RLIMIT_CPU, (more if hard < 0 else min(more, hard), more + 1 if hard < 0 else hard))
            resource.setrlimit(resource.RLIMIT_FSIZE, (0, 0))
            try:
                resource.setrlimit(resource.RLIMIT_AS, (memory_mb << 20, memory_mb << 20))
            except (ValueError, OSError):
                pass
            sys.stdout = sys.stderr = io.StringIO()
            try:
                data = pickle.dumps((call(), None))
            except BaseException as error:
                data = pickle.dumps((None, type(error).__name__))
            with os.fdopen(write, "wb") as pipe:
                pipe.write(data)
        finally:
            os._exit(0)
    os.close(write)
    parts, end = [], time.monotonic() + seconds
    try:
        while (left := end - time.monotonic()) > 0:
            if select.select([read], [], [], left)[0]:
                part = os.read(read, 1 << 16)
                if not part:
                    break
                parts.append(part)
        else:
            return None, "TimeoutError"
        return pickle.loads(b"".join(parts)) if parts else (None, "Killed")
    finally:
        os.close(read)
        try:
            os.kill(pid, signal.SIGKILL) if nested else os.killpg(pid, signal.SIGKILL)
        except OSError:
            pass
        os.waitpid(pid, 0)
