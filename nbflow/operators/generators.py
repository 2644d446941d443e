"""Stand-in code generators behind one interface.

No pretrained weights are at hand, so each model family is stood in for by a small method that shares its
data path: what it sees of an example, and how much of it. Every generator has ``fit(train) -> model`` and
``model.generate(examples) -> (example_id, code)``; ``ExternalGenerator`` plugs in a real model instead. The
scores of stand-ins are ours and are never shown as those of the models they stand for.
"""

from __future__ import annotations

import math
import re
from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, FloatType, StringType

from nbflow.functions.parsing import dataflow, subtrees
from nbflow.operators import inputs
from nbflow.session import discard, many_tasks, settle

DIM = 256
#: Query vectors of one block and pool vectors of one part in a search.
BLOCK, PART = 2048, 8192


def renamed(code: str, old: str, new: str) -> str:
    return re.sub(rf"\b{re.escape(old)}\b", new, code)


@F.pandas_udf(StringType())
def renamed_udf(code: pd.Series, old: pd.Series, new: pd.Series) -> pd.Series:
    return pd.Series([renamed(c, o, n) if c is not None else "" for c, o, n in zip(code, old, new, strict=True)], index=code.index)


def hashed(words: Column, dim: int = DIM) -> Column:
    return F.transform(words, lambda w: F.pmod(F.xxhash64(w), F.lit(dim)).cast("int"))


def bucket_weights(rows: DataFrame, column: str, dim: int = DIM) -> np.ndarray:
    """Inverse document frequency by bucket: one aggregate of at most ``dim`` rows."""
    n = max(1, rows.count())
    seen = rows.select(F.explode(F.array_distinct(column)).alias("b")).groupBy("b").agg(F.count("*").alias("n")).collect()
    out = np.full(dim, math.log(1 + n))
    for r in seen:
        out[r["b"]] = math.log(1 + n / (1 + r["n"]))
    return out


def encoder(weights: np.ndarray):
    """An Arrow UDF from buckets to a unit vector."""

    @F.pandas_udf(ArrayType(FloatType()))
    def encode(buckets: pd.Series) -> pd.Series:
        def one(b):
            v = np.log1p(np.bincount(np.asarray(b if b is not None else [], dtype=int), minlength=len(weights))) * weights
            norm = np.linalg.norm(v)
            return (v / norm if norm else v).astype(np.float32)

        return buckets.map(one)

    return encode


def nearest(queries: DataFrame, pool: DataFrame, k: int = 1) -> DataFrame:
    """(example_id, id, score): the k pool rows (id, vec) of largest inner product for each query (example_id, vec).

    Blocks of queries meet parts of the pool, each pair one matrix product; a part sends on k rows per query.
    Exact; work is queries times pool, and nothing grows on the driver."""
    q_blocks, p_parts = max(1, -(-queries.count() // BLOCK)), max(1, -(-pool.count() // PART))
    q = queries.groupBy(F.pmod(F.xxhash64("example_id"), F.lit(q_blocks)).alias("qb")).agg(F.collect_list("example_id").alias("q_ids"), F.flatten(F.collect_list("vec")).alias("q_vecs"))
    p = pool.groupBy(F.pmod(F.xxhash64("id"), F.lit(p_parts)).alias("pp")).agg(F.collect_list("id").alias("p_ids"), F.flatten(F.collect_list("vec")).alias("p_vecs"))

    @F.pandas_udf("array<struct<example_id: string, id: string, score: double>>")
    def top(q_ids: pd.Series, q_vecs: pd.Series, p_ids: pd.Series, p_vecs: pd.Series) -> pd.Series:
        out = []
        for a, x, b, y in zip(q_ids, q_vecs, p_ids, p_vecs, strict=True):
            scores = np.round(np.asarray(x, np.float64).reshape(len(a), -1) @ np.asarray(y, np.float64).reshape(len(b), -1).T, 9)
            b = np.asarray(b, dtype=object)
            by_name = np.argsort(b.astype(str), kind="stable")
            order = by_name[np.argsort(-scores[:, by_name], axis=1, kind="stable")[:, :k]]
            out.append([{"example_id": a[i], "id": str(b[j]), "score": float(scores[i, j])} for i in range(len(a)) for j in order[i]])
        return pd.Series(out)

    found = q.crossJoin(p).select(F.explode(top("q_ids", "q_vecs", "p_ids", "p_vecs")).alias("x")).select("x.*")
    best = found.groupBy("example_id").agg(F.slice(F.array_sort(F.collect_list(F.struct((-F.col("score")).alias("minus"), "id"))), 1, k).alias("best"))
    return best.select("example_id", F.explode("best").alias("b")).select("example_id", F.col("b.id").alias("id"), (-F.col("b.minus")).alias("score"))


def _copied(found: DataFrame, examples: DataFrame, train: DataFrame, mask: tuple = inputs.MASKS[0]) -> DataFrame:
    """The targets found, with the example's variable in place of theirs; only the code shows what that is called, so
    under a mask without code they stay as they are."""
    shown = train.select(F.col("example_id").alias("id"), "target_code", F.col("var").alias("old"))
    rows = found.join(shown, "id").join(examples.select("example_id", F.col("var").alias("new")), "example_id")
    return rows.select("example_id", (renamed_udf("target_code", "old", "new") if mask[1] else F.col("target_code")).alias("code"))


# --- features of a joint encoder's variants


@F.pandas_udf(ArrayType(StringType()))
def _flow(code: pd.Series) -> pd.Series:
    return code.map(lambda c: dataflow(c or "") or [])


@F.pandas_udf(ArrayType(StringType()))
def _shapes(code: pd.Series) -> pd.Series:
    return code.map(lambda c: subtrees(c or "") or [])


def joint_words(examples: DataFrame, features: str, mask, parts: dict) -> DataFrame:
    """(example_id, words): what a single encoder sees within its one budget, and what its variant adds.

    plain: tokens; dataflow: and edges from definitions to uses; ast: and shapes of subtrees; identifier: names
    count three times; denoise: tokens with one in seven masked, as if restored from noise."""
    base = inputs.serialize_joint(examples, 256, 256, mask, **parts).select("example_id", "ctx_tokens", "data_tokens")
    words = F.concat("ctx_tokens", "data_tokens")
    if features in ("dataflow", "ast"):
        code = examples.select("example_id", inputs.context_text(mask[1], 0).alias("code"))
        more = _flow("code") if features == "dataflow" else _shapes("code")
        return base.join(code.select("example_id", more.alias("more")), "example_id").select("example_id", F.concat(words, "more").alias("words"))
    if features == "identifier":
        names = F.filter("ctx_tokens", lambda w: w.rlike("^[A-Za-z_]\\w*$"))
        return base.select("example_id", F.concat(words, names, names).alias("words"))
    if features == "denoise":
        return base.select("example_id", F.transform(words, lambda w, i: F.when(F.pmod(i, F.lit(7)) == 3, F.lit("<mask>")).otherwise(w)).alias("words"))
    return base.select("example_id", words.alias("words"))


@dataclass
class JointRetriever:
    """One encoder over context and data within one budget; generates the nearest training target, renamed."""

    features: str = "plain"
    mask: tuple = inputs.MASKS[0]
    parts: dict = field(default_factory=dict)

    def vectors(self, examples: DataFrame, weights=None):
        rows = joint_words(examples, self.features, self.mask, self.parts).select("example_id", hashed(F.col("words")).alias("b"))
        weights = bucket_weights(rows, "b") if weights is None else weights
        return rows.select("example_id", encoder(weights)("b").alias("vec")), weights

    def fit(self, train: DataFrame) -> JointRetriever:
        self.train = train
        self.pool, self.weights = self.vectors(train)
        return self

    def generate(self, examples: DataFrame) -> DataFrame:
        queries, _ = self.vectors(examples, self.weights)
        return _copied(nearest(queries, self.pool.withColumnRenamed("example_id", "id")), examples, self.train, self.mask)


@dataclass
class TwoTowerRetriever:
    """Two encoders, one for context and one for data, each with a budget of its own; their states are put side by
    side. ``balance`` weighs the first and is tuned on the dev split, one job per value, until it stops helping."""

    balance: float = 0.5
    mask: tuple = inputs.MASKS[0]
    parts: dict = field(default_factory=dict)

    def vectors(self, examples: DataFrame, weights=None):
        rows = inputs.serialize_dual(examples, 512, 512, self.mask, **self.parts)
        rows = rows.select("example_id", hashed(F.col("ctx_tokens")).alias("c"), hashed(F.col("data_tokens")).alias("d"))
        weights = (bucket_weights(rows, "c"), bucket_weights(rows, "d")) if weights is None else weights
        rows = rows.select("example_id", encoder(weights[0])("c").alias("c"), encoder(weights[1])("d").alias("d"))
        scaled = lambda c, w: F.transform(c, lambda x: (x * math.sqrt(w)).cast("float"))
        return rows.select("example_id", F.concat(scaled("c", self.balance), scaled("d", 1 - self.balance)).alias("vec")), weights

    def fit(self, train: DataFrame, dev: DataFrame | None = None, patience: int = 1) -> TwoTowerRetriever:
        self.train = train
        if dev is not None:
            best, worse = -1.0, 0
            for balance in (0.2, 0.4, 0.5, 0.6, 0.8):
                trial = TwoTowerRetriever(balance, self.mask, self.parts).fit(train)
                score = trial.generate(dev).join(dev.select("example_id", "target_code"), "example_id").agg(F.avg((F.col("code") == F.col("target_code")).cast("double"))).first()[0] or 0.0
                if score > best:
                    best, worse, self.balance = score, 0, balance
                else:
                    worse += 1
                    if worse > patience:
                        break
        self.pool, self.weights = self.vectors(train)
        return self

    def generate(self, examples: DataFrame) -> DataFrame:
        queries, _ = self.vectors(examples, self.weights)
        return _copied(nearest(queries, self.pool.withColumnRenamed("example_id", "id")), examples, self.train, self.mask)


@dataclass
class PromptCopy:
    """A prompted model's stand-in: of its k demonstrations it answers with the one most like the example, by the tokens
    of what the mask and the parts of frames leave of both; with none, with the last context cell it sees."""

    k: int = 2
    seed: str = ""
    mask: tuple = inputs.MASKS[0]
    parts: dict = field(default_factory=dict)

    def fit(self, train: DataFrame) -> PromptCopy:
        self.train = train
        return self

    def generate(self, examples: DataFrame) -> DataFrame:
        if not self.k:
            return CopyLast(self.mask).fit(self.train).generate(examples)
        _, code, text, a, b = self.mask
        demos = inputs.ring_demos(self.train, examples, self.k, self.seed)
        seen = F.array_distinct(inputs.tokens(F.concat_ws("\n", inputs.context_text(code, text), inputs.data_text(a, b, **self.parts))))
        rows = demos.join(examples.select("example_id", seen.alias("a")), "example_id").join(self.train.select(F.col("example_id").alias("demo_id"), seen.alias("b")), "demo_id")
        alike = F.coalesce(F.try_divide(F.size(F.array_intersect("a", "b")), F.size(F.array_union("a", "b"))), F.lit(0.0))
        best = rows.groupBy("example_id").agg(F.min_by("demo_id", F.struct(-alike, F.col("demo_rank"))).alias("id"))
        return _copied(best, examples, self.train, self.mask)


@dataclass
class LowRankHead:
    """Frozen features and a trained low-rank map (two factors) to classes of targets: training targets with the
    variable left out. An epoch is one pass: each task takes steps over batches of its rows from the factors it is given,
    and the driver averages the tasks' factors by their rows. Factors and classes are all that the driver holds; no
    training row is left out. With ``dev``, training ends once the loss on it has not fallen for ``patience`` epochs."""

    rank: int = 8
    epochs: int = 5
    batch: int = 3
    rate: float = 0.1
    patience: int = 1
    mask: tuple = inputs.MASKS[0]
    parts: dict = field(default_factory=dict)

    def _rows(self, examples: DataFrame, vectors: DataFrame, number: DataFrame) -> DataFrame:
        shape = renamed_udf(F.col("target_code"), F.col("var"), F.lit("__frame__"))
        return vectors.join(examples.select("example_id", shape.alias("shape")), "example_id").join(number, "shape").select("example_id", "vec", "label")

    def fit(self, train: DataFrame, dev: DataFrame | None = None) -> LowRankHead:
        self.frozen = JointRetriever("plain", self.mask, self.parts).fit(train)
        shape = renamed_udf(F.col("target_code"), F.col("var"), F.lit("__frame__"))
        counts = train.select(shape.alias("shape")).groupBy("shape").agg(F.count("*").alias("n")).orderBy(F.col("n").desc(), "shape").collect()
        self.classes = [r["shape"] for r in counts]
        number = train.sparkSession.createDataFrame([(s, i) for i, s in enumerate(self.classes)], "shape string, label int")
        rows = settle(self._rows(train, self.frozen.pool, number), "features")
        held = settle(self._rows(dev, self.frozen.vectors(dev, self.frozen.weights)[0], number), "features") if dev is not None else None
        rng = np.random.default_rng(3)
        self.down, self.up = rng.normal(0, 0.3, (DIM, self.rank)), np.zeros((self.rank, len(self.classes)))
        self.losses, self.dev_losses, best, worse = [], [], None, 0
        for epoch in range(self.epochs):
            self.down, self.up, loss = self._epoch(rows, epoch, self.batch)
            self.losses.append(loss)
            if held is None:
                continue
            self.dev_losses.append(self._epoch(held, epoch, 0)[2])
            if best is None or self.dev_losses[-1] < best[0]:
                best, worse = (self.dev_losses[-1], self.down, self.up), 0
            else:
                worse += 1
                if worse > self.patience:
                    break
        if best is not None:
            _, self.down, self.up = best
        discard(rows, *([held] if held is not None else []))
        return self

    def _epoch(self, rows: DataFrame, epoch: int, batch: int):
        """(down, up, mean loss) after a pass; with no batch size, of the factors as they are."""
        start, rate = (self.down, self.up), self.rate

        def losses(x, y, down, up):
            h = x @ down
            s = h @ up
            p = np.exp(s - s.max(1, keepdims=True))
            p /= p.sum(1, keepdims=True)
            return h, p, -float(np.log(p[np.arange(len(y)), y] + 1e-12).sum())

        def run(batches):
            down, up = start[0].copy(), start[1].copy()
            seen = [np.full(down.shape, 1e-8), np.full(up.shape, 1e-8)]
            loss, n = 0.0, 0
            for pdf in batches:
                pdf = pdf.sort_values("example_id")
                x, y = np.stack(pdf["vec"].to_numpy()).astype(float) if len(pdf) else np.zeros((0, DIM)), pdf["label"].to_numpy()
                order = np.random.default_rng(epoch).permutation(len(y)) if batch else np.arange(len(y))
                for part in np.array_split(order, max(1, -(-len(y) // (batch or 1024)))):
                    if not len(part):
                        continue
                    h, p, more = losses(x[part], y[part], down, up)
                    loss, n = loss + more, n + len(part)
                    if not batch:
                        continue
                    p[np.arange(len(part)), y[part]] -= 1
                    grads = x[part].T @ (p @ up.T) / len(part), h.T @ p / len(part)
                    for value, grad, acc in zip((down, up), grads, seen, strict=True):
                        acc += grad**2
                        value -= rate * grad / np.sqrt(acc)
            if n:
                yield pd.DataFrame([{"down": down.ravel().tolist(), "up": up.ravel().tolist(), "loss": loss, "n": n}])

        parts = rows.mapInPandas(run, "down array<double>, up array<double>, loss double, n long").collect()
        total = sum(p["n"] for p in parts)
        if not total:
            return *start, 0.0
        mean = lambda name, shape: np.sum([np.array(p[name]) * (p["n"] / total) for p in parts], axis=0).reshape(shape)
        return mean("down", start[0].shape), mean("up", start[1].shape), sum(p["loss"] for p in parts) / total

    def generate(self, examples: DataFrame) -> DataFrame:
        queries, _ = self.frozen.vectors(examples, self.frozen.weights)
        down, up, classes = self.down, self.up, self.classes

        @F.pandas_udf(StringType())
        def best(vec: pd.Series) -> pd.Series:
            x = np.stack(vec.to_numpy()).astype(float) if len(vec) else np.zeros((0, DIM))
            return pd.Series([classes[i] for i in (x @ down @ up).argmax(1)] if classes else [""] * len(vec), index=vec.index)

        rows = queries.select("example_id", best("vec").alias("shape")).join(examples.select("example_id", "var"), "example_id")
        return rows.select("example_id", renamed_udf(F.col("shape"), F.lit("__frame__"), F.col("var")).alias("code"))


#: What the indicator sketch supposes where its input doesn't show it (fixed values, as in the published case).
GUESSES = {"column": "Status", "flag": "M", "name": "is_status"}


@dataclass
class IndicatorSketch:
    """The case study's generator: the one program that turns a column of words into an indicator, with its three blanks
    (the column, the word, the new name) filled in from what it sees of the two frames, and guessed where it sees nothing.

    column: one that the input has and the output hasn't, by the headers; word: that of the input's values in the rows
    where the output's new column is one; name: a column that only the output has."""

    mask: tuple = inputs.MASKS[0]
    parts: dict = field(default_factory=dict)

    def fit(self, train: DataFrame) -> IndicatorSketch:
        return self

    def generate(self, examples: DataFrame) -> DataFrame:
        _, code, _, sees_in, sees_out = self.mask
        headers, values = self.parts.get("with_columns", True), self.parts.get("with_values", True)
        gone = F.get(F.array_except("in_frame.columns", "out_frame.columns"), F.lit(0))
        new = F.get(F.array_except("out_frame.columns", "in_frame.columns"), F.lit(0))
        at = lambda frame, name: (F.array_position(f"{frame}.columns", name) - 1).cast("int")
        pairs = F.arrays_zip(F.transform("in_frame.rows", lambda r: F.get(r, at("in_frame", gone))).alias("word"), F.transform("out_frame.rows", lambda r: F.get(r, at("out_frame", new))).alias("sign"))
        flag = F.get(F.filter(pairs, lambda p: p["sign"] == "1"), F.lit(0))["word"]
        shown = lambda seen, value, guess: F.coalesce(value if seen else F.lit(None).cast("string"), F.lit(GUESSES[guess]))
        column, name = shown(sees_in and headers, gone, "column"), shown(sees_out and headers, new, "name")
        flag = shown(sees_in and sees_out and values, flag, "flag")
        var = F.col("var") if code else F.lit("df")
        made = F.concat(var, F.lit("['"), name, F.lit("'] = ("), var, F.lit("['"), column, F.lit("'] == '"), flag, F.lit("').astype(int)\n"), var, F.lit(" = "), var, F.lit(".drop('"), column, F.lit("', axis=1)"))
        return examples.select("example_id", made.alias("code"))


@dataclass
class CopyLast:
    """Answers with the last line of the code context, if the mask leaves any."""

    mask: tuple = inputs.MASKS[0]

    def fit(self, train: DataFrame) -> CopyLast:
        return self

    def generate(self, examples: DataFrame) -> DataFrame:
        return examples.select("example_id", (F.element_at(F.split("code_ctx", "\n"), -1) if self.mask[1] else F.lit("")).alias("code"))


@dataclass
class ModeTarget:
    """Answers with the most frequent training target, renamed."""

    def fit(self, train: DataFrame) -> ModeTarget:
        shape = renamed_udf(F.col("target_code"), F.col("var"), F.lit("__frame__"))
        self.mode = train.select(shape.alias("shape")).groupBy("shape").agg(F.count("*").alias("n")).orderBy(F.col("n").desc(), "shape").limit(1)
        return self

    def generate(self, examples: DataFrame) -> DataFrame:
        return examples.select("example_id", "var").crossJoin(F.broadcast(self.mode)).select("example_id", renamed_udf(F.col("shape"), F.lit("__frame__"), F.col("var")).alias("code"))


# --- by example


def _steps(frame: pd.DataFrame, goal: list[str]):
    """(code with {v}, result) of catalogue steps that a frame allows, pruned by the goal's columns."""
    have = [str(c) for c in frame.columns]
    yield "{v} = {v}.dropna()", lambda f: f.dropna()
    yield "{v} = {v}.drop_duplicates()", lambda f: f.drop_duplicates()
    yield "{v} = {v}.fillna(0)", lambda f: f.fillna(0)
    yield "{v} = {v} * 2", lambda f: f * 2
    gone = [c for c in have if c not in goal]
    if gone and all(c in have for c in goal):
        yield f"{{v}} = {{v}}.drop(columns={gone!r})", lambda f: f.drop(columns=gone)
    if len(have) == len(goal):
        names = {a: b for a, b in zip(have, goal, strict=True) if a != b}
        if names:
            yield f"{{v}} = {{v}}.rename(columns={names!r})", lambda f: f.rename(columns=names)
    for c in have:
        yield f"{{v}} = {{v}}.sort_values({c!r})", lambda f, c=c: f.sort_values(c)
        yield f"{{v}} = {{v}}.sort_values({c!r}, ascending=False)", lambda f, c=c: f.sort_values(c, ascending=False)
        yield f"{{v}}[{c!r}] = {{v}}[{c!r}].str.upper()", lambda f, c=c: f.assign(**{c: f[c].str.upper()})
        yield f"{{v}}[{c!r}] = {{v}}[{c!r}].astype(float).round(1)", lambda f, c=c: f.assign(**{c: f[c].astype(float).round(1)})
    if goal == ["variable", "value"] or goal[-2:] == ["variable", "value"]:
        ids = goal[:-2]
        if all(c in have for c in ids):
            values = [c for c in have if c not in ids]
            yield f"{{v}} = {{v}}.melt(id_vars={ids!r}, value_vars={values!r})", lambda f: f.melt(id_vars=ids, value_vars=values)


def synthesize(frame_in: dict, frame_out: dict, max_len: int = 2) -> str | None:
    """The first sequence of at most ``max_len`` catalogue steps that turns the stored rows of one frame into those of
    the other; None if there is none. Only frames that are stored whole can be judged."""
    from nbflow.functions.sandbox import _cell

    def table(frame) -> pd.DataFrame:
        out = pd.DataFrame([list(r) for r in frame["rows"]], columns=list(frame["columns"]))
        for c, kind in zip(out.columns, frame["dtypes"], strict=True):
            if kind in ("int", "float"):
                out[c] = pd.to_numeric(out[c], errors="coerce")
                if kind == "float":
                    out[c] = out[c].astype(float)
        return out

    rows = lambda f: [[_cell(x) for x in r] for r in f.itertuples(index=False, name=None)]
    want, goal = rows(table(frame_out)), [str(c) for c in frame_out["columns"]]

    def programs(length: int):
        """All sequences of ``length`` steps that apply, one at a time: none is kept or left out."""
        if not length:
            yield "", table(frame_in)
            return
        for code, frame in programs(length - 1):
            for step, run in _steps(frame, goal):
                try:
                    made = run(frame)
                except Exception:  # noqa: S112  (a step that doesn't apply)
                    continue
                yield f"{code}\n{step}".strip(), made

    for length in range(1, max_len + 1):
        for code, made in programs(length):
            if [str(c) for c in made.columns] == goal and rows(made)[: len(want)] == want:
                return code
    return None


@dataclass
class ByExample:
    """Sees only the two frames: searches the catalogue for steps that map one to the other. Examples are few bytes and
    take long to search, so their number of tasks is given."""

    max_len: int = 2

    def fit(self, train: DataFrame) -> ByExample:
        return self

    def generate(self, examples: DataFrame) -> DataFrame:
        longest = self.max_len

        @F.pandas_udf(StringType())
        def search(frames: pd.DataFrame) -> pd.Series:
            return pd.Series([(synthesize(a, b, longest) or "").replace("{v}", v) for a, b, v in zip(frames["a"], frames["b"], frames["v"], strict=True)], index=frames.index)

        dealt = examples.select("example_id", "in_frame", "out_frame", "var").repartition(many_tasks(examples.sparkSession), "example_id")
        return dealt.select("example_id", search(F.struct(F.col("in_frame").alias("a"), F.col("out_frame").alias("b"), F.col("var").alias("v"))).alias("code"))


@dataclass
class ExternalGenerator:
    """A real model: ``make`` loads it once per task and gives a function from an array of prompts to codes."""

    make: Callable
    batch: int = 32

    def fit(self, train: DataFrame) -> ExternalGenerator:
        return self

    def generate(self, examples: DataFrame) -> DataFrame:
        from pyspark.ml.functions import predict_batch_udf

        answer = predict_batch_udf(self.make, return_type=StringType(), batch_size=self.batch)
        return inputs.build_prompt(examples).select("example_id", answer("prompt").alias("code"))


# --- errors of known kinds


def corrupt(examples: DataFrame, percent: int, kind: str = "rename_col") -> DataFrame:
    """(example_id, code): the targets, of which a share chosen by arithmetic has one seeded error: a misspelt
    column key, a changed number or flag, or a missing last step."""
    digest = F.substring(F.md5(F.concat(F.lit(kind), "example_id")), 1, 8)
    chosen = F.pmod(F.conv(digest, 16, 10).cast("long"), F.lit(100)) < percent
    code = F.col("target_code")
    wrong = {
        "rename_col": F.when(code.rlike(r"'\w+'"), F.regexp_replace(code, r"'(\w+)'", "'$1_x'")).otherwise(F.concat(code, F.lit("\n__missing__"))),
        "swap_literal": F.when(code.rlike(r"\d"), F.regexp_replace(code, r"\b(\d+)\b", "9$1")).otherwise(F.concat(code, F.lit("\n__missing__"))),
        "drop_stmt": F.when(F.size(F.split(code, "\n")) > 1, F.array_join(F.slice(F.split(code, "\n"), F.lit(1), F.size(F.split(code, "\n")) - 1), "\n")).otherwise(F.lit("pass")),
    }[kind]
    return examples.select("example_id", F.when(chosen, wrong).otherwise(code).alias("code"))


# --- sizes


def parameter_count(layers: int, d: int, f: int, vocab: int, towers: int) -> int:
    """Weights of an encoder-decoder with ``towers`` encoders: attention and feed-forward blocks and one embedding."""
    encoder_, decoder_ = layers * (4 * d * d + 2 * d * f), layers * (8 * d * d + 2 * d * f)
    return towers * encoder_ + decoder_ + vocab * d


def lora_param_count(layers: int, d: int, rank: int, matrices: int) -> int:
    """Weights of the two factors added to ``matrices`` square projections of each layer."""
    return layers * matrices * 2 * d * rank


#: Published model families (fixed values: names, sizes in billions of weights where stated, windows in tokens).
LLM_CONFIGS = (("StarCoder-15B", 8192), ("CodeLlama-34B", 16384), ("Phind-CodeLlama-34B", 16384), ("DeepSeek-Coder-33B", 16384), ("Codex", 8192), ("GPT 3.5", 4096), ("GPT 4", 8192))
PLM_CONFIGS = (("GraphCodeBERT", "dataflow"), ("CodeBERT", "plain"), ("UniXcoder", "ast"), ("PLBART", "denoise"), ("CodeT5", "identifier"))
LORA_CONFIGS = (("Deepseek-Coder-1.3B", 24, 2048), ("CodeGen-6B", 33, 4096), ("Mistral-7B-Instruct", 32, 4096), ("CodeLlama-7b-Python", 32, 4096), ("Deepseek-Coder-6.7B", 32, 4096))
