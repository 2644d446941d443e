"""Accuracy of generated code: exact match, the four parts of CodeBLEU, and their mean.

Plain functions over two strings, and Arrow UDFs of them for frames. Choices where the definition is open:
scores are means over examples; an edge-less reference graph gives 1 if the candidate has none either, else
0; code that can't be parsed scores 0 on structure and data flow; n-grams above one are smoothed by one.
"""

from __future__ import annotations

import keyword
import math
from collections import Counter

import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DoubleType, StringType, StructField, StructType

from nbflow.functions.parsing import code_tokens, dataflow, subtrees

#: Weights of keywords and of other tokens in the weighted n-gram match (fixed values).
KEYWORD_WEIGHT, OTHER_WEIGHT = 1.0, 0.2
PARTS = ("ngram", "weighted", "syntax", "dataflow")


def _precision(reference: list[str], candidate: list[str], n: int, weigh) -> tuple[float, float]:
    grams = lambda t: Counter(tuple(t[i : i + n]) for i in range(len(t) - n + 1))
    have, want = grams(candidate), grams(reference)
    weight = (lambda g: weigh(g[0])) if n == 1 else (lambda g: 1.0)
    return sum(min(c, want[g]) * weight(g) for g, c in have.items()), sum(c * weight(g) for g, c in have.items())


def _bleu(reference: list[str], candidate: list[str], weigh, smoothing: str = "add1", most: int = 4) -> float:
    if not reference or not candidate:
        return float(reference == candidate)
    logs = []
    for n in range(1, most + 1):
        hit, all_ = _precision(reference, candidate, n, weigh)
        if n > 1 and smoothing == "add1":
            hit, all_ = hit + 1, all_ + 1
        if hit == 0 or all_ == 0:
            return 0.0
        logs.append(math.log(hit / all_))
    short = min(0.0, 1 - len(reference) / len(candidate))
    return math.exp(short + sum(logs) / most)


def ngram_match(reference: str, candidate: str, smoothing: str = "add1") -> float:
    return _bleu(code_tokens(reference), code_tokens(candidate), lambda t: 1.0, smoothing)


def weighted_ngram_match(reference: str, candidate: str, smoothing: str = "add1") -> float:
    return _bleu(code_tokens(reference), code_tokens(candidate), lambda t: KEYWORD_WEIGHT if keyword.iskeyword(t) else OTHER_WEIGHT, smoothing)


def _clipped(reference: list[str] | None, candidate: list[str] | None) -> float:
    if candidate is None or reference is None:
        return 0.0
    if not reference:
        return float(not candidate)
    want, have = Counter(reference), Counter(candidate)
    return sum(min(c, have[x]) for x, c in want.items()) / sum(want.values())


def ast_match(reference: str, candidate: str) -> float:
    return _clipped(subtrees(reference), subtrees(candidate))


def dataflow_match(reference: str, candidate: str) -> float:
    return _clipped(dataflow(reference), dataflow(candidate))


def code_bleu_parts(reference: str, candidate: str) -> tuple[float, float, float, float]:
    return ngram_match(reference, candidate), weighted_ngram_match(reference, candidate), ast_match(reference, candidate), dataflow_match(reference, candidate)


def code_bleu(reference: str, candidate: str, weights: tuple[float, ...] = (0.25,) * 4) -> float:
    return sum(w * p for w, p in zip(weights, code_bleu_parts(reference, candidate), strict=True))


@F.pandas_udf(StructType([StructField(p, DoubleType()) for p in PARTS]))
def code_bleu_udf(reference: pd.Series, candidate: pd.Series) -> pd.DataFrame:
    return pd.DataFrame([code_bleu_parts(r or "", c or "") for r, c in zip(reference, candidate, strict=True)], columns=list(PARTS), index=reference.index)


@F.pandas_udf(ArrayType(StringType()))
def subtrees_udf(code: pd.Series) -> pd.Series:
    return code.map(lambda c: subtrees(c or "") or [])


@F.pandas_udf(ArrayType(StringType()))
def tokens_udf(code: pd.Series) -> pd.Series:
    return code.map(lambda c: code_tokens(c or ""))


@F.pandas_udf(DoubleType())
def corpus_bleu_udaf(reference: pd.Series, candidate: pd.Series) -> float:
    """The n-gram match of a whole group: counts are added up before they are divided (for groups of bounded size)."""
    hits, alls, short_ref, short_cand = [0.0] * 4, [0.0] * 4, 0, 0
    for r, c in zip(reference, candidate, strict=True):
        a, b = code_tokens(r or ""), code_tokens(c or "")
        short_ref, short_cand = short_ref + len(a), short_cand + len(b)
        for n in range(4):
            hit, all_ = _precision(a, b, n + 1, lambda t: 1.0)
            hits[n], alls[n] = hits[n] + hit, alls[n] + all_
    if not short_cand or not all(hits):
        return 0.0
    return math.exp(min(0.0, 1 - short_ref / short_cand) + sum(math.log(h / a) for h, a in zip(hits, alls, strict=True)) / 4)
