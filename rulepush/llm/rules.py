"""Operator 6: quality rules as a learned decision list.

Statistics of every whole text come from one Arrow pass. Sequential covering learns rules for rejected documents
from labelled statistics: each rule is a conjunction of thresholds grown by information gain on two thirds of the
labelled rows, pruned on the rest, and kept only if it stays precise there. The list is emitted as one ordered
Spark conditional expression, so applying it is part of the scan's stage.

Null texts have no words and fail the base rule. Labels with null or conflicting quality are not learned from;
without labels of both kinds the list is empty and only the base rule rejects. Repeated rows are judged each.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import WORD, saved, small_batches, table
from .tokenization import row_slices

#: Characters that count as symbols (fixed value of the contract).
SYMBOLS = "#*$%&|<>"
_WORDS = re.compile(WORD).findall
BASE = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]
MORE = ["n_upper", "n_digits", "n_marks", "n_distinct"]


def repeat_words(words: list[str]) -> tuple[int, int]:
    """(words inside three-word windows found twice or more, distinct words)."""
    n = len(words)
    code: dict[str, int] = {}
    ids = np.fromiter((code.setdefault(w, len(code)) for w in words), np.int64, n)
    if n < 4:
        return 0, len(code)
    m = len(code)
    pair = ids[:-1] * m + ids[1:]
    if m >= 1 << 20:
        pair, m = np.unique(pair, return_inverse=True)[1], len(code)
    window = pair[:-1] * m + ids[2:]
    _, back, count = np.unique(window, return_inverse=True, return_counts=True)
    hit = count[back] > 1
    covered = np.zeros(n, bool)
    for shift in range(3):
        covered[shift : n - 2 + shift] |= hit
    return int(covered.sum()), len(code)


def statistics_of(text: str) -> tuple[int, ...]:
    words = _WORDS(text)
    letters = np.bincount(np.frombuffer(text.encode("latin-1", "replace"), np.uint8), minlength=256)
    lines = [x for x in text.split("\n") if x.strip(" \t\n\x0b\x0c\r")]
    repeated, distinct = repeat_words(words)
    return (
        len(words), sum(map(len, words)), sum(map(text.count, SYMBOLS)), len(lines) - len(set(lines)), repeated,
        int(letters[65:91].sum()), int(letters[48:58].sum()), text.count("!") + text.count("?"), distinct,
    )


def statistics(docs: DataFrame) -> DataFrame:
    """(doc_id, statistics) of each row of docs(doc_id, text)."""
    small_batches(docs.sparkSession)

    def run(batches):
        for batch in batches:
            for at, n in row_slices(batch.column(1), 4 << 20):
                rows = [statistics_of(t or "") for t in batch.column(1).slice(at, n).to_pylist()]
                cols = np.array(rows, np.int64).reshape(-1, len(BASE) + len(MORE)).T
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(at, n), *(pa.array(np.ascontiguousarray(c)) for c in cols)], ["doc_id", *BASE, *MORE])

    return docs.select("doc_id", "text").mapInArrow(run, ", ".join(f"{c} long" for c in ["doc_id", *BASE, *MORE]))


#: Features the rules test, as (name, numerator, denominator): the same expression in Spark and in the learner.
FEATURES = [
    ("words", "n_words", None), ("word_length", "word_chars", "n_words"), ("symbols", "n_symbols", "word_chars"), ("dup_lines", "n_dup_lines", "n_words"),
    ("repeats", "n_repeat_words", "n_words"), ("upper", "n_upper", "word_chars"), ("digits", "n_digits", "word_chars"), ("marks", "n_marks", "n_words"), ("distinct", "n_distinct", "n_words"),
]


def feature(i: int) -> Column:
    _, top, under = FEATURES[i]
    value = F.col(top).cast("double")
    return value if under is None else value / F.greatest(F.col(under), F.lit(1)).cast("double")


def feature_matrix(rows: np.ndarray) -> np.ndarray:
    named = dict(zip([*BASE, *MORE], rows.T.astype(np.float64)))
    return np.stack([named[top] if under is None else named[top] / np.maximum(named[under], 1) for _, top, under in FEATURES], 1)


Condition = tuple[int, str, float]


def _holds(x: np.ndarray, rule: list[Condition]) -> np.ndarray:
    out = np.ones(len(x), bool)
    for i, side, cut in rule:
        out &= x[:, i] <= cut if side == "<=" else x[:, i] > cut
    return out


def _gain(p0: float, n0: float, p: np.ndarray, n: np.ndarray) -> np.ndarray:
    with np.errstate(divide="ignore", invalid="ignore"):
        g = p * (np.log2(p / (p + n)) - np.log2(p0 / (p0 + n0)))
    return np.where(p > 0, g, -np.inf)


def grow(x: np.ndarray, y: np.ndarray, cuts: list[np.ndarray], most: int = 4) -> list[Condition]:
    rule: list[Condition] = []
    inside = np.ones(len(x), bool)
    while len(rule) < most:
        p0, n0 = float((y & inside).sum()), float((~y & inside).sum())
        if not p0 or not n0:
            break
        best = (0.0, None)
        for i, cut in enumerate(cuts):
            at = np.searchsorted(cut, x[inside, i], side="left")  # value <= cut[j] iff at <= j
            pos = np.cumsum(np.bincount(at[y[inside]], minlength=len(cut) + 1))[:-1].astype(float)
            neg = np.cumsum(np.bincount(at[~y[inside]], minlength=len(cut) + 1))[:-1].astype(float)
            for side, p, n in (("<=", pos, neg), (">", p0 - pos, n0 - neg)):
                g = _gain(p0, n0, p, n)
                j = int(np.argmax(g)) if len(g) else 0
                if len(g) and g[j] > best[0] + 1e-9:
                    best = (float(g[j]), (i, side, float(cut[j])))
        if best[1] is None:
            break
        rule.append(best[1])
        inside &= _holds(x, [best[1]])
    return rule


def prune(x: np.ndarray, y: np.ndarray, rule: list[Condition]) -> list[Condition]:
    def worth(r):
        h = _holds(x, r)
        p, n = (y & h).sum(), (~y & h).sum()
        return (p - n) / max(1, p + n)

    return max((rule[:k] for k in range(1, len(rule) + 1)), key=lambda r: (worth(r), -len(r)), default=[])


def learn(x: np.ndarray, y: np.ndarray, most_rules: int = 16, precision: float = 0.95, seed: int = 7) -> list[list[Condition]]:
    """Ordered rules for y (rejected) over features x."""
    rules: list[list[Condition]] = []
    if not y.any() or y.all():
        return rules
    part = np.random.default_rng(seed).random(len(y)) < 2 / 3
    cuts = [np.unique(np.quantile(x[:, i], np.linspace(0, 1, 129)[:-1])) for i in range(x.shape[1])]
    open_ = np.ones(len(y), bool)
    while len(rules) < most_rules and (y & open_ & part).sum() >= 5:
        g, p = open_ & part, open_ & ~part
        rule = grow(x[g], y[g], cuts)
        rule = prune(x[p], y[p], rule) if rule else rule
        hit = _holds(x, rule) & open_ if rule else np.zeros(len(y), bool)
        good, bad = (y & hit & ~part).sum(), (~y & hit & ~part).sum()
        if not rule or good < 2 or good < precision * (good + bad):
            break
        rules.append(rule)
        open_ &= ~hit
    return rules


def as_expression(rules: list[list[Condition]]) -> Column:
    """True where the list keeps a row: the first rule that holds rejects, and the default keeps."""
    out = None
    for rule in rules:
        cond = F.lit(True)
        for i, side, cut in rule:
            cond = cond & (feature(i) <= cut if side == "<=" else feature(i) > cut)
        out = F.when(cond, False) if out is None else out.when(cond, False)
    return F.lit(True) if out is None else out.otherwise(True)


def quality_rules(docs: DataFrame, labels: DataFrame, sample: int = 20_000) -> DataFrame:
    """Operator 6's query. sample: bound of the labelled rows learned from, the least by a hash of doc_id."""
    stats = saved(statistics(docs), "statistics")
    clear = labels.filter("doc_id is not null and quality is not null").groupBy("doc_id").agg(F.min("quality").alias("lo"), F.max("quality").alias("hi")).filter("lo = hi")
    chosen = clear.orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample)
    least = F.min(F.struct("lo", *BASE, *MORE)).alias("r")  # of texts that share an id, one
    rows = stats.join(F.broadcast(chosen), "doc_id").groupBy("doc_id").agg(least).orderBy("doc_id").select("r.*").toPandas().to_numpy(np.int64)
    x = feature_matrix(rows[:, 1:])
    rules = learn(x, rows[:, 0] == 0)
    failed = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    return stats.select("doc_id", *BASE, failed.alias("base_failed"), (~failed & as_expression(rules)).alias("kept"))


def query(spark, sf_dir: str) -> DataFrame:
    return quality_rules(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
