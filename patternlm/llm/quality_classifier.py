"""Quality classifier: a sparse rule ensemble compiled into column expressions.

Shallow trees grown on bootstrap samples give candidate rules: every path from the root is a conjunction of threshold tests on text
statistics. A logistic model over the rules' 0/1 values with an L1 penalty keeps few of them. Scoring is one projection of built-in
functions: the logistic of a weighted sum of conjunctions.

Fitting uses at most `most_rows` labelled rows, chosen by a hash of the id (a broadcast of so many ids, a collect of so many rows
of statistics); scoring covers all rows. With one class only, or no label, the score is the smoothed share of label 1 (0.5 without labels). Null
and empty texts have statistics of zero and get a score; repeated rows get equal scores; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce
from typing import NamedTuple

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from patternlm.llm.common import column, crc_mod, let
from patternlm.llm.quality_rules import measured

MOST_ROWS = 20_000
TREES = 40
DEPTH = 3
BINS = 32

STATISTICS = (
    "log_words", "mean_word_chars", "symbols_per_word", "stop_word_share", "shouted_share", "dup_line_share", "bullet_line_share",
    "ellipsis_line_share", "repeat_word_share", "words_per_line", "upper_share", "digit_share", "bar_share", "mark_share",
)


class Test(NamedTuple):
    stat: str
    above: bool  # value > threshold, else value <= threshold
    threshold: float


class RuleModel(NamedTuple):
    bias: float
    rules: list[tuple[tuple[Test, ...], float]]


def with_statistics(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """docs with a struct __x of STATISTICS."""
    out = measured(docs, text_col)
    q, text = F.col("__q"), F.coalesce(column(text_col), F.lit(""))
    n, chars = F.greatest(q["n_words"], F.lit(1)), F.greatest(F.length(text), F.lit(1))
    share = lambda pattern: (F.length(text) - F.length(F.regexp_replace(text, pattern, ""))) / chars
    x = {
        "log_words": F.log1p(q["n_words"].cast("double")), "repeat_word_share": q["n_repeat_words"] / n, "words_per_line": q["n_words"] / F.greatest(q["n_lines"], F.lit(1)),
        "upper_share": share(r"[A-Z]+"), "digit_share": share(r"[0-9]+"), "bar_share": share(r"\|+"), "mark_share": share(r"[!?.,;:]+"),
    }
    return out.withColumn("__x", F.struct(*((x[s] if s in x else q[s]).cast("double").alias(s) for s in STATISTICS)))


def _grow(binned: np.ndarray, y: np.ndarray, w: np.ndarray, depth: int, features: Sequence[int], path: tuple, out: list[tuple]) -> None:
    """Splits by Gini gain on histograms; every node but the root adds its path."""
    if path:
        out.append(path)
    if depth == 0 or len(y) < 20 or y.min() == y.max():
        return
    best, total, pos = None, w.sum(), (w * y).sum()
    for f in features:
        n = np.cumsum(np.bincount(binned[:, f], weights=w, minlength=BINS + 1))[:-1]
        p = np.cumsum(np.bincount(binned[:, f], weights=w * y, minlength=BINS + 1))[:-1]
        ok = (n > 0) & (n < total)
        if not ok.any():
            continue
        gain = np.where(ok, p * p / np.maximum(n, 1e-12) + (pos - p) ** 2 / np.maximum(total - n, 1e-12), -1.0)
        b = int(gain.argmax())
        if best is None or gain[b] > best[0] + 1e-12:
            best = (gain[b], f, b)
    if best is None or best[0] <= pos * pos / total + 1e-9:
        return
    _, f, b = best
    low = binned[:, f] <= b
    _grow(binned[low], y[low], w[low], depth - 1, features, (*path, (f, False, b)), out)
    _grow(binned[~low], y[~low], w[~low], depth - 1, features, (*path, (f, True, b)), out)


def _lasso(z: np.ndarray, y: np.ndarray, penalty: float, steps: int = 600) -> tuple[float, np.ndarray]:
    """L1 logistic regression by accelerated proximal gradient; the bias is free."""
    n, m = z.shape
    scale = 4.0 * n / max(np.linalg.norm(np.c_[np.ones(n), z], 2) ** 2, 1e-9)
    w, v, b, c, t = np.zeros(m), np.zeros(m), 0.0, 0.0, 1.0
    for _ in range(steps):
        r = 1 / (1 + np.exp(-np.clip(z @ v + c, -60, 60))) - y
        w2 = v - scale * (z.T @ r) / n
        w2 = np.sign(w2) * np.maximum(np.abs(w2) - scale * penalty, 0)
        b2 = c - scale * r.mean()
        t2 = (1 + np.sqrt(1 + 4 * t * t)) / 2
        v, c = w2 + (t - 1) / t2 * (w2 - w), b2 + (t - 1) / t2 * (b2 - b)
        w, b, t = w2, b2, t2
    return b, w


def fit(x: np.ndarray, y: np.ndarray, stats: Sequence[str] = STATISTICS, trees: int = TREES, depth: int = DEPTH, penalty: float = 2e-4, seed: int = 11) -> RuleModel:
    """A rule ensemble for 0/1 labels y."""
    if len(y) == 0 or y.min() == y.max():
        p = (y.sum() + 1) / (len(y) + 2)
        return RuleModel(float(np.log(p / (1 - p))), [])
    cuts = [np.unique(np.quantile(x[:, f], np.linspace(0, 1, BINS + 1)[1:-1])) for f in range(x.shape[1])]
    binned = np.stack([np.searchsorted(c, x[:, f], side="left") for f, c in enumerate(cuts)], 1)
    rng, paths = np.random.default_rng(seed), []
    for _ in range(trees):
        rows = rng.integers(0, len(y), len(y))
        features = rng.choice(x.shape[1], max(2, x.shape[1] // 2), replace=False)
        _grow(binned[rows], y[rows], np.ones(len(y)), depth, features, (), paths)
    rules = list(dict.fromkeys(tuple(Test(stats[f], above, float(cuts[f][b])) for f, above, b in path if b < len(cuts[f])) for path in paths))
    at = {s: i for i, s in enumerate(stats)}
    z = np.stack([reduce(np.logical_and, ((x[:, at[t.stat]] > t.threshold) == t.above for t in r)) for r in rules], 1).astype(float)
    keep = (z.std(0) > 0).nonzero()[0]
    keep = keep[np.unique(z[:, keep], axis=1, return_index=True)[1]]
    b, w = _lasso(z[:, keep], y.astype(float), penalty)
    return RuleModel(float(b), [(rules[i], float(v)) for i, v in zip(keep, w, strict=True) if v])


def compiled(model: RuleModel, x: Column) -> Column:
    """The score as one column expression over a struct of statistics."""
    total = F.lit(model.bias)
    for tests, weight in model.rules:
        hold = reduce(lambda a, b: a & b, ((x[t.stat] > t.threshold) if t.above else (x[t.stat] <= t.threshold) for t in tests))
        total = total + F.when(hold, F.lit(weight)).otherwise(F.lit(0.0))
    return F.lit(1.0) / (F.lit(1.0) + F.exp(-total))


def labelled_rows(docs: DataFrame, labels: DataFrame, most_rows: int = MOST_ROWS) -> tuple[np.ndarray, np.ndarray]:
    """Statistics and labels of at most most_rows documents, by hash of the id."""
    one = labels.where("doc_id IS NOT NULL AND quality IS NOT NULL").groupBy("doc_id").agg(F.max("quality").alias("quality"))
    chosen = one.orderBy(F.xxhash64("doc_id", F.lit("fit")), "doc_id").limit(most_rows)
    met = with_statistics(docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id"))
    rows = met.select("quality", *(F.col("__x")[s].alias(s) for s in STATISTICS)).toPandas()
    order = np.lexsort([rows[s].to_numpy() for s in ("quality", *STATISTICS)])  # rows come in any order
    return rows[list(STATISTICS)].to_numpy(float)[order], rows["quality"].to_numpy(int)[order]


def quality_classifier(docs: DataFrame, model: RuleModel, held_out: Column | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Every row of docs: doc_id, held_out, score, predicted."""
    held = F.lit(False) if held_out is None else held_out
    # bound to a lambda variable, the rules are evaluated as an expression tree; as generated code, hundreds of them make methods that cost the compiler gigabytes
    score = let(F.col("__x"), lambda x: compiled(model, x))
    out = with_statistics(docs.select(column(id_col).alias("doc_id"), column(text_col).alias("text"))).select("doc_id", held.alias("held_out"), score.alias("score"))
    return out.select("doc_id", "held_out", "score", F.when(F.col("score") >= 0.5, 1).otherwise(0).alias("predicted"))


def learn_and_score(docs: DataFrame, labels: DataFrame, folds: int = 3, fold: int = 1, most_rows: int = MOST_ROWS) -> DataFrame:
    """Fit on labels outside the held-out fold, then score all rows of docs."""
    held = crc_mod(F.col("doc_id"), folds) == fold
    model = fit(*labelled_rows(docs, labels.where(~held), most_rows))
    return quality_classifier(docs, model, held)
