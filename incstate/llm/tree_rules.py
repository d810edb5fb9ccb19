"""Quality rules: base limits and gradient-boosted trees over document statistics.

The trees are grown here by histograms on the logistic loss, with monotonic constraints: along a
constrained statistic a split may only order its children's values one way, and bounds handed down keep
later splits from undoing it.  The forest is flattened into node arrays, and all documents of a slice go
down all trees at once.
"""

from __future__ import annotations

from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from incstate.llm.common import bound_batches, flat, slices
from incstate.llm.text_stats import COUNTS, SHARES, stats

#: Most labelled rows that the trees are fitted on, those of the smallest id hashes.
TRAINING_ROWS = 20_000
TREES = 60
LEVELS = 4
RATE = 0.15
BINS = 64
LEAST_ROWS = 20
RIDGE = 1.0
VERDICT = 0.5
LEAST_WORDS = 50
MOST_REPEAT_PERCENT = 50
#: More of these never makes a document better.
FALLING = ("symbol_share", "dup_line_share", "repeat_share", "upper_share", "shout_share")


class Forest(NamedTuple):
    """Node arrays: ``feature`` is -1 in a leaf, ``root`` has each tree's first node."""

    feature: np.ndarray
    threshold: np.ndarray
    left: np.ndarray
    right: np.ndarray
    value: np.ndarray
    root: np.ndarray
    base: float

    def score(self, x: np.ndarray) -> np.ndarray:
        """Probability of label 1 for each row of ``x``."""
        node = np.broadcast_to(self.root, (len(x), len(self.root))).copy()
        row = np.arange(len(x))[:, None]
        for _ in range(LEVELS):
            feature = self.feature[node]
            inner = feature >= 0
            below = x[row, np.maximum(feature, 0)] <= self.threshold[node]
            node = np.where(inner, np.where(below, self.left[node], self.right[node]), node)
        return 1 / (1 + np.exp(-(self.base + self.value[node].sum(axis=1))))


def fit(x: np.ndarray, y: np.ndarray, sign: np.ndarray) -> Forest:
    """Boost on rows ``x`` with labels ``y``; ``sign`` is 1, -1 or 0 for each column."""
    edges = [np.unique(np.quantile(x[:, f], np.linspace(0, 1, BINS + 1)[1:-1])) for f in range(x.shape[1])] if len(x) else []
    bins = np.column_stack([np.searchsorted(e, x[:, f], "left") for f, e in enumerate(edges)]) if len(x) else x
    feature, threshold, left, right, value, roots = [], [], [], [], [], []
    rate = np.clip(y.mean(), 1e-3, 1 - 1e-3) if len(y) else 0.5
    base = float(np.log(rate / (1 - rate)))
    margin = np.full(len(x), base)

    def node() -> int:
        for a, v in zip((feature, threshold, left, right, value), (-1, 0.0, -1, -1, 0.0)):
            a.append(v)
        return len(feature) - 1

    def weight(g: np.ndarray, h: np.ndarray) -> np.ndarray:
        return -g / (h + RIDGE)

    def gain(g: np.ndarray, h: np.ndarray, w: np.ndarray) -> np.ndarray:
        return -(2 * g * w + (h + RIDGE) * w * w)

    for _ in range(TREES if len(x) else 0):
        p = 1 / (1 + np.exp(-margin))
        grad, hess = p - y, p * (1 - p)
        roots.append(node())
        todo = [(roots[-1], np.arange(len(x)), -np.inf, np.inf, 0)]
        while todo:
            at, rows, low, high, level = todo.pop()
            g, h = grad[rows].sum(), hess[rows].sum()
            own = float(np.clip(weight(g, h), low, high))
            value[at] = RATE * own
            best = (1e-6, None)
            for f, e in enumerate(edges) if level < LEVELS and len(rows) >= 2 * LEAST_ROWS else ():
                b = bins[rows, f]
                gl, hl, nl = (np.bincount(b, w, minlength=len(e) + 1).cumsum()[:-1] for w in (grad[rows], hess[rows], None))
                wl, wr = np.clip(weight(gl, hl), low, high), np.clip(weight(g - gl, h - hl), low, high)
                won = gain(gl, hl, wl) + gain(g - gl, h - hl, wr) - gain(g, h, own)
                bad = (nl < LEAST_ROWS) | (len(rows) - nl < LEAST_ROWS) | (sign[f] * (wr - wl) < 0)
                won = np.where(bad, -np.inf, won)
                if len(won) and won.max() > best[0]:
                    k = int(won.argmax())
                    best = (float(won[k]), (f, k, wl[k], wr[k]))
            if best[1] is None:
                margin[rows] += value[at]
                continue
            f, k, wl, wr = best[1]
            feature[at], threshold[at] = f, float(edges[f][k])
            left[at], right[at] = node(), node()
            middle = (wl + wr) / 2
            goes = bins[rows, f] <= k
            ends = {1: ((low, middle), (middle, high)), -1: ((middle, high), (low, middle)), 0: ((low, high),) * 2}[int(sign[f])]
            todo.append((left[at], rows[goes], *ends[0], level + 1))
            todo.append((right[at], rows[~goes], *ends[1], level + 1))
    return Forest(*(np.array(a, k) for a, k in zip((feature, threshold, left, right, value, roots), (int, float, int, int, float, int))), base)


@F.arrow_udf(T.ArrayType(T.DoubleType()))
def _shares(text: pa.Array) -> pa.Array:
    text = flat(text)
    x = np.concatenate([np.zeros((0, len(SHARES))), *(stats(text[a:b])[1] for a, b in slices(text))])
    return pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1) * len(SHARES), pa.int32()), pa.array(x.ravel()))


def training_rows(docs: DataFrame, labels: DataFrame, most: int = TRAINING_ROWS) -> tuple[np.ndarray, np.ndarray]:
    """Statistics and labels of at most ``most`` labelled documents, the same ones in every run."""
    known = labels.where("doc_id is not null and quality in (0, 1)").groupBy("doc_id").agg(F.min("quality").alias("y"))
    chosen = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)
    rows = (
        docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id")
        .select("doc_id", "y", _shares(F.coalesce("text", F.lit(""))).alias("x"))
        .dropDuplicates(["doc_id"]).toPandas().sort_values("doc_id")
    )
    x = np.array(rows["x"].to_list(), float).reshape(-1, len(SHARES))
    return x, rows["y"].to_numpy(float)


def quality_rules(docs: DataFrame, labels: DataFrame, most: int = TRAINING_ROWS) -> DataFrame:
    """``docs(doc_id, text)`` to ``doc_id``, the base counts, ``base_failed, score, kept``; one row per input row.

    The trees learn ``labels(doc_id, quality)`` from at most ``most`` labelled documents; labels that are
    null or of unknown documents are left out, and without any label all documents score one half (kept
    if the base limits allow).  ``base_failed`` holds for fewer than 50 words or more than 50% words in
    repeated three-word windows; null texts count as empty.  Repeated rows and null ids are judged like
    others; an empty table gives no rows; other columns are ignored.  A very long text is a slice of its
    own, read whole.
    """
    bound_batches(docs)
    x, y = training_rows(docs, labels, most)
    forest = fit(x, y, np.array([-1 if s in FALLING else 0 for s in SHARES]))
    kind = T.StructType()
    for c in COUNTS:
        kind = kind.add(c, "long")

    @F.arrow_udf(kind.add("score", "double"))
    def judge(text: pa.Array) -> pa.Array:
        text = flat(text)
        columns: list[list[np.ndarray]] = [[np.zeros(0, np.int64)] for _ in COUNTS] + [[np.zeros(0)]]
        for a, b in slices(text):
            counts, shares = stats(text[a:b])
            for held, c in zip(columns, COUNTS):
                held.append(counts[c].astype(np.int64))
            columns[-1].append(forest.score(shares))
        return pa.StructArray.from_arrays([pa.array(np.concatenate(c)) for c in columns], names=[*COUNTS, "score"])

    failed = (F.col("n_words") < LEAST_WORDS) | (100 * F.col("n_repeat_words") > MOST_REPEAT_PERCENT * F.col("n_words"))
    return (
        docs.select("doc_id", judge(F.coalesce("text", F.lit(""))).alias("j"))
        .select("doc_id", "j.*")
        .withColumn("base_failed", failed)
        .withColumn("kept", ~F.col("base_failed") & (F.col("score") >= VERDICT))
    )
