"""Quality scores by voting of the nearest labelled documents in a latent semantic space.

A text's terms are hashed byte trigrams and binned document statistics.  On a bounded sample of labelled
texts the term weights (inverse document frequencies) and a truncated singular value decomposition are
fitted; the sample's latent vectors and labels are sent to every task, which compares all its documents
with all of them in blocks of exact cosines.  The nearest vote with a weight that falls steeply with
distance; votes are corrected for the sample being drawn evenly from both labels.
"""

from __future__ import annotations

from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from incstate.llm.common import Ragged, bound_batches, flat, slices
from incstate.llm.text_stats import SHARES, stats

#: Most labelled rows of each label that the space is fitted on and that vote.
ROWS_PER_LABEL = 1500
TRIGRAM_TERMS = 2048
LATENT = 64
NEIGHBOURS = 25
SHARPNESS = 30.0
THRESHOLD = 0.7
STATISTIC_WEIGHT = 0.8
SLICE = 2 << 20

#: Upper ends of the bins of each statistic that gives terms.
BIN_ENDS = {
    "log_words": (2.5, 4.0, 5.5, 7.0), "symbol_share": (0.01, 0.03, 0.08, 0.15), "dup_line_share": (0.1, 0.3, 0.6),
    "repeat_share": (0.05, 0.2, 0.5, 0.8), "upper_share": (0.1, 0.3, 0.6), "shout_share": (0.05, 0.3, 0.7),
    "distinct_share": (0.1, 0.3, 0.5, 0.8),
}
TERMS = TRIGRAM_TERMS + sum(len(v) + 1 for v in BIN_ENDS.values())


def term_counts(texts: pa.Array) -> np.ndarray:
    """``float32[texts, TERMS]``: logarithms of one plus the trigram counts, and 0/1 for statistics."""
    r = Ragged(texts)
    raw = r.bytes.astype(np.uint32)
    out = np.zeros((r.n, TERMS), np.float32)
    if len(raw) > 2:
        key = (raw[:-2] * np.uint32(0x9E3779B1) + raw[1:-1] * np.uint32(0x85EBCA77) + raw[2:] * np.uint32(0xC2B2AE3D)) >> np.uint32(21)
        doc = np.repeat(np.arange(r.n), np.diff(r.bounds))
        ok = doc[:-2] == doc[2:]
        flat_ = np.bincount(doc[:-2][ok] * TRIGRAM_TERMS + key[ok], minlength=r.n * TRIGRAM_TERMS)
        out[:, :TRIGRAM_TERMS] = np.log1p(flat_.reshape(r.n, TRIGRAM_TERMS))
    shares = stats(texts)[1]
    at = TRIGRAM_TERMS
    for name, ends in BIN_ENDS.items():
        out[np.arange(r.n), at + np.searchsorted(ends, shares[:, SHARES.index(name)])] = 1
        at += len(ends) + 1
    return out


class Space(NamedTuple):
    """Term weights, term axes, the voters' latent vectors, their votes, and the rate of label 1."""

    weight: np.ndarray
    axes: np.ndarray
    voters: np.ndarray
    vote: np.ndarray
    label: np.ndarray
    prior: float

    def latent(self, counts: np.ndarray) -> np.ndarray:
        return _unit(weighted(counts, self.weight) @ self.axes)

    def score(self, counts: np.ndarray) -> np.ndarray:
        """Share of the nearest voters' weight that is for label 1."""
        if not len(self.voters):
            return np.full(len(counts), self.prior)
        z = self.latent(counts)
        near = z @ self.voters.T
        k = min(NEIGHBOURS, near.shape[1])
        best = np.argpartition(-near, k - 1, axis=1)[:, :k]
        cosine = np.take_along_axis(near, best, axis=1).astype(float)
        w = np.exp(SHARPNESS * (cosine - cosine.max(axis=1, keepdims=True))) * self.vote[best]
        out = (w * self.label[best]).sum(axis=1) / w.sum(axis=1)
        return np.where(np.abs(z).sum(axis=1) > 0, np.clip(out, 0, 1), self.prior)


def _unit(x: np.ndarray) -> np.ndarray:
    return x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-12)


def weighted(counts: np.ndarray, weight: np.ndarray) -> np.ndarray:
    x = counts * weight
    x[:, :TRIGRAM_TERMS] = _unit(x[:, :TRIGRAM_TERMS])
    x[:, TRIGRAM_TERMS:] *= np.float32(STATISTIC_WEIGHT / np.sqrt(len(BIN_ENDS)))
    return x


def fit_space(counts: np.ndarray, label: np.ndarray, prior: float, seed: int = 3) -> Space:
    """Fit on the sample's term counts; ``prior`` is the rate of label 1 among all labelled rows."""
    n = len(counts)
    if not n:
        return Space(np.ones(TERMS, np.float32), np.zeros((TERMS, 1), np.float32), np.zeros((0, 1), np.float32), np.zeros(0), label, prior)
    weight = (np.log((1 + n) / (1 + (counts > 0).sum(axis=0))) + 1).astype(np.float32)
    weight[TRIGRAM_TERMS:] = 1
    x = weighted(counts, weight)
    rank = min(LATENT, n, TERMS)
    probe = x.T @ np.random.default_rng(seed).standard_normal((n, min(n, rank + 10)), dtype=np.float32)
    for _ in range(4):
        probe = x.T @ (x @ np.linalg.qr(probe)[0])
    basis = np.linalg.qr(probe)[0]
    turn = np.linalg.svd(x @ basis, full_matrices=False)[2][:rank]
    axes = (basis @ turn.T).astype(np.float32)
    rate = label.mean()
    share = np.where(label == 1, prior / max(rate, 1e-9), (1 - prior) / max(1 - rate, 1e-9))
    return Space(weight, axes, _unit(x @ axes), share, label, prior)


@F.arrow_udf(T.BinaryType())
def _counts(text: pa.Array) -> pa.Array:
    text = flat(text)
    return pa.array([row.tobytes() for a, b in slices(text, SLICE) for row in term_counts(text[a:b])], pa.binary())


def held_out(doc_id):
    """Whether an id belongs to the rows that are never learnt from."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 4 == 2, F.lit(False))


def learn(docs: DataFrame, labels: DataFrame, per_label: int = ROWS_PER_LABEL) -> Space:
    """Fit on at most ``per_label`` learnable documents of each label, the same ones in every run."""
    bound_batches(docs)
    known = (
        labels.where("doc_id is not null and quality in (0, 1)").where(~held_out(F.col("doc_id")))
        .groupBy("doc_id").agg(F.min("quality").alias("y"))
    )
    prior = known.agg(F.avg("y")).first()[0]
    order = [F.xxhash64("doc_id"), F.col("doc_id")]
    chosen = known.where("y = 0").orderBy(*order).limit(per_label).unionByName(known.where("y = 1").orderBy(*order).limit(per_label))
    rows = (
        docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id")
        .select("doc_id", "y", _counts(F.coalesce("text", F.lit(""))).alias("x"))
        .dropDuplicates(["doc_id"]).toPandas().sort_values("doc_id")
    )
    x = np.frombuffer(b"".join(rows["x"]), np.float32).reshape(-1, TERMS)
    return fit_space(x, rows["y"].to_numpy(float), 0.5 if prior is None else float(prior))


def scored(docs: DataFrame, space: Space, name: str = "score", text: str = "text") -> DataFrame:
    """``docs`` with the score of each text; a null text counts as empty."""

    @F.arrow_udf(T.DoubleType())
    def vote(texts: pa.Array) -> pa.Array:
        texts = flat(texts)
        return pa.array(np.concatenate([np.zeros(0), *(space.score(term_counts(texts[a:b])) for a, b in slices(texts, SLICE))]))

    return docs.withColumn(name, vote(F.coalesce(F.col(text), F.lit(""))))


def quality_scores(docs: DataFrame, labels: DataFrame, per_label: int = ROWS_PER_LABEL) -> DataFrame:
    """``docs(doc_id, text)`` to ``doc_id, held_out, score, predicted``, one row per input row.

    Labels are read only from rows whose crc32(doc_id) mod 4 is not 2, at most ``per_label`` of each
    label; null labels are left out, and without any label all score one half.  A null id is never held
    out; empty texts, ties and repeated rows are scored like others; an empty table gives no rows; other
    columns are ignored.  A very long text is a slice of its own, read whole.
    """
    space = learn(docs, labels, per_label)
    return scored(docs.select("doc_id", "text"), space).select(
        "doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted")
    )


def keep_good(docs: DataFrame, labels: DataFrame, per_label: int = ROWS_PER_LABEL) -> DataFrame:
    """The rows of ``docs`` that score ``THRESHOLD`` or more, with their columns unchanged."""
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"))
    return scored(rows, learn(docs, labels, per_label), "score", "row.text").where(F.col("score") >= THRESHOLD).select("row.*")
