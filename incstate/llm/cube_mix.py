"""Mixing sources to target weights by balanced (cube-method) sampling.

Every document of a source is wanted ``target / source_size`` times.  The whole part is taken outright;
the fraction is an inclusion probability, and the cube method moves all fractions of a source along
directions that keep the source's token total and document total, until each fraction is 0 or 1.  The
flight runs over hashed chunks of a source in parallel, then over what the chunks leave (two documents
each), until one chunk is left.  Its landing problem, ``LANDING`` documents of spread sizes, is solved by
trying all roundings for the one that misses the token total least, then the document total.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from incstate.llm.common import cut, word_count

WEIGHTS = (5.0, 2.0, 1.0)
MOST_COPIES = 3
CHUNK = 4096
#: Documents that a chunk leaves open; those of a source's last chunk are rounded together.
LANDING = 14
#: The table of sources is broadcast up to this many rows and joined by a shuffle beyond.
BROADCAST_SOURCES = 100_000

_EPS = 1e-9


def source_targets(
    units: DataFrame, weights: tuple[float, ...] = WEIGHTS, share: float = 1.0, most: float = MOST_COPIES
) -> DataFrame:
    """``units(source, size, m)`` to ``(source, source_no, units, source_size, target)``.

    Sources in code-point order, null last, weigh ``weights`` cyclically and share ``share`` of all
    tokens.  A target stops at ``most`` times its source's size and the excess goes to the others by
    weight; the level at which that settles is found in one pass over the sources ordered by
    size/weight.  Only the table of sources (one row each) passes through a single task.
    """
    per = units.groupBy("source").agg(
        F.count("*").alias("units"), F.sum(F.col("size") * F.col("m")).cast("long").alias("source_size")
    )
    everything = Window.orderBy(F.col("source").asc_nulls_last())
    per = per.withColumn("source_no", F.row_number().over(everything).cast("long"))
    weight = F.element_at(
        F.array(*[F.lit(float(w)) for w in weights]), (F.pmod(F.col("source_no") - 1, F.lit(len(weights))) + 1).cast("int")
    )
    per = per.withColumn("w", weight).withColumn("cap", F.col("source_size") * F.lit(float(most)))
    rising = Window.orderBy((F.col("cap") / F.col("w")).asc(), "source_no")
    all_rows = Window.partitionBy()
    per = (
        per.withColumn("total", F.sum("source_size").over(all_rows) * F.lit(float(share)))
        .withColumn("capped", F.coalesce(F.sum("cap").over(rising.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0)))
        .withColumn("left_w", F.sum("w").over(rising.rowsBetween(0, Window.unboundedFollowing)))
        .withColumn("level", (F.col("total") - F.col("capped")) / F.col("left_w"))
    )
    settled = F.min(F.when(F.col("level") * F.col("w") <= F.col("cap"), F.struct(F.col("cap") / F.col("w"), "source_no", "level"))).over(all_rows)
    per = per.withColumn("at", settled["level"])
    target = F.when(F.col("at").isNull(), F.col("cap")).otherwise(F.least(F.col("cap"), F.col("at") * F.col("w")))
    return per.select("source", "source_no", "units", "source_size", target.cast("double").alias("target"))


def _kernel(rows: list[tuple[float, ...]]) -> list[float]:
    """A vector that all ``rows`` (each one longer than their number) map to zero."""
    if len(rows) == 2:
        (a, b, c), (d, e, f) = rows
        u = [b * f - c * e, c * d - a * f, a * e - b * d]
        size = max(abs(x) for x in u)
        if size > _EPS * max(1.0, abs(a), abs(b), abs(c)) * max(1.0, abs(d), abs(e), abs(f)):
            return [x / size for x in u]
        row = rows[0] if any(rows[0]) else rows[1]
        return _kernel([row[:2]]) + [0.0]
    (a, b) = rows[0]
    if not a:
        return [1.0, 0.0]
    size = max(abs(a), abs(b))
    return [-b / size, a / size] if b else [0.0, 1.0]


def flight(prob: np.ndarray, keep: np.ndarray, draw: np.random.Generator) -> None:
    """Move ``prob`` in place, in order, until at most ``keep.shape[1]`` entries are strictly between 0 and 1.

    ``keep`` has one column for each total to hold: sum(prob * keep[:, c]) stays as it was.
    """
    width = keep.shape[1]
    p = prob.tolist()
    x = keep.tolist()
    active: list[int] = []
    chance = iter(draw.random(len(p) + 1).tolist())
    for k in range(len(p) + 1):
        active = [i for i in active if _EPS < p[i] < 1 - _EPS]
        if k < len(p) and _EPS < p[k] < 1 - _EPS:
            active.append(k)
        if len(active) <= width:
            continue
        u = _kernel([tuple(x[i][c] for i in active) for c in range(width)])
        up = min(((1 - p[i]) / v if v > 0 else -p[i] / v) for i, v in zip(active, u) if v)
        down = min((p[i] / v if v > 0 else (p[i] - 1) / v) for i, v in zip(active, u) if v)
        step = up if next(chance) * (up + down) < down else -down
        for i, v in zip(active, u):
            q = p[i] + step * v
            p[i] = 0.0 if q < _EPS else 1.0 if q > 1 - _EPS else q
    prob[:] = p


def land(prob: np.ndarray, totals: np.ndarray) -> None:
    """Round the few open entries of ``prob`` so that the first total stays nearest, then the second."""
    open_ = np.flatnonzero((prob > 0) & (prob < 1))
    if not len(open_):
        return
    ways = (np.arange(1 << len(open_))[:, None] >> np.arange(len(open_))) & 1
    off = np.abs((ways - prob[open_]) @ totals[open_])
    prob[open_] = ways[np.lexsort((off[:, 1], off[:, 0]))[0]]


def _settling(level: int, last: bool, seed: int):
    def run(table: pd.DataFrame) -> pd.DataFrame:
        return _settle(table, level, last, seed)

    return run


def _settle(table: pd.DataFrame, level: int, last: bool, seed: int) -> pd.DataFrame:
    table = table.sort_values(["w", "doc_id", "m"], ascending=[False, True, True], kind="stable", na_position="first")
    prob = table["p"].to_numpy(float).copy()
    m = table["m"].to_numpy(float)
    totals = np.column_stack([m * table["size"].to_numpy(float), m])
    draw = np.random.default_rng([seed, level, int(table["source_no"].iloc[0]), int(table["chunk"].iloc[0])])
    fly = np.flatnonzero((prob > 0) & (prob < 1))
    hold = fly[np.linspace(0, len(fly) - 1, LANDING - 2).astype(int)] if len(fly) > LANDING else fly
    fly = np.setdiff1d(fly, hold)
    moving = prob[fly]
    flight(moving, totals[fly], draw)
    prob[fly] = moving
    if last:
        land(prob, totals)
    return table.assign(p=prob)[["doc_id", "source_no", "size", "m", "w", "p"]]


def mix(
    docs: DataFrame,
    size: str | None = None,
    weights: tuple[float, ...] = WEIGHTS,
    share: float = 1.0,
    most: float = MOST_COPIES,
    chunk: int = CHUNK,
    seed: int = 17,
) -> DataFrame:
    """Decide how often each document enters the mix.

    Returns ``doc_id, source, size, source_size, target, copies, m``: one row for each distinct
    (doc_id, source, size), ``m`` being how many input rows are equal in these; equal rows share one
    decision.  ``size`` names a column to use instead of the number of words.  A null text has size 0,
    a null source is a source (the last), sources of size 0 take nothing, an empty table gives no rows.
    The same rows give the same mix in any order and partitioning.  Other columns are ignored.
    """
    length = F.coalesce(F.col(size).cast("long"), F.lit(0)) if size else word_count(F.col("text"))
    units = (
        docs.select("doc_id", "source", length.alias("size")).groupBy("doc_id", "source", "size").agg(F.count("*").alias("m"))
    )
    units = cut(units)
    sources = cut(source_targets(units, weights, share, most))
    about = sources.agg(F.count("*"), F.max("units")).first()
    small = F.broadcast(sources) if about[0] <= BROADCAST_SOURCES else sources
    rate = F.when(F.col("source_size") > 0, F.least(F.lit(float(most)), F.col("target") / F.col("source_size"))).otherwise(0.0)
    units = (
        units.join(small, units["source"].eqNullSafe(small["source"]))
        .select(units["doc_id"], units["size"], units["m"], "source_no", "units", rate.alias("rate"))
        .withColumn("whole", F.floor(F.col("rate") + F.lit(_EPS)))
        .withColumn("p", F.greatest(F.col("rate") - F.col("whole"), F.lit(0.0)))
    )
    whole = units.select("source_no", "whole").distinct()
    todo = units.select("doc_id", "source_no", "size", "m", (F.col("size") * F.col("m")).alias("w"), "p", "units")
    settled: list[DataFrame] = []
    count, level = int(about[1] or 0), 0
    while True:
        last = count <= chunk
        parts = F.lit(1) if last else F.greatest(F.lit(1), F.ceil(F.col("units") / F.lit(chunk)))
        held = todo.withColumn("chunk", F.pmod(F.xxhash64("doc_id", "size", F.lit(level)), parts.cast("long")))
        moved = held.groupBy("source_no", "chunk").applyInPandas(
            _settling(level, last, seed),
            "doc_id long, source_no long, size long, m long, w long, p double",
        )
        if last:
            settled.append(moved)
            break
        moved = cut(moved)
        settled.append(moved.where("p = 0 or p = 1"))
        rest = moved.where("p > 0 and p < 1")
        left = rest.groupBy("source_no").agg(F.count("*").alias("units"))
        count = int(left.agg(F.max("units")).first()[0] or 0)
        todo = rest.join(F.broadcast(left) if about[0] <= BROADCAST_SOURCES else left, "source_no")
        level += 1
    out = settled[0]
    for more in settled[1:]:
        out = out.unionByName(more)
    small = F.broadcast(cut(sources.join(whole, "source_no"))) if about[0] <= BROADCAST_SOURCES else sources.join(whole, "source_no")
    return out.join(small, "source_no").select(
        "doc_id", "source", "size", "source_size", "target", (F.col("whole") + F.col("p")).cast("long").alias("copies"), "m"
    )


def decisions(docs: DataFrame, **kwargs) -> DataFrame:
    """One row per input row: ``doc_id, size, source_size, target, taken`` and ``copies``."""
    return (
        mix(docs, **kwargs)
        .withColumn("_row", F.explode(F.sequence(F.lit(1).cast("long"), F.col("m"))))
        .select("doc_id", "size", "source_size", "target", (F.col("copies") * F.col("size")).alias("taken"), "copies")
    )


def apply_mix(docs: DataFrame, **kwargs) -> DataFrame:
    """The mixed corpus: every row of ``docs`` as often as the mix takes it, with its columns unchanged."""
    chosen = mix(docs, **kwargs).where("copies > 0").select("doc_id", "source", F.col("size").alias("length"), "copies")
    named = kwargs.get("size")
    length = F.coalesce(F.col(f"row.{named}").cast("long"), F.lit(0)) if named else word_count(F.col("row.text"))
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row")).withColumn("words", length)
    on = F.col("row.doc_id").eqNullSafe(F.col("doc_id")) & F.col("row.source").eqNullSafe(F.col("source")) & (F.col("words") == F.col("length"))
    return rows.join(chosen, on).withColumn("copy", F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies")))).select("row.*")
