"""Embedding near-duplicates by counting collisions of sorted one-dimensional projections.

All pairs of a large table can't be counted, so counting is done within regions.  A region is the upper tail
of a seeded Gaussian direction: vectors whose projection is at least ``tail``, about ``REGION_ROWS`` of them.
Within a region every vector is projected on ``PROJECTIONS`` further directions; each projection is sorted,
every vector is a query whose window of half-width ``window`` is centred on its own value (a range of ranks,
found by bisection), and a pair collides on a projection when one lies in the other's window.  Pairs with at
least ``count`` collisions are verified by their cosine in double precision.

For unit vectors at cosine c two projections are bivariate normal with correlation c, whatever the data, and
projections are independent.  So the odds that a pair shares a region and those that it reaches the count are
binomial, and the number of directions and the count are calculated from the wanted recall, in the same way
at every size; nothing is fitted and every vector is indexed.  Directions grow with the table, their rows per
vector hardly.  Up to ``REGION_ROWS`` vectors are one region.  Where one family of directions would be too
large for a task's memory, a region is the tail of one direction of each of several families.

A pair is counted for links in the first region that it shares, so no pair table is made: tasks return link
counts per vector and, for components, one edge per vector to a local root.  A region that turns out larger
(a group of near copies may hold a third of all rows, and has that many links) is dealt to tasks as pairs of
blocks.  Equal vectors are compared once, as one vector with a multiplicity.
"""

from __future__ import annotations

import math
from statistics import NormalDist
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from incstate.llm.common import cut, flat
from incstate.llm.components import connected_components

REGION_ROWS = 2048
#: Rows of a block of a larger region.
BLOCK_ROWS = 2048
#: Directions of a family that a task holds (64 MB at 64 dimensions).
MOST_DIRECTIONS = 1 << 18
PROJECTIONS = 32
#: Half-width of a window, in deviations of the difference of two vectors at the wanted cosine.
WINDOW_SIGMAS = 1.0
#: Queries that are counted at a time against their region.
TILE = 256


class Plan(NamedTuple):
    """Calibrated settings: ``families`` of ``directions``, tail start, window half-width, least count."""

    families: int
    directions: int
    tail: float
    window: float
    count: int


def both_tails(tail: float, cosine: float) -> float:
    """Probability that two standard normals of correlation ``cosine`` both reach ``tail``."""
    x = np.linspace(max(tail, -9.0), max(tail, -9.0) + 18, 8001)
    cdf = np.array([NormalDist().cdf((cosine * v - tail) / math.sqrt(1 - cosine * cosine)) for v in x])
    return float(np.trapezoid(np.exp(-x * x / 2) / math.sqrt(2 * math.pi) * cdf, x))


def least_count(odds: float, trials: int, missed: float) -> int:
    """The largest count that ``trials`` of ``odds`` fall short of with probability ``missed`` at most."""
    below = 0.0
    for k in range(trials + 1):
        below += math.comb(trials, k) * odds**k * (1 - odds) ** (trials - k)
        if below > missed:
            return k
    return trials


def calibrate(n: int, cosine: float, recall: float = 0.98, rows: int | None = None) -> Plan:
    """Settings under which a pair at exactly ``cosine`` is verified with probability ``recall`` or more.

    Half of the misses are granted to the regions, half to the count.
    """
    share, missed = min(1.0, (rows or REGION_ROWS) / max(n, 1)), (1 - recall) / 2
    for families in (1, 2, 3, 4):
        each = share ** (1 / families)
        tail = -math.inf if each == 1 else NormalDist().inv_cdf(1 - each)
        both = 1.0 if each == 1 else both_tails(tail, cosine)
        lost = 1 - (1 - missed) ** (1 / families)
        directions = 1 if each == 1 else math.ceil(math.log(lost) / math.log1p(-both))
        if directions <= MOST_DIRECTIONS:
            break
    sigma = math.sqrt(2 - 2 * cosine)
    odds = 2 * NormalDist().cdf(WINDOW_SIGMAS) - 1
    return Plan(families, directions, tail, WINDOW_SIGMAS * sigma, least_count(odds, PROJECTIONS, missed))


def directions_of(width: int, number: int, family: int, seed: int) -> np.ndarray:
    return np.random.default_rng([seed, width, family]).standard_normal((width, number), dtype=np.float32)


def usable(vector) -> F.Column:
    """True for vectors that can have a cosine: not null, no null or non-finite entry, not all zero."""
    bad = F.exists(vector, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == F.lit(float("inf"))))
    return F.coalesce(vector.isNotNull() & ~bad & F.exists(vector, lambda x: x != 0), F.lit(False))


def _unit(values: np.ndarray) -> np.ndarray:
    x = values.astype(np.float64)
    x /= np.abs(x).max(axis=1, keepdims=True)
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def _regions(plan: Plan, seed: int):
    """Arrow kernel: vectors to one row for each region that holds them; ``regions`` are all of its vector's."""
    made: dict[tuple[int, int], np.ndarray] = {}

    def tails(x: np.ndarray, width: int, family: int) -> tuple[np.ndarray, np.ndarray]:
        if (width, family) not in made:
            made[width, family] = directions_of(width, plan.directions, family, seed)
        return np.nonzero(x @ made[width, family] >= plan.tail)

    def run(batches):
        for batch in batches:
            # So many rows at a time that their projections take 16 MB at most.
            step = max(1, (1 << 22) // plan.directions)
            for at in range(0, batch.num_rows, step):
                part = batch.slice(at, step)
                column = part.column("vector")
                widths = np.diff(column.offsets.to_numpy())
                values, ends = column.flatten().to_numpy(zero_copy_only=False), np.cumsum(widths)
                for width in np.unique(widths).tolist():
                    rows = np.flatnonzero(widths == width)
                    x = _unit(values[ends[rows][:, None] - width + np.arange(width)]).astype(np.float32)
                    row, region = tails(x, width, 0)
                    for family in range(1, plan.families):
                        more, other = tails(x, width, family)
                        count = np.bincount(more, minlength=len(rows))
                        first = np.cumsum(count) - count
                        times = count[row]
                        nth = np.arange(times.sum()) - np.repeat(np.cumsum(times) - times, times)
                        region = np.repeat(region, times) * plan.directions + other[np.repeat(first[row], times) + nth]
                        row = np.repeat(row, times)
                    count = np.bincount(row, minlength=len(rows))
                    first = np.cumsum(count) - count
                    times = count[row]
                    ends_ = np.append(0, np.cumsum(times))
                    every = region[np.repeat(first[row], times) + np.arange(ends_[-1]) - np.repeat(ends_[:-1], times)]
                    take = pa.array(rows[row])
                    yield pa.RecordBatch.from_arrays(
                        [
                            part.column("node").take(take),
                            part.column("copies").take(take),
                            column.take(take),
                            pa.array(np.full(len(row), width), pa.int32()),
                            pa.array(region, pa.int64()),
                            pa.ListArray.from_arrays(pa.array(ends_, pa.int32()), pa.array(every, pa.int64())),
                        ],
                        names=["node", "copies", "vector", "width", "region", "regions"],
                    )

    return run


class Windows(NamedTuple):
    """A region's sorted projections: each row's rank on each, and the first rank and length of its window."""

    rank: np.ndarray
    low: np.ndarray
    size: np.ndarray


def windows(x: np.ndarray, half: float, seed: int, projections: int | None = None) -> Windows:
    """The windows of the rows of ``x`` (unit vectors) on all projections."""
    number = projections or PROJECTIONS
    value = (x @ directions_of(x.shape[1], number, -1 % (1 << 32), seed).astype(np.float64)).T
    kind = np.uint16 if len(x) < 1 << 15 else np.uint32
    rank, low, size = (np.empty(value.shape, kind) for _ in range(3))
    for j, v in enumerate(value):
        order = np.argsort(v, kind="stable")
        rank[j, order] = np.arange(len(v))
        line = v[order]
        low[j] = np.searchsorted(line, v - half, "left")
        size[j] = np.searchsorted(line, v + half, "right") - low[j]
    return Windows(rank, low, size)


def collided(w: Windows, queries: slice, others: slice, least: int) -> tuple[np.ndarray, np.ndarray]:
    """Pairs (query, other) of ``least`` collisions or more, as row numbers."""
    count = np.zeros((queries.stop - queries.start, others.stop - others.start), np.uint8)
    for rank, low, size in zip(w.rank[:, others], w.low[:, queries], w.size[:, queries]):
        # Below the window the difference wraps round to a large number.
        count += (rank[None, :] - low[:, None]) < size[:, None]
    left, right = np.nonzero(count >= least)
    return left + queries.start, right + others.start


def _roots(n: int, left: np.ndarray, right: np.ndarray) -> np.ndarray:
    root = np.arange(n)
    while True:
        low = root.copy()
        np.minimum.at(low, left, root[right])
        np.minimum.at(low, right, root[left])
        low = np.minimum(low, low[low])
        if (low == root).all():
            return root
        root = low


def _first_shared(regions: np.ndarray, left: np.ndarray, right: np.ndarray, here: int) -> np.ndarray:
    """Whether ``here`` is the first region of each pair; ``regions`` are padded, -1 and -2 on the two sides."""
    out = np.ones(len(left), bool)
    before = np.where(regions < here, regions, -1)
    for at in range(0, len(left), 1 << 15):
        s = slice(at, at + (1 << 15))
        a, b = before[left[s]], before[right[s]]
        out[s] = ~((a[:, :, None] == b[:, None, :]) & (a[:, :, None] >= 0)).any(axis=(1, 2))
    return out


def _link_task(plan: Plan, cosine: float, seed: int):
    def run(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        width, here, a, b = (k.as_py() for k in key)
        table = table.sort_by([("block", "ascending"), ("node", "ascending")])
        node, copies = table.column("node").to_numpy(), table.column("copies").to_numpy()
        n, split = len(node), int((table.column("block").to_numpy() == a).sum())
        x = _unit(flat(table.column("vector")).flatten().to_numpy(zero_copy_only=False).reshape(n, width))
        lists = flat(table.column("regions"))
        held = np.diff(lists.offsets.to_numpy())
        regions = np.full((n, held.max()), -1, np.int64)
        regions[np.arange(held.max()) < held[:, None]] = lists.flatten().to_numpy()
        w = windows(x, plan.window, seed)
        links, lefts, rights = np.zeros(n, np.int64), [], []
        for at in range(0, split, TILE):
            queries = slice(at, min(at + TILE, split))
            others = slice(at, n) if a == b else slice(split, n)
            left, right = collided(w, queries, others, plan.count)
            ahead = left < right
            left, right = left[ahead], right[ahead]
            near = np.empty(len(left), bool)
            for k in range(0, len(left), 1 << 15):
                s = slice(k, k + (1 << 15))
                near[s] = np.einsum("ij,ij->i", x[left[s]], x[right[s]]) >= cosine
            left, right = left[near], right[near]
            mine = _first_shared(regions, left, right, here)
            left, right = left[mine], right[mine]
            np.add.at(links, left, copies[right])
            np.add.at(links, right, copies[left])
            # One edge per row and tile is enough for the components.
            root = _roots(n, left, right)
            some = np.flatnonzero(root != np.arange(n))
            lefts.append(some)
            rights.append(root[some])
        root = _roots(n, np.concatenate(lefts), np.concatenate(rights)) if lefts else np.arange(n)
        some = links > 0
        return pa.table({"node": node[some], "links": links[some], "root": node[root[some]]})

    return run


def collision_links(vectors: DataFrame, cosine: float = 0.9, recall: float = 0.98, seed: int = 23) -> DataFrame:
    """``vectors(vec_id, embedding)`` to ``vec_id, n_links, component_id, kept``, one row per input row.

    Vectors that are null, all zero, or hold null or non-finite entries link with nothing, nor do vectors
    of different lengths.  Equal vectors (ties, repeated rows) are linked with each other, and with
    whatever any one of them is linked with.  Vectors are told apart by themselves, not by their ids:
    rows of one id are separate vectors.  ``component_id`` passes over null ids and is null only where a
    component has no other; ``kept`` holds where it is the row's own id, null for null included.  An
    empty table gives no rows; other columns are ignored.
    """
    kind = vectors.schema["embedding"].dataType
    wanted = "float" if isinstance(kind, T.ArrayType) and isinstance(kind.elementType, T.FloatType) else "double"
    base = cut(vectors.select("vec_id", F.col("embedding").cast(f"array<{wanted}>").alias("vector")).withColumn("ok", usable(F.col("vector"))))
    classes = cut(
        base.where("ok").groupBy("vector").agg(F.min("vec_id").alias("rep"), F.count("*").alias("copies"))
        .withColumn("node", F.monotonically_increasing_id())
    )
    plan = calibrate(classes.count(), cosine, recall)
    members = cut(
        classes.select("node", "copies", "vector").mapInArrow(
            _regions(plan, seed), f"node long, copies long, vector array<{wanted}>, width int, region long, regions array<long>"
        )
    )
    sizes = members.groupBy("width", "region").agg(F.count("*").alias("rows")).where("rows > 1")
    blocks = F.when(F.col("rows") <= 2 * BLOCK_ROWS, 1).otherwise(F.ceil(F.col("rows") / F.lit(BLOCK_ROWS))).cast("int")
    dealt = (
        members.join(sizes.select("width", "region", blocks.alias("blocks")), ["width", "region"])
        .withColumn("block", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int"))
        .withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
        .withColumn("a", F.least("block", "other"))
        .withColumn("b", F.greatest("block", "other"))
    )
    found = cut(dealt.groupBy("width", "region", "a", "b").applyInArrow(_link_task(plan, cosine, seed), "node long, links long, root long"))
    links = found.groupBy("node").agg(F.sum("links").alias("links"))
    groups = connected_components(found.select(F.col("node").alias("u"), F.col("root").alias("v")))
    labelled = cut(
        classes.select("node", "rep").join(groups, F.col("node") == F.col("id"), "left").select("node", "rep", F.coalesce("component", "node").alias("label"))
    )
    lowest = cut(labelled.groupBy("label").agg(F.min("rep").alias("component_id")))
    linked = (
        classes.select("node", "vector", "copies").join(links, "node", "left")
        .join(labelled.join(lowest, "label").select("node", "component_id"), "node")
        .select("vector", (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("n_links"), "component_id")
    )
    good = base.where("ok").join(cut(linked), "vector").select("vec_id", "n_links", "component_id")
    alone = base.where("not ok").select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    return good.unionByName(alone).withColumn("kept", F.col("vec_id").eqNullSafe(F.col("component_id")))
