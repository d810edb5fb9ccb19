"""MinHash near-duplicates by an LSH forest.

A document is the set of its distinct word shingles.  Equal sets are one class, which gets ``HASHES``
MinHash values; every tree sorts the classes by its own ``DEPTH`` of them.  Classes next to each other in
a tree are candidates if they share a prefix of ``SHORTEST`` values.  Where candidates join more than
``CROWD`` classes, these get trees of 5 and then, where still crowded, of 6 values: as many of them
(``MORE_TREES``) that a pair at the threshold 0.8 keeps its odds of 0.9998 to share a key in some tree, since
(1 - 0.8**4)**16, (1 - 0.8**5)**22 and (1 - 0.8**6)**28 are all about 0.0002.

Candidates that hang together form a cluster, and all links of a cluster are confirmed on full sets, so
a pair need not be next to each other to be found.  Each set is read once for its cluster, which is
confirmed in memory: a shingle order by frequency leaves few sets to compare (a set that reaches 80% of
another shares one of its rarest 20% of shingles), and sets that are already connected are skipped.
Clusters of more than ``BLOCK`` classes are dealt as pairs of blocks.  No pairs leave a task but one link
per class and local component.

The neighbours come from a range sort on the whole order, ties broken by class, so that a region of any
size is spread over tasks; the pairs across task borders are added from the border rows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from incstate.llm.common import Ragged, bound_batches, cut, flat, mix64, slices, written
from incstate.llm.components import connected_components

WORDS = 4
TREES = 16
DEPTH = 8
SHORTEST = 4
#: Trees of crowded regions by depth.
MORE_TREES = {5: 22, 6: 28}
HASHES = max(TREES * DEPTH, *(d * t for d, t in MORE_TREES.items()))
#: Classes that a region may join at one depth before it is cut deeper.
CROWD = 20_000
BLOCK = 1024

_STEP = np.array([1, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F, 0xE7037ED1A0B428DB, 0x8EBC6AF09C88C6E3], np.uint64)


def shingle_sets(texts: pa.Array, words: int = WORDS) -> tuple[np.ndarray, np.ndarray]:
    """All documents' distinct shingle hashes, document after document and ascending in each, and their numbers."""
    ragged = Ragged(texts, lower=True)
    h, first, counts = ragged.hashes(), ragged.first, ragged.counts
    run = np.zeros(len(h), np.uint64)
    tag = np.uint64(0x9FB21C651E98DF25)
    for j in range(words):
        run[: len(h) - j] += h[j:] * _STEP[j]
    run = mix64(run)
    sets = []
    for a, n in zip(first[:-1].tolist(), counts.tolist()):
        if n >= words:
            sets.append(np.unique(run[a : a + n - words + 1]))
        elif n:
            whole = (h[a : a + n] * _STEP[:n]).sum(dtype=np.uint64, keepdims=True)
            sets.append(mix64(whole + tag * np.full(1, n, np.uint64)))
        else:
            sets.append(np.zeros(0, np.uint64))
    return (np.concatenate(sets) if sets else np.zeros(0, np.uint64)), np.array([len(s) for s in sets], np.int64)


def signatures(values: np.ndarray, counts: np.ndarray, hashes: int = HASHES, seed: int = 5) -> np.ndarray:
    """``uint32[documents, hashes]`` of MinHash values; rows of empty sets hold the largest value."""
    out = np.full((len(counts), hashes), 0xFFFFFFFF, np.uint32)
    some = counts > 0
    if not some.any():
        return out
    starts = (np.cumsum(counts) - counts)[some]
    draw = np.random.default_rng(seed)
    factor = draw.integers(1, 1 << 63, hashes, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
    shift = draw.integers(0, 1 << 63, hashes, dtype=np.uint64)
    held = np.empty_like(values)
    for i in range(hashes):
        np.bitwise_xor(values, shift[i], out=held)
        np.multiply(held, factor[i], out=held)
        out[some, i] = np.minimum.reduceat(held, starts) >> np.uint64(32)
    return out


def _class_keys(values: np.ndarray, counts: np.ndarray) -> np.ndarray:
    total = np.zeros(len(counts), np.uint64)
    some = counts > 0
    if some.any():
        total[some] = np.add.reduceat(mix64(values ^ np.uint64(0x5851F42D4C957F2D)), (np.cumsum(counts) - counts)[some])
    return mix64(total + counts.astype(np.uint64)).view(np.int64)


@F.arrow_udf(T.StructType().add("n", "long").add("node", "long").add("sig", "binary"))
def _profile(text: pa.Array) -> pa.Array:
    n, node, sig = [], [], []
    text = flat(text)
    for a, b in slices(text):
        values, counts = shingle_sets(text[a:b])
        n.append(counts)
        node.append(_class_keys(values, counts))
        sig += [row.astype(">u4").tobytes() for row in signatures(values, counts)]
    return pa.StructArray.from_arrays(
        [pa.array(np.concatenate(n or [np.zeros(0, np.int64)])), pa.array(np.concatenate(node or [np.zeros(0, np.int64)])), pa.array(sig, pa.binary())],
        names=["n", "node", "sig"],
    )


@F.arrow_udf(T.StructType().add("node", "long").add("set", T.ArrayType(T.LongType())))
def _keyed_set(text: pa.Array) -> pa.Array:
    values, counts, node = [np.zeros(0, np.uint64)], [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
    text = flat(text)
    for a, b in slices(text):
        v, c = shingle_sets(text[a:b])
        values.append(v)
        counts.append(c)
        node.append(_class_keys(v, c))
    ends = np.concatenate([[0], np.cumsum(np.concatenate(counts))])
    sets = pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(np.concatenate(values).view(np.int64)))
    return pa.StructArray.from_arrays([pa.array(np.concatenate(node)), sets], names=["node", "set"])


def _neighbours(batches):
    """Sorted rows (tree, key, node) to pairs next to each other; the task's first and last row as borders."""
    last = None
    names = ["a", "b", "common", "tree", "key"]

    def made(rows: list[tuple]) -> pa.RecordBatch:
        kinds = (pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.binary())
        return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], names=names)

    for batch in batches:
        out = []
        for tree, key, node in zip(*(batch.column(i).to_pylist() for i in range(3))):
            if last is None:
                out.append((node, None, 0, tree, key))
            elif tree == last[0]:
                common = _common_prefix(last[1], key)
                if common >= SHORTEST:
                    out.append((last[2], node, common, tree, None))
            last = (tree, key, node)
        yield made(out)
    if last is not None:
        yield made([(last[2], None, 0, last[0], last[1])])


def _common_prefix(a: bytes, b: bytes) -> int:
    """Number of leading values that two keys share."""
    for i in range(DEPTH):
        if a[4 * i : 4 * i + 4] != b[4 * i : 4 * i + 4]:
            return i
    return DEPTH


def _adjacent(trees: DataFrame) -> DataFrame:
    """``(a, b, common)``: classes next to each other in some tree and their longest prefix in any."""
    parts = int(trees.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    scan = cut(
        trees.repartitionByRange(parts, "tree", "key", "node")
        .sortWithinPartitions("tree", "key", "node")
        .mapInArrow(_neighbours, "a long, b long, common int, tree int, key binary")
    )
    ends = Window.orderBy("tree", "key", "a")  # two rows a task
    before = F.lag("key").over(ends)
    shared = [(F.substring(before, 1, 4 * d) == F.substring("key", 1, 4 * d)).cast("int") for d in range(SHORTEST, DEPTH + 1)]
    border = (
        scan.where("b is null")
        .withColumn("b", F.lag("a").over(ends))
        .withColumn("same", F.lag("tree").over(ends) == F.col("tree"))
        .withColumn("common", sum(shared, F.lit(SHORTEST - 1)))
        .where(f"same and a <> b and common >= {SHORTEST}")
        .select("a", "b", "common")
    )
    pairs = scan.where("b is not null").select("a", "b", "common").unionByName(border)
    return pairs.groupBy(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).agg(F.max("common").alias("common"))


def _crowded(classes: DataFrame, depth: int) -> DataFrame:
    """Links ``(u, v)`` of classes that share all ``depth`` values of some of the trees for this depth.

    One link to the smallest class of a key joins all that share it.
    """
    keys = [F.struct(F.lit(t).alias("tree"), F.substring("sig", 4 * depth * t + 1, 4 * depth).alias("key")) for t in range(MORE_TREES[depth])]
    trees = written(classes.select("node", F.explode(F.array(*keys)).alias("x")).select("x.tree", "x.key", "node"))
    low = trees.groupBy("tree", "key").agg(F.min("node").alias("u"), F.count("*").alias("size")).where("size > 1").drop("size")
    return trees.join(low, ["tree", "key"]).where("node <> u").select("u", F.col("node").alias("v")).distinct()


def _clusters(near: DataFrame, classes: DataFrame, crowd: int) -> DataFrame:
    """``(node, cluster)`` of candidates; classes in clusters above ``crowd`` are dealt anew by deeper trees."""
    done: list[DataFrame] = []
    links = near.select(F.col("a").alias("u"), F.col("b").alias("v"))
    for depth in (*MORE_TREES, None):
        found = cut(connected_components(links))
        large = found.groupBy("component").agg(F.count("*").alias("size")).where(F.col("size") > crowd)
        if depth is None or large.isEmpty():
            done.append(found)
            break
        done.append(found.join(large, "component", "left_anti"))
        inside = found.join(large, "component", "left_semi").select(F.col("id").alias("node"))
        links = cut(_crowded(classes.join(inside, "node", "left_semi"), depth))
    out = done[0]
    for more in done[1:]:
        out = out.unionByName(more)
    return out.select(F.col("id").alias("node"), F.col("component").alias("cluster"))


def linked_sets(sets: list[np.ndarray], percent: int, side: np.ndarray | None = None) -> np.ndarray:
    """Local component roots of ``sets`` under links of similarity ``percent``/100, each confirmed on full sets.

    With ``side`` only pairs on different sides are compared.
    """
    n = len(sets)
    size = np.array([len(s) for s in sets])
    owner = np.repeat(np.arange(n), size)
    _, token, count = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    # Tokens numbered by frequency, so that sorted sets begin with their rarest.
    rank = np.empty(len(count), np.int64)
    rank[np.argsort(count, kind="stable")] = np.arange(len(count))
    token = rank[token]
    token = token[np.lexsort((token, owner))]
    start = np.cumsum(size) - size

    def index(tokens: np.ndarray, owners: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        ends = np.concatenate(([0], np.cumsum(np.bincount(tokens, minlength=len(count)))))
        return ends, owners[np.argsort(tokens, kind="stable")]

    def met(tokens: np.ndarray, ends: np.ndarray, owners: np.ndarray) -> np.ndarray:
        low, long = ends[tokens], ends[tokens + 1] - ends[tokens]
        return owners[np.repeat(low - np.cumsum(long) + long, long) + np.arange(long.sum())]

    # A set that can link holds at least percent of the larger one, so it meets a prefix this long.
    prefix = size - -(-size * percent // 100) + 1
    head = np.arange(len(token)) - np.repeat(start, size) < np.repeat(prefix, size)
    every, rare = index(token, owner), index(token[head], owner[head])
    root = np.arange(n)
    for i in range(n):
        own = token[start[i] : start[i] + size[i]]
        other = np.unique(met(own[: prefix[i]], *rare))
        other = other[root[other] != root[i]]
        if side is not None:
            other = other[side[other] != side[i]]
        if not len(other):
            continue
        both = np.bincount(met(own, *every), minlength=n)[other]
        good = other[both * 100 >= (size[i] + size[other] - both) * percent]
        if len(good):
            joined = np.unique(np.append(root[good], root[i]))
            root[np.isin(root, joined)] = joined[0]
    return root


def _confirm(percent: int):
    def run(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        node = table.column("node").to_numpy()
        held = flat(table.column("set"))
        ends, values = held.offsets.to_numpy(), held.values.to_numpy(zero_copy_only=False)
        sets = [values[x:y] for x, y in zip(ends[:-1], ends[1:])]
        across = table.column("block").to_numpy() if key[1].as_py() != key[2].as_py() else None
        root = linked_sets(sets, percent, across)
        some = root != np.arange(len(root))
        return pa.table({"a": pa.array(node[some], pa.int64()), "b": pa.array(node[root[some]], pa.int64())})

    return run


def forest_links(docs: DataFrame, percent: int = 80, crowd: int = CROWD, block: int = BLOCK) -> tuple[DataFrame, DataFrame]:
    """The classes of ``docs(doc_id, text)`` and their components.

    Returns ``(rows, labels)``: ``rows(doc_id, mark, n, node)`` for every input row (``mark`` is a hash of the
    text, ``node`` names the set) and ``labels(id, component)`` for every class that is linked with another.
    """
    bound_batches(docs)
    text = F.coalesce("text", F.lit(""))
    base = docs.select("doc_id", F.xxhash64(text).alias("mark"), text.alias("text"))
    profile = written(base.select("doc_id", "mark", _profile("text").alias("p")).select("doc_id", "mark", "p.*"))
    rows = profile.select("doc_id", "mark", "n", "node")
    classes = profile.where("n > 0").groupBy("node").agg(F.first("sig").alias("sig"))
    keys = [F.struct(F.lit(t).alias("tree"), F.substring("sig", 4 * DEPTH * t + 1, 4 * DEPTH).alias("key")) for t in range(TREES)]
    trees = classes.select("node", F.explode(F.array(*keys)).alias("x")).select("x.tree", "x.key", "node")
    clusters = cut(_clusters(cut(_adjacent(written(trees))), classes, crowd))
    sizes = clusters.groupBy("cluster").agg(F.ceil(F.count("*") / F.lit(block)).cast("int").alias("blocks"))
    member = clusters.join(sizes, "cluster").withColumn("block", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int"))
    member = cut(member)
    # One row's text for each member: null and repeated ids are told apart by their texts' hashes.
    first = (
        rows.where("n > 0").groupBy("node").agg(F.min(F.struct("doc_id", "mark")).alias("rep")).join(member, "node")
        .select(F.col("rep.doc_id").alias("_id"), F.col("rep.mark").alias("_mark"))
    )
    texts = base.join(first, F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("mark") == F.col("_mark"))).select("text")
    sets = texts.select(_keyed_set("text").alias("s")).select("s.node", "s.set").join(member, "node").dropDuplicates(["node"])
    dealt = (
        sets.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
        .withColumn("x", F.least("block", "other"))
        .withColumn("y", F.greatest("block", "other"))
        .select("cluster", "x", "y", "block", "node", "set")
    )
    links = dealt.groupBy("cluster", "x", "y").applyInArrow(_confirm(percent), "a long, b long")
    return rows, connected_components(links.select(F.col("a").alias("u"), F.col("b").alias("v")))


def _named(classes: DataFrame, labels: DataFrame) -> DataFrame:
    """``classes(node, low)`` to ``(node, low)`` with the lowest ``low`` of each class's component.

    What is joined is cut off first, so that the planner can split a join with the classes of a large component.
    """
    labelled = cut(classes.join(labels, F.col("node") == F.col("id"), "left").select("node", "low", F.coalesce("component", "node").alias("label")))
    lowest = cut(labelled.groupBy("label").agg(F.min("low").alias("low")))
    return cut(labelled.select("node", "label").join(lowest, "label").select("node", "low"))


def near_duplicates(docs: DataFrame, percent: int = 80) -> DataFrame:
    """``docs(doc_id, text)`` to ``doc_id, n_shingles, component_id, kept``, one row per input row.

    ``component_id`` is the smallest doc_id reachable by links of Jaccard similarity ``percent``/100 or
    more, ``kept`` whether that is the row's own.  A document of fewer than four words has its whole
    sequence as its one shingle; null, empty and blank texts have none and link with nothing.  Repeated
    rows are linked with each other (a null id stays null and is kept).  A text of any length is one set,
    held whole by one task.  An empty table gives no rows; other columns are ignored.
    """
    rows, labels = forest_links(docs, percent)
    some = rows.where("n > 0")
    names = _named(some.groupBy("node").agg(F.min("doc_id").alias("low")), labels)
    linked = some.join(names, "node").select("doc_id", "n", F.col("low").alias("component_id"))
    alone = rows.where("n = 0").select("doc_id", "n", F.col("doc_id").alias("component_id"))
    return linked.unionByName(alone).select(
        "doc_id", F.col("n").alias("n_shingles"), "component_id", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)).alias("kept")
    )


def keep_one(docs: DataFrame, percent: int = 80) -> DataFrame:
    """One row of ``docs`` for each component, that of the smallest id, with its columns unchanged.

    Null ids come last, and of rows of one id that of the smallest text hash stays, of equal rows any one.
    Documents without words are linked with nothing and all stay.
    """
    rows, labels = forest_links(docs, percent)
    some = rows.where("n > 0").groupBy("node", "doc_id", "mark").agg(F.count("*").alias("times"))
    low = F.min(F.struct(F.col("doc_id").isNull().alias("last"), "doc_id", "mark", "times")).alias("low")
    one = _named(some.groupBy("node").agg(low), labels).select("low").distinct().select("low.doc_id", "low.mark", "low.times")
    kept = cut(one.unionByName(rows.where("n = 0").select("doc_id", "mark", F.lit(1).cast("long").alias("times")).distinct()))
    whole = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.xxhash64(F.coalesce("text", F.lit(""))).alias("_mark"))
    met = whole.join(kept, F.col("row.doc_id").eqNullSafe(F.col("doc_id")) & (F.col("_mark") == F.col("mark")))
    if not kept.where("times > 1").isEmpty():
        met = met.where("times = 1").unionByName(met.where("times > 1").dropDuplicates(["doc_id", "mark"]))
    return met.select("row.*")
