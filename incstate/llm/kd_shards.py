"""Sharding by a k-d tree over document metadata, in DataFrame operations only.

A node of the tree owns a run of shards.  It is split where the metadata dimension in which it is widest
reaches the weighted quantile that divides its bytes as its shards divide; the quantile comes from a
histogram of byte weights over that dimension, refined inside the cut bin by the hash of the text and,
only for a text whose copies outweigh ``TOLERANCE`` of a shard, by the hash of the document id.  So equal
texts stay together unless that would unbalance the shards, and the law is "bytes": sizes near equal.
All levels together read one narrow table of metadata; what reaches the driver is one row per node.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from incstate.llm.common import cut

SHARDS = 24
BINS = 4096
#: Share of a shard's bytes below which a run of equal texts is never divided.
TOLERANCE = 0.01
SLOT_ROWS = 20_000
ROW_BYTES = 8


def default_dimensions(text: Column) -> list[Column]:
    """Length, non-ASCII share, blanks per character and line ends per character of a text."""
    chars = F.greatest(F.length(text), F.lit(1)).cast("double")
    return [
        F.log1p(F.octet_length(text).cast("double")) / F.lit(20.0),
        F.octet_length(text) / chars - F.lit(1.0),
        (F.length(text) - F.length(F.replace(text, F.lit(" "), F.lit("")))) / chars,
        (F.length(text) - F.length(F.replace(text, F.lit("\n"), F.lit("")))) / chars,
    ]


def _bits(value: Column, bits: int, skip: int = 0) -> Column:
    """``bits`` of a hash from the top, below the first ``skip``, as an int from 0."""
    return F.shiftrightunsigned(value, 64 - bits - skip).bitwiseAND((1 << bits) - 1).cast("int")


def _cut_bin(table: DataFrame, goal: str = "goal") -> DataFrame:
    """``table(node, goal, bin, weight)`` to one row per node: the bin where the running weight reaches the goal."""
    run = Window.partitionBy("node").orderBy("bin")
    reached = table.withColumn("upto", F.sum("weight").over(run)).withColumn("below", F.col("upto") - F.col("weight"))
    return reached.where((F.col("below") < F.col(goal)) & (F.col("upto") >= F.col(goal))).select("node", goal, "bin", "below", "upto")


def _values(df: DataFrame, rows: list[tuple], names: list[str]) -> DataFrame:
    """A literal table of at most one row per node."""
    body = ", ".join("(" + ", ".join(f"CAST('{float(v)!r}' AS DOUBLE)" if isinstance(v, float) else str(v) for v in r) + ")" for r in rows)
    return F.broadcast(df.sparkSession.sql(f"SELECT * FROM VALUES {body} AS t({', '.join(names)})"))


def _split(points: DataFrame, nodes: dict[int, int], dims: int, slack: float) -> tuple[DataFrame, dict[int, int]]:
    """One level: every node of more than one shard in two."""
    widths = [F.struct((F.max(f"x{d}") - F.min(f"x{d}")).alias("w"), F.min(f"x{d}").alias("lo")).alias(f"d{d}") for d in range(dims)]
    rows = points.where("open").groupBy("node").agg(F.sum("weight").alias("weight"), *widths).collect()
    params, after = [], {k: v for k, v in nodes.items() if v == 1}
    for r in rows:
        leaves = nodes[r["node"]]
        d = max(range(dims), key=lambda i: (r[f"d{i}"]["w"], -i))
        wide, low = r[f"d{d}"]["w"], r[f"d{d}"]["lo"]
        goal = r["weight"] * (leaves // 2) / leaves
        params.append((r["node"], d, float(low), float(BINS / wide if wide > 0 else 0.0), float(goal), r["node"] + leaves // 2))
        after[r["node"]], after[r["node"] + leaves // 2] = leaves // 2, leaves - leaves // 2
    if not params:
        return points, {k: 1 for k in nodes}
    table = _values(points, params, ["node", "dim", "low", "scale", "goal", "right"])
    x = F.element_at(F.array(*[f"x{d}" for d in range(dims)]), F.col("dim") + 1)
    seen = points.join(table, "node").withColumn("bin", F.least(F.lit(BINS - 1), F.floor((x - F.col("low")) * F.col("scale"))).cast("int"))
    first = _cut_bin(seen.groupBy("node", "goal", "bin").agg(F.sum("weight").alias("weight"))).collect()
    stage = [(r["node"], r["bin"], float(r["goal"] - r["below"])) for r in first]
    cuts = {r["node"]: [r["bin"], 0, 0] for r in first}
    for step, at in ((1, _bits(F.col("th"), 12)), (2, _bits(F.col("ih"), 12))):
        inner = seen.drop("goal").join(_values(points, stage, ["node", "at0", "goal", *["at1"] * (step == 2)]), "node").where("bin = at0")
        if step == 2:
            inner = inner.where(_bits(F.col("th"), 12) == F.col("at1"))
        inner = inner.select("node", "goal", at.alias("bin"), "weight")
        found = _cut_bin(inner.groupBy("node", "goal", "bin").agg(F.sum("weight").alias("weight"))).collect()
        stage = []
        for r in found:
            nearer = r["bin"] if r["goal"] - r["below"] <= r["upto"] - r["goal"] else r["bin"] + 1
            if step == 1 and r["upto"] - r["below"] > slack:
                cuts[r["node"]][1] = r["bin"]
                stage.append((r["node"], cuts[r["node"]][0], float(r["goal"] - r["below"]), r["bin"]))
            else:
                cuts[r["node"]][step] = nearer
        stage = [(n, b, g, a) for n, b, g, a in stage]
        if not stage:
            break
    places = _values(points, [(n, *c) for n, c in cuts.items()], ["node", "c0", "c1", "c2"])
    key = F.struct(F.col("bin"), _bits(F.col("th"), 12), _bits(F.col("ih"), 12))
    moved = (
        points.join(F.broadcast(table), "node", "left")
        .join(places, "node", "left")
        .withColumn("bin", F.least(F.lit(BINS - 1), F.floor((x - F.col("low")) * F.col("scale"))).cast("int"))
        .withColumn("node", F.when(F.col("open") & (key >= F.struct("c0", "c1", "c2")), F.col("right")).otherwise(F.col("node")))
        .drop("dim", "low", "scale", "goal", "right", "c0", "c1", "c2", "bin")
    )
    single = [k for k, v in after.items() if v == 1]
    return moved.withColumn("open", ~F.col("node").isin(single) if single else F.lit(True)), after


def kd_shards(docs: DataFrame, shards: int = SHARDS, dimensions: list[Column] | None = None) -> DataFrame:
    """``docs(doc_id, text)`` to ``doc_id, size, text_crc32, law, shard, slot, grown_shard``.

    ``size`` is the text's UTF-8 bytes plus 8 (a null text counts as empty).  ``shard`` runs from 0 to
    ``shards - 1`` and ``slot`` from 0 without gaps in each shard; ``grown_shard`` is null under this law.
    Null ids, empty texts, ties and repeated rows are ordinary points; rows that are equal may be divided
    between two shards only where they outweigh 1% of one.  An empty table gives no rows; other columns are
    ignored; of a very long text only its length, hashes and shares are kept after the scan.  Slots are numbered in hashed runs of about 20,000 rows whose offsets are summed first, so no
    shard is ever sorted in one task.
    """
    text = F.coalesce(F.col("text"), F.lit(""))
    dims = dimensions or default_dimensions(text)
    points = cut(
        docs.select(
            "doc_id",
            (F.octet_length(text) + F.lit(ROW_BYTES)).cast("long").alias("size"),
            F.crc32(text.cast("binary")).alias("text_crc32"),
            F.xxhash64(text).alias("th"),
            F.xxhash64(F.lit(7), F.col("doc_id")).alias("ih"),
            *[F.coalesce(d.cast("double"), F.lit(-1.0)).alias(f"x{i}") for i, d in enumerate(dims)],
        ).withColumn("weight", F.col("size").cast("double"))
    )
    whole = points.agg(F.count("*"), F.sum("weight")).first()
    slack = (whole[1] or 0.0) / shards * TOLERANCE
    tree, nodes = points.withColumn("node", F.lit(0)).withColumn("open", F.lit(shards > 1)), {0: shards}
    while any(v > 1 for v in nodes.values()):
        tree, nodes = _split(tree, nodes, len(dims), slack)
    runs = max(1, -(-whole[0] // (SLOT_ROWS * shards)))
    placed = tree.select("doc_id", "size", "text_crc32", F.col("node").alias("shard"), F.pmod("ih", F.lit(runs)).alias("run"), "th")
    before = Window.partitionBy("shard").orderBy("run").rowsBetween(Window.unboundedPreceding, -1)
    offsets = placed.groupBy("shard", "run").agg(F.count("*").alias("rows")).select(
        "shard", "run", F.coalesce(F.sum("rows").over(before), F.lit(0)).alias("offset")
    )
    order = Window.partitionBy("shard", "run").orderBy("doc_id", "th", "size")
    return (
        placed.withColumn("at", F.row_number().over(order))
        .join(offsets, ["shard", "run"])
        .select(
            "doc_id",
            "size",
            "text_crc32",
            F.lit("bytes").alias("law"),
            F.col("shard").cast("int").alias("shard"),
            (F.col("offset") + F.col("at") - 1).cast("long").alias("slot"),
            F.lit(None).cast("int").alias("grown_shard"),
        )
    )
