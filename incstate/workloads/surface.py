"""Registered queries: relational operators, functions, streams and user functions over the derived tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from incstate.functions import udfs
from incstate.operators import graph, relational
from incstate.operators.partition import derive_partitions
from incstate.plans.baselines import dense_unitary_apply
from incstate.plans.wide import Gate
from incstate.sources.tables import table
from incstate.streaming import edits
from incstate.workloads import circuits, sql, states
from incstate.workloads.queries import _EMB, _LINES, B, N, _line_parts, _literal, _quantised, _rows_of, fixed, register

_PARTS = sql.slot_parts(_LINES, N, B)

# Roll-ups of circuit statistics over the customers' hierarchy

_OWNED = f"""SELECT r_name, n_name, kind, CAST(CASE WHEN kind = 'CNOT' THEN 1 ELSE 0 END AS BIGINT) AS cnot FROM ({sql.ORDERS}) g
  JOIN orders ON o_orderkey = circuit_id JOIN customer ON c_custkey = o_custkey JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey"""


def _owned(spark, sf_dir) -> DataFrame:
    t = lambda name: table(spark, sf_dir, name)
    places = t("nation").join(t("region"), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "n_name", "r_name")
    owners = t("orders").select("o_orderkey", "o_custkey").join(t("customer").select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
    # Nations are 25 rows at every size.
    owners = owners.join(F.broadcast(places), F.col("c_nationkey") == F.col("n_nationkey"))
    gates = circuits.order_gates(spark, sf_dir).select("circuit_id", "kind", (F.col("kind") == "CNOT").cast("long").alias("cnot"))
    return gates.join(owners, F.col("circuit_id") == F.col("o_orderkey")).select("r_name", "n_name", "kind", "cnot")


def _filled(df: DataFrame, *cols: str) -> DataFrame:
    return df.select(*[F.coalesce(c, F.lit("all")).alias(c) if c in cols else F.col(c) for c in df.columns])


@register("stats_rollup", f"SELECT coalesce(r_name, 'all') AS r_name, coalesce(n_name, 'all') AS n_name, count(*) AS gates, CAST(sum(cnot) AS BIGINT) AS cnots FROM ({_OWNED}) GROUP BY ROLLUP (r_name, n_name)")
def stats_rollup(spark, sf_dir):
    made = _owned(spark, sf_dir).rollup("r_name", "n_name").agg(F.count("*").alias("gates"), F.sum("cnot").alias("cnots"))
    return _filled(made, "r_name", "n_name")


@register("stats_cube", f"SELECT coalesce(r_name, 'all') AS r_name, coalesce(kind, 'all') AS kind, count(*) AS gates FROM ({_OWNED}) GROUP BY CUBE (r_name, kind)")
def stats_cube(spark, sf_dir):
    return _filled(_owned(spark, sf_dir).cube("r_name", "kind").agg(F.count("*").alias("gates")), "r_name", "kind")


@register("stats_grouping_sets", f"SELECT coalesce(r_name, 'all') AS r_name, coalesce(kind, 'all') AS kind, count(*) AS gates FROM ({_OWNED}) GROUP BY GROUPING SETS ((r_name), (kind), ())")
def stats_grouping_sets(spark, sf_dir):
    r, k = F.col("r_name"), F.col("kind")
    return _filled(_owned(spark, sf_dir).groupingSets([[r], [k], []], r, k).agg(F.count("*").alias("gates")), "r_name", "kind")


_PIVOT = ("H", "X", "CNOT", "RX")


@register("stats_pivot", "SELECT circuit_id, " + ", ".join(f"CAST(sum(CASE WHEN kind = '{k}' THEN 1 ELSE 0 END) AS BIGINT) AS {k.lower()}" for k in _PIVOT) + f" FROM ({sql.ORDERS}) GROUP BY circuit_id")
def stats_pivot(spark, sf_dir):
    made = circuits.order_gates(spark, sf_dir).groupBy("circuit_id").pivot("kind", list(_PIVOT)).count()
    return made.select("circuit_id", *[F.coalesce(k, F.lit(0).cast("long")).alias(k.lower()) for k in _PIVOT])


# Joins


@register("join_broadcast", "SELECT p_type, count(*) AS gates FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_type")
def join_broadcast(spark, sf_dir):
    """The gate library is left to the planner's own size check."""
    library = table(spark, sf_dir, "part").select("p_partkey", "p_type")
    return table(spark, sf_dir, "lineitem").select("l_partkey").join(library, F.col("l_partkey") == F.col("p_partkey")).groupBy("p_type").agg(F.count("*").alias("gates"))


_OVER = f"""SELECT a.circuit_id, a.slot_no AS slot_a, a.part_no AS part_a, b.slot_no AS slot_b, b.part_no AS part_b FROM ({_PARTS}) a JOIN ({_PARTS}) b
  ON a.circuit_id = b.circuit_id AND a.slot_no < b.slot_no AND a.lo_block <= b.hi_block AND b.lo_block <= a.hi_block"""


@register("join_interval", _OVER)
def join_interval(spark, sf_dir):
    """Overlapping partitions by a binned range join."""
    parts = _line_parts(spark, sf_dir).select("circuit_id", "slot_no", "part_no", F.col("lo_block").alias("lo"), F.col("hi_block").alias("hi"))
    met = relational.interval_join(parts, parts, ["circuit_id"], bin_size=4).where("slot_no < r_slot_no")
    return met.select("circuit_id", F.col("slot_no").alias("slot_a"), F.col("part_no").alias("part_a"), F.col("r_slot_no").alias("slot_b"), F.col("r_part_no").alias("part_b"))


@register("join_theta_overlap", _OVER)
def join_theta_overlap(spark, sf_dir):
    """The same by an equi-join with range conditions."""
    a, b = _line_parts(spark, sf_dir).alias("a"), _line_parts(spark, sf_dir).alias("b")
    on = (F.col("a.circuit_id") == F.col("b.circuit_id")) & (F.col("a.slot_no") < F.col("b.slot_no")) & (F.col("a.lo_block") <= F.col("b.hi_block")) & (F.col("b.lo_block") <= F.col("a.hi_block"))
    return a.join(b, on).select("a.circuit_id", F.col("a.slot_no").alias("slot_a"), F.col("a.part_no").alias("part_a"), F.col("b.slot_no").alias("slot_b"), F.col("b.part_no").alias("part_b"))


@register(
    "join_asof",
    """SELECT e.event_id, coalesce(s.event_id, -1) AS net FROM (SELECT * FROM events WHERE event_type = 'view') e
    ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'signup') s ON e.user_id = s.user_id AND e.ts >= s.ts""",
)
def join_asof(spark, sf_dir):
    """Each view with the user's latest signup before it."""
    e = table(spark, sf_dir, "events").select("event_id", "user_id", "ts", "event_type")
    opened = e.where("event_type = 'signup'").select("user_id", "ts", F.col("event_id").alias("net"))
    met = relational.asof_join(e.where("event_type = 'view'").drop("event_type"), opened, ["user_id"], "ts", "net")
    return met.select("event_id", F.coalesce("net", F.lit(-1).cast("long")).alias("net"))


@register("join_semi", f"SELECT circuit_id, gate_no FROM ({sql.ORDERS}) WHERE circuit_id IN (SELECT o_orderkey FROM orders WHERE o_orderstatus = 'F')")
def join_semi(spark, sf_dir):
    done = table(spark, sf_dir, "orders").where("o_orderstatus = 'F'").select(F.col("o_orderkey").alias("circuit_id"))
    return circuits.order_gates(spark, sf_dir).join(done, "circuit_id", "left_semi").select("circuit_id", "gate_no")


@register("join_anti", f"SELECT circuit_id, gate_no FROM ({sql.ORDERS}) WHERE circuit_id NOT IN (SELECT o_orderkey FROM orders WHERE o_orderstatus = 'F')")
def join_anti(spark, sf_dir):
    done = table(spark, sf_dir, "orders").where("o_orderstatus = 'F'").select(F.col("o_orderkey").alias("circuit_id"))
    return circuits.order_gates(spark, sf_dir).join(done, "circuit_id", "left_anti").select("circuit_id", "gate_no")


@register(
    "join_full_diff",
    """WITH a AS (SELECT l_partkey % 64 AS idx, count(*) AS x FROM lineitem WHERE l_quantity < 10 GROUP BY 1), b AS (SELECT l_partkey % 64 AS idx, count(*) AS y FROM lineitem WHERE l_quantity > 48 GROUP BY 1)
    SELECT coalesce(a.idx, b.idx) AS idx, coalesce(x, 0) - coalesce(y, 0) AS diff FROM a FULL JOIN b ON a.idx = b.idx""",
)
def join_full_diff(spark, sf_dir):
    """Two sparse histograms subtracted; missing rows are zeros."""
    lines = table(spark, sf_dir, "lineitem")
    count = lambda rule, name: lines.where(rule).groupBy(F.pmod("l_partkey", F.lit(64)).alias("idx")).agg(F.count("*").alias(name))
    zero = F.lit(0).cast("long")
    return count("l_quantity < 10", "x").join(count("l_quantity > 48", "y"), "idx", "full_outer").select("idx", (F.coalesce("x", zero) - F.coalesce("y", zero)).alias("diff"))


@register(
    "join_lateral_terms",
    f"""SELECT circuit_id, gate_no, r AS row_bit, c AS col_bit, {sql.fixed('x')} AS re_q, {sql.fixed('y')} AS im_q FROM (
      SELECT circuit_id, gate_no, unnest([0, 0, 1, 1]) AS r, unnest([0, 1, 0, 1]) AS c, unnest([ar, br, cr, dr]) AS x, unnest([ai, bi, ci, di]) AS y FROM ({sql.entries(sql.ORDERS)}))
    WHERE abs(x) + abs(y) > 1e-12""",
)
def join_lateral_terms(spark, sf_dir):
    """The nonzero matrix terms of each gate by a lateral call of a table function."""
    udfs.register_all(spark)
    circuits.order_gates(spark, sf_dir).createOrReplaceTempView("lateral_gates")
    made = spark.sql("SELECT g.circuit_id, g.gate_no, t.row_bit, t.col_bit, t.re, t.im FROM lateral_gates g, LATERAL gate_terms(g.kind, g.theta) t")
    return made.select("circuit_id", "gate_no", "row_bit", "col_bit", fixed(F.col("re")).alias("re_q"), fixed(F.col("im")).alias("im_q"))


_CROSS = [Gate("H", (0,)), Gate("CNOT", (4, 0)), Gate("RY", (2,), 0.8)]


@register("join_cross_unitary", sql.amplitude_rows(sql.states(_literal(_CROSS), 6, _EMB)))
def join_cross_unitary(spark, sf_dir):
    """The dense matrix as a join on the source index and a sum."""
    return _quantised(dense_unitary_apply(_rows_of(spark, sf_dir), 6, _CROSS))


# Windows


@register("win_rank", f"SELECT circuit_id, gate_no, row_number() OVER w AS nth, rank() OVER k AS kind_rank, dense_rank() OVER k AS kind_dense, ntile(3) OVER w AS third FROM ({sql.ORDERS}) WINDOW w AS (PARTITION BY circuit_id ORDER BY (circuit_id * 48271 + gate_no * 16807) % 2147483647, gate_no), k AS (PARTITION BY circuit_id ORDER BY kind)")
def win_rank(spark, sf_dir):
    w = Window.partitionBy("circuit_id").orderBy(circuits.level_rank(F.col("circuit_id"), F.col("gate_no")), "gate_no")
    k = Window.partitionBy("circuit_id").orderBy("kind")
    return circuits.order_gates(spark, sf_dir).select("circuit_id", "gate_no", F.row_number().over(w).alias("nth"), F.rank().over(k).alias("kind_rank"), F.dense_rank().over(k).alias("kind_dense"), F.ntile(3).over(w).alias("third"))


@register("win_lag_link", f"SELECT circuit_id, k AS block_id, slot_no, coalesce(lag(slot_no) OVER w, -1) AS before, coalesce(lead(slot_no) OVER w, -1) AS after FROM (SELECT *, unnest(range(lo_block, hi_block + 1)) AS k FROM ({_PARTS})) WINDOW w AS (PARTITION BY circuit_id, k ORDER BY slot_no)")
def win_lag_link(spark, sf_dir):
    w = Window.partitionBy("circuit_id", "block_id").orderBy("slot_no")
    blocks = graph.written_blocks(_line_parts(spark, sf_dir))
    return blocks.select("circuit_id", "block_id", "slot_no", F.coalesce(F.lag("slot_no").over(w), F.lit(-1)).alias("before"), F.coalesce(F.lead("slot_no").over(w), F.lit(-1)).alias("after"))


@register(
    "win_running_max",
    f"""WITH RECURSIVE p AS (SELECT circuit_id, lo_block AS lo, hi_block AS hi FROM ({_PARTS}) WHERE mode = 'mono'),
    n AS (SELECT *, row_number() OVER (PARTITION BY circuit_id ORDER BY lo, hi) AS nth FROM p),
    r AS (SELECT circuit_id, nth, lo, hi, 1 AS isle FROM n WHERE nth = 1
      UNION ALL SELECT n.circuit_id, n.nth, CASE WHEN n.lo <= r.hi THEN r.lo ELSE n.lo END, CASE WHEN n.lo <= r.hi THEN greatest(r.hi, n.hi) ELSE n.hi END, CASE WHEN n.lo <= r.hi THEN isle ELSE isle + 1 END
      FROM r JOIN n ON n.circuit_id = r.circuit_id AND n.nth = r.nth + 1)
    SELECT circuit_id, min(lo) AS lo, max(hi) AS hi, count(*) AS n FROM r GROUP BY circuit_id, isle""",
)
def win_running_max(spark, sf_dir):
    """Partitions of a circuit fused where their spans overlap."""
    parts = _line_parts(spark, sf_dir).where("mode = 'mono'").select("circuit_id", F.col("lo_block").alias("lo"), F.col("hi_block").alias("hi"))
    return relational.islands(parts, ["circuit_id"])


@register("win_moving_avg", f"SELECT user_id, event_id, {sql.fixed('avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 4 PRECEDING AND CURRENT ROW)')} AS avg_q FROM events")
def win_moving_avg(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-4, 0)
    return table(spark, sf_dir, "events").select("user_id", "event_id", fixed(F.avg("value").over(w)).alias("avg_q"))


@register("win_range_frame", f"SELECT user_id, event_id, count(*) OVER w AS edits, {sql.fixed('sum(value) OVER w')} AS sum_q FROM events WINDOW w AS (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW)")
def win_range_frame(spark, sf_dir):
    """Edits of the day before each one, ties included."""
    w = Window.partitionBy("user_id").orderBy("at").rangeBetween(-86_400_000_000, 0)
    at = F.expr("timestampdiff(MICROSECOND, TIMESTAMP_NTZ '1970-01-01', ts)")
    e = table(spark, sf_dir, "events").select("user_id", "event_id", "value", at.alias("at"))
    return e.select("user_id", "event_id", F.count("*").over(w).alias("edits"), fixed(F.sum("value").over(w)).alias("sum_q"))


@register("win_last_value", "SELECT user_id, event_id, coalesce(last_value(CASE WHEN event_type = 'signup' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), -1) AS net FROM events")
def win_last_value(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    net = F.last(F.when(F.col("event_type") == "signup", F.col("event_id")), ignorenulls=True).over(w)
    return table(spark, sf_dir, "events").select("user_id", "event_id", F.coalesce(net, F.lit(-1).cast("long")).alias("net"))


@register("win_cumulative_prob", f"SELECT circuit_id, idx, {sql.fixed('sum(x * x) OVER (PARTITION BY circuit_id ORDER BY idx)')} AS c_q FROM (SELECT circuit_id, unnest(range(0, 64)) AS idx, unnest(re) AS x FROM ({_EMB}))")
def win_cumulative_prob(spark, sf_dir):
    w = Window.partitionBy("circuit_id").orderBy("idx")
    return _rows_of(spark, sf_dir).select("circuit_id", "idx", fixed(F.sum(F.col("re") * F.col("re")).over(w)).alias("c_q"))


# Set operations over blocks

_FIRST = f"SELECT DISTINCT circuit_id, k AS block_id FROM (SELECT *, unnest(range(lo_block, hi_block + 1)) AS k FROM ({_PARTS})) WHERE slot_no = 0"
_SECOND = _FIRST.replace("slot_no = 0", "slot_no = 1")


def _slot_blocks(spark, sf_dir, slot: int) -> DataFrame:
    return graph.written_blocks(_line_parts(spark, sf_dir).where(F.col("slot_no") == slot)).select("circuit_id", "block_id")


@register("set_union_frontier", f"{_FIRST} UNION {_SECOND}")
def set_union_frontier(spark, sf_dir):
    return _slot_blocks(spark, sf_dir, 0).unionByName(_slot_blocks(spark, sf_dir, 1)).distinct()


@register("set_intersect_blocks", f"{_FIRST} INTERSECT {_SECOND}")
def set_intersect_blocks(spark, sf_dir):
    return _slot_blocks(spark, sf_dir, 0).intersect(_slot_blocks(spark, sf_dir, 1))


@register("set_except_clean", f"{_FIRST} EXCEPT {_SECOND}")
def set_except_clean(spark, sf_dir):
    return _slot_blocks(spark, sf_dir, 0).subtract(_slot_blocks(spark, sf_dir, 1))


@register("set_except_all", f"SELECT kind, target FROM ({sql.ORDERS}) EXCEPT ALL SELECT kind, target FROM ({sql.PARTS})")
def set_except_all(spark, sf_dir):
    return circuits.order_gates(spark, sf_dir).select("kind", "target").exceptAll(circuits.part_gates(spark, sf_dir).select("kind", "target"))


# Approximations (their error bounds are tested)


@register("approx_basis_distinct")
def approx_basis_distinct(spark, sf_dir):
    lines = table(spark, sf_dir, "lineitem")
    return lines.groupBy("l_linenumber").agg(F.approx_count_distinct("l_partkey", 0.02).alias("near"), F.countDistinct("l_partkey").alias("exact"))


@register("approx_heavy_outcomes", "SELECT l_partkey % 32 AS item, count(*) AS count FROM lineitem GROUP BY 1 QUALIFY rank() OVER (ORDER BY count(*) DESC) <= 5")
def approx_heavy_outcomes(spark, sf_dir):
    """The five most frequent outcomes and ties with the fifth; the sketch is exact for so few distinct ones."""
    top = table(spark, sf_dir, "lineitem").agg(F.expr("approx_top_k(l_partkey % 32, 32)").alias("top"))
    fifth = F.element_at("top", F.least(F.size("top"), F.lit(5)))["count"]
    return top.select(fifth.alias("least"), F.explode("top").alias("x")).where("x.count >= least").select("x.*")


@register("approx_prob_quantile")
def approx_prob_quantile(spark, sf_dir):
    p = F.col("re") * F.col("re")
    return _rows_of(spark, sf_dir).groupBy("circuit_id").agg(F.percentile_approx(p, 0.5, 1000).alias("median"), F.expr("percentile(re * re, 0.5)").alias("exact"))


# Scalar functions


@register("scalar_bits", "SELECT l_orderkey, l_linenumber, l_partkey, bit_count(l_partkey) AS ones, xor(l_partkey, 85) & 1023 AS flipped, (l_partkey >> 3) & 1 AS bit3, l_suppkey << 2 AS scaled FROM lineitem")
def scalar_bits(spark, sf_dir):
    p = F.col("l_partkey")
    return table(spark, sf_dir, "lineitem").select(
        "l_orderkey", "l_linenumber", "l_partkey", F.bit_count(p).cast("long").alias("ones"), p.bitwiseXOR(85).bitwiseAND(1023).alias("flipped"),
        F.shiftright(p, 3).bitwiseAND(1).alias("bit3"), F.shiftleft("l_suppkey", 2).alias("scaled"),
    )


@register("scalar_strings", "SELECT doc_id, length(text) AS chars, len(string_split(text, ' ')) AS words, lower(lang) || '-' || source AS tag, lpad(CAST(doc_id AS VARCHAR), 8, '0') AS padded FROM documents")
def scalar_strings(spark, sf_dir):
    d = table(spark, sf_dir, "documents")
    return d.select("doc_id", F.length("text").cast("long").alias("chars"), F.size(F.split("text", " ")).cast("long").alias("words"), F.concat_ws("-", F.lower("lang"), "source").alias("tag"), F.lpad(F.col("doc_id").cast("string"), 8, "0").alias("padded"))


@register("scalar_dates", "SELECT event_id, strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, hour(ts) AS hour, epoch_us(ts) AS micros FROM events")
def scalar_dates(spark, sf_dir):
    e = table(spark, sf_dir, "events")
    return e.select("event_id", F.to_date("ts").cast("string").alias("day"), F.hour("ts").cast("long").alias("hour"), F.expr("timestampdiff(MICROSECOND, TIMESTAMP_NTZ '1970-01-01', ts)").alias("micros"))


@register("scalar_arrays", f"SELECT vec_id, {sql.fixed('list_sum(list_transform(embedding[1:8], lambda v: CAST(v AS DOUBLE) * v))')} AS head_q, len(list_filter(embedding, lambda v: v > 0)) AS positive, {sql.fixed('list_max(list_transform(embedding, lambda v: CAST(v AS DOUBLE)))')} AS top_q FROM embeddings")
def scalar_arrays(spark, sf_dir):
    v = F.transform("embedding", lambda x: x.cast("double"))
    head = F.aggregate(F.slice(v, 1, 8), F.lit(0.0), lambda s, x: s + x * x)
    return table(spark, sf_dir, "embeddings").select("vec_id", fixed(head).alias("head_q"), F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("positive"), fixed(F.array_max(v)).alias("top_q"))


@register("scalar_maps", f"SELECT circuit_id, CAST(max(CASE WHEN kind = 'H' THEN n ELSE 0 END) AS BIGINT) AS h, count(*) AS kinds FROM (SELECT circuit_id, kind, count(*) AS n FROM ({sql.ORDERS}) GROUP BY ALL) GROUP BY circuit_id")
def scalar_maps(spark, sf_dir):
    per = circuits.order_gates(spark, sf_dir).groupBy("circuit_id", "kind").agg(F.count("*").alias("n"))
    m = per.groupBy("circuit_id").agg(F.map_from_entries(F.collect_list(F.struct("kind", "n"))).alias("m"))
    return m.select("circuit_id", F.coalesce(F.try_element_at("m", F.lit("H")), F.lit(0).cast("long")).alias("h"), F.map_size("m").cast("long").alias("kinds") if hasattr(F, "map_size") else F.size("m").cast("long").alias("kinds"))


@register("scalar_json", "SELECT event_id, CAST(json_extract(props, '$.k') AS INT) AS k, CAST(json_extract(props, '$.k') AS INT) % 4 AS target FROM events")
def scalar_json(spark, sf_dir):
    k = F.from_json("props", "k int")["k"]
    return table(spark, sf_dir, "events").select("event_id", k.alias("k"), F.pmod(k, F.lit(4)).alias("target"))


# Streams, run to the end of their input


@register("stream_tumbling", "SELECT user_id, epoch_us(date_trunc('day', ts)) AS start, count(*) AS edits, CAST(sum(CASE WHEN event_type = 'error' THEN 1 ELSE 0 END) AS BIGINT) AS removals FROM events GROUP BY 1, 2")
def stream_tumbling(spark, sf_dir):
    done = edits.drained(edits.iterations(edits.event_stream(spark, sf_dir)), "complete")
    return done.select("user_id", F.unix_micros(F.col("window.start")).alias("start"), "edits", "removals")


@register(
    "stream_sliding",
    "SELECT user_id, start, count(*) AS edits FROM (SELECT user_id, unnest([epoch_us(date_trunc('day', ts)), epoch_us(date_trunc('day', ts)) - 86400000000]) AS start FROM events) GROUP BY ALL",
)
def stream_sliding(spark, sf_dir):
    done = edits.drained(edits.iterations(edits.event_stream(spark, sf_dir), "2 days", "1 day"), "complete")
    return done.select("user_id", F.unix_micros(F.col("window.start")).alias("start"), "edits")


@register(
    "stream_session",
    """SELECT user_id, epoch_us(min(ts)) AS start, count(*) AS edits FROM (
      SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS nth FROM (
        SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events)) GROUP BY user_id, nth""",
)
def stream_session(spark, sf_dir):
    done = edits.drained(edits.bursts(edits.event_stream(spark, sf_dir)), "complete")
    return done.select("user_id", F.unix_micros(F.col("session_window.start")).alias("start"), "edits")


@register("stream_dedup", "SELECT DISTINCT event_id FROM events")
def stream_dedup(spark, sf_dir):
    return edits.drained(edits.once(edits.event_stream(spark, sf_dir))).select("event_id")


@register("stream_static_join", "SELECT event_id, CASE event_type WHEN 'click' THEN 'CNOT' WHEN 'view' THEN 'H' ELSE 'RZ' END AS kind FROM events WHERE event_type IN ('click', 'view', 'purchase')")
def stream_static_join(spark, sf_dir):
    kinds = spark.sql("SELECT * FROM VALUES ('click', 'CNOT'), ('view', 'H'), ('purchase', 'RZ') AS t(event_type, kind)")
    return edits.drained(edits.named(edits.event_stream(spark, sf_dir), kinds)).select("event_id", "kind")


@register("stream_stream_join", "SELECT a.event_id, b.event_id AS purchase_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'signup' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 2 HOUR")
def stream_stream_join(spark, sf_dir):
    return edits.drained(edits.confirmed(edits.event_stream(spark, sf_dir)))


@register("stream_stateful_circuit")
def stream_stateful_circuit(spark, sf_dir):
    """Each user's live circuit after all events (compared with the batch fold in tests)."""
    done = edits.drained(edits.stateful_circuits(edits.event_stream(spark, sf_dir)), "update")
    last = done.groupBy("circuit_id").agg(F.max_by(F.struct("live_gates", "edits", "p0"), "_batch").alias("x"))
    return last.select("circuit_id", "x.live_gates", "x.edits", fixed(F.col("x.p0")).alias("p0_q"))


@register(
    "stream_late",
    """SELECT user_id, epoch_us(day) AS start, count(*) AS edits FROM (SELECT user_id, date_trunc('day', ts) AS day FROM events)
    WHERE day + INTERVAL 1 DAY <= (SELECT max(ts) FROM events) - INTERVAL 1 HOUR GROUP BY user_id, day""",
)
def stream_late(spark, sf_dir):
    """Windows that the watermark has closed by the end of the input (append mode)."""
    done = edits.drained(edits.iterations(edits.event_stream(spark, sf_dir)))
    return done.select("user_id", F.unix_micros(F.col("window.start")).alias("start"), "edits")


# User functions


@register("udf_block_kernel", f"SELECT circuit_id, idx, {sql.fixed('CASE WHEN (idx & 1) = 0 THEN (re[idx + 1] + re[idx + 2]) / sqrt(2) ELSE (re[idx] - re[idx + 1]) / sqrt(2) END')} AS re_q FROM (SELECT circuit_id, unnest(range(0, 64)) AS idx, re FROM ({_EMB}))")
def udf_block_kernel(spark, sf_dir):
    made = states.embeddings(spark, sf_dir).select("circuit_id", F.posexplode(udfs.hadamard_blocks("re")).alias("idx", "x"))
    return made.select("circuit_id", F.col("idx").cast("long").alias("idx"), fixed(F.col("x")).alias("re_q"))


@register("udaf_fidelity", f"""SELECT a.circuit_id, {sql.fixed('pow(list_sum(list_transform(list_zip(a.re, b.re), lambda x: x[1] * x[2])), 2) + pow(list_sum(list_transform(list_zip(a.re, b.im), lambda x: x[1] * x[2])), 2)')} AS fidelity_q
    FROM ({_EMB}) a JOIN ({sql.states(_literal(_CROSS), 6, _EMB)}) b ON a.circuit_id = b.circuit_id""")
def udaf_fidelity(spark, sf_dir):
    """The squared overlap of each state with itself after three gates, by an aggregate function over rows."""
    before = _rows_of(spark, sf_dir).select("circuit_id", "idx", F.col("re").alias("ar"), F.col("im").alias("ai"))
    after = dense_unitary_apply(_rows_of(spark, sf_dir), 6, _CROSS)
    met = before.join(after, ["circuit_id", "idx"])
    return met.groupBy("circuit_id").agg(udfs.overlap("ar", "ai", "re", "im").alias("f")).select("circuit_id", fixed(F.col("f")).alias("fidelity_q"))


@register(
    "udtf_partition_ranges",
    f"SELECT circuit_id, gate_no, part_no, lo_block, hi_block, n_tasks FROM ({sql.partitions(sql.ORDERS, 5, 4)})",
)
def udtf_partition_ranges(spark, sf_dir):
    udfs.register_all(spark)
    circuits.order_gates(spark, sf_dir).createOrReplaceTempView("range_gates")
    return spark.sql(
        "SELECT g.circuit_id, g.gate_no, t.* FROM range_gates g, LATERAL partition_ranges(g.kind, g.target, CASE WHEN g.kind = 'CNOT' THEN g.control ELSE -1 END, g.theta, 5, 4) t"
    )


@register("udtf_parse_gates", f"SELECT circuit_id, CAST(gate_no AS INT) AS gate_no, kind, target, {sql.fixed('theta')} AS theta_q FROM ({sql.documents(6)})")
def udtf_parse_gates(spark, sf_dir):
    udfs.register_all(spark)
    table(spark, sf_dir, "documents").createOrReplaceTempView("parse_documents")
    made = spark.sql("SELECT d.doc_id AS circuit_id, t.* FROM parse_documents d, LATERAL parse_gates(d.text, 6) t")
    return made.select("circuit_id", "gate_no", "kind", "target", fixed(F.col("theta")).alias("theta_q"))


@register("partitions_count_by_size", f"SELECT target, count(*) AS partitions FROM (SELECT p.*, g.target FROM ({sql.partitions(sql.ORDERS, 5, 2)}) p JOIN ({sql.ORDERS}) g ON g.circuit_id = p.circuit_id AND g.gate_no = p.gate_no) GROUP BY target")
def partitions_count_by_size(spark, sf_dir):
    gates = circuits.order_gates(spark, sf_dir)
    made = derive_partitions(gates, 5, 2)
    return made.join(gates.select("circuit_id", "gate_no", "target"), ["circuit_id", "gate_no"]).groupBy("target").agg(F.count("*").alias("partitions"))


