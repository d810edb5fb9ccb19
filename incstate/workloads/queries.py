"""Registered queries of the engine, each with the SQL that checks it where SQL can."""

from __future__ import annotations

import math
from collections.abc import Callable

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from incstate import metrics
from incstate.functions.gates import classify
from incstate.operators import graph, update
from incstate.operators.partition import derive_partitions, enumerate_partitions
from incstate.plans import many, small
from incstate.plans.wide import Gate, apply_mono, apply_superposition
from incstate.sources.tables import table
from incstate.workloads import circuits, sql, states

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def register(name: str, oracle: str | None = None) -> Callable[[Query], Query]:
    def put(f: Query) -> Query:
        QUERIES[name] = f
        if oracle:
            ORACLES[name] = oracle
        return f

    return put


def fixed(x: Column) -> Column:
    """A number as a whole multiple of 1e-8, rounded away from ties."""
    return F.floor(x * 1e8 + 0.37).cast("long")


def amplitude_rows(vectors: DataFrame, *keys: str) -> DataFrame:
    keys = keys or ("circuit_id",)
    return vectors.select(*keys, F.posexplode(F.arrays_zip("re", "im")).alias("idx", "a")).select(
        *keys, F.col("idx").cast("long").alias("idx"), fixed(F.col("a.re")).alias("re_q"), fixed(F.col("a.im")).alias("im_q")
    )


def probability_rows(rows: DataFrame) -> DataFrame:
    return rows.withColumn("p", F.col("re") * F.col("re") + F.col("im") * F.col("im"))


# States


@register(
    "encode_embeddings",
    f"""SELECT circuit_id, idx, {sql.fixed('x')} AS re_q, CAST(0 AS BIGINT) AS im_q FROM (
    SELECT vec_id AS circuit_id, unnest(range(0, 64)) AS idx, unnest(list_transform(e, lambda v: v / norm)) AS x FROM (
      SELECT vec_id, e, sqrt(list_sum(list_transform(e, lambda v: v * v))) AS norm FROM (SELECT vec_id, list_transform(embedding, lambda v: CAST(v AS DOUBLE)) AS e FROM embeddings)))""",
)
def encode_embeddings(spark, sf_dir):
    return amplitude_rows(states.embeddings(spark, sf_dir))


def _quantised(rows: DataFrame) -> DataFrame:
    return rows.select("circuit_id", "idx", fixed(F.col("re")).alias("re_q"), fixed(F.col("im")).alias("im_q"))


@register(
    "encode_histogram",
    f"""SELECT CAST(0 AS BIGINT) AS circuit_id, l_partkey % 1024 AS idx, {sql.fixed('sqrt(count(*) / CAST((SELECT count(*) FROM lineitem) AS DOUBLE))')} AS re_q, CAST(0 AS BIGINT) AS im_q
    FROM lineitem GROUP BY l_partkey % 1024""",
)
def encode_histogram(spark, sf_dir):
    return _quantised(states.histogram(spark, sf_dir))


@register(
    "encode_value",
    f"""SELECT CAST(0 AS BIGINT) AS circuit_id, o_custkey % 1024 AS idx, {sql.fixed('sqrt(sum(o_totalprice) / (SELECT sum(o_totalprice) FROM orders))')} AS re_q, CAST(0 AS BIGINT) AS im_q
    FROM orders GROUP BY o_custkey % 1024""",
)
def encode_value(spark, sf_dir):
    return _quantised(states.values(spark, sf_dir))


@register(
    "encode_events",
    f"""SELECT CAST(0 AS BIGINT) AS circuit_id, idx, {sql.fixed('a * cos(phase)')} AS re_q, {sql.fixed('a * sin(phase)')} AS im_q FROM (
    SELECT user_id % 128 AS idx, sqrt(sum(value) / (SELECT sum(value) FROM events)) AS a, pi() * 2 * min(CAST(json_extract(props, '$.k') AS INT)) / CAST(100 AS DOUBLE) AS phase
    FROM events GROUP BY user_id % 128)""",
)
def encode_events(spark, sf_dir):
    return _quantised(states.events(spark, sf_dir))


# Circuits

_GATE = "circuit_id, gate_no, net_no, kind, target, control, " + sql.fixed("theta") + " AS theta_q"


def _gate_rows(gates: DataFrame) -> DataFrame:
    return gates.select("circuit_id", "gate_no", "net_no", "kind", "target", "control", fixed(F.col("theta")).alias("theta_q"))


@register("circuit_from_orders", f"SELECT {_GATE} FROM ({sql.ORDERS})")
def circuit_from_orders(spark, sf_dir):
    return _gate_rows(circuits.order_gates(spark, sf_dir))


@register("circuit_from_suppliers", f"SELECT {_GATE} FROM ({sql.suppliers(6)})")
def circuit_from_suppliers(spark, sf_dir):
    return _gate_rows(circuits.supplier_gates(spark, sf_dir))


@register("circuit_from_part", f"SELECT {_GATE} FROM ({sql.PARTS})")
def circuit_from_part(spark, sf_dir):
    return _gate_rows(circuits.part_gates(spark, sf_dir))


@register("circuit_from_text", f"SELECT {_GATE} FROM ({sql.documents(6)})")
def circuit_from_text(spark, sf_dir):
    return _gate_rows(circuits.document_gates(spark, sf_dir))


@register("net_conflicts", f"SELECT circuit_id, net_no, gate_no, kind FROM ({sql.accepted(sql.ORDER_LINES)}) WHERE NOT accepted")
def net_conflicts(spark, sf_dir):
    return circuits.judge_nets(circuits.order_gates(spark, sf_dir, "line")).where("not accepted").select("circuit_id", "net_no", "gate_no", "kind")


@register("net_accept", f"SELECT circuit_id, net_no, gate_no, kind FROM ({sql.accepted(sql.ORDER_LINES)}) WHERE accepted")
def net_accept(spark, sf_dir):
    return circuits.accepted_gates(circuits.order_gates(spark, sf_dir, "line")).select("circuit_id", "net_no", "gate_no", "kind")


_MODE = "CASE shape WHEN 'mix' THEN 'sup' WHEN 'id' THEN 'id' ELSE 'mono' END"


@register("gate_modes", f"SELECT circuit_id, gate_no, shape, {_MODE} AS mode FROM ({sql.entries(sql.ORDERS)})")
def gate_modes(spark, sf_dir):
    return classify(circuits.order_gates(spark, sf_dir)).select("circuit_id", "gate_no", "shape", "mode")


@register("gate_mode_counts", f"SELECT kind, {_MODE} AS mode, count(*) AS gates FROM ({sql.entries(sql.ORDERS)}) GROUP BY ALL")
def gate_mode_counts(spark, sf_dir):
    return classify(circuits.order_gates(spark, sf_dir)).groupBy("kind", "mode").agg(F.count("*").alias("gates"))


# Partitions and graphs


@register("partitions_closed", sql.partitions(sql.suppliers(6), 6, 4))
def partitions_closed(spark, sf_dir):
    return derive_partitions(circuits.supplier_gates(spark, sf_dir), 6, 4)


@register("partitions_enum", sql.partitions(sql.ORDERS, 5, 2))
def partitions_enum(spark, sf_dir):
    """Partitions by walking every operation, the truth that the closed form is held against."""
    return enumerate_partitions(circuits.order_gates(spark, sf_dir), 5, 2)


@register("partitions_orders", sql.partitions(sql.ORDERS, 5, 4))
def partitions_orders(spark, sf_dir):
    return derive_partitions(circuits.order_gates(spark, sf_dir), 5, 4)


_SWEEP = (1, 2, 4, 8, 16, 32, 64)


@register(
    "partitions_block_sweep",
    " UNION ALL ".join(f"SELECT circuit_id, CAST({b} AS BIGINT) AS block_size, count(*) AS partitions, CAST(sum(n_tasks) AS BIGINT) AS tasks FROM ({sql.partitions(sql.suppliers(6), 6, b)}) GROUP BY circuit_id" for b in _SWEEP),
)
def partitions_block_sweep(spark, sf_dir):
    gates = circuits.supplier_gates(spark, sf_dir)
    out = None
    for b in _SWEEP:
        one = derive_partitions(gates, 6, b).groupBy("circuit_id").agg(F.count("*").alias("partitions"), F.sum("n_tasks").alias("tasks"))
        one = one.select("circuit_id", F.lit(b).cast("long").alias("block_size"), "partitions", "tasks")
        out = one if out is None else out.unionByName(one)
    return out


N, B = 5, 4
_LINES = f"SELECT * EXCLUDE (accepted, mask) FROM ({sql.accepted(sql.ORDER_LINES)}) WHERE accepted"


def _line_parts(spark, sf_dir) -> DataFrame:
    return graph.slot_partitions(circuits.accepted_gates(circuits.order_gates(spark, sf_dir, "line")), N, B)


@register(
    "slots",
    f"""SELECT circuit_id, slot_no, net_no, mode, array_to_string(list_sort(list(gate_no)), ',') AS gate_nos, max(span) AS span
    FROM ({sql.slot_table(_LINES, N, B)}) GROUP BY circuit_id, slot_no, net_no, mode""",
)
def slots(spark, sf_dir):
    made = graph.layout_slots(circuits.accepted_gates(circuits.order_gates(spark, sf_dir, "line")), N, B)
    return made.withColumn("gate_nos", F.array_join(F.col("gate_nos").cast("array<string>"), ","))


@register("slot_partitions", sql.slot_parts(_LINES, N, B))
def slot_partitions(spark, sf_dir):
    return _line_parts(spark, sf_dir)


@register("edges", sql.edges(sql.slot_parts(_LINES, N, B)))
def edges(spark, sf_dir):
    return graph.link_partitions(_line_parts(spark, sf_dir))


@register("edges_bruteforce", f"SELECT * FROM ({sql.edges(sql.slot_parts(_LINES, N, B))}) WHERE src_part <> -1")
def edges_bruteforce(spark, sf_dir):
    return graph.link_by_intersection(_line_parts(spark, sf_dir))


@register(
    "graph_stats",
    f"""SELECT p.circuit_id, partitions, static_tasks, sub_tasks, written_blocks, coalesce(e.edges, 0) AS edges FROM (
      SELECT circuit_id, count(*) AS partitions, count(*) + count(DISTINCT CASE WHEN mode = 'sup' THEN slot_no END) + 1 AS static_tasks,
        CAST(sum(CASE WHEN n_tasks > 1 THEN n_tasks ELSE 0 END) AS BIGINT) AS sub_tasks, CAST(sum(hi_block - lo_block + 1) AS BIGINT) AS written_blocks
      FROM ({sql.slot_parts(_LINES, N, B)}) GROUP BY circuit_id) p
    LEFT JOIN (SELECT circuit_id, count(*) AS edges FROM ({sql.edges(sql.slot_parts(_LINES, N, B))}) GROUP BY circuit_id) e ON e.circuit_id = p.circuit_id""",
)
def graph_stats(spark, sf_dir):
    parts = _line_parts(spark, sf_dir)
    return graph.graph_stats(parts, graph.link_partitions(parts))


@register(
    "graph_waves",
    f"""WITH RECURSIVE p AS MATERIALIZED ({sql.slot_parts(_LINES, N, B)}), e AS MATERIALIZED ({sql.edges('SELECT * FROM p')}),
    node AS (SELECT circuit_id, slot_no, part_no FROM p UNION SELECT circuit_id, slot_no, -1 FROM p WHERE mode = 'sup'),
    walk AS (
      SELECT circuit_id, slot_no, part_no, 0 AS wave FROM node
      UNION SELECT e.circuit_id, e.dst_slot, e.dst_part, wave + 1 FROM walk w JOIN e ON e.circuit_id = w.circuit_id AND e.src_slot = w.slot_no AND e.src_part = w.part_no)
    SELECT circuit_id, slot_no, part_no, max(wave) AS wave FROM walk GROUP BY ALL""",
)
def graph_waves(spark, sf_dir):
    parts = _line_parts(spark, sf_dir)
    return graph.task_waves(parts, graph.link_partitions(parts))


@register(
    "graph_width",
    f"""WITH w AS ({ORACLES['graph_waves']}) SELECT circuit_id, max(nodes) AS widest, CAST(FLOOR(avg(nodes) * 1e8 + 0.37) AS BIGINT) AS mean_q
    FROM (SELECT circuit_id, wave, count(*) AS nodes FROM w GROUP BY ALL) GROUP BY circuit_id""",
)
def graph_width(spark, sf_dir):
    """How many partitions of a circuit can run together."""
    width = metrics.wave_width(graph_waves(spark, sf_dir))
    return width.select("circuit_id", "widest", fixed(F.col("mean_width")).alias("mean_q"))


_NAME = "CASE WHEN {p} = -1 THEN 'sync_' || {s} ELSE 's' || {s} || '_p' || {p} END"


@register(
    "dot_dump",
    f"""SELECT circuit_id, 'digraph partitions {{' || chr(10) || string_agg('  ' || {_NAME.format(s='src_slot', p='src_part')} || ' -> ' || {_NAME.format(s='dst_slot', p='dst_part')} || ';', chr(10)
      ORDER BY src_slot, src_part, dst_slot, dst_part) || chr(10) || '}}' AS dot FROM ({sql.edges(sql.slot_parts(_LINES, N, B))}) GROUP BY circuit_id""",
)
def dot_dump(spark, sf_dir):
    return graph.graph_dot(graph.link_partitions(_line_parts(spark, sf_dir)))


# Edits: each circuit loses one gate and gets one

_RANK = "(circuit_id * 48271 + gate_no * 16807) % 2147483647"
_EDIT = f"""SELECT *, row_number() OVER (PARTITION BY circuit_id ORDER BY {_RANK}, gate_no) AS hash_no FROM ({sql.ORDERS})"""
_OLD = f"SELECT circuit_id, gate_no * 10 AS gate_no, net_no * 10 AS net_no, kind, target, control, theta FROM ({sql.ORDERS})"
_AFTER_REMOVE = f"SELECT circuit_id, gate_no * 10 AS gate_no, net_no * 10 AS net_no, kind, target, control, theta FROM ({_EDIT}) WHERE hash_no <> 1"
_PUT = f"SELECT circuit_id, gate_no * 10 + 5 AS gate_no, net_no * 10 + 5 AS net_no, 'X' AS kind, CAST(circuit_id % 5 AS INT) AS target, CAST(0 AS INT) AS control, CAST(0 AS DOUBLE) AS theta FROM ({_EDIT}) WHERE hash_no = 2"
_AFTER_INSERT = f"{_OLD} UNION ALL {_PUT}"
_AFTER_BOTH = f"{_AFTER_REMOVE} UNION ALL {_PUT}"


def _numbered(gates: DataFrame) -> DataFrame:
    return gates.withColumn("gate_no", F.col("gate_no") * 10).withColumn("net_no", F.col("net_no") * 10)


def edited(gates: DataFrame, remove: bool, insert: bool) -> DataFrame:
    """Gates numbered in tens, after the edit of each circuit that the hash order of its gates picks."""
    order = Window.partitionBy("circuit_id").orderBy(circuits.level_rank(F.col("circuit_id"), F.col("gate_no")), "gate_no")
    ranked = gates.withColumn("hash_no", F.row_number().over(order))
    out = _numbered(ranked.where("hash_no <> 1") if remove else ranked).drop("hash_no")
    if insert:
        put = _numbered(ranked.where("hash_no = 2")).drop("hash_no")
        put = put.withColumn("gate_no", F.col("gate_no") + 5).withColumn("net_no", F.col("net_no") + 5).withColumn("kind", F.lit("X"))
        put = put.withColumn("target", F.pmod("circuit_id", F.lit(5)).cast("int")).withColumn("controls", F.array().cast("array<int>")).withColumn("theta", F.lit(0.0))
        out = out.unionByName(put.withColumn("control", F.lit(0)))
    return out


def _stable(gates: DataFrame) -> DataFrame:
    """Partitions whose slot number is the gate's own, which edits of others don't change."""
    return graph.slot_partitions(gates, N, B).withColumn("slot_no", F.col("net_no").cast("int"))


def _stable_sql(gates: str) -> str:
    return f"SELECT * REPLACE (CAST(net_no AS INT) AS slot_no) FROM ({sql.slot_parts(gates, N, B)})"


def _edit_graphs(spark, sf_dir, remove: bool, insert: bool) -> tuple[DataFrame, DataFrame, DataFrame]:
    gates = circuits.order_gates(spark, sf_dir)
    old, new = _stable(_numbered(gates)), _stable(edited(gates, remove, insert))
    return new, graph.link_partitions(new), update.frontiers(new, old, graph.link_partitions(old))


def _frontier_sql(new: str) -> str:
    return f"""
    SELECT circuit_id, slot_no, part_no, 'inserted' AS reason FROM np WHERE (circuit_id, slot_no) NOT IN (SELECT DISTINCT circuit_id, slot_no FROM op)
    UNION
    SELECT e.circuit_id, e.dst_slot, e.dst_part, 'successor' FROM oe e JOIN op ON op.circuit_id = e.circuit_id AND op.slot_no = e.src_slot AND op.part_no = e.src_part
    WHERE (e.circuit_id, e.src_slot) NOT IN (SELECT DISTINCT circuit_id, slot_no FROM np) AND (e.circuit_id, e.dst_slot) IN (SELECT DISTINCT circuit_id, slot_no FROM np)"""


def _affected_sql(new: str) -> str:
    return f"""WITH RECURSIVE op AS MATERIALIZED ({_stable_sql(_OLD)}), np AS MATERIALIZED ({_stable_sql(new)}),
    oe AS MATERIALIZED ({sql.edges('SELECT * FROM op')}), ne AS MATERIALIZED ({sql.edges('SELECT * FROM np')}),
    fr AS ({_frontier_sql(new)}),
    reach AS (
      SELECT circuit_id, slot_no, part_no FROM fr
      UNION SELECT e.circuit_id, e.dst_slot, e.dst_part FROM reach r JOIN ne e ON e.circuit_id = r.circuit_id AND e.src_slot = r.slot_no AND e.src_part = r.part_no)"""


for _name, _new, _remove, _insert in (
    ("affected_remove", _AFTER_REMOVE, True, False),
    ("affected_insert", _AFTER_INSERT, False, True),
    ("affected_mixed", _AFTER_BOTH, True, True),
):

    @register(_name, f"{_affected_sql(_new)} SELECT circuit_id, slot_no, part_no FROM reach WHERE part_no <> -1")
    def _affected(spark, sf_dir, remove=_remove, insert=_insert):
        _, links, start = _edit_graphs(spark, sf_dir, remove, insert)
        return update.affected(links, start)


@register("affected_by_hops", f"{_affected_sql(_AFTER_BOTH)} SELECT circuit_id, slot_no, part_no FROM reach WHERE part_no <> -1")
def affected_by_hops(spark, sf_dir):
    _, links, start = _edit_graphs(spark, sf_dir, True, True)
    return update.affected_by_hops(links, start).select("circuit_id", "slot_no", "part_no")


@register("frontiers", f"{_affected_sql(_AFTER_BOTH)} SELECT circuit_id, slot_no, part_no, reason FROM fr")
def frontiers(spark, sf_dir):
    return _edit_graphs(spark, sf_dir, True, True)[2]


@register("relink_after_edit", f"WITH np AS MATERIALIZED ({_stable_sql(_AFTER_BOTH)}) SELECT * FROM ({sql.edges('SELECT * FROM np')})")
def relink_after_edit(spark, sf_dir):
    """Old edges kept where no touched block is concerned, the partitions over touched blocks linked anew."""
    gates = circuits.order_gates(spark, sf_dir)
    old, new = _stable(_numbered(gates)), _stable(edited(gates, True, True))
    return graph.relink(new, graph.link_partitions(old), graph.changed_blocks(new, old))


@register(
    "affected_amplitudes",
    f"""{_affected_sql(_AFTER_BOTH)} SELECT circuit_id, count(DISTINCT (slot_no, part_no)) AS affected_parts, count(DISTINCT k) * {B} AS span_amplitudes FROM (
    SELECT np.circuit_id, np.slot_no, np.part_no, unnest(range(lo_block, hi_block + 1)) AS k FROM np JOIN reach r ON r.circuit_id = np.circuit_id AND r.slot_no = np.slot_no AND r.part_no = np.part_no)
    GROUP BY circuit_id""",
)
def affected_amplitudes(spark, sf_dir):
    parts, links, start = _edit_graphs(spark, sf_dir, True, True)
    return update.affected_amplitudes(parts, update.affected(links, start), B)


# Full simulation


@register("full_orders", sql.amplitude_rows(sql.states(sql.ORDERS, 5)))
def full_orders(spark, sf_dir):
    return amplitude_rows(many.simulate_many(circuits.order_gates(spark, sf_dir), 5))


@register("full_suppliers", sql.amplitude_rows(sql.states(sql.suppliers(6), 6)))
def full_suppliers(spark, sf_dir):
    return amplitude_rows(many.simulate_many(circuits.supplier_gates(spark, sf_dir), 6))


@register("full_parts", sql.amplitude_rows(sql.states(sql.PARTS, 5)))
def full_parts(spark, sf_dir):
    return amplitude_rows(many.simulate_many(circuits.part_gates(spark, sf_dir), 5))


@register("full_documents", sql.amplitude_rows(sql.states(sql.documents(6), 6)))
def full_documents(spark, sf_dir):
    return amplitude_rows(many.simulate_texts(table(spark, sf_dir, "documents"), 6))


_EMB = """SELECT vec_id AS circuit_id, list_transform(e, lambda v: v / norm) AS re, [CAST(0 AS DOUBLE) FOR i IN range(0, 64)] AS im FROM (
  SELECT vec_id, e, sqrt(list_sum(list_transform(e, lambda v: v * v))) AS norm FROM (SELECT vec_id, list_transform(embedding, lambda v: CAST(v AS DOUBLE)) AS e FROM embeddings))"""
_EMB_IDS = "SELECT DISTINCT vec_id AS circuit_id FROM embeddings"


def _literal(gates: list[Gate]) -> str:
    rows = ", ".join(f"({k}, '{g.kind}', {g.target}, {g.qubits[1] if len(g.qubits) > 1 else 0}, CAST({g.theta or 0!r} AS DOUBLE))" for k, g in enumerate(gates, 1))
    return f"SELECT circuit_id, gate_no, gate_no AS net_no, kind, target, control, theta FROM ({_EMB_IDS}), (VALUES {rows}) v(gate_no, kind, target, control, theta)"


_DEMO = [Gate("H", (5,)), Gate("RX", (0,), 0.7), Gate("CNOT", (2, 5)), Gate("T", (1,)), Gate("RY", (3,), 1.1), Gate("RZ", (4,), 2.3), Gate("Y", (2,)), Gate("H", (1,))]


def _rows_of(spark, sf_dir) -> DataFrame:
    return many.to_rows(states.embeddings(spark, sf_dir))


@register("full_embeddings", sql.amplitude_rows(sql.states(_literal(_DEMO), 6, _EMB)))
def full_embeddings(spark, sf_dir):
    """The minimum slice: row layout, monomial projections and summed superposition terms."""
    rows = _rows_of(spark, sf_dir)
    for g in _DEMO:
        rows = apply_superposition(rows, [g]) if g.form == "mix" else apply_mono(rows, g)
    return _quantised(rows)


def _mono_query(name: str, gates: list[Gate]) -> None:
    @register(name, sql.amplitude_rows(sql.states(_literal(gates), 6, _EMB)))
    def run(spark, sf_dir):
        rows = _rows_of(spark, sf_dir)
        for g in gates:
            rows = apply_mono(rows, g)
        return _quantised(rows)


_mono_query("mono_permute", [Gate("X", (0,)), Gate("CNOT", (3, 1)), Gate("CNOT", (5, 0)), Gate("X", (4,))])
_mono_query("mono_phase", [Gate("Z", (0,)), Gate("S", (1,)), Gate("SDG", (2,)), Gate("T", (3,)), Gate("TDG", (4,)), Gate("RZ", (5,), 0.9)])
_mono_query("mono_special_rotation", [Gate("RX", (2,), math.pi), Gate("RY", (1,), math.pi), Gate("RX", (0,), 2 * math.pi), Gate("Y", (5,))])

# Exchanges and doubly controlled gates by index arithmetic
_CZ = "CASE WHEN (idx & 1) = 1 AND ((idx >> 3) & 1) = 1 THEN -1 ELSE 1 END"
_SWAPPED = "CASE WHEN ((idx >> 1) & 1) <> ((idx >> 4) & 1) THEN xor(idx, 18) ELSE idx END"
_CCX = f"CASE WHEN (({_SWAPPED}) & 5) = 5 THEN xor({_SWAPPED}, 32) ELSE {_SWAPPED} END"


@register(
    "mono_swap_cz_ccx",
    f"""SELECT circuit_id, {_CCX} AS idx, {sql.fixed(f'x * ({_CZ})')} AS re_q, CAST(0 AS BIGINT) AS im_q FROM (
    SELECT circuit_id, unnest(range(0, 64)) AS idx, unnest(re) AS x FROM ({_EMB}))""",
)
def mono_swap_cz_ccx(spark, sf_dir):
    rows = _rows_of(spark, sf_dir)
    for g in (Gate("CZ", (0, 3)), Gate("SWAP", (1, 4)), Gate("CCX", (5, 0, 2))):
        rows = apply_mono(rows, g)
    return _quantised(rows)


def _net_query(name: str, gates: list[Gate]) -> None:
    @register(name, sql.amplitude_rows(sql.states(_literal(gates), 6, _EMB)))
    def run(spark, sf_dir):
        return _quantised(apply_superposition(_rows_of(spark, sf_dir), gates))


_net_query("super_h_net", [Gate("H", (q,)) for q in range(6)])
_net_query("super_rx_ry", [Gate("RX", (0,), 0.4), Gate("RY", (2,), 1.9), Gate("RX", (5,), 2.6)])
_net_query("super_two_qubit_terms", [Gate("H", (1,)), Gate("RY", (4,), 0.3)])


# Incremental updates

BLOCK = 4


def _summary_sql(size: int) -> str:
    """Two probabilities and two sums over all amplitudes, with weights that tell each amplitude and its phase."""
    over = f"FOR i IN range(0, {size})"
    return f"""{sql.fixed(f'list_sum([re[i + 1] * re[i + 1] + im[i + 1] * im[i + 1] {over} IF (i & 1) = 1])')} AS p1_q,
      {sql.fixed('re[1] * re[1] + im[1] * im[1]')} AS p0_q,
      {sql.fixed(f'list_sum([re[i + 1] * cos(i + 1) + im[i + 1] * sin(2 * i + 1) {over}])')} AS probe_a_q,
      {sql.fixed(f'list_sum([re[i + 1] * sin(i + 2) - im[i + 1] * cos(3 * i + 1) {over}])')} AS probe_b_q"""


def fixed_values(x: np.ndarray) -> np.ndarray:
    """As :func:`fixed`, of an array."""
    return np.floor(x * 1e8 + 0.37).astype(np.int64)


def _summary_of(psi: np.ndarray) -> dict[str, np.ndarray]:
    p, i = psi.real**2 + psi.imag**2, np.arange(psi.shape[1])
    a = psi.real @ np.cos(i + 1) + psi.imag @ np.sin(2 * i + 1)
    b = psi.real @ np.sin(i + 2) - psi.imag @ np.cos(3 * i + 1)
    return {"p1_q": fixed_values(p[:, 1::2].sum(axis=1)), "p0_q": fixed_values(p[:, 0]), "probe_a_q": fixed_values(a), "probe_b_q": fixed_values(b)}


#: The SQL's summary, taken where the states are made.
SUMMARY = ("p1_q bigint, p0_q bigint, probe_a_q bigint, probe_b_q bigint", _summary_of)
#: Counts alone.
NO_STATE = ("", lambda psi: {})


def _summaries(log: DataFrame, n: int, block_size: int) -> DataFrame:
    return small.incremental_many(log, n, block_size, measure=SUMMARY).select("circuit_id", "iter", "p1_q", "p0_q", "probe_a_q", "probe_b_q")


@register(
    "inc_level_by_level",
    f"""WITH g AS MATERIALIZED ({_LINES}), lv AS (SELECT *, dense_rank() OVER (PARTITION BY circuit_id ORDER BY net_no) AS iter FROM g),
    r AS (SELECT circuit_id, row_number() OVER (PARTITION BY circuit_id ORDER BY net_no, gate_no) AS gate_no, net_no, kind, target, control, theta, iter FROM lv)
    SELECT circuit_id, iter, {_summary_sql(32)}
    FROM (SELECT s.*, iter FROM ({sql.states('SELECT circuit_id, gate_no, net_no, kind, target, control, theta FROM r', 5, steps=True)}) s
      JOIN (SELECT circuit_id, iter, max(gate_no) AS step FROM r GROUP BY ALL) e ON e.circuit_id = s.circuit_id AND e.step = s.step)""",
)
def inc_level_by_level(spark, sf_dir):
    gates = circuits.accepted_gates(circuits.order_gates(spark, sf_dir, "line"))
    return _summaries(circuits.net_log(gates), 5, BLOCK)


def _per_iter(insert: bool) -> str:
    """The circuit after every iteration, as (circuit_id, iter) keyed gates."""
    ranked = f"SELECT *, (dense_rank() OVER (PARTITION BY circuit_id ORDER BY {_RANK.replace('gate_no', 'net_no')}, net_no) - 1) // 3 AS in_iter FROM ({sql.ORDERS})"
    keep = "in_iter <= iter" if insert else "in_iter > iter"
    iters = f"SELECT DISTINCT circuit_id, in_iter AS iter FROM ({ranked})"
    if not insert:
        iters += f" UNION SELECT DISTINCT circuit_id, -1 FROM ({ranked})"
    return f"SELECT r.circuit_id, i.iter, gate_no, net_no, kind, target, control, theta FROM ({ranked}) r JOIN ({iters}) i ON i.circuit_id = r.circuit_id AND {keep}"


def _empty_sql(size: int) -> str:
    """The lists of the zero state."""
    return f"[CAST(CASE WHEN i = 0 THEN 1 ELSE 0 END AS DOUBLE) FOR i IN range(0, {size})] AS re, [CAST(0 AS DOUBLE) FOR i IN range(0, {size})] AS im"


def _inc_sql(insert: bool) -> str:
    some = f"SELECT circuit_id, iter, {_summary_sql(32)} FROM ({sql.states(_per_iter(insert), 5, key='circuit_id, iter')})"
    if insert:
        return some
    last = f"SELECT circuit_id, max((nth - 1) // 3) AS iter FROM (SELECT circuit_id, row_number() OVER (PARTITION BY circuit_id ORDER BY gate_no) AS nth FROM ({sql.ORDERS})) GROUP BY circuit_id"
    return f"{some} UNION ALL SELECT circuit_id, iter, {_summary_sql(32)} FROM (SELECT *, {_empty_sql(32)} FROM ({last}))"


@register("inc_insert", _inc_sql(True))
def inc_insert(spark, sf_dir):
    return _summaries(circuits.insertion_log(circuits.order_gates(spark, sf_dir)), 5, BLOCK)


@register("inc_remove", _inc_sql(False))
def inc_remove(spark, sf_dir):
    return _summaries(circuits.removal_log(circuits.order_gates(spark, sf_dir)), 5, BLOCK)


#: Users' events as a stack of live gates, folded event by event; the stack at the end of each day is a circuit.
_EVENT_GATES = """
  SELECT circuit_id, iter, g.seq AS gate_no, g.seq AS net_no, kind, target, control, theta FROM (SELECT circuit_id, iter, unnest(stack) AS seq FROM days) s
  JOIN ev g ON g.user_id = s.circuit_id AND g.seq = s.seq"""
_EVENT_DAYS = """WITH RECURSIVE ev AS MATERIALIZED (
    SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY seq) AS nth, CASE WHEN event_type = 'error' THEN -1 ELSE 1 END AS d FROM (
      SELECT user_id, event_type, CAST(ts AS DATE) AS day, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS seq,
        CASE event_type WHEN 'click' THEN 'CNOT' WHEN 'view' THEN 'H' WHEN 'purchase' THEN 'RZ' END AS kind, CAST(k % 4 AS INT) AS target,
        CAST((k % 4 + 1 + (k // 4) % 3) % 4 AS INT) AS control, pi() * 2 * k / CAST(100 AS DOUBLE) AS theta
      FROM (SELECT *, CAST(json_extract(props, '$.k') AS INT) AS k FROM events))
    WHERE event_type IN ('click', 'view', 'purchase', 'error')
  ), fold AS (
    SELECT user_id, CAST(0 AS BIGINT) AS nth, CAST([] AS BIGINT[]) AS stack, CAST(NULL AS DATE) AS day, FALSE AS edit FROM (SELECT DISTINCT user_id FROM ev)
    UNION ALL
    SELECT f.user_id, e.nth, CASE WHEN d = 1 THEN list_append(stack, e.seq) WHEN len(stack) > 0 THEN stack[1:len(stack) - 1] ELSE stack END, e.day, d = 1 OR len(stack) > 0
    FROM fold f JOIN ev e ON e.user_id = f.user_id AND e.nth = f.nth + 1
  ), days AS MATERIALIZED (
    SELECT user_id AS circuit_id, dense_rank() OVER (PARTITION BY user_id ORDER BY day) AS iter, stack
    FROM (SELECT user_id, day, arg_max(stack, nth) AS stack FROM fold WHERE edit GROUP BY user_id, day))"""


@register(
    "inc_mixed",
    f"""{_EVENT_DAYS} SELECT circuit_id, iter, {_summary_sql(16)} FROM ({sql.states(_EVENT_GATES, 4, key='circuit_id, iter')})
    UNION ALL SELECT circuit_id, iter, {_summary_sql(16)} FROM (SELECT circuit_id, iter, {_empty_sql(16)} FROM days WHERE len(stack) = 0)""",
)
def inc_mixed(spark, sf_dir):
    """Days of events as iterations of mixed edits; the state after every update."""
    return _summaries(circuits.event_log(spark, sf_dir), 4, 2)


@register("inc_mixed_counts")
def inc_mixed_counts(spark, sf_dir):
    """What every update of :func:`inc_mixed` recomputed (bounds and totals are tested)."""
    done = small.incremental_many(circuits.event_log(spark, sf_dir), 4, 2, measure=NO_STATE)
    return done.select("circuit_id", "iter", "frontier_parts", "affected_parts", "span_amplitudes", "written_blocks", "total_blocks")


@register(
    "inc_report_counts",
    f"""WITH p AS MATERIALIZED ({sql.slot_parts(_LINES, N, B)}), n AS (SELECT *, dense_rank() OVER (PARTITION BY circuit_id ORDER BY net_no) AS iter FROM (SELECT DISTINCT circuit_id, net_no FROM ({_LINES})))
    SELECT n.circuit_id, n.iter, count(p.part_no) AS affected_parts, count(DISTINCT k) * {B} AS span_amplitudes, CAST(coalesce(sum(blocks), 0) AS BIGINT) AS written_blocks FROM n
    LEFT JOIN (SELECT circuit_id, net_no, CASE WHEN k = lo_block THEN part_no END AS part_no, k, 1 AS blocks FROM (SELECT *, unnest(range(lo_block, hi_block + 1)) AS k FROM p)) p
      ON p.circuit_id = n.circuit_id AND p.net_no = n.net_no
    GROUP BY n.circuit_id, n.iter""",
)
def inc_report_counts(spark, sf_dir):
    gates = circuits.accepted_gates(circuits.order_gates(spark, sf_dir, "line"))
    done = small.incremental_many(circuits.net_log(gates), N, B, measure=NO_STATE)
    return done.select("circuit_id", "iter", "affected_parts", "span_amplitudes", "written_blocks")
