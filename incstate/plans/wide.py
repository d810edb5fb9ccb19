"""One wide state: row layout in column expressions, block layout in array kernels.

Row layout ``(circuit_id, idx, re, im)``: a monomial gate is a projection, so runs of them collapse into
one; a superposition net adds up 2**k exploded terms per amplitude.  Block layout ``(circuit_id, block_id,
re, im)``: gates inside a block never move data; gates on block bits group the 2**k blocks that they couple.
"""

from __future__ import annotations

from itertools import product
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from incstate.functions.gates import matrix, shape

#: Mixing gates of a net that one sum of terms takes; more are applied in several passes.
TERM_GATES = 3


class Gate(NamedTuple):
    """One gate of one circuit: ``qubits`` are the target and then the controls (SWAP: the pair first)."""

    kind: str
    qubits: tuple[int, ...]
    theta: float | None = None

    @property
    def target(self) -> int:
        return self.qubits[0]

    @property
    def controls(self) -> tuple[int, ...]:
        return self.qubits[1:]

    @property
    def form(self) -> str:
        return shape(self.kind, self.theta)

    @property
    def held(self) -> int:
        return sum(1 << q for q in (self.qubits[2:] if self.kind == "SWAP" else self.controls))

    @property
    def matrix(self) -> np.ndarray:
        return matrix(self.kind, self.theta)


def _num(x: float):
    return F.lit(float(x))


def apply_mono(state: DataFrame, gate: Gate) -> DataFrame:
    """A monomial gate on rows: a new index and a factor, no shuffle."""
    i = F.col("idx")
    ok = i.bitwiseAND(gate.held) == gate.held
    if gate.form == "exchange":
        a, b = gate.qubits[:2]
        differ = F.shiftright(i, a).bitwiseXOR(F.shiftright(i, b)).bitwiseAND(1) == 1
        return state.withColumn("idx", F.when(ok & differ, i.bitwiseXOR((1 << a) | (1 << b))).otherwise(i))
    u, t = gate.matrix, gate.target
    one = F.shiftright(i, t).bitwiseAND(1) == 1
    swap = gate.form == "swap"
    zero_to, one_to = (u[1, 0], u[0, 1]) if swap else (u[0, 0], u[1, 1])
    fr = F.when(~ok, _num(1)).when(one, _num(one_to.real)).otherwise(_num(zero_to.real))
    fi = F.when(~ok, _num(0)).when(one, _num(one_to.imag)).otherwise(_num(zero_to.imag))
    to = F.when(ok, i.bitwiseXOR(1 << t)).otherwise(i) if swap else i
    keep = [c for c in state.columns if c not in ("idx", "re", "im")]
    return state.select(*keep, to.alias("idx"), (F.col("re") * fr - F.col("im") * fi).alias("re"), (F.col("re") * fi + F.col("im") * fr).alias("im"))


def mixing_terms(gates: list[Gate]) -> list[tuple[int, list[tuple[int, int, complex]]]]:
    """The nonzeros of a net's product matrix by the mixing targets: for each exclusive-or mask a list of
    (bits of the source, of those targets, factor)."""
    out = []
    for flips in product((0, 1), repeat=len(gates)):
        mask = sum(f << g.target for f, g in zip(flips, gates))
        rows = []
        for bits in product((0, 1), repeat=len(gates)):
            factor = np.prod([g.matrix[b ^ f, b] for g, b, f in zip(gates, bits, flips)])
            if abs(factor) > 0:
                rows.append((sum(b << g.target for b, g in zip(bits, gates)), sum(1 << g.target for g in gates), complex(factor)))
        if rows:
            out.append((mask, rows))
    return out


def apply_superposition(state: DataFrame, gates: list[Gate]) -> DataFrame:
    """The mixing gates of one net on rows: each amplitude sends 2**k terms, which are added by index."""
    for at in range(0, len(gates), TERM_GATES):
        part = gates[at : at + TERM_GATES]
        keep = [c for c in state.columns if c not in ("idx", "re", "im")]
        plain = [g for g in part if not g.held]
        for g in part:
            if g.held:
                state = _sum_terms(state, [g], keep, g.held)
        if plain:
            state = _sum_terms(state, plain, keep, 0)
    return state


def _sum_terms(state: DataFrame, gates: list[Gate], keep: list[str], held: int) -> DataFrame:
    i = F.col("idx")
    terms = []
    for mask, rows in mixing_terms(gates):
        fr, fi = _num(0), _num(0)
        for bits, over, factor in rows:
            hit = i.bitwiseAND(over) == bits
            fr, fi = F.when(hit, _num(factor.real)).otherwise(fr), F.when(hit, _num(factor.imag)).otherwise(fi)
        if held:
            idle = i.bitwiseAND(held) != held
            fr, fi = F.when(idle, _num(1.0 if mask == 0 else 0.0)).otherwise(fr), F.when(idle, _num(0)).otherwise(fi)
        terms.append(F.struct(i.bitwiseXOR(mask).alias("idx"), (F.col("re") * fr - F.col("im") * fi).alias("re"), (F.col("re") * fi + F.col("im") * fr).alias("im")))
    sent = state.select(*keep, F.explode(F.array(*terms)).alias("x")).select(*keep, "x.*")
    return sent.groupBy(*keep, "idx").agg(F.sum("re").alias("re"), F.sum("im").alias("im"))


def apply_net(state: DataFrame, gates: list[Gate]) -> DataFrame:
    """All gates of a net: its mixing gates, then its monomial ones."""
    mixing = [g for g in gates if g.form == "mix"]
    state = apply_superposition(state, mixing) if mixing else state
    for g in gates:
        if g.form not in ("mix", "id"):
            state = apply_mono(state, g)
    return state


def zero_state(spark, n: int, circuit_id: int = 0) -> DataFrame:
    """|0...0> as one row; absent rows are zeros."""
    return spark.range(1).select(F.lit(circuit_id).cast("long").alias("circuit_id"), F.col("id").alias("idx"), F.lit(1.0).alias("re"), F.lit(0.0).alias("im"))


# Block layout


def rows_to_blocks(rows: DataFrame, block_size: int) -> DataFrame:
    """Rows (zeros may be missing) to blocks of ``block_size``; blocks without a row are missing too."""
    b = block_size.bit_length() - 1
    entry = F.collect_list(F.struct(F.col("idx").bitwiseAND(block_size - 1).cast("int").alias("i"), "re", "im"))
    made = rows.groupBy("circuit_id", F.shiftright("idx", b).alias("block_id")).agg(F.map_from_entries(F.transform(entry, lambda x: F.struct(x["i"], F.struct(x["re"], x["im"])))).alias("m"))
    every = F.sequence(F.lit(0), F.lit(block_size - 1))
    pick = lambda k: F.transform(every, lambda i: F.coalesce(F.element_at("m", i)[k], F.lit(0.0)))
    return made.select("circuit_id", "block_id", pick("re").alias("re"), pick("im").alias("im"))


def blocks_to_rows(blocks: DataFrame, block_size: int) -> DataFrame:
    return blocks.select("circuit_id", "block_id", F.posexplode(F.arrays_zip("re", "im")).alias("i", "a")).select(
        "circuit_id", (F.col("block_id") * block_size + F.col("i")).alias("idx"), "a.re", "a.im"
    )


def blocks_of(table: pa.Table | pa.RecordBatch) -> np.ndarray:
    parts = []
    for name in ("re", "im"):
        column = table.column(name)
        column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
        parts.append(column.flatten().to_numpy(zero_copy_only=False).reshape(len(column), -1))
    return parts[0] + 1j * parts[1]


def blocks_table(circuit: np.ndarray, block: np.ndarray, psi: np.ndarray) -> pa.Table:
    ends = pa.array(np.arange(len(psi) + 1) * (psi.shape[1] if psi.ndim == 2 else 0), pa.int32())
    lists = [pa.ListArray.from_arrays(ends, pa.array(np.ascontiguousarray(x).ravel())) for x in (psi.real, psi.imag)]
    return pa.table({"circuit_id": pa.array(circuit, pa.int64()), "block_id": pa.array(block, pa.int64()), "re": lists[0], "im": lists[1]})


def block_kernel(psi: np.ndarray, block: np.ndarray, gates: list[Gate], b: int) -> np.ndarray:
    """Gates on a set of blocks that is closed under the block bits they couple."""
    order = np.argsort(block)
    inside = np.arange(psi.shape[1])
    index = (block[:, None] << b) | inside[None, :]

    def at(source: np.ndarray) -> np.ndarray:
        where = order[np.searchsorted(block, source >> b, sorter=order)] if len(block) else source
        return psi[where, source & (psi.shape[1] - 1)]

    for g in gates:
        ok = (index & g.held) == g.held
        if g.form == "exchange":
            p, q = g.qubits[:2]
            differ = ((index >> p) ^ (index >> q)) & 1 == 1
            source = np.where(ok & differ, index ^ ((1 << p) | (1 << q)), index)
            psi = at(source) if max(p, q) >= b else np.take_along_axis(psi, source & (psi.shape[1] - 1), axis=1)
            continue
        u, t = g.matrix, g.target
        bit = (index >> t) & 1
        if g.form in ("one", "full"):
            psi = np.where(ok, np.where(bit == 1, u[1, 1], u[0, 0]) * psi, psi)
            continue
        source = np.where(ok, index ^ (1 << t), index)
        partner = at(source) if t >= b else np.take_along_axis(psi, source & (psi.shape[1] - 1), axis=1)
        psi = np.where(ok, u[bit, bit] * psi + u[bit, 1 - bit] * partner, psi)
    return psi


def coupled_bits(gates: list[Gate], b: int) -> int:
    """Mask of the block-id bits along which the gates exchange amplitudes."""
    mask = 0
    for g in gates:
        moved = g.qubits[:2] if g.form == "exchange" else (g.target,) if g.form in ("swap", "mix") else ()
        for q in moved:
            mask |= 1 << (q - b) if q >= b else 0
    return mask


BLOCK_SCHEMA = "circuit_id bigint, block_id bigint, re array<double>, im array<double>"


def apply_blocks(blocks: DataFrame, gates: list[Gate], block_size: int) -> DataFrame:
    """Gates in order on the block layout: a shuffle only if they couple blocks, and then one."""
    b = block_size.bit_length() - 1
    mask = coupled_bits(gates, b)

    def made(table) -> pa.Table:
        block = np.asarray(table.column("block_id").to_numpy())
        circuit = np.asarray(table.column("circuit_id").to_numpy())
        return blocks_table(circuit, block, block_kernel(blocks_of(table), block, gates, b))

    if not mask:
        def each(batches):
            for batch in batches:
                yield from made(batch).to_batches()

        return blocks.mapInArrow(each, BLOCK_SCHEMA)

    def group(table: pa.Table) -> pa.Table:
        return made(table)

    return blocks.groupBy("circuit_id", F.col("block_id").bitwiseAND(~mask).alias("couple")).applyInArrow(group, BLOCK_SCHEMA)
