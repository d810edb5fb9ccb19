"""Baselines: whole re-simulation by level and by gate, sparse rows, and the dense product."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from incstate.plans.store import shared_folder
from incstate.plans.wide import Gate, apply_blocks, apply_mono, apply_superposition


def levels_of(gates: list[tuple[int, Gate]]) -> list[list[Gate]]:
    out: dict[int, list[Gate]] = {}
    for net, g in gates:
        out.setdefault(net, []).append(g)
    return [out[k] for k in sorted(out)]


def resim_levelwise(blocks: DataFrame, gates: list[tuple[int, Gate]], block_size: int) -> DataFrame:
    """The whole circuit on the block layout, with a barrier (a checkpoint) after every level."""
    shared_folder(blocks.sparkSession)
    for level in levels_of(gates):
        for g in level:
            if g.form != "id":
                blocks = apply_blocks(blocks, [g], block_size)
        blocks = blocks.checkpoint(eager=True)
    return blocks


def resim_gatewise(rows: DataFrame, gates: list[tuple[int, Gate]], every: int = 8) -> DataFrame:
    """The whole circuit on the row layout, one shuffle per gate; lineage is cut every few gates."""
    shared_folder(rows.sparkSession)
    for k, (_, g) in enumerate(gates, 1):
        if g.form == "mix":
            rows = apply_superposition(rows, [g])
        elif g.form != "id":
            rows = apply_mono(rows, g).repartition("circuit_id", "idx")
        if k % every == 0:
            rows = rows.checkpoint(eager=True)
    return rows


def sparse_rows(rows: DataFrame, gates: list[tuple[int, Gate]], least: float = 1e-24) -> DataFrame:
    """As rows, dropping amplitudes whose square is at most ``least`` after every superposition."""
    for _, g in gates:
        if g.form == "mix":
            rows = apply_superposition(rows, [g]).where(F.col("re") * F.col("re") + F.col("im") * F.col("im") > least)
        elif g.form != "id":
            rows = apply_mono(rows, g)
    return rows


def unitary(n: int, gates: list[Gate]) -> np.ndarray:
    """The dense product matrix of gates, for a handful of qubits."""
    size = 1 << n
    out = np.eye(size, dtype=complex)
    i = np.arange(size)
    for g in gates:
        m = np.zeros((size, size), complex)
        ok = (i & g.held) == g.held
        if g.form == "exchange":
            a, b = g.qubits[:2]
            source = np.where(ok & (((i >> a) ^ (i >> b)) & 1 == 1), i ^ ((1 << a) | (1 << b)), i)
            m[i, source] = 1
        else:
            u, bit = g.matrix, (i >> g.target) & 1
            m[i, i] = np.where(ok, u[bit, bit], 1)
            m[i, i ^ (1 << g.target)] += np.where(ok, u[bit, 1 - bit], 0)
        out = m @ out
    return out


def dense_unitary_apply(rows: DataFrame, n: int, gates: list[Gate]) -> DataFrame:
    """State times the dense matrix, as a join and a sum (tiny ``n`` only; the matrix has 4**n entries)."""
    if n > 8:
        raise ValueError("the dense product is for at most 8 qubits")
    m = unitary(n, gates)
    entries = [(int(r), int(c), float(m[r, c].real), float(m[r, c].imag)) for r, c in zip(*np.nonzero(np.abs(m) > 1e-15))]
    table = F.broadcast(rows.sparkSession.createDataFrame(entries, "r bigint, c bigint, mr double, mi double"))
    met = rows.join(table, rows["idx"] == table["c"])
    return met.groupBy("circuit_id", F.col("r").alias("idx")).agg(
        F.sum(F.col("mr") * F.col("re") - F.col("mi") * F.col("im")).alias("re"), F.sum(F.col("mr") * F.col("im") + F.col("mi") * F.col("re")).alias("im")
    )
