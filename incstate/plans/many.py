"""Many circuits at once: one shuffle by circuit, then one vectorised kernel per batch of circuits.

A circuit is a row with its gates as an array; its vector is an array too.  The kernel applies the k-th
gates of all circuits of a batch together, so its Python work grows with the longest circuit of a batch,
not with the number of circuits.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from incstate.functions.gates import KINDS, matrix, matrix_array

#: Amplitudes that a kernel call holds.
KERNEL_AMPLITUDES = 1 << 20
#: Code points of the texts that a kernel call holds, but for the last text.
KERNEL_SIGNS = 1 << 23

VECTOR = T.StructType().add("re", T.ArrayType(T.DoubleType())).add("im", T.ArrayType(T.DoubleType()))


def _mask(qubits: Column) -> Column:
    one = F.lit(1).cast("long")
    return F.aggregate(qubits, F.lit(0).cast("long"), lambda m, q: m.bitwiseOR(F.call_function("shiftleft", one, q)))


def pack_gates(gates: DataFrame, order: list[str] | None = None) -> DataFrame:
    """``gates`` to ``circuit_id, ops``: each circuit's gates in order as numbers (see :func:`run_circuits`)."""
    key = F.struct(*[F.col(c) for c in order or ["gate_no"]])
    controls = F.coalesce("controls", F.array().cast("array<int>"))
    swap = F.col("kind") == "SWAP"
    op = F.struct(
        key.alias("key"),
        F.col("target").cast("int").alias("t"),
        F.when(swap, F.element_at(controls, 1)).otherwise(F.lit(-1)).cast("int").alias("other"),
        _mask(F.when(swap, F.slice(controls, 2, 62)).otherwise(controls)).alias("held"),
        F.coalesce(matrix_array(F.col("kind"), F.col("theta")), F.array_repeat(F.lit(0.0), 8)).alias("u"),
    )
    drop = lambda x: F.struct(x["t"].alias("t"), x["other"].alias("other"), x["held"].alias("held"), x["u"].alias("u"))
    return gates.groupBy("circuit_id").agg(F.transform(F.array_sort(F.collect_list(op)), drop).alias("ops"))


def _apply(psi: np.ndarray, t: np.ndarray, other: np.ndarray, held: np.ndarray, u: np.ndarray) -> np.ndarray:
    """One gate on each row of ``psi``."""
    rows, size = psi.shape
    i = np.arange(size)
    ok = (i & held[:, None]) == held[:, None]
    swap = other >= 0
    out = psi
    if not swap.all():
        partner = i ^ (1 << t)[:, None]
        bit = (i >> t[:, None]) & 1
        row = np.arange(rows)[:, None]
        made = u[row, bit, bit] * psi + u[row, bit, 1 - bit] * np.take_along_axis(psi, partner, axis=1)
        out = np.where(ok & ~swap[:, None], made, psi)
    if swap.any():
        o = np.maximum(other, 0)
        differ = ((i >> t[:, None]) ^ (i >> o[:, None])) & 1 == 1
        source = np.where(differ, i ^ ((1 << t) | (1 << o))[:, None], i)
        out = np.where(ok & swap[:, None], np.take_along_axis(psi, source, axis=1), out)
    return out


def run_circuits(ops: pa.Array, psi: np.ndarray) -> np.ndarray:
    """Apply each row's ops to its row of ``psi``."""
    depth = np.diff(ops.offsets.to_numpy())
    held = ops.flatten()
    t, other, mask = (held.field(c).to_numpy(zero_copy_only=False) for c in ("t", "other", "held"))
    entries = held.field("u").flatten().to_numpy(zero_copy_only=False).reshape(-1, 4, 2)
    u = (entries[:, :, 0] + 1j * entries[:, :, 1]).reshape(-1, 2, 2)
    start = np.cumsum(depth) - depth
    psi = psi.copy()
    for k in range(int(depth.max(initial=0))):
        on = np.flatnonzero(depth > k)
        g = start[on] + k
        psi[on] = _apply(psi[on], t[g].astype(np.int64), other[g].astype(np.int64), mask[g], u[g])
    return psi


def word_gates(text: str, n: int) -> tuple[np.ndarray, ...]:
    """Kind code, target, control and length of every blank-separated word's gate."""
    signs = np.frombuffer(text.encode("utf-32-le"), np.uint32)
    blank = np.flatnonzero(signs == 32)
    start = np.concatenate(([0], blank + 1))
    length = np.append(blank, len(signs)) - start
    first = np.where(length > 0, np.append(signs, 0)[start], 0).astype(np.int64)
    target = first % n
    return (length + first) % len(KINDS), target, (target + 1 + length % (n - 1)) % n, length


def run_texts(texts: list[str], n: int) -> np.ndarray:
    """The final vectors of the circuits of whole texts, one row each."""
    made = [word_gates(x, n) for x in texts]
    # The longest first, so that the circuits still running are a leading slice.
    order = sorted(range(len(made)), key=lambda i: -len(made[i][0]))
    depth = np.array([len(made[i][0]) for i in order], np.int64)
    start = np.cumsum(depth) - depth
    code, target, control, length = (np.concatenate([made[i][c] for i in order]) for c in range(4))
    held = np.where(code == KINDS.index("CNOT"), 1 << control, 0)
    # A gate's matrix is that of its kind and its word's length.
    known, which = np.unique(length * len(KINDS) + code, return_inverse=True)
    u = np.stack([matrix(KINDS[k % len(KINDS)], np.pi * (k // len(KINDS)) / 6) for k in known.tolist()])
    psi = np.zeros((len(made), 1 << n), complex)
    psi[:, 0] = 1
    none = np.full(len(made), -1)
    running = np.searchsorted(-depth, -np.arange(depth[0]), side="left")
    for k, on in enumerate(running.tolist()):
        g = start[:on] + k
        psi[:on] = _apply(psi[:on], target[g], none[:on], held[g], u[which[g]])
    out = np.empty_like(psi)
    out[order] = psi
    return out


def _vectors(psi: np.ndarray) -> pa.Array:
    ends = pa.array(np.arange(len(psi) + 1) * psi.shape[1], pa.int32())
    parts = [pa.ListArray.from_arrays(ends, pa.array(np.ascontiguousarray(x).ravel())) for x in (psi.real, psi.imag)]
    return pa.StructArray.from_arrays(parts, names=["re", "im"])


def _kernel(n: int):
    @F.arrow_udf(VECTOR)
    def run(ops: pa.Array, re: pa.Array, im: pa.Array) -> pa.Array:
        ops, re, im = (x.combine_chunks() if isinstance(x, pa.ChunkedArray) else x for x in (ops, re, im))
        out, step = [], max(1, KERNEL_AMPLITUDES >> n)
        for at in range(0, len(ops), step):
            part = [x[at : at + step] for x in (ops, re, im)]
            have = np.array(part[1].is_valid())
            psi = np.zeros((len(part[0]), 1 << n), complex)
            psi[~have, 0] = 1
            if have.any():
                a, b = (x.flatten().to_numpy(zero_copy_only=False).reshape(-1, 1 << n) for x in part[1:])
                psi[have] = a + 1j * b
            out.append(_vectors(run_circuits(part[0], psi)))
        return pa.concat_arrays(out) if out else _vectors(np.zeros((0, 1 << n), complex))

    return run


def simulate_many(gates: DataFrame, n: int, start: DataFrame | None = None, order: list[str] | None = None) -> DataFrame:
    """Final vectors ``circuit_id, re, im`` of all circuits, from |0...0> or from ``start(circuit_id, re, im)``."""
    packed = pack_gates(gates, order)
    null = F.lit(None).cast("array<double>")
    if start is None:
        packed = packed.withColumn("_re", null).withColumn("_im", null)
    else:
        ops = packed.schema["ops"].dataType.simpleString()
        packed = start.select("circuit_id", F.col("re").alias("_re"), F.col("im").alias("_im")).join(packed, "circuit_id", "left")
        packed = packed.withColumn("ops", F.coalesce("ops", F.array().cast(ops)))
    return packed.select("circuit_id", _kernel(n)("ops", "_re", "_im").alias("v")).select("circuit_id", "v.re", "v.im")


def simulate_texts(docs: DataFrame, n: int) -> DataFrame:
    """``docs(doc_id, text)`` to final vectors ``circuit_id, re, im``: each row's words are the gates of one circuit.

    Nothing is shuffled: a text stays one row and becomes gates in the kernel.  A null text is no circuit.
    """

    @F.arrow_udf(VECTOR)
    def run(text: pa.Array) -> pa.Array:
        out, part, signs = [], [], 0
        for x in text.to_pylist():
            part.append(x)
            signs += len(x)
            if signs >= KERNEL_SIGNS or len(part) >= KERNEL_AMPLITUDES >> n:
                out.append(_vectors(run_texts(part, n)))
                part, signs = [], 0
        if part or not out:
            out.append(_vectors(run_texts(part, n) if part else np.zeros((0, 1 << n), complex)))
        return pa.concat_arrays(out)

    text = F.coalesce("text", F.lit(""))
    return docs.where("text is not null").select(F.col("doc_id").alias("circuit_id"), run(text).alias("v")).select("circuit_id", "v.re", "v.im")


def to_rows(vectors: DataFrame) -> DataFrame:
    """``circuit_id, re, im`` arrays to ``circuit_id, idx, re, im`` rows."""
    return vectors.select("circuit_id", F.posexplode(F.arrays_zip("re", "im")).alias("idx", "a")).select(
        "circuit_id", F.col("idx").cast("long").alias("idx"), "a.re", "a.im"
    )


def to_vectors(rows: DataFrame, n: int) -> DataFrame:
    """Rows, zeros left out or not, to whole arrays."""
    at = F.map_from_entries(F.collect_list(F.struct("idx", F.struct("re", "im"))))
    made = rows.groupBy("circuit_id").agg(at.alias("m"))
    pick = lambda part: F.transform(F.sequence(F.lit(0).cast("long"), F.lit((1 << n) - 1).cast("long")), lambda i: F.coalesce(F.element_at("m", i)[part], F.lit(0.0)))
    return made.select("circuit_id", pick("re").alias("re"), pick("im").alias("im"))
