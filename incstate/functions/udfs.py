"""User functions for SQL: table functions for matrix terms, partitions and circuit text; array kernels."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from incstate.functions.gates import matrix
from incstate.operators.partition import log2, pattern


@F.udtf(returnType="row_bit int, col_bit int, re double, im double")
class GateTerms:
    """The nonzero entries of a gate's 2x2 matrix."""

    def eval(self, kind: str, theta: float):
        u = matrix(kind, theta)
        for r in (0, 1):
            for c in (0, 1):
                if abs(u[r, c]) > 1e-12:
                    yield r, c, float(u[r, c].real), float(u[r, c].imag)


@F.udtf(returnType="part_no int, lo_block bigint, hi_block bigint, n_tasks bigint")
class PartitionRanges:
    """A gate's partitions on ``n`` qubits with a block size; ``control`` below 0 means none."""

    def eval(self, kind: str, target: int, control: int, theta: float, n: int, block_size: int):
        b = log2(block_size, n)
        p = pattern(kind, target, () if control < 0 else (control,), theta, n, b)
        for k in range(p.count if p else 0):
            lo, hi = p.bounds(k, b)
            yield k, lo, hi, p.tasks


@F.udtf(returnType="gate_no int, kind string, target int, theta double")
class ParseGates:
    """Gates of words: one per blank-separated word of the whole text, by its length and first code point."""

    def eval(self, text: str | None, n: int):
        from incstate.functions.gates import KINDS

        for k, word in enumerate([] if text is None else text.split(" ")):
            first = ord(word[0]) if word else 0
            yield k, KINDS[(len(word) + first) % 12], first % n, float(np.pi * len(word) / 6)


@F.arrow_udf(T.ArrayType(T.DoubleType()))
def hadamard_blocks(block: pa.Array) -> pa.Array:
    """The lowest-qubit Hadamard on blocks of one power-of-two size, as an array kernel."""
    block = block.combine_chunks() if isinstance(block, pa.ChunkedArray) else block
    if not len(block):
        return pa.array([], pa.list_(pa.float64()))
    x = block.flatten().to_numpy(zero_copy_only=False).reshape(len(block), -1, 2)
    y = np.stack((x[:, :, 0] + x[:, :, 1], x[:, :, 0] - x[:, :, 1]), axis=2) / np.sqrt(2)
    ends = pa.array(np.arange(len(block) + 1) * x.shape[1] * 2, pa.int32())
    return pa.ListArray.from_arrays(ends, pa.array(y.ravel()))


@F.pandas_udf(T.DoubleType())
def overlap(ar: pd.Series, ai: pd.Series, br: pd.Series, bi: pd.Series) -> float:
    """Aggregate: the squared overlap of two states given as rows of amplitudes."""
    return float(abs(np.vdot(ar.to_numpy() + 1j * ai.to_numpy(), br.to_numpy() + 1j * bi.to_numpy())) ** 2)


def register_all(spark: SparkSession) -> None:
    """Make ``gate_terms``, ``partition_ranges``, ``parse_gates``, ``hadamard_blocks`` and ``overlap`` usable in SQL."""
    spark.udtf.register("gate_terms", GateTerms)
    spark.udtf.register("partition_ranges", PartitionRanges)
    spark.udtf.register("parse_gates", ParseGates)
    spark.udf.register("hadamard_blocks", hadamard_blocks)
    spark.udf.register("overlap", overlap)
