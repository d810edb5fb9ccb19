from __future__ import annotations

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from incstate.functions.gates import KINDS, classify, decompose, matrix, matrix_array, shape
from incstate.operators.partition import pattern
from incstate.plans.baselines import unitary
from incstate.plans.wide import Gate


def same(a, b):
    """Equal up to a global phase."""
    k = np.unravel_index(np.abs(a).argmax(), a.shape)
    return np.allclose(a * (b[k] / a[k]), b, atol=1e-9)


def test_algebra():
    i = np.eye(2)
    for k in ("X", "Y", "Z", "H"):
        assert np.allclose(matrix(k) @ matrix(k), i)
    assert np.allclose(matrix("S") @ matrix("S"), matrix("Z"))
    assert np.allclose(matrix("T") @ matrix("T"), matrix("S"))
    assert np.allclose(matrix("S") @ matrix("SDG"), i) and np.allclose(matrix("T") @ matrix("TDG"), i)
    assert same(matrix("RX", math.pi), matrix("X"))


def test_shapes_come_from_matrices():
    assert [shape(k) for k in ("X", "Z", "H", "S", "CNOT", "SWAP")] == ["swap", "one", "mix", "one", "swap", "exchange"]
    assert shape("RX", math.pi) == "swap" and shape("RX", 2 * math.pi) == "full" and shape("RX", 4 * math.pi) == "id"
    assert shape("RY", 1.0) == "mix" and shape("RZ", 1.0) == "full" and shape("RZ", 0.0) == "id"
    with pytest.raises(ValueError):
        shape("NOPE")
    with pytest.raises(ValueError):
        shape("RX")


@pytest.mark.parametrize("kind,qubits,n", [("SWAP", (0, 2), 3), ("CZ", (1, 0), 2), ("CCX", (2, 0, 1), 3)])
def test_decompositions(kind, qubits, n):
    parts = [Gate(k, q, t) for k, q, t in decompose(kind, *qubits)]
    assert same(unitary(n, parts), unitary(n, [Gate(kind, qubits)]))


def test_columns_agree_with_arrays(spark):
    rows = [(k, t) for k in [*KINDS, "CZ", "CCX"] for t in (0.3, math.pi, 2 * math.pi, 4 * math.pi)]
    df = spark.createDataFrame(rows, "kind string, theta double")
    for r in classify(df).select("kind", "theta", "shape", matrix_array(F.col("kind"), F.col("theta")).alias("u")).collect():
        assert r["shape"] == shape(r["kind"], r["theta"])
        u = np.array(r["u"]).reshape(2, 2, 2)
        assert np.allclose(u[..., 0] + 1j * u[..., 1], matrix(r["kind"], r["theta"]))
    with pytest.raises(Exception, match="unknown gate kind"):
        classify(spark.createDataFrame([("NOPE", 0.0)], "kind string, theta double")).collect()


def brute(kind, target, controls, theta, n, b):
    """Partitions by walking every operation."""
    form, size = shape(kind, theta), 1 << n
    held = sum(1 << c for c in (controls[1:] if kind == "SWAP" else controls))
    ops = []
    for i in range(size):
        if i & held != held:
            continue
        if form == "exchange":
            lo, hi = sorted((target, controls[0]))
            if i >> lo & 1 and not i >> hi & 1:
                ops.append((i, i ^ (1 << lo) ^ (1 << hi)))
        elif form == "swap" and not i >> target & 1:
            ops.append((i, i | 1 << target))
        elif form == "one" and i >> target & 1 or form == "full":
            ops.append((i, i))
    tasks = [(min(x for x, _ in c) >> b, max(y for _, y in c) >> b) for c in (ops[k : k + (1 << b)] for k in range(0, len(ops), 1 << b))]
    out = []
    for lo, hi in tasks:
        if out and lo <= out[-1][1]:
            out[-1] = [out[-1][0], max(hi, out[-1][1]), out[-1][2] + 1]
        else:
            out.append([lo, hi, 1])
    return [tuple(x) for x in out]


@pytest.mark.parametrize("n", [3, 5])
def test_closed_form_partitions(n):
    cases = [(k, t, (), th) for k, th in (("X", None), ("Z", None), ("RZ", 0.7), ("Y", None)) for t in range(n)]
    cases += [(k, t, (c,), None) for k in ("CNOT", "CZ", "SWAP") for t in range(n) for c in range(n) if c != t]
    cases += [("CCX", t, (c, d), None) for t in range(n) for c in range(n) for d in range(c) if t not in (c, d)]
    for kind, t, c, th in cases:
        for b in range(n + 1):
            p = pattern(kind, t, c, th, n, b)
            assert [(*p.bounds(k, b), p.tasks) for k in range(p.count)] == brute(kind, t, c, th, n, b), (kind, t, c, b)
