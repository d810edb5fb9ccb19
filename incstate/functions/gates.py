"""Gate catalogue as column expressions and as small arrays.

A gate is a 2x2 matrix on a target qubit under any number of control qubits, or an exchange of two
qubits.  What a gate does to the state vector is read off its matrix, not its name: ``swap`` exchanges
amplitudes in pairs, ``one`` scales those whose target bit is 1, ``full`` scales both halves, ``id`` does
nothing and ``mix`` creates superposition.  So a rotation by a multiple of pi is found to be monomial.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Kinds in the order of the codes that the derived circuits use.
KINDS = ("H", "X", "Y", "Z", "S", "SDG", "T", "TDG", "RX", "RY", "RZ", "CNOT")
ALIASES = {"CNOT": "X", "CX": "X", "CCX": "X", "CZ": "Z", "CY": "Y", "CH": "H", "CRZ": "RZ", "CRX": "RX", "CRY": "RY"}
TOLERANCE = 1e-12

_R = 1 / math.sqrt(2)
#: Matrices of the kinds without angle, row by row, real and imaginary parts in turn.
_FIXED = {
    "H": (_R, 0, _R, 0, _R, 0, -_R, 0),
    "X": (0, 0, 1, 0, 1, 0, 0, 0),
    "Y": (0, 0, 0, -1, 0, 1, 0, 0),
    "Z": (1, 0, 0, 0, 0, 0, -1, 0),
    "S": (1, 0, 0, 0, 0, 0, 0, 1),
    "SDG": (1, 0, 0, 0, 0, 0, 0, -1),
    "T": (1, 0, 0, 0, 0, 0, _R, _R),
    "TDG": (1, 0, 0, 0, 0, 0, _R, -_R),
}


def base_kind(kind: str) -> str:
    return ALIASES.get(kind, kind)


def matrix(kind: str, theta: float | None = None) -> np.ndarray:
    """The 2x2 matrix of a kind (of the base kind where it is controlled)."""
    base = base_kind(kind)
    if base in _FIXED:
        u = np.array(_FIXED[base], float)
    elif base in ("RX", "RY", "RZ"):
        if theta is None:
            raise ValueError(f"{kind} needs an angle")
        c, s = (0.0 if abs(v) < TOLERANCE else v for v in (math.cos(theta / 2), math.sin(theta / 2)))
        u = np.array({"RX": (c, 0, 0, -s, 0, -s, c, 0), "RY": (c, 0, -s, 0, s, 0, c, 0), "RZ": (c, -s, 0, 0, 0, 0, c, s)}[base])
    else:
        raise ValueError(f"unknown gate kind {kind}")
    return (u[0::2] + 1j * u[1::2]).reshape(2, 2)


def shape(kind: str, theta: float | None = None) -> str:
    """``swap``, ``one``, ``full``, ``id`` or ``mix``; ``exchange`` for SWAP."""
    if kind == "SWAP":
        return "exchange"
    u = matrix(kind, theta)
    if abs(u[0, 1]) < TOLERANCE and abs(u[1, 0]) < TOLERANCE:
        ones = [abs(u[i, i] - 1) < TOLERANCE for i in (0, 1)]
        return "id" if all(ones) else "one" if ones[0] else "full"
    return "swap" if abs(u[0, 0]) < TOLERANCE and abs(u[1, 1]) < TOLERANCE else "mix"


def _snapped(value: Column) -> Column:
    return F.when(F.abs(value) < TOLERANCE, F.lit(0.0)).otherwise(value)


def _plain_kinds() -> dict[str, str]:
    """Kinds without angle, composed names included, with their base."""
    return {k: base_kind(k) for k in [*_FIXED, *ALIASES] if base_kind(k) in _FIXED}


def _turns(kind: Column, name: str) -> Column:
    return kind.isin([k for k in [name, *ALIASES] if base_kind(k) == name])


def matrix_array(kind: Column, theta: Column) -> Column:
    """The eight matrix entries of each row's gate, row by row, real and imaginary parts in turn."""
    fixed = F.create_map(*[x for k, of in _plain_kinds().items() for x in (F.lit(k), F.array(*[F.lit(float(v)) for v in _FIXED[of]]))])
    half = theta / F.lit(2.0)
    c, s, zero = _snapped(F.cos(half)), _snapped(F.sin(half)), F.lit(0.0)
    return (
        F.when(_turns(kind, "RX"), F.array(c, zero, zero, -s, zero, -s, c, zero))
        .when(_turns(kind, "RY"), F.array(c, zero, -s, zero, s, zero, c, zero))
        .when(_turns(kind, "RZ"), F.array(c, -s, zero, zero, zero, zero, c, s))
        .otherwise(F.element_at(fixed, kind))
    )


def shape_column(kind: Column, theta: Column) -> Column:
    """:func:`shape` of each row's gate: of plain kinds by their matrices, of rotations by their angle."""
    of = {k: shape(base) for k, base in _plain_kinds().items()} | {"SWAP": "exchange"}
    plain = F.create_map(*[F.lit(x) for kv in of.items() for x in kv])
    c, s = F.cos(theta / F.lit(2.0)), F.sin(theta / F.lit(2.0))
    whole = F.when(c > 0, "id").otherwise("full")
    straight = F.abs(s) < TOLERANCE
    return (
        F.when(_turns(kind, "RZ"), F.when(straight, whole).otherwise("full"))
        .when(_turns(kind, "RX") | _turns(kind, "RY"), F.when(straight, whole).when(F.abs(c) < TOLERANCE, "swap").otherwise("mix"))
        .otherwise(F.element_at(plain, kind))
    )


def classify(gates: DataFrame) -> DataFrame:
    """``gates`` with ``shape`` and ``mode`` (``mono``, ``sup`` or ``id``); unknown kinds raise at run time."""
    made = shape_column(F.col("kind"), F.col("theta"))
    known = F.col("kind").isin([*KINDS, *ALIASES, "SWAP"])
    checked = F.when(known, made).otherwise(F.raise_error(F.concat(F.lit("unknown gate kind "), F.coalesce("kind", F.lit("null")))))
    mode = F.when(F.col("shape") == "mix", "sup").when(F.col("shape") == "id", "id").otherwise("mono")
    return gates.withColumn("shape", checked).withColumn("mode", mode)


def decompose(kind: str, *qubits: int) -> list[tuple[str, tuple[int, ...], float | None]]:
    """A composed gate as (kind, (target, controls...), angle) of the basic kinds, first to last."""
    if kind == "SWAP":
        a, b = qubits
        return [("CNOT", (a, b), None), ("CNOT", (b, a), None), ("CNOT", (a, b), None)]
    if kind == "CZ":
        t, c = qubits
        return [("H", (t,), None), ("CNOT", (t, c), None), ("H", (t,), None)]
    if kind == "CCX":
        t, b, a = qubits
        return [
            ("H", (t,), None), ("CNOT", (t, b), None), ("TDG", (t,), None), ("CNOT", (t, a), None), ("T", (t,), None),
            ("CNOT", (t, b), None), ("TDG", (t,), None), ("CNOT", (t, a), None), ("T", (b,), None), ("T", (t,), None),
            ("H", (t,), None), ("CNOT", (b, a), None), ("T", (a,), None), ("TDG", (b,), None), ("CNOT", (b, a), None),
        ]
    return [(kind, qubits, None)]
