"""Generated circuit families, as lists of nets of gates (textbook constructions)."""

from __future__ import annotations

import math

from incstate.functions.gates import decompose
from incstate.plans.wide import Gate

Nets = list[list[Gate]]


def _line(*gates: Gate) -> Nets:
    return [[g] for g in gates]


def ghz(n: int) -> Nets:
    return _line(Gate("H", (0,)), *[Gate("CNOT", (i + 1, i)) for i in range(n - 1)])


def qft(n: int) -> Nets:
    """Without final swaps; a controlled phase is three RZ and two CNOT, up to a global phase."""
    out: list[Gate] = []
    for j in range(n - 1, -1, -1):
        out.append(Gate("H", (j,)))
        for k in range(j - 1, -1, -1):
            phi = math.pi / (1 << (j - k))
            out += [Gate("RZ", (k,), phi / 2), Gate("CNOT", (j, k)), Gate("RZ", (j,), -phi / 2), Gate("CNOT", (j, k)), Gate("RZ", (j,), phi / 2)]
    return _line(*out)


def bv(n: int, secret: int) -> Nets:
    """The hidden bits of ``secret`` over the lower ``n - 1`` qubits."""
    top = n - 1
    nets = [[Gate("X", (top,))], [Gate("H", (q,)) for q in range(n)]]
    nets += _line(*[Gate("CNOT", (top, q)) for q in range(n - 1) if secret >> q & 1])
    return [*nets, [Gate("H", (q,)) for q in range(n - 1)]]


def coin(n: int) -> Nets:
    return [[Gate("H", (q,)) for q in range(n - 1)], *_line(*[Gate("CNOT", (n - 1, q)) for q in range(n - 1)])]


def _toffoli(target: int, x: int, y: int, expand: bool = False) -> list[Gate]:
    return [Gate(k, q, th) for k, q, th in decompose("CCX", target, x, y)] if expand else [Gate("CCX", (target, x, y))]


def _ripple(x: list[int], y: list[int], carry: int, out: int, expand: bool = False) -> list[Gate]:
    """The number on qubits ``y`` gains that on ``x``; ``carry`` is 0 and ``out`` is flipped by the last carry."""
    chain, gates = [carry, *x], []
    for low, p, q in zip(chain, x, y):
        gates += [Gate("CNOT", (q, p)), Gate("CNOT", (low, p)), *_toffoli(p, low, q, expand)]
    gates.append(Gate("CNOT", (out, x[-1])))
    for low, p, q in reversed(list(zip(chain, x, y))):
        gates += [*_toffoli(p, low, q, expand), Gate("CNOT", (low, p)), Gate("CNOT", (q, low))]
    return gates


def _set(qubits: list[int], value: int) -> list[Gate]:
    return [Gate("X", (q,)) for k, q in enumerate(qubits) if value >> k & 1]


def adder(m: int, a: int, b: int, expand: bool = True) -> Nets:
    """``b += a`` on ``2m + 2`` qubits: carry-in 0, then b and a bits in turn, carry-out last."""
    bits_b, bits_a = [1 + 2 * i for i in range(m)], [2 + 2 * i for i in range(m)]
    return _line(*_set(bits_a, a), *_set(bits_b, b), *_ripple(bits_a, bits_b, 0, 2 * m + 1, expand))


def _products(m: int) -> list[Gate]:
    """The product of two numbers on ``5m + 1`` qubits: carry, a, b, the row to add, the product (``2m``)."""
    a, b, row, product = ([1 + k * m + i for i in range(m)] for k in range(4))
    product += [4 * m + 1 + i for i in range(m)]
    gates = []
    for i in range(m):
        made = [g for k in range(m) for g in _toffoli(row[k], a[i], b[k])]
        gates += [*made, *_ripple(row, product[i : i + m], 0, product[i + m]), *made]
    return gates


def multiplier(m: int, a: int, b: int) -> Nets:
    return _line(*_set([1 + i for i in range(m)], a), *_set([1 + m + i for i in range(m)], b), *_products(m))


def scaling(m: int, factor: int, b: int) -> Nets:
    """``factor`` times ``b``: carry, the ``m`` bits of b, then ``m`` plus the factor's bits of product."""
    bits, product = [1 + i for i in range(m)], [1 + m + i for i in range(m + factor.bit_length())]
    sums = [g for i in range(factor.bit_length()) if factor >> i & 1 for g in _ripple(bits, product[i : i + m], 0, product[i + m])]
    return _line(*_set(bits, b), *sums)


def factoring(m: int) -> Nets:
    """Every product of two ``m``-bit numbers at once; the layout is that of :func:`multiplier`."""
    return [[Gate("H", (1 + q,)) for q in range(2 * m)], *_line(*_products(m))]


def key_exchange(bits: list[int], sent: list[int], read: list[int]) -> Nets:
    """Bits sent in one of two bases each and read in one of two."""
    pick = lambda kind, chosen: [Gate(kind, (q,)) for q, x in enumerate(chosen) if x]
    return [net for net in (pick("X", bits), pick("H", sent), pick("H", read)) if net]


def network(layers: list[list[float]]) -> Nets:
    """Layers of a rotation on every qubit and a ring of CNOTs."""
    nets: Nets = []
    for angles in layers:
        n = len(angles)
        nets += [[Gate("RY", (q,), x) for q, x in enumerate(angles)], *_line(*[Gate("CNOT", ((q + 1) % n, q)) for q in range(n)])]
    return nets


def satisfying(clauses: list[tuple[tuple[int, int], tuple[int, int]]], rounds: int = 1) -> Nets:
    """Search over three variables (lowest qubits) for what meets three clauses of two ``(variable, wanted)`` each."""
    both = lambda t, x, y: [Gate("H", (t,)), Gate("CCX", (t, x, y)), Gate("H", (t,))]
    judge = []
    for k, clause in enumerate(clauses):
        turn = [Gate("X", (v,)) for v, wanted in clause if wanted]
        judge += [Gate("X", (3 + k,)), *turn, Gate("CCX", (3 + k, clause[0][0], clause[1][0])), *turn]
    nets: Nets = [[Gate("H", (q,)) for q in range(3)]]
    for _ in range(rounds):
        nets += _line(*judge, *both(5, 3, 4), *reversed(judge))
        around = [[Gate("H", (q,)) for q in range(3)], [Gate("X", (q,)) for q in range(3)]]
        nets += [*around, *_line(*both(2, 0, 1)), *reversed(around)]
    return nets


def order_finding(bits: int, base: int) -> Nets:
    """The order of ``base`` modulo 15, read off ``bits`` counting qubits; four work qubits start at 1.

    A base is a power of two or minus one: such a product turns the bits around and flips them all.
    """
    if math.gcd(base, 15) != 1:
        raise ValueError(f"{base} has no order modulo 15")
    work = [bits + i for i in range(4)]
    nets: Nets = [[Gate("X", (work[0],))], [Gate("H", (q,)) for q in range(bits)]]
    for q in range(bits):
        factor = pow(base, 1 << q, 15)
        flip = factor not in (1, 2, 4, 8)
        for _ in range(((15 - factor) if flip else factor).bit_length() - 1):
            for x, y in ((work[2], work[3]), (work[1], work[2]), (work[0], work[1])):
                nets += _line(Gate("CNOT", (x, y)), Gate("CCX", (y, q, x)), Gate("CNOT", (x, y)))
        if flip:
            nets += _line(*[Gate("CNOT", (w, q)) for w in work])
    return [*nets, *_counted(bits)]


def eigensolver(filled: list[int], strings: list[tuple[str, float]]) -> Nets:
    """An ansatz of rotations about products of X and Y on all qubits, from a state with some qubits set."""
    nets: Nets = [[Gate("X", (q,)) for q in filled]]
    for axes, angle in strings:
        n = len(axes)
        turn = lambda sign: [Gate("H", (q,)) if x == "X" else Gate("RX", (q,), sign * math.pi / 2) for q, x in enumerate(axes)]  # noqa: B023, E731
        ladder = [Gate("CNOT", (q + 1, q)) for q in range(n - 1)]
        nets += [turn(1), *_line(*ladder, Gate("RZ", (n - 1,), angle), *reversed(ladder)), turn(-1)]
    return nets


def ising(n: int, angles: list[tuple[float, float]]) -> Nets:
    """One step per (field, coupling) pair of angles."""
    nets: Nets = []
    for field, coupling in angles:
        nets.append([Gate("RX", (q,), field) for q in range(n)])
        for q in range(n - 1):
            nets += _line(Gate("CNOT", (q + 1, q)), Gate("RZ", (q + 1,), coupling), Gate("CNOT", (q + 1, q)))
    return nets


def qaoa(n: int, edges: list[tuple[int, int]], angles: list[tuple[float, float]]) -> Nets:
    nets: Nets = [[Gate("H", (q,)) for q in range(n)]]
    for cost, mix in angles:
        for x, y in edges:
            nets += _line(Gate("CNOT", (y, x)), Gate("RZ", (y,), cost), Gate("CNOT", (y, x)))
        nets.append([Gate("RX", (q,), mix) for q in range(n)])
    return nets


def simon(m: int, secret: int) -> Nets:
    """A two-to-one function with period ``secret``: m data qubits (low) and m result qubits."""
    nets: Nets = [[Gate("H", (q,)) for q in range(m)], *_line(*[Gate("CNOT", (m + q, q)) for q in range(m)])]
    if secret:
        lead = secret.bit_length() - 1
        nets += _line(*[Gate("CNOT", (m + q, lead)) for q in range(m) if secret >> q & 1])
    return [*nets, [Gate("H", (q,)) for q in range(m)]]


def qpe(bits: int, phase: float) -> Nets:
    """Phase estimation of a phase gate on the top qubit (set to 1); counting qubits are the lower ``bits``."""
    top = bits
    nets: Nets = [[Gate("X", (top,))], [Gate("H", (q,)) for q in range(bits)]]
    for q in range(bits):
        phi = 2 * math.pi * phase * (1 << q)
        nets += _line(Gate("RZ", (q,), phi / 2), Gate("CNOT", (top, q)), Gate("RZ", (top,), -phi / 2), Gate("CNOT", (top, q)), Gate("RZ", (top,), phi / 2))
    return [*nets, *_counted(bits)]


def _counted(bits: int) -> Nets:
    """The inverse transform of the lower ``bits`` qubits, which count with their bits reversed."""
    flip = {q: bits - 1 - q for q in range(bits)}
    inverse = [g for net in reversed(qft(bits)) for g in net]
    return _line(*[Gate(g.kind, tuple(flip[q] for q in g.qubits), None if g.theta is None else -g.theta) for g in inverse])


def flat(nets: Nets) -> list[tuple[int, Gate]]:
    return [(k, g) for k, net in enumerate(nets) for g in net]


def counts(nets: Nets) -> tuple[int, int]:
    """Gates and CNOTs."""
    gates = [g for net in nets for g in net]
    return len(gates), sum(g.kind == "CNOT" for g in gates)
