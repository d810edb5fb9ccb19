"""Uses of incremental updates: equivalence, stepping through, and editing a circuit towards a state."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

from incstate.plans.small import SmallCircuit
from incstate.plans.wide import Gate


def final_state(gates: list[tuple[int, Gate]], n: int, block_size: int = 4) -> np.ndarray:
    circuit = SmallCircuit(n, block_size)
    for number, (net, gate) in enumerate(gates):
        circuit.insert(number, net, gate)
    circuit.update()
    return circuit.final


def equivalent(a: list[tuple[int, Gate]], b: list[tuple[int, Gate]], n: int, tolerance: float = 1e-9) -> bool:
    """Whether two circuits take zero to the same state up to phase."""
    return abs(abs(np.vdot(final_state(a, n), final_state(b, n))) - 1) < tolerance


def step_through(gates: list[tuple[int, Gate]], n: int, block_size: int = 4) -> Iterator[tuple[int, np.ndarray, dict[str, int]]]:
    """The state after each gate and the counts of the update that gave it."""
    circuit = SmallCircuit(n, block_size)
    for number, (net, gate) in enumerate(gates):
        circuit.insert(number, net, gate)
        report = circuit.update()
        yield number, circuit.final, report


def greedy_edit(target: np.ndarray, choices: list[Gate], n: int, steps: int, block_size: int = 4) -> tuple[list[Gate], float]:
    """Append, ``steps`` times at most, the gate that brings the state nearest to ``target``; each trial is one
    inserted gate, updated and removed again."""
    circuit = SmallCircuit(n, block_size)
    circuit.update()
    best, chosen = abs(np.vdot(target, circuit.final)) ** 2, []
    for step in range(steps):
        trials = []
        for k, gate in enumerate(choices):
            circuit.insert(step, step, gate)
            circuit.update()
            trials.append((abs(np.vdot(target, circuit.final)) ** 2, -k))
            circuit.remove(step)
            circuit.update()
        score, k = max(trials)
        if score <= best + 1e-12:
            break
        best = score
        chosen.append(choices[-k])
        circuit.insert(step, step, choices[-k])
        circuit.update()
    return chosen, best
