"""Incremental updates of many small circuits: each circuit's edit log is replayed by one in-memory engine.

The engine keeps block versions per slot as arrays that slots share until they write them.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from incstate.operators.partition import Pattern, log2, pattern
from incstate.plans.replay import COUNTS, Measure, replay_tables
from incstate.plans.wide import Gate, block_kernel, coupled_bits


class SmallCircuit:
    """Nets are numbers in order; gates have numbers; all in one process."""

    def __init__(self, n: int, block_size: int, sync: str = "global"):
        self.n, self.b, self.sync = n, log2(block_size, n), sync
        self.n_blocks = 1 << (n - self.b)
        self.gates: dict[int, tuple[int, Gate]] = {}
        self.slots: list[tuple] = []
        self.patterns: dict[int, Pattern | None] = {}
        #: Of each slot met: its partitions' spans, its gates and the block bits that they couple.
        self.known: dict[tuple, tuple[list[tuple[int, int]], list[Gate], int]] = {}
        self.versions: dict[tuple, dict[int, np.ndarray]] = {}
        start = np.zeros((self.n_blocks, 1 << self.b), complex)
        start[0, 0] = 1
        self.start = dict(enumerate(start))

    def accepts(self, net: int, gate: Gate) -> bool:
        """Whether no gate of the net uses one of the qubits."""
        return not any(m == net and set(g.qubits) & set(gate.qubits) for m, g in self.gates.values())

    def insert(self, number: int, net: int, gate: Gate) -> None:
        self.gates[number] = (net, gate)
        self.patterns[number] = pattern(gate.kind, gate.target, gate.controls, gate.theta, self.n, self.b)

    def remove(self, number: int) -> None:
        self.gates.pop(number, None)

    def _layout(self) -> list[tuple]:
        mixing: dict[int, list[int]] = {}
        single = []
        for number, (net, g) in sorted(self.gates.items()):
            if g.form == "mix":
                mixing.setdefault(net, []).append(number)
            elif g.form != "id":
                lo, hi = self.patterns[number].bounds(0, self.b)
                single.append((net, 1, hi - lo, number, (number,)))
        return sorted([(net, 0, 0, 0, tuple(m)) for net, m in mixing.items()] + single)

    def _slot(self, slot: tuple) -> tuple[list[tuple[int, int]], list[Gate], int]:
        if slot not in self.known:
            gates, p = [self.gates[k][1] for k in slot[4]], self.patterns[slot[4][0]]
            self.known[slot] = [p.bounds(k, self.b) for k in range(p.count)], gates, coupled_bits(gates, self.b)
        return self.known[slot]

    def update(self) -> dict[str, int]:
        """Recompute what changed since the last update; the counts of what was done."""
        slots = self._layout()
        before = set(self.slots)
        now = set(slots)
        dirty = np.zeros(self.n_blocks, bool)
        gone = [s for s in self.slots if s not in now]
        lost = [(s, set(self.versions[s])) for s in gone]
        report = {"affected_parts": 0, "span_amplitudes": 0, "written_blocks": 0, "frontier_parts": 0, "total_blocks": len(slots) * self.n_blocks}
        latest = dict(self.start)
        spanned: set[int] = set()
        waiting = sorted(lost)
        removed = np.zeros(self.n_blocks, bool)
        for s in slots:
            while waiting and waiting[0][0] < s:
                removed[list(waiting.pop(0)[1])] = True
            spans, gates, mask = self._slot(s)
            if s not in before:
                hit = spans
            elif not (dirty.any() or removed.any()):
                hit = []
            elif s[1] == 0:
                hit = spans if self.sync == "global" else self._coupled(spans, mask, dirty | removed)
            else:
                open_ = dirty | removed
                hit = [(lo, hi) for lo, hi in spans if open_[lo : hi + 1].any()]
            fresh = hit if s not in before else [(lo, hi) for lo, hi in hit if removed[lo : hi + 1].any() or s[1] == 0 and removed.any()]
            report["frontier_parts"] += len(fresh)
            report["affected_parts"] += len(hit)
            blocks = sorted({k for lo, hi in hit for k in range(lo, hi + 1)})
            if blocks:
                need = set(blocks)
                for q in range(self.n - self.b):
                    if mask >> q & 1:
                        need |= {k ^ (1 << q) for k in need}
                order = np.array(sorted(need))
                made = block_kernel(np.stack([latest[k] for k in order.tolist()]), order, gates, self.b)
                held = self.versions.setdefault(s, {})
                at = {int(k): i for i, k in enumerate(order)}
                for k in blocks:
                    held[k] = made[at[k]]
                dirty[blocks] = True
                removed[blocks] = False
                spanned.update(blocks)
                report["written_blocks"] += len(blocks)
            latest.update(self.versions.get(s, {}))
        for s in gone:
            del self.versions[s]
            del self.known[s]
        report["span_amplitudes"] = len(spanned) << self.b
        self.slots = slots
        self.final = np.concatenate([latest[k] for k in range(self.n_blocks)])
        return report

    def _coupled(self, spans, mask, dirty) -> list[tuple[int, int]]:
        groups = set((np.flatnonzero(dirty) & ~mask).tolist())
        return [(lo, hi) for lo, hi in spans if lo & ~mask in groups]


_STATE = "re array<double>, im array<double>"


def replay(log: list[dict], n: int, block_size: int, sync: str = "global", check_nets: bool = True) -> list[dict]:
    """Run one circuit's edits (in order) with an update after each iteration."""
    circuit = SmallCircuit(n, block_size, sync)
    out = []
    for at, e in enumerate(log):
        if e["op"] == "insert":
            gate = Gate(e["kind"], (e["target"], *(e["controls"] or ())), e["theta"])
            if not check_nets or circuit.accepts(e["net_no"], gate):
                circuit.insert(e["gate_no"], e["net_no"], gate)
        elif e["op"] == "remove":
            circuit.remove(e["gate_no"])
        if at + 1 == len(log) or log[at + 1]["iter"] != e["iter"]:
            report = circuit.update()
            out.append({"iter": e["iter"], **report, "re": circuit.final.real.tolist(), "im": circuit.final.imag.tolist()})
    return out


def incremental_many(
    log: DataFrame, n: int, block_size: int, sync: str = "global", measure: tuple[str, Measure] | None = None
) -> DataFrame:
    """Replay all circuits' logs ``(circuit_id, seq, iter, op, net_no, gate_no, kind, target, controls, theta)``.

    Returns one row per circuit and iteration with the update's counts and the state after it, or, where
    ``measure`` is given, what it makes of the states (its columns and a function of an array of vectors).  One
    shuffle by circuit; a circuit's log must fit a task.
    """

    def run(batches):
        return replay_tables(batches, n, block_size, sync, measure and measure[1])

    entry = ["circuit_id", "iter", "op", "net_no", "gate_no", "kind", "target", "controls", "theta"]
    # The window brings a circuit's edits together and in order; the number keeps it in the plan.
    order = Window.partitionBy("circuit_id").orderBy("seq")
    sorted_log = log.select(*entry, "seq").withColumn("nth", F.row_number().over(order)).drop("seq")
    more = _STATE if measure is None else measure[0]
    schema = ", ".join(["circuit_id bigint, iter bigint", *[f"{k} bigint" for k in COUNTS], *([more] if more else [])])
    return sorted_log.mapInArrow(run, schema)
