"""One editable circuit: nets, gates, modifiers, queries, and updates that recompute what changed.

The circuit's description is small and lives on the driver; amplitudes never do.  An update walks the
slots in order with the set of blocks that differ from the stored versions: a partition is recomputed if
its slot is new or it covers a changed block, and then all its blocks count as changed.  That is the set
reachable from the frontier in the partition graph, found in one pass.
"""

from __future__ import annotations

import itertools
import time
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from incstate.operators.partition import Pattern, log2, pattern
from incstate.plans.store import START, CowStore, within
from incstate.plans.wide import Gate, apply_blocks, blocks_to_rows


class NetConflictError(ValueError):
    """A gate was inserted on a qubit that its net already uses."""


@dataclass(frozen=True)
class Net:
    id: int


@dataclass(frozen=True)
class GateRef:
    id: int
    net: int
    gate: Gate


@dataclass
class Slot:
    """A step of the state: one monomial gate, or all mixing gates of a net."""

    id: str
    net: int
    gates: list[GateRef]
    patterns: list[Pattern]
    key: tuple

    def partitions(self, b: int) -> list[tuple[int, int]]:
        p = self.patterns[0]
        return [p.bounds(k, b) for k in range(p.count)]


@dataclass
class UpdateReport:
    """What one update did; amplitudes are counted once however many slots rewrite them."""

    frontier: list[tuple[str, int]] = field(default_factory=list)
    affected: list[tuple[str, int]] = field(default_factory=list)
    span_amplitudes: int = 0
    touched_amplitudes: int = 0
    written_blocks: int = 0
    slots: int = 0
    #: Jobs of the update: partitions of a wave run together.
    waves: int = 0
    seconds: float = 0.0


class Circuit:
    """``n`` qubits, qubit ``n - 1`` the most significant; a list of nets of gates on disjoint qubits."""

    def __init__(self, spark: SparkSession, n: int, block_size: int = 256, sync: str = "global", materialize_all: bool = False, start: DataFrame | None = None):
        if n < 1:
            raise ValueError("a circuit has at least one qubit")
        if sync not in ("global", "coupled"):
            raise ValueError("sync is global or coupled")
        self.spark, self.n, self.sync = spark, n, sync
        self.b = log2(block_size, n)
        self.block_size = 1 << self.b
        self.n_blocks = 1 << (n - self.b)
        self.store = CowStore(spark, materialize_all=materialize_all)
        self.nets: list[int] = []
        self.gates: dict[int, GateRef] = {}
        self._ids = itertools.count(1)
        self._slots: list[Slot] = []
        self._dirty_slots: set[str] = set()
        self._start = start
        self._started = False
        self._gone: list[tuple[tuple, list[tuple[int, int]]]] = []

    @property
    def qubits(self) -> tuple[int, ...]:
        """Qubit numbers, the most significant first."""
        return tuple(range(self.n - 1, -1, -1))

    # Modifiers

    def insert_net(self, after: Net | None = None) -> Net:
        """A new empty net right after ``after``, or first."""
        net = next(self._ids)
        self.nets.insert(0 if after is None else self._place(after) + 1, net)
        return Net(net)

    def remove_net(self, net: Net) -> None:
        """Remove a net with its gates."""
        self._place(net)
        for g in [g for g in self.gates.values() if g.net == net.id]:
            self.remove_gate(g)
        self.nets.remove(net.id)

    def insert_gate(self, kind: str, net: Net, *qubits: int, theta: float | None = None) -> GateRef:
        """Add a gate to a net; the target comes first, then controls."""
        self._place(net)
        gate = Gate(kind, tuple(qubits), theta)
        gate.form  # noqa: B018  an unknown kind or a missing angle raises here
        needed = {"CNOT": 2, "CX": 2, "CZ": 2, "CCX": 3}.get(kind)
        if not qubits or len(set(qubits)) < len(qubits) or any(not 0 <= q < self.n for q in qubits) or kind == "SWAP" and len(qubits) < 2:
            raise ValueError(f"{kind} can't act on qubits {qubits} of {self.n}")
        if needed and len(qubits) != needed:
            raise ValueError(f"{kind} acts on {needed} qubits")
        used = {q for g in self.gates.values() if g.net == net.id for q in g.gate.qubits}
        if used & set(qubits):
            raise NetConflictError(f"net {net.id} already uses qubits {sorted(used & set(qubits))}")
        ref = GateRef(next(self._ids), net.id, gate)
        self.gates[ref.id] = ref
        return ref

    def remove_gate(self, gate: GateRef) -> None:
        if self.gates.pop(gate.id, None) is None:
            raise KeyError(f"gate {gate.id} isn't in the circuit")

    def _place(self, net: Net) -> int:
        if net.id not in self.nets:
            raise KeyError(f"net {net.id} isn't in the circuit")
        return self.nets.index(net.id)

    # State update

    def _layout(self) -> list[Slot]:
        """Slots in order; a slot's id stays while its gates do."""
        out = []
        by_net: dict[int, list[GateRef]] = {}
        for g in self.gates.values():
            by_net.setdefault(g.net, []).append(g)
        known = {s.id: s.key for s in self._slots}
        for place, net in enumerate(self.nets):
            mixing = [g for g in by_net.get(net, ()) if g.gate.form == "mix"]
            if mixing:
                p = [pattern(g.gate.kind, g.gate.target, g.gate.controls, g.gate.theta, self.n, self.b) for g in mixing]
                out.append(Slot(f"mix{net}", net, mixing, p, (place, -1, 0, 0)))
            singles = []
            for g in by_net.get(net, ()):
                p = pattern(g.gate.kind, g.gate.target, g.gate.controls, g.gate.theta, self.n, self.b) if g.gate.form != "mix" else None
                if p is not None:
                    lo, hi = p.bounds(0, self.b)
                    singles.append(Slot(f"gate{g.id}", net, [g], [p], (place, 0, hi - lo, g.id)))
            # Slots that are stored keep their order within a net; new ones go by span.
            old = [s for s in singles if s.id in known]
            old.sort(key=lambda s: known[s.id][2:])
            for s in sorted((s for s in singles if s.id not in known), key=lambda s: s.key):
                at = next((i for i, o in enumerate(old) if o.key > s.key), len(old))
                old.insert(at, s)
            out += old
        return out

    def _partitions_changed(self, slot: Slot, dirty: np.ndarray, all_new: bool) -> list[int]:
        parts = slot.partitions(self.b)
        if all_new:
            return list(range(len(parts)))
        if slot.id.startswith("mix"):
            if self.sync == "global":
                return list(range(len(parts))) if dirty.any() else []
            mask = 0
            for g in slot.gates:
                mask |= 1 << (g.gate.target - self.b) if g.gate.target >= self.b else 0
            groups = np.unique(np.flatnonzero(dirty) & ~mask)
            return [k for k, (lo, _) in enumerate(parts) if lo & ~mask in groups]
        run = np.concatenate(([0], np.cumsum(dirty)))
        return [k for k, (lo, hi) in enumerate(parts) if run[hi + 1] > run[lo]]

    def update_state(self, execute: bool = True) -> UpdateReport:
        """Recompute what the modifiers since the last update affect; the first call simulates everything.

        With ``execute`` false only the report is made, and nothing is changed.
        """
        began = time.time()
        report = UpdateReport()
        slots = self._layout()
        before = {s.id: s for s in self._slots}
        now = {s.id: s for s in slots}
        changed = {s.id for s in slots if s.id not in before or [g.id for g in before[s.id].gates] != [g.id for g in s.gates]}
        gone = [s for s in self._slots if s.id not in now]
        if execute and not self._started:
            self._begin()
        store = self.store
        if execute:
            for s in gone:
                store.forget(s.id)
            store.order = [START, *[s.id for s in slots]]
        # What a removed slot wrote is changed from its old place on.
        old_order = [s.id for s in self._slots]
        lost: dict[str | None, list[Slot]] = {}
        for s in gone:
            later = [i for i in old_order[old_order.index(s.id) + 1 :] if i in now]
            lost.setdefault(later[0] if later else None, []).append(s)
        from_removed = np.zeros(self.n_blocks, bool)
        dirty = np.zeros(self.n_blocks, bool)
        spanned: set[int] = set()
        touched: set[int] = set()
        work: list[tuple[Slot, int, list[set[int]]]] = []
        for place, slot in enumerate(slots, 1):
            for s in lost.get(slot.id, ()):
                for lo, hi in s.partitions(self.b):
                    from_removed[lo : hi + 1] = True
            parts = slot.partitions(self.b)
            hit = self._partitions_changed(slot, dirty | from_removed, slot.id in changed)
            if not hit:
                continue
            source = set(range(len(parts))) if slot.id in changed else set(self._partitions_changed(slot, from_removed, False))
            report.frontier += [(slot.id, k) for k in hit if k in source]
            report.affected += [(slot.id, k) for k in hit]
            blocks = sorted({k for p in hit for k in range(parts[p][0], parts[p][1] + 1)})
            dirty[blocks] = True
            for k in blocks:
                # The first reader of a removed writer's block is its successor; later ones follow from it.
                from_removed[k] = False
            spanned.update(blocks)
            touched.update(self._touched(slot, blocks))
            report.slots += 1
            work.append((slot, place, [set(range(parts[p][0], parts[p][1] + 1)) for p in hit]))
        waves = self._waves(work)
        report.waves = len(waves)
        if execute:
            for wave in waves:
                made = [self._made(*one) for one in wave]
                store.write_wave(made)
                report.written_blocks += sum(len(ids) for _, _, ids in made)
            self._slots = slots
        report.span_amplitudes, report.touched_amplitudes = len(spanned) * self.block_size, len(touched) * self.block_size
        report.seconds = time.time() - began
        return report

    def _begin(self) -> None:
        if self._start is None:
            zero = F.array_repeat(F.lit(0.0), self.block_size)
            one = F.concat(F.array(F.lit(1.0)), F.array_repeat(F.lit(0.0), self.block_size - 1))
            start = self.spark.range(self.n_blocks).select(
                F.lit(0).cast("long").alias("circuit_id"), F.col("id").alias("block_id"),
                F.when(F.col("id") == 0, one).otherwise(zero).alias("re"), zero.alias("im"),
            )
        else:
            start = self._start
        self.store.write(START, start, set(range(self.n_blocks)))
        self._started = True

    def _wanted(self, slot: Slot, blocks: set[int]) -> set[int]:
        """Blocks that a slot reads to write ``blocks``."""
        wanted = set(blocks)
        if slot.id.startswith("mix"):
            for g in (g.gate for g in slot.gates):
                if g.target >= self.b:
                    wanted |= {k ^ (1 << (g.target - self.b)) for k in wanted}
        return wanted

    def _waves(self, work: list[tuple[Slot, int, list[set[int]]]]) -> list[list[tuple[Slot, int, set[int]]]]:
        """Partitions in waves: one comes after the last wave that writes a block it reads; those of a slot in a
        wave are taken together, and the mixing ones of a slot all at once, behind their common node.

        Slots read versions by place, so an earlier slot may run after or beside one that writes what it read.
        """
        if self.store.materialize_all:
            return [[(slot, place, set(range(self.n_blocks)))] for slot, place, _ in work]
        out: list[dict[int, tuple[Slot, int, set[int]]]] = []
        ready = np.zeros(self.n_blocks, np.int64)
        for slot, place, parts in work:
            for blocks in [set().union(*parts)] if slot.id.startswith("mix") else parts:
                read, write = (np.fromiter(x, np.int64, len(x)) for x in (self._wanted(slot, blocks), blocks))
                wave = int(ready[read].max(initial=0))
                if wave == len(out):
                    out.append({})
                out[wave].setdefault(place, (slot, place, set()))[2].update(blocks)
                ready[write] = wave + 1
        return [list(w.values()) for w in out]

    def _made(self, slot: Slot, place: int, blocks: set[int]) -> tuple[str, DataFrame, set[int]]:
        wanted = self._wanted(slot, blocks)
        made = apply_blocks(self.store.read(place - 1, wanted), [g.gate for g in slot.gates], self.block_size)
        return slot.id, made.where(within(blocks)) if wanted != blocks else made, blocks

    def _touched(self, slot: Slot, blocks: list[int]) -> list[int]:
        """Those of ``blocks`` in which some amplitude changes, not only lies in a span."""
        if slot.id.startswith("mix"):
            return blocks
        g = slot.gates[0].gate
        held = g.held | (1 << g.target if g.form == "one" else 0)
        high = held >> self.b
        return [k for k in blocks if k & high == high and self._moves(g, k)]

    def _moves(self, g: Gate, block: int) -> bool:
        if g.form != "exchange":
            return True
        a, c = (q - self.b for q in g.qubits[:2])
        return a < 0 or c < 0 or (block >> a ^ block >> c) & 1 == 1

    # Queries

    def blocks(self, upto: int | None = None) -> DataFrame:
        """Blocks of the current state, or after the first ``upto`` slots."""
        if not self._started:
            self.update_state()
        return self.store.read(upto)

    def state(self, upto: int | None = None) -> DataFrame:
        """Rows ``circuit_id, idx, re, im`` of the state."""
        return blocks_to_rows(self.blocks(upto), self.block_size)

    def amplitude(self, i: int) -> complex:
        """One amplitude; only its block is read."""
        if not 0 <= i < 1 << self.n:
            raise IndexError(i)
        if not self._started:
            self.update_state()
        row = self.store.read(None, {i >> self.b}).select(F.col("re")[i & (self.block_size - 1)], F.col("im")[i & (self.block_size - 1)]).first()
        return complex(row[0], row[1])

    def probabilities(self) -> DataFrame:
        return self.state().select("idx", (F.col("re") * F.col("re") + F.col("im") * F.col("im")).alias("p"))

    def marginal(self, *qubits: int) -> DataFrame:
        """``outcome, p`` over the given qubits, the first the least significant."""
        bits = [F.shiftright("idx", q).bitwiseAND(1) * (1 << k) for k, q in enumerate(qubits)]
        return self.probabilities().groupBy(sum(bits[1:], bits[0]).alias("outcome")).agg(F.sum("p").alias("p"))

    def top_states(self, k: int) -> DataFrame:
        return self.probabilities().orderBy(F.col("p").desc(), "idx").limit(k)

    def expect_z(self, q: int) -> float:
        return self.probabilities().agg(F.sum(F.col("p") * (1 - 2 * F.shiftright("idx", q).bitwiseAND(1)))).first()[0]

    def norm(self) -> float:
        return self.probabilities().agg(F.sum("p")).first()[0]

    def sample(self, shots: int, seed: int = 0) -> DataFrame:
        """``shot, idx``: seeded draws by inverse cumulative probability, bucketed by block totals."""
        per = self.probabilities().withColumn("block_id", F.shiftright("idx", self.b))
        from pyspark.sql import Window

        base = per.groupBy("block_id").agg(F.sum("p").alias("w"))
        before = Window.orderBy("block_id").rowsBetween(Window.unboundedPreceding, -1)
        base = base.withColumn("base", F.coalesce(F.sum("w").over(before), F.lit(0.0)))
        within = Window.partitionBy("block_id").orderBy("idx")
        steps = per.join(base, "block_id").withColumn("hi", F.col("base") + F.sum("p").over(within)).withColumn("lo", F.col("hi") - F.col("p"))
        draws = self.spark.range(shots).select(F.col("id").alias("shot"), F.rand(seed).alias("u"))
        # One row a block: broadcast up to a fixed number of blocks, else left to the planner.
        small = F.broadcast(base) if self.n_blocks <= 1 << 16 else base
        spots = draws.join(small, (F.col("u") >= F.col("base")) & (F.col("u") < F.col("base") + F.col("w")))
        return spots.select("shot", "u", "block_id").join(steps.select("block_id", "idx", "lo", "hi"), "block_id").where("u >= lo and u < hi").select("shot", "idx")

    def dump_graph(self) -> str:
        """The partition graph in DOT."""
        last: dict[int, str] = {}
        lines = ["digraph partitions {"]
        for slot in self._layout():
            name = [f"{slot.id}_p{k}" for k in range(len(slot.partitions(self.b)))]
            if slot.id.startswith("mix"):
                lines += [f"  {x} -> sync_{slot.id};" for x in sorted(set(last.values()))]
                lines += [f"  sync_{slot.id} -> {x};" for x in name]
            else:
                for x, (lo, hi) in zip(name, slot.partitions(self.b)):
                    lines += [f"  {y} -> {x};" for y in sorted({last[k] for k in range(lo, hi + 1) if k in last})]
            for x, (lo, hi) in zip(name, slot.partitions(self.b)):
                last.update(dict.fromkeys(range(lo, hi + 1), x))
        lines += [f"  {y} -> output;" for y in sorted(set(last.values()))]
        return "\n".join([*lines, "}"])

    def edges(self) -> set[tuple[str, str]]:
        """The edges of :meth:`dump_graph`."""
        return {tuple(x.strip(" ;").split(" -> ")) for x in self.dump_graph().splitlines()[1:-1]}

    def gate_list(self) -> list[tuple[int, Gate]]:
        """Net place and gate, in order."""
        place = {net: i for i, net in enumerate(self.nets)}
        return [(place[g.net], g.gate) for g in sorted(self.gates.values(), key=lambda g: (place[g.net], g.id))]
