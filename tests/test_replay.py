"""The batched replay of edit logs against the engine that takes one circuit and one slot at a time."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pytest

from incstate.plans import replay as many
from incstate.plans.small import replay

KINDS = ["H", "X", "Y", "Z", "S", "T", "RX", "RY", "RZ", "CNOT", "CZ", "CH", "SWAP", "CCX"]
ROW = pa.schema([
    ("circuit_id", pa.int64()), ("iter", pa.int64()), ("op", pa.string()), ("net_no", pa.int64()), ("gate_no", pa.int64()),
    ("kind", pa.string()), ("target", pa.int32()), ("controls", pa.list_(pa.int32())), ("theta", pa.float64()),
])


def random_log(rng, circuit, n, length):
    out, made, it = [], [], int(rng.integers(-2, 3))
    for k in range(length):
        it += int(rng.integers(0, 3) == 0) * int(rng.integers(1, 3))
        e = {"circuit_id": circuit, "iter": it, "op": "insert", "net_no": 0, "gate_no": 0, "kind": None, "target": None, "controls": [], "theta": None}
        if made and rng.random() < 0.35:
            e |= {"op": "remove", "gate_no": int(rng.choice(made + [999]))}
        else:
            kind = str(rng.choice(KINDS))
            qubits = rng.permutation(n)[: {"CNOT": 2, "CZ": 2, "CH": 2, "SWAP": 2, "CCX": 3}.get(kind, 1)].tolist()
            e |= {"net_no": int(rng.integers(0, 6)), "gate_no": int(rng.permutation(1000)[0]) * 100 + k, "kind": kind, "target": qubits[0], "controls": qubits[1:]}
            e["theta"] = float(rng.choice([np.pi, 2 * np.pi, 4 * np.pi, 0.7, 2.1]))
            made.append(e["gate_no"])
        out.append(e)
    return out


@pytest.mark.parametrize("n, block, sync", [(3, 1, "global"), (4, 2, "coupled"), (5, 4, "global"), (4, 16, "global"), (5, 4, "coupled")])
def test_batches_equal_one_circuit_at_a_time(n, block, sync, monkeypatch):
    """States and every count, with refusals, shared nets, removals of gates that aren't there, and one-edit circuits."""
    monkeypatch.setattr(many, "BATCH_AMPLITUDES", 4000)
    rng = np.random.default_rng(n * 100 + block)
    logs = [random_log(rng, c, n, int(rng.integers(1, 40))) for c in range(60)]
    rows = [e for log in logs for e in log]
    batches = pa.Table.from_pylist(rows, ROW).to_batches(max_chunksize=97)
    whole = list(many.whole_circuits(iter(batches), 150))
    assert sum(map(len, whole)) == len(rows) and len(whole) > 1
    got = [r for b in many.replay_tables(iter(batches), n, block, sync, None) for r in b.to_pylist()]
    got.sort(key=lambda r: r["circuit_id"])
    want = [{"circuit_id": c} | r for c, log in enumerate(logs) for r in replay(log, n, block, sync)]
    assert len(got) == len(want)
    for a, b in zip(got, want):
        assert {k: a[k] for k in b if k not in ("re", "im")} == {k: b[k] for k in b if k not in ("re", "im")}
        assert np.allclose(a["re"], b["re"]) and np.allclose(a["im"], b["im"])


def test_a_gate_put_back_before_the_update_changes_nothing():
    e = {"circuit_id": 5, "iter": 1, "op": "insert", "net_no": 1, "gate_no": 7, "kind": "H", "target": 0, "controls": [], "theta": None}
    log = [e, e | {"iter": 2, "op": "remove"}, e | {"iter": 2}, e | {"iter": 3, "op": "remove"}, e | {"iter": 3, "kind": "X"}]
    a, b, c = (r for x in many.replay_tables(iter(pa.Table.from_pylist(log, ROW).to_batches()), 2, 2, "global", None) for r in x.to_pylist())
    assert a["affected_parts"] == 2 and b["affected_parts"] == 0 and b["re"] == a["re"]
    assert c["re"] == [0, 1, 0, 0] and c["affected_parts"] > 0


def test_many_short_logs_take_few_steps(monkeypatch):
    """Python's work grows with the longest log, not with the number of circuits."""
    steps, real = [], many.Batch._visit
    monkeypatch.setattr(many.Batch, "_visit", lambda self, *a: steps.append(1) or real(self, *a))
    e = {"op": "insert", "kind": "H", "controls": [], "theta": None}
    rows = [e | {"circuit_id": c, "iter": k, "net_no": k, "gate_no": k, "target": (c + k) % 5} for c in range(5000) for k in range(4)]
    out = list(many.replay_tables(iter(pa.Table.from_pylist(rows, ROW).to_batches()), 5, 4, "global", lambda psi: {"norm": (abs(psi) ** 2).sum(axis=1)}))
    assert sum(map(len, out)) == 20000 and len(steps) < 100 and all(np.allclose(b["norm"], 1) for b in out)
