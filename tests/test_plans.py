from __future__ import annotations

import numpy as np
import pytest

from incstate import metrics
from incstate.operators import relational
from incstate.operators.partition import log2
from incstate.plans import planner
from incstate.plans.baselines import unitary
from incstate.plans.many import simulate_many, to_rows, to_vectors
from incstate.plans.small import SmallCircuit
from incstate.plans.wide import Gate, blocks_table, blocks_to_rows
from incstate.sources import gate_source
from incstate.sources.gate_text import gate_lines, read_gate_text, write_gate_text
from incstate.sources.tables import write_report
from incstate.workloads import families, uses


def test_choices():
    assert planner.choose_plan(5, 14_743) == "many" and planner.choose_plan(30, 1) == "wide"
    assert planner.choose_block_size(20, 8) == 1 << 15 and planner.choose_block_size(4, 16) == 1
    assert planner.choose_block_size(42, 1000) == planner.LARGEST_BLOCK
    gates, new = planner.relabel([Gate("H", (4,)), Gate("H", (4,)), Gate("Z", (0,)), Gate("CNOT", (3, 0))], 5)
    assert new[4] == 0 and new[3] == 1 and gates[3].qubits == (1, new[0])
    runs = planner.fuse([g for _, g in families.flat(families.qft(8))], 3, 2)
    assert len(runs) < 20 and sum(map(len, runs)) == families.counts(families.qft(8))[0]
    with pytest.raises(ValueError):
        log2(12, 5)


@pytest.mark.parametrize("coupled", [1, 3])
def test_fused_simulation(spark, coupled):
    gates = [g for _, g in families.flat(families.adder(1, 1, 1))] + [g for _, g in families.flat(families.qft(4))]
    v = np.zeros((8, 2), complex)
    v[0, 0] = 1
    start = spark.createDataFrame(blocks_table(np.zeros(8, np.int64), np.arange(8), v))
    rows = blocks_to_rows(planner.simulate_wide(start, gates, 2, coupled), 2).orderBy("idx").toPandas()
    assert np.allclose(rows.re + 1j * rows.im, unitary(4, gates)[:, 0])


def test_many_plan_with_swaps_and_start(spark):
    gates = [Gate("H", (0,)), Gate("SWAP", (0, 2)), Gate("CCX", (1, 0, 2)), Gate("CZ", (1, 2)), Gate("RY", (1,), 0.3)]
    rows = [(1, k, k, g.kind, g.target, list(g.qubits[1:]), g.theta) for k, g in enumerate(gates)]
    df = spark.createDataFrame(rows, "circuit_id bigint, gate_no bigint, net_no bigint, kind string, target int, controls array<int>, theta double")
    v = np.arange(1, 9) / np.linalg.norm(np.arange(1, 9))
    start = spark.createDataFrame([(1, v.tolist(), [0.0] * 8), (2, v.tolist(), [0.0] * 8)], "circuit_id bigint, re array<double>, im array<double>")
    out = {r.circuit_id: np.array(r.re) + 1j * np.array(r.im) for r in simulate_many(df, 3, start).collect()}
    assert np.allclose(out[1], unitary(3, gates) @ v) and np.allclose(out[2], v)
    back = to_vectors(to_rows(start), 3).where("circuit_id = 1").first()
    assert np.allclose(back.re, v)


def test_text_round_trips(spark, tmp_path):
    rows = [(1, 1, 0, "H", 0, [], None), (1, 2, 0, "RZ", 1, [], 0.25), (1, 3, 1, "CNOT", 1, [0], None)]
    gates = spark.createDataFrame(rows, "circuit_id bigint, gate_no bigint, net_no bigint, kind string, target int, controls array<int>, theta double")
    assert gate_lines(gates).first().value == "h q[0];\nrz(0.25) q[1];\nbarrier;\ncnot q[1],q[0];"
    write_gate_text(gates.coalesce(1), str(tmp_path / "text"))
    read = [tuple(r)[1:] for r in read_gate_text(spark, str(tmp_path / "text" / "*.txt")).orderBy("gate_no").collect()]
    assert read == [r[1:] for r in rows]
    gate_source.register(spark)
    (tmp_path / "own").mkdir()
    (tmp_path / "own" / "a.txt").write_text(gate_lines(gates).first().value)
    own = spark.read.format("gate_text").option("path", str(tmp_path / "own")).load().orderBy("gate_no").collect()
    assert [tuple(r)[1:] for r in own] == [r[1:] for r in rows]
    write_report(gates.select("kind"), str(tmp_path / "report"))
    assert spark.read.json(str(tmp_path / "report")).count() == 3


def test_relational_operators(spark):
    a = spark.createDataFrame([(1, 0, 5), (1, 60, 200), (2, 3, 3)], "k int, lo long, hi long")
    b = spark.createDataFrame([(1, 5, 70), (1, 199, 300), (2, 4, 9)], "k int, lo long, hi long")
    got = {(r.lo, r.r_lo) for r in relational.interval_join(a, b, ["k"], bin_size=8).collect()}
    assert got == {(0, 5), (60, 5), (60, 199)}
    isles = relational.islands(a.unionByName(b), ["k"]).orderBy("k", "lo").collect()
    assert [(r.k, r.lo, r.hi, r.n) for r in isles] == [(1, 0, 300, 4), (2, 3, 3, 1), (2, 4, 9, 1)]


def test_metrics(spark):
    s = metrics.speedup([2.0, 8.0], [1.0, 2.0])
    assert s["total"] == pytest.approx(10 / 3) and s["mean"] == 3 and s["geometric"] == pytest.approx(8**0.5)
    h = spark.createDataFrame([(1, 1, 2.0), (1, 2, 3.0)], "c int, i int, ms double")
    assert [r.cumulative_ms for r in metrics.cumulative(h, "ms", ["c"], "i").orderBy("i").collect()] == [2.0, 5.0]
    rows = spark.createDataFrame([(0, 0, 0.6, 0.0), (0, 1, 0.0, 0.8)], "circuit_id bigint, idx bigint, re double, im double")
    assert metrics.norm_error(rows).first().error < 1e-12 and metrics.fidelity(rows, rows).first().fidelity == pytest.approx(1)
    assert metrics.max_difference(rows, rows.where("idx = 0")).first().difference == pytest.approx(0.8)
    assert metrics.time_runs(lambda: None, 3)["runs"] == 3 and metrics.peak_memory_gb() > 0


def test_uses():
    cnot = [(0, Gate("H", (0,))), (1, Gate("CZ", (0, 1))), (2, Gate("H", (0,)))]
    start = [(0, Gate("H", (1,)))]
    shift = lambda gates, k: [(k + net, g) for net, g in gates]
    assert uses.equivalent(start + shift(cnot, 1), start + [(1, Gate("CNOT", (0, 1)))], 2)
    assert not uses.equivalent(start, [(0, Gate("X", (0,)))], 2)
    steps = list(uses.step_through(families.flat(families.ghz(3)), 3))
    assert len(steps) == 3 and abs(abs(steps[-1][1][7]) ** 2 - 0.5) < 1e-9
    target = uses.final_state(families.flat(families.ghz(3)), 3)
    chosen, score = uses.greedy_edit(target, [Gate("H", (0,)), Gate("CNOT", (1, 0)), Gate("CNOT", (2, 1)), Gate("X", (0,))], 3, 5)
    assert 0.5 - 1e-9 <= score <= 1 + 1e-9 and len(chosen) <= 5


def test_monomial_circuits_gain_most():
    shares = {}
    for name, nets in (("adder", families.adder(2, 1, 2, expand=False)), ("qft", families.qft(6))):
        c = SmallCircuit(6, 4)
        gates = families.flat(nets)
        for k, (net, g) in enumerate(gates):
            c.insert(k, net, g)
        full = c.update()["affected_parts"]
        spread = []
        for k in range(0, len(gates), 3):
            c.remove(k)
            spread.append(c.update()["affected_parts"])
            c.insert(k, *gates[k])
            c.update()
        shares[name] = np.mean(spread) / full
    assert shares["adder"] < shares["qft"]
