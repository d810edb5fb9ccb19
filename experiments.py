"""The experiments as JSON lines: full and incremental times with both baselines, edits, block sizes, cores, stores.

    python experiments.py [runs|edits|blocks|cores|stores ...]

Every experiment prints one JSON line per setting.  ``runs`` times the engine level by level and in full against
two re-simulating plans and prints the ratio of totals; ``edits`` 50 iterations of insertions, removals and both;
``blocks`` block sizes of the transform up to one block; ``cores`` full and incremental runs by local threads, each
in a process of its own, the last with one block for the whole vector on one core; ``stores`` copy-on-write
against materialising every slot.
"""

from __future__ import annotations

import json
import subprocess
import sys
import time

import numpy as np

from incstate.metrics import peak_memory_gb, saturation, speedup, time_inc, time_runs
from incstate.plans.small import SmallCircuit
from incstate.workloads import families

FAMILIES = {
    "qft": (10, lambda: families.qft(10)), "adder": (10, lambda: families.adder(4, 9, 5)), "ising": (10, lambda: families.ising(10, [(0.3, 0.7), (0.5, 0.2)])),
    "bv": (10, lambda: families.bv(10, 341)), "coin": (10, lambda: families.coin(10)), "qaoa": (6, lambda: families.qaoa(6, [(q, (q + 1) % 6) for q in range(6)], [(0.4, 0.3)] * 3)),
    "qpe": (9, lambda: families.qpe(8, 0.3)), "simon": (6, lambda: families.simon(3, 5)),
}


def say(**row) -> None:
    print(json.dumps(row), flush=True)


def session(cores: int):
    from pyspark.sql import SparkSession

    spark = (
        SparkSession.builder.master(f"local[{cores}]").config("spark.sql.shuffle.partitions", str(2 * cores)).config("spark.driver.memory", "8g")
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def build(n: int, nets: families.Nets, block: int) -> SmallCircuit:
    circuit = SmallCircuit(n, block)
    for k, (net, gate) in enumerate(families.flat(nets)):
        circuit.insert(k, net, gate)
    return circuit


def levels(n: int, nets: families.Nets, block: int, fresh: bool):
    """One step a net: insert it and bring the state up to date, from the last state or (``fresh``) from zero."""
    circuit, held, steps, number = SmallCircuit(n, block), [], [], 0

    def step(net, numbered):
        nonlocal circuit
        held.extend((k, net, g) for k, g in numbered)
        if fresh:
            circuit = SmallCircuit(n, block)
        for k, at, g in held if fresh else [(k, net, g) for k, g in numbered]:
            circuit.insert(k, at, g)
        circuit.update()

    for net, gates in enumerate(nets):
        numbered = list(enumerate(gates, number))
        number += len(gates)
        steps.append(lambda net=net, numbered=numbered: step(net, numbered))
    return steps


def runs() -> None:
    """Engine (blocks of 64) against level-wise and whole-vector re-simulation; whole-vector blocks stand for the dense simulator."""
    totals: dict[str, list[float]] = {"engine_full": [], "engine_inc": [], "levelwise_inc": [], "dense_full": [], "dense_inc": []}
    for name, (n, make) in FAMILIES.items():
        nets = make()
        row = {
            "engine_full": time_runs(lambda: build(n, nets, 64).update(), 3)["mean"], "engine_inc": time_inc(lambda: levels(n, nets, 64, False))["total"],
            "levelwise_inc": time_inc(lambda: levels(n, nets, 64, True))["total"], "dense_full": time_runs(lambda: build(n, nets, 1 << n).update(), 3)["mean"],
            "dense_inc": time_inc(lambda: levels(n, nets, 1 << n, True))["total"],
        }
        for k, v in row.items():
            totals[k].append(v)
        gates, cnots = families.counts(nets)
        say(experiment="runs", family=name, qubits=n, gates=gates, cnots=cnots, memory_gb=round(peak_memory_gb(), 3), **{k: round(v, 4) for k, v in row.items()})
    for base in ("levelwise_inc", "dense_inc"):
        say(experiment="runs", ratio=f"{base}/engine_inc", **{k: round(v, 3) for k, v in speedup(totals[base], totals["engine_inc"]).items()})
    say(experiment="runs", ratio="dense_full/engine_full", **{k: round(v, 3) for k, v in speedup(totals["dense_full"], totals["engine_full"]).items()})


def edits(iterations: int = 50, per_iteration: int = 3) -> None:
    """Random insertions, removals and both, ``iterations`` of each, against a fresh run after every one."""
    for name in ("qft", "adder"):
        n, make = FAMILIES[name]
        gates = families.flat(make())
        for kind in ("insert", "remove", "mixed"):
            draw = np.random.default_rng(5)
            live = {} if kind == "insert" else dict(enumerate(gates))
            if kind == "mixed":
                live = {k: g for k, g in live.items() if k % 2}
            circuit = SmallCircuit(n, 64)
            for k, (net, g) in live.items():
                circuit.insert(k, net, g)
            circuit.update()
            ours, fresh, written, total = [], [], 0, 0
            for at in range(iterations):
                adds = kind == "insert" or kind == "mixed" and at % 2 == 0
                rest = [k for k in range(len(gates)) if (k in live) != adds]
                for k in draw.permutation(rest)[:per_iteration].tolist():
                    if adds:
                        live[k] = gates[k]
                        circuit.insert(k, *gates[k])
                    else:
                        del live[k]
                        circuit.remove(k)
                began = time.perf_counter()
                report = circuit.update()
                ours.append(time.perf_counter() - began)
                written, total = written + report["written_blocks"], total + report["total_blocks"]
                began = time.perf_counter()
                other = SmallCircuit(n, 64)
                for k, (net, g) in sorted(live.items()):
                    other.insert(k, net, g)
                other.update()
                fresh.append(time.perf_counter() - began)
                assert np.allclose(circuit.final, other.final)
            say(
                experiment="edits", family=name, kind=kind, iterations=iterations, inc_s=round(sum(ours), 4), fresh_s=round(sum(fresh), 4), ratio=round(sum(fresh) / sum(ours), 2),
                faster_at=sum(a < b for a, b in zip(ours, fresh)), blocks_written_share=round(written / max(total, 1), 3), cumulative_s=[round(x, 4) for x in np.cumsum(ours)[9::10].tolist()],
            )


def blocks(n: int = 15) -> None:
    """The transform of ``n`` qubits by block size, to one block for the vector (which one core then works on)."""
    from incstate.operators.partition import log2, pattern

    nets = families.qft(n)
    for bits in (4, 6, 8, 10, 12, n):
        b = log2(1 << bits, n)
        parts = [p for _, g in families.flat(nets) if (p := pattern(g.kind, g.target, g.controls, g.theta, n, b))]
        say(
            experiment="blocks", qubits=n, block=1 << bits, partitions=sum(p.count for p in parts), tasks=sum(p.count * p.tasks for p in parts),
            full_s=round(time_runs(lambda: build(n, nets, 1 << bits).update(), 1)["mean"], 3),
        )


def one_core_run(cores: int, what: str) -> None:
    """A child of ``cores``: many circuits in full, or their logs replayed, on so many threads."""
    from incstate.workloads.queries import QUERIES

    spark = session(cores)
    query, data = QUERIES["full_suppliers" if what == "full" else "inc_insert"], "/root/testdata/sf0.01"
    run = lambda: query(spark, data).write.format("noop").mode("overwrite").save()
    run()
    say(seconds=round(time_runs(run, 1)["mean"], 3))


def cores() -> None:
    for what in ("full", "inc"):
        took = {}
        for k in (1, 2, 4, 8):
            done = subprocess.run([sys.executable, __file__, "--child", str(k), what], capture_output=True, text=True, check=True)
            took[k] = json.loads(done.stdout.strip().splitlines()[-1])["seconds"]
        say(experiment="cores", run=what, seconds=took, saturates_at=saturation(took))
    n, make = FAMILIES["qft"]
    say(experiment="cores", run="one block, one core", seconds=round(time_runs(lambda: build(n, make(), 1 << n).update(), 3)["mean"], 4))


def stores() -> None:
    """Versions that a store keeps of all slots' blocks: written ones alone, all of them, and of every second slot."""
    for name, (n, make) in FAMILIES.items():
        circuit = build(n, make(), 16)
        report = circuit.update()
        by_slot = [len(circuit.versions[s]) for s in circuit.slots]
        say(
            experiment="stores", family=name, qubits=n, block=16, copy_on_write=sum(by_slot), materialise_all=report["total_blocks"],
            every_second=sum(by_slot[1::2]), saved=round(1 - sum(by_slot) / report["total_blocks"], 3),
        )


if __name__ == "__main__":
    if sys.argv[1:2] == ["--child"]:
        one_core_run(int(sys.argv[2]), sys.argv[3])
    else:
        known = {"runs": runs, "edits": edits, "blocks": blocks, "cores": cores, "stores": stores}
        for name in sys.argv[1:] or known:
            known[name]()
