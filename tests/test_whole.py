"""Queries that must cover every row and word, against brute force."""

from __future__ import annotations

import numpy as np
import pytest

from incstate.functions.gates import KINDS, matrix
from incstate.workloads import measures, surface  # noqa: F401
from incstate.workloads.queries import QUERIES


def fixed(x):
    return int(np.floor(x * 1e8 + 0.37))


@pytest.fixture(scope="module")
def texts(spark, tmp_path_factory):
    """A table of documents, most of them longer than 200 words."""
    draw = np.random.default_rng(11)
    word = lambda: "".join(chr(c) for c in draw.choice([97, 98, 110, 0xE9, 0x4E2D, 0x1F600], draw.integers(0, 7)))
    rows = [(k, " ".join(word() for _ in range(n))) for k, n in enumerate([450, 201, 200, 21, 1])] + [(5, ""), (6, None)]
    at = str(tmp_path_factory.mktemp("whole"))
    spark.createDataFrame(rows, "doc_id long, text string").write.parquet(f"{at}/documents.parquet")
    return at, {k: t.split(" ") for k, t in rows if t is not None}


def gate(word):
    first = ord(word[0]) if word else 0
    kind, target = KINDS[(len(word) + first) % 12], first % 6
    return kind, target, (target + 1 + len(word) % 5) % 6, np.pi * len(word) / 6


def final(words):
    psi = np.zeros(64, complex)
    psi[0] = 1
    for kind, t, c, theta in map(gate, words):
        u, new = matrix(kind, theta), psi.copy()
        for i in range(64):
            if kind != "CNOT" or i >> c & 1:
                b = i >> t & 1
                new[i] = u[b, b] * psi[i] + u[b, 1 - b] * psi[i ^ 1 << t]
        psi = new
    return psi


def test_circuit_from_text_has_every_word(spark, texts):
    at, docs = texts
    got = {tuple(r) for r in QUERIES["circuit_from_text"](spark, at).collect()}
    assert got == {(d, k, k, *gate(w)[:3], fixed(gate(w)[3])) for d, ws in docs.items() for k, w in enumerate(ws)}


def test_full_documents_runs_every_word(spark, texts):
    at, docs = texts
    got = {(r.circuit_id, r.idx): (r.re_q, r.im_q) for r in QUERIES["full_documents"](spark, at).collect()}
    want = {(d, i): (fixed(x.real), fixed(x.imag)) for d, ws in docs.items() for i, x in enumerate(final(ws))}
    assert got.keys() == want.keys() and all(max(abs(a - b) for a, b in zip(got[k], want[k])) <= 1 for k in want)


def order_rows(spark, data):
    """The gates of all orders, from the table itself."""
    lines = spark.read.parquet(f"{data}/lineitem.parquet").toPandas()
    lines = lines.sort_values(["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice"])
    lines["nth"] = lines.groupby("l_orderkey").cumcount() + 1
    for r in lines.itertuples():
        t = r.l_partkey % 5
        kind = KINDS[(r.l_linenumber + r.l_partkey) % 12]
        yield r.l_orderkey, r.nth, kind, t, (t + 1 + r.l_suppkey % 4) % 5, np.pi * float(r.l_quantity) / 25


def test_lateral_terms_of_every_order(spark, data):
    ours = QUERIES["join_lateral_terms"](spark, data).toPandas()
    want = {}
    for order, nth, kind, _, _, theta in order_rows(spark, data):
        u = matrix(kind, theta)
        want |= {(order, nth, r, c): u[r, c] for r in (0, 1) for c in (0, 1) if abs(u[r, c]) > 1e-12}
    got = {(r.circuit_id, r.gate_no, r.row_bit, r.col_bit): (r.re_q, r.im_q) for r in ours.itertuples()}
    assert len(ours) == len(want) and got.keys() == want.keys()
    assert all(abs(got[k][0] - fixed(want[k].real)) <= 1 and abs(got[k][1] - fixed(want[k].imag)) <= 1 for k in want)


def test_partition_ranges_of_every_order(spark, data):
    """Tasks of 4 operations, joined while their blocks overlap; a mixing gate has one task a block."""
    want = set()
    for order, nth, kind, t, c, theta in order_rows(spark, data):
        u = matrix(kind, theta)
        held = 1 << c if kind == "CNOT" else 0
        apart = abs(u[0, 1]) + abs(u[1, 0]) > 1e-12
        if apart and abs(u[0, 0]) + abs(u[1, 1]) > 1e-12:
            want |= {(order, nth, k, k, k, 1) for k in range(8)}
            continue
        ones = [abs(u[b, b] - 1) < 1e-12 for b in (0, 1)]
        if not apart and all(ones):
            continue
        keep = [i for i in range(32) if i & held == held and not (apart and i >> t & 1) and not (not apart and ones[0] and not i >> t & 1)]
        ops, parts = [(i, i | 1 << t if apart else i) for i in keep], []
        for at in range(0, len(ops), 4):
            lo, hi = ops[at][0] // 4, max(x[1] for x in ops[at : at + 4]) // 4
            if parts and lo <= parts[-1][1]:
                parts[-1] = [parts[-1][0], max(hi, parts[-1][1]), parts[-1][2] + 1]
            else:
                parts.append([lo, hi, 1])
        want |= {(order, nth, k, *p) for k, p in enumerate(parts)}
    got = [tuple(r) for r in QUERIES["udtf_partition_ranges"](spark, data).select("circuit_id", "gate_no", "part_no", "lo_block", "hi_block", "n_tasks").collect()]
    assert len(got) == len(want) and set(got) == want


def test_parse_gates_reads_every_word(spark, texts):
    at, docs = texts
    got = [tuple(r) for r in QUERIES["udtf_parse_gates"](spark, at).select("circuit_id", "gate_no", "kind", "target", "theta_q").collect()]
    want = {(d, k, *gate(w)[:2], fixed(gate(w)[3])) for d, ws in docs.items() for k, w in enumerate(ws)}
    assert len(got) == len(want) and set(got) == want


def test_family_ising_has_a_step_for_every_line_number(spark, data, monkeypatch):
    made, real = [], measures.families.ising
    monkeypatch.setattr(measures.families, "ising", lambda n, steps: made.append(len(steps)) or real(n, steps))
    rows = QUERIES["family_ising"](spark, data).collect()
    assert made == [spark.read.parquet(f"{data}/lineitem.parquet").select("l_linenumber").distinct().count()] and made[0] > 3
    assert abs(sum(r.p_q for r in rows) - 10**8) < 1000
