"""Choices before execution: which plan, which block size, which qubits inside blocks, which gates share an exchange."""

from __future__ import annotations

from pyspark.sql import DataFrame

from incstate.plans.store import shared_folder
from incstate.plans.wide import Gate, apply_blocks, coupled_bits

#: Vectors up to this many qubits are one array of a row.
MANY_QUBITS = 16
#: Block bits that one exchange may couple: groups of 2**k blocks meet in a task.
COUPLED = 4
LARGEST_BLOCK = 1 << 18


def choose_plan(n: int, circuits: int) -> str:
    """``many`` (a row per circuit) for small vectors of many circuits, ``wide`` (a state in blocks) otherwise."""
    return "many" if n <= MANY_QUBITS and (circuits > 1 or n <= 10) else "wide"


def choose_block_size(n: int, cores: int) -> int:
    """At least four blocks a core where the vector allows it, and at most ``LARGEST_BLOCK`` amplitudes."""
    size = 1
    while size * 2 <= LARGEST_BLOCK and size * 2 * 4 * cores <= 1 << n:
        size *= 2
    return size


def relabel(gates: list[Gate], n: int) -> tuple[list[Gate], list[int]]:
    """Gates with the qubits that move amplitudes most often numbered lowest, and each old qubit's new number."""
    moves = [0] * n
    for g in gates:
        for q in g.qubits[:2] if g.form == "exchange" else (g.target,) if g.form in ("swap", "mix") else ():
            moves[q] += 1
    new = [0] * n
    for place, q in enumerate(sorted(range(n), key=lambda q: (-moves[q], q))):
        new[q] = place
    return [Gate(g.kind, tuple(new[q] for q in g.qubits), g.theta) for g in gates], new


def fuse(gates: list[Gate], b: int, coupled: int = COUPLED) -> list[list[Gate]]:
    """Runs of gates that need one exchange: together they couple at most ``coupled`` block bits."""
    out: list[list[Gate]] = []
    mask = 0
    for g in gates:
        more = mask | coupled_bits([g], b)
        if out and more.bit_count() <= max(coupled, coupled_bits([g], b).bit_count()):
            out[-1].append(g)
            mask = more
        else:
            out.append([g])
            mask = coupled_bits([g], b)
    return out


def simulate_wide(blocks: DataFrame, gates: list[Gate], block_size: int, coupled: int = COUPLED, cut_every: int = 4) -> DataFrame:
    """All gates on the block layout, fused; lineage is cut every few exchanges."""
    shared_folder(blocks.sparkSession)
    for k, run in enumerate(fuse([g for g in gates if g.form != "id"], block_size.bit_length() - 1, coupled), 1):
        blocks = apply_blocks(blocks, run, block_size)
        if k % cut_every == 0:
            blocks = blocks.checkpoint(eager=True)
    return blocks
