"""Row types of circuits, states, graphs and reports."""

from __future__ import annotations

GATE = "circuit_id bigint, gate_no bigint, net_no bigint, kind string, target int, controls array<int>, theta double"
STATE = "circuit_id bigint, idx bigint, re double, im double"
BLOCKS = "circuit_id bigint, block_id bigint, re array<double>, im array<double>"
SLOT = "circuit_id bigint, slot_no int, net_no bigint, mode string, gate_nos array<bigint>, span bigint"
PARTITION = "circuit_id bigint, slot_no int, part_no int, lo_block bigint, hi_block bigint, n_tasks bigint"
EDGE = "circuit_id bigint, src_slot int, src_part int, dst_slot int, dst_part int"
MODIFIER = (
    "circuit_id bigint, seq bigint, iter bigint, op string, net_no bigint, gate_no bigint, kind string, "
    "target int, control int, theta double, ts timestamp"
)
VERSION = "circuit_id bigint, slot_no int, block_id bigint, re array<double>, im array<double>"

#: part_no of the synchronisation node before a superposition slot.
SYNC = -1
