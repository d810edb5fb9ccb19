"""DuckDB forms of circuits, graphs and states: what the registered queries are compared with.

They share no logic with the operators: partitions come from enumerated operations, links from the last
writer of each block, reachable sets and states from recursion.
"""

from __future__ import annotations

_KINDS = "['H', 'X', 'Y', 'Z', 'S', 'SDG', 'T', 'TDG', 'RX', 'RY', 'RZ', 'CNOT']"

ORDER_ROWS = f"""
  SELECT l_orderkey AS circuit_id,
    row_number() OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_extendedprice) AS gate_no,
    CAST(l_linenumber AS BIGINT) AS line_no, {_KINDS}[(l_linenumber + l_partkey) % 12 + 1] AS kind, CAST(l_partkey % 5 AS INT) AS target,
    CAST((l_partkey % 5 + 1 + l_suppkey % 4) % 5 AS INT) AS control, pi() * l_quantity / CAST(25 AS DOUBLE) AS theta
  FROM lineitem"""

ORDERS = f"SELECT circuit_id, gate_no, gate_no AS net_no, kind, target, control, theta FROM ({ORDER_ROWS})"
ORDER_LINES = f"SELECT circuit_id, gate_no, line_no AS net_no, kind, target, control, theta FROM ({ORDER_ROWS})"


def suppliers(n: int) -> str:
    return f"""
  SELECT circuit_id, gate_no, gate_no AS net_no, kind, target, control, theta FROM (
    SELECT l_suppkey AS circuit_id,
      row_number() OVER (PARTITION BY l_suppkey ORDER BY l_shipdate, l_orderkey, l_linenumber, l_partkey, l_extendedprice) AS gate_no,
      {_KINDS}[(l_linenumber + l_partkey) % 12 + 1] AS kind, CAST(l_partkey % {n} AS INT) AS target,
      CAST((l_partkey % {n} + 1 + l_suppkey % {n - 1}) % {n} AS INT) AS control, pi() * l_quantity / CAST(25 AS DOUBLE) AS theta
    FROM lineitem)"""


PARTS = f"""
  SELECT circuit_id, gate_no, gate_no AS net_no, kind, target, control, theta FROM (
    SELECT l.circuit_id, l.gate_no, CASE p_type WHEN 'ECONOMY' THEN 'RX' WHEN 'LARGE' THEN 'RY' WHEN 'MEDIUM' THEN 'RZ'
      WHEN 'PROMO' THEN 'H' WHEN 'SMALL' THEN 'T' WHEN 'STANDARD' THEN 'CNOT' END AS kind, l.target, l.control,
      pi() * p_size / CAST(25 AS DOUBLE) AS theta
    FROM (SELECT *, l_partkey FROM (SELECT l_partkey, l_orderkey AS circuit_id,
        row_number() OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_extendedprice) AS gate_no,
        CAST(l_partkey % 5 AS INT) AS target, CAST((l_partkey % 5 + 1 + l_suppkey % 4) % 5 AS INT) AS control FROM lineitem)) l
    JOIN part ON l.l_partkey = p_partkey)"""


def documents(n: int) -> str:
    return f"""
  SELECT circuit_id, gate_no, gate_no AS net_no, {_KINDS}[(len + a) % 12 + 1] AS kind, CAST(a % {n} AS INT) AS target,
    CAST((a % {n} + 1 + len % {n - 1}) % {n} AS INT) AS control, pi() * len / CAST(6 AS DOUBLE) AS theta
  FROM (
    SELECT circuit_id, gate_no, CAST(length(word) AS BIGINT) AS len, CASE WHEN word = '' THEN 0 ELSE unicode(word) END AS a FROM (
      SELECT doc_id AS circuit_id, unnest(range(0, len(w))) AS gate_no, unnest(w) AS word
      FROM (SELECT doc_id, string_split(text, ' ') AS w FROM documents)))"""


def accepted(gates: str) -> str:
    """Gates that no accepted earlier gate of their net conflicts with, with ``accepted`` for all."""
    return f"""
  SELECT g.*, list_contains(good, gate_no) AS accepted FROM (SELECT *, (1 << target) | (CASE WHEN kind = 'CNOT' THEN 1 << control ELSE 0 END) AS mask FROM ({gates})) g
  JOIN (
    WITH RECURSIVE m AS (
      SELECT circuit_id, net_no, gate_no, (1 << target) | (CASE WHEN kind = 'CNOT' THEN 1 << control ELSE 0 END) AS mask,
        row_number() OVER (PARTITION BY circuit_id, net_no ORDER BY gate_no) AS nth FROM ({gates})
    ), f AS (
      SELECT circuit_id, net_no, nth, mask AS used, [gate_no] AS good FROM m WHERE nth = 1
      UNION ALL
      SELECT m.circuit_id, m.net_no, m.nth, CASE WHEN (used & mask) = 0 THEN used | mask ELSE used END,
        CASE WHEN (used & mask) = 0 THEN list_append(good, gate_no) ELSE good END
      FROM f JOIN m ON m.circuit_id = f.circuit_id AND m.net_no = f.net_no AND m.nth = f.nth + 1
    ) SELECT circuit_id, net_no, arg_max(good, nth) AS good FROM f GROUP BY circuit_id, net_no
  ) a ON a.circuit_id = g.circuit_id AND a.net_no = g.net_no"""


_C = "(CASE WHEN abs(cos(theta / 2)) < 1e-12 THEN CAST(0 AS DOUBLE) ELSE cos(theta / 2) END)"
_S = "(CASE WHEN abs(sin(theta / 2)) < 1e-12 THEN CAST(0 AS DOUBLE) ELSE sin(theta / 2) END)"
_H = "(CAST(1 AS DOUBLE) / sqrt(CAST(2 AS DOUBLE)))"
_ROWS = {
    "H": (_H, 0, _H, 0, _H, 0, f"(-{_H})", 0), "X": (0, 0, 1, 0, 1, 0, 0, 0), "CNOT": (0, 0, 1, 0, 1, 0, 0, 0), "Y": (0, 0, 0, -1, 0, 1, 0, 0),
    "Z": (1, 0, 0, 0, 0, 0, -1, 0), "S": (1, 0, 0, 0, 0, 0, 0, 1), "SDG": (1, 0, 0, 0, 0, 0, 0, -1), "T": (1, 0, 0, 0, 0, 0, _H, _H),
    "TDG": (1, 0, 0, 0, 0, 0, _H, f"(-{_H})"), "RX": (_C, 0, 0, f"(-{_S})", 0, f"(-{_S})", _C, 0), "RY": (_C, 0, f"(-{_S})", 0, _S, 0, _C, 0),
    "RZ": (_C, f"(-{_S})", 0, 0, 0, 0, _C, _S),
}
_NAMES = ("ar", "ai", "br", "bi", "cr", "ci", "dr", "di")


def entries(gates: str) -> str:
    """``gates`` with matrix entries a b / c d, the control mask and the gate's effect ``shape``."""
    cols = ", ".join(
        "CASE kind " + " ".join(f"WHEN '{k}' THEN CAST({row[i]} AS DOUBLE)" for k, row in _ROWS.items()) + f" END AS {name}" for i, name in enumerate(_NAMES)
    )
    return f"""
  SELECT *, CASE WHEN abs(br) + abs(bi) + abs(cr) + abs(ci) < 1e-12 THEN
      CASE WHEN abs(ar - 1) + abs(ai) < 1e-12 AND abs(dr - 1) + abs(di) < 1e-12 THEN 'id' WHEN abs(ar - 1) + abs(ai) < 1e-12 THEN 'one' ELSE 'full' END
    WHEN abs(ar) + abs(ai) + abs(dr) + abs(di) < 1e-12 THEN 'swap' ELSE 'mix' END AS shape
  FROM (SELECT *, CASE WHEN kind = 'CNOT' THEN 1 << control ELSE 0 END AS held, {cols} FROM ({gates}))"""


def _half(i: str, part: str) -> str:
    """Real or imaginary part of a new amplitude."""
    other = f"xor({i}, 1 << target) + 1"
    mul = lambda x, y, at: f"{x} * re[{at}] - {y} * im[{at}]" if part == "re" else f"{x} * im[{at}] + {y} * re[{at}]"
    here = f"{i} + 1"
    return (
        f"CASE WHEN ({i} & held) <> held THEN {part}[{here}] WHEN (({i} >> target) & 1) = 0 THEN "
        f"({mul('ar', 'ai', here)}) + ({mul('br', 'bi', other)}) ELSE ({mul('dr', 'di', here)}) + ({mul('cr', 'ci', other)}) END"
    )


def states(gates: str, n: int, start: str | None = None, steps: bool = False, key: str = "circuit_id") -> str:
    """``circuit_id, step, re, im``: lists after all gates (in gate_no order), or after each of them with ``steps``.

    ``start`` gives ``circuit_id, re, im`` of circuits that don't start at zero."""
    size = 1 << n
    zero = f"SELECT {key}, [CAST(CASE WHEN i = 0 THEN 1 ELSE 0 END AS DOUBLE) FOR i IN range(0, {size})] AS re, [CAST(0 AS DOUBLE) FOR i IN range(0, {size})] AS im FROM (SELECT DISTINCT {key} FROM u)"
    same = " AND ".join(f"u.{k.strip()} = s.{k.strip()}" for k in key.split(","))
    keys = ", ".join(f"s.{k.strip()}" for k in key.split(","))
    pick = "SELECT * FROM s" if steps else f"SELECT * FROM s QUALIFY step = max(step) OVER (PARTITION BY {key})"
    return f"""
  WITH RECURSIVE u AS MATERIALIZED (SELECT *, row_number() OVER (PARTITION BY {key} ORDER BY gate_no) AS nth FROM ({entries(gates)})),
  s AS (
    SELECT {key}, CAST(0 AS BIGINT) AS step, re, im FROM ({start or zero})
    UNION ALL
    SELECT {keys}, s.step + 1, [{_half('i', 're')} FOR i IN range(0, {size})], [{_half('i', 'im')} FOR i IN range(0, {size})]
    FROM s JOIN u ON {same} AND u.nth = s.step + 1
  ) {pick}"""


def fixed(x: str) -> str:
    """A number as a whole multiple of 1e-8, rounded away from ties."""
    return f"CAST(FLOOR(({x}) * 1e8 + 0.37) AS BIGINT)"


def amplitude_rows(lists: str, key: str = "circuit_id") -> str:
    """Rows of quantised amplitudes."""
    return f"""SELECT {key}, idx, {fixed('r')} AS re_q, {fixed('m')} AS im_q FROM (
    SELECT {key}, unnest(range(0, len(re))) AS idx, unnest(re) AS r, unnest(im) AS m FROM ({lists}))"""


def partitions(gates: str, n: int, block: int) -> str:
    """Partitions of every gate by walking its operations in index order, ``block`` of them a task."""
    size = 1 << n
    return f"""
  WITH e AS MATERIALIZED (SELECT * FROM ({entries(gates)}) WHERE shape <> 'id'),
  ops AS (
    SELECT circuit_id, gate_no, i AS lo, CASE WHEN shape = 'swap' THEN i | (1 << target) ELSE i END AS hi
    FROM e, range(0, {size}) r(i)
    WHERE shape <> 'mix' AND (i & held) = held AND (shape <> 'swap' OR ((i >> target) & 1) = 0) AND (shape <> 'one' OR ((i >> target) & 1) = 1)
  ), task AS (
    SELECT circuit_id, gate_no, nth // {block} AS task, min(lo) // {block} AS lo, max(hi) // {block} AS hi
    FROM (SELECT *, row_number() OVER (PARTITION BY circuit_id, gate_no ORDER BY lo) - 1 AS nth FROM ops) GROUP BY ALL
  ), marked AS (
    SELECT *, CASE WHEN lo <= max(hi) OVER (PARTITION BY circuit_id, gate_no ORDER BY task ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) THEN 0 ELSE 1 END AS new
    FROM task
  ), island AS (
    SELECT *, sum(new) OVER (PARTITION BY circuit_id, gate_no ORDER BY task) - 1 AS part FROM marked
  )
  SELECT circuit_id, gate_no, CAST(part AS INT) AS part_no, min(lo) AS lo_block, max(hi) AS hi_block, count(*) AS n_tasks FROM island GROUP BY circuit_id, gate_no, part
  UNION ALL
  SELECT circuit_id, gate_no, CAST(k AS INT), k, k, 1 FROM e, range(0, {max(1, size // block)}) r(k) WHERE shape = 'mix'"""


def slot_table(gates: str, n: int, block: int) -> str:
    """``circuit_id, gate_no, net_no, mode, span, slot_no`` per gate."""
    return f"""
  SELECT *, CAST(dense_rank() OVER (PARTITION BY circuit_id ORDER BY net_no, mode DESC, CASE WHEN mode = 'sup' THEN 0 ELSE span END, CASE WHEN mode = 'sup' THEN 0 ELSE gate_no END) - 1 AS INT) AS slot_no
  FROM (
    SELECT e.circuit_id, e.gate_no, e.net_no, CASE WHEN shape = 'mix' THEN 'sup' ELSE 'mono' END AS mode, span
    FROM ({entries(gates)}) e JOIN (
      SELECT circuit_id, gate_no, max(hi_block - lo_block + 1) AS span FROM ({partitions(gates, n, block)}) GROUP BY ALL
    ) p ON p.circuit_id = e.circuit_id AND p.gate_no = e.gate_no)"""


def slot_parts(gates: str, n: int, block: int) -> str:
    return f"""
  SELECT s.circuit_id, s.slot_no, s.net_no, s.mode, s.gate_no, p.part_no, p.lo_block, p.hi_block, p.n_tasks
  FROM (SELECT * FROM ({slot_table(gates, n, block)}) QUALIFY row_number() OVER (PARTITION BY circuit_id, slot_no ORDER BY gate_no) = 1) s
  JOIN ({partitions(gates, n, block)}) p ON p.circuit_id = s.circuit_id AND p.gate_no = s.gate_no"""


def edges(parts: str) -> str:
    """Links to the last writer of each block, and those from sync nodes."""
    return f"""
  SELECT circuit_id, src.slot AS src_slot, src.part AS src_part, dst_slot, dst_part FROM (
    SELECT r.circuit_id, r.slot_no AS dst_slot, CASE WHEN r.mode = 'sup' THEN -1 ELSE r.part_no END AS dst_part,
      arg_max(struct_pack(slot := w.slot_no, part := w.part_no), w.slot_no) AS src
    FROM (SELECT *, unnest(range(lo_block, hi_block + 1)) AS k FROM ({parts})) r
    JOIN (SELECT *, unnest(range(lo_block, hi_block + 1)) AS k FROM ({parts})) w
      ON w.circuit_id = r.circuit_id AND w.k = r.k AND w.slot_no < r.slot_no
    GROUP BY r.circuit_id, r.slot_no, r.part_no, r.mode, r.k)
  GROUP BY ALL
  UNION ALL
  SELECT circuit_id, slot_no, -1, slot_no, part_no FROM ({parts}) WHERE mode = 'sup'"""
