"""Registered queries: circuits of the suite with known outcomes, parameters read from the tables."""

from __future__ import annotations

from pyspark.sql import functions as F

from incstate.sources.tables import table
from incstate.workloads import families, sql
from incstate.workloads.measures import _PROBABILITIES, _family_rows, _simulate_family
from incstate.workloads.queries import fixed, probability_rows, register


def _parities(spark, sf_dir, n: int) -> list[int]:
    """Whether the region of each of the first ``n`` nations has an odd key."""
    rows = table(spark, sf_dir, "nation").where(F.col("n_nationkey") < n).select("n_nationkey", (F.col("n_regionkey") % 2).alias("odd"))
    return [int(r.odd) for r in rows.orderBy("n_nationkey").collect()]


def _parity_sql(n: int) -> str:
    return f"SELECT list(n_regionkey % 2 ORDER BY n_nationkey) AS w FROM nation WHERE n_nationkey < {n}"


def _regions(spark, sf_dir) -> int:
    return table(spark, sf_dir, "region").count()


_CERTAIN = "CAST(CASE WHEN i = {at} THEN 100000000 ELSE 0 END AS BIGINT) AS p_q"


@register(
    "family_multiplier",
    "WITH v AS (SELECT CAST(count(*) % 3 + 1 AS BIGINT) AS a, CAST((SELECT count(*) % 4 FROM region) AS BIGINT) + 2 AS b FROM nation) SELECT i AS idx, "
    + _CERTAIN.format(at="(a << 1) + (b << 3) + ((a * b) << 7)") + " FROM range(0, 2048) r(i), v",
)
def family_multiplier(spark, sf_dir):
    """The product of two numbers of two bits beside its factors."""
    a, b = table(spark, sf_dir, "nation").count() % 3 + 1, _regions(spark, sf_dir) % 4 + 2
    return _simulate_family(spark, families.multiplier(2, a, b), 11)


@register(
    "family_scaling",
    "WITH v AS (SELECT CAST(count(*) AS BIGINT) AS b FROM region) SELECT i AS idx, " + _CERTAIN.format(at="(b << 1) + ((3 * b) << 4)") + " FROM range(0, 512) r(i), v",
)
def family_scaling(spark, sf_dir):
    """Three times the number of regions."""
    return _simulate_family(spark, families.scaling(3, 3, _regions(spark, sf_dir)), 9)


@register(
    "family_factoring",
    "SELECT a, b, CAST(6250000 AS BIGINT) AS p_q FROM range(0, 4) x(a), range(0, 4) y(b) WHERE a * b = (SELECT count(*) + 1 FROM region)",
)
def family_factoring(spark, sf_dir):
    """The factors that meet where the product register holds one more than the number of regions."""
    rows = probability_rows(_family_rows(spark, families.factoring(2), 11)).where(F.col("p") > 1e-9)
    part = lambda low, bits: F.shiftright("idx", low).bitwiseAND((1 << bits) - 1)
    return rows.where(part(7, 4) == _regions(spark, sf_dir) + 1).select(part(1, 2).alias("a"), part(3, 2).alias("b"), fixed(F.col("p")).alias("p_q"))


@register(
    "family_key_exchange",
    f"WITH v AS ({_parity_sql(24)}) SELECT i AS idx, "
    + sql.fixed("list_aggregate([CAST(CASE WHEN w[9 + q] <> w[17 + q] THEN 0.5 WHEN ((i >> q) & 1) = w[1 + q] THEN 1 ELSE 0 END AS DOUBLE) FOR q IN range(0, 8)], 'product')")
    + " AS p_q FROM range(0, 256) r(i), v",
)
def family_key_exchange(spark, sf_dir):
    """A bit that is read in the basis it was sent in comes out as it was; the others are even."""
    odd = _parities(spark, sf_dir, 24)
    return _simulate_family(spark, families.key_exchange(odd[:8], odd[8:16], odd[16:]), 8)


_NETWORK = """
  SELECT 0 AS circuit_id, n_nationkey // 8 * 16 + n_nationkey % 8 AS gate_no, 0 AS net_no, 'RY' AS kind, CAST(n_nationkey % 8 AS INT) AS target, 0 AS control,
    n_regionkey + n_nationkey / CAST(10 AS DOUBLE) AS theta FROM nation WHERE n_nationkey < 24
  UNION ALL
  SELECT 0, s * 16 + 8 + q, 0, 'CNOT', CAST((q + 1) % 8 AS INT), CAST(q AS INT), 0 FROM range(0, 3) l(s), range(0, 8) r(q)"""


@register("family_network", f"{_PROBABILITIES} FROM ({sql.states(_NETWORK, 8)})")
def family_network(spark, sf_dir):
    """Three layers of eight rotations by the keys of nations and their regions."""
    rows = table(spark, sf_dir, "nation").where("n_nationkey < 24").orderBy("n_nationkey").collect()
    angles = [r.n_regionkey + r.n_nationkey / 10 for r in rows]
    return _simulate_family(spark, families.network([angles[k : k + 8] for k in range(0, 24, 8)]), 8)


_MET = " AND ".join(f"(((i >> {k}) & 1) = w[{2 * k + 1}] OR ((i >> {(k + 1) % 3}) & 1) = w[{2 * k + 2}])" for k in range(3))
_TURN = "3 * asin(sqrt(m / CAST(8 AS DOUBLE)))"


@register(
    "family_satisfying",
    f"WITH x AS (SELECT i, {_MET} AS met FROM range(0, 8) r(i), ({_parity_sql(6)})), c AS (SELECT CAST(count(*) FILTER (WHERE met) AS DOUBLE) AS m FROM x) SELECT i AS idx, "
    + sql.fixed(f"CASE WHEN met THEN pow(sin({_TURN}), 2) / m ELSE pow(cos({_TURN}), 2) / (8 - m) END") + " AS p_q FROM x, c",
)
def family_satisfying(spark, sf_dir):
    """One round of search for what meets three clauses, wanted values from the nations."""
    w = _parities(spark, sf_dir, 6)
    clauses = [((k, w[2 * k]), ((k + 1) % 3, w[2 * k + 1])) for k in range(3)]
    rows = probability_rows(_family_rows(spark, families.satisfying(clauses), 6))
    return rows.groupBy(F.col("idx").bitwiseAND(7).alias("idx")).agg(fixed(F.sum("p")).alias("p_q"))


@register(
    "family_order",
    "WITH v AS (SELECT CAST(count(*) + 2 AS BIGINT) AS b FROM region), o AS (SELECT min(k) AS o FROM range(1, 9) r(k), v WHERE CAST(pow(b, k) AS BIGINT) % 15 = 1) "
    "SELECT i AS idx, CAST(CASE WHEN list_sum([((i >> q) & 1) << (3 - q) FOR q IN range(0, 4)]) % (16 // o) = 0 THEN 100000000 // o ELSE 0 END AS BIGINT) AS p_q FROM range(0, 16) r(i), o",
)
def family_order(spark, sf_dir):
    """Counts (their bits reversed) are even over the multiples of 16 by the order modulo 15."""
    rows = probability_rows(_family_rows(spark, families.order_finding(4, _regions(spark, sf_dir) + 2), 8))
    return rows.groupBy(F.col("idx").bitwiseAND(15).alias("idx")).agg(fixed(F.sum("p")).alias("p_q"))


#: Products of X and Y with an odd number of Y: the double excitation of four orbitals.
_STRINGS = ("XXXY", "XXYX", "XYXX", "YXXX", "YYYX", "YYXY", "YXYY", "XYYY")
_ANSATZ = f"""
  SELECT 0 AS circuit_id, q - 2 AS gate_no, 0 AS net_no, 'X' AS kind, CAST(q AS INT) AS target, 0 AS control, CAST(0 AS DOUBLE) AS theta FROM range(0, 2) r(q)
  UNION ALL
  SELECT 0, s * 16 + q + side * 11, 0, CASE WHEN substr(axes, CAST(q AS INT) + 1, 1) = 'X' THEN 'H' ELSE 'RX' END, CAST(q AS INT), 0, (1 - 2 * side) * pi() / 2
  FROM (VALUES {', '.join(f"({k}, '{x}')" for k, x in enumerate(_STRINGS))}) v(s, axes), range(0, 4) r(q), range(0, 2) t(side)
  UNION ALL
  SELECT 0, s * 16 + CASE side WHEN 0 THEN 4 + q ELSE 10 - q END, 0, 'CNOT', CAST(q + 1 AS INT), CAST(q AS INT), 0 FROM range(0, 8) v(s), range(0, 3) r(q), range(0, 2) t(side)
  UNION ALL
  SELECT 0, s * 16 + 7, 0, 'RZ', 3, 0, a FROM range(0, 8) v(s) JOIN (SELECT n_regionkey, avg(n_nationkey) / CAST(20 AS DOUBLE) AS a FROM nation GROUP BY n_regionkey) n ON n_regionkey = s % 5"""


@register("family_eigensolver", f"{_PROBABILITIES} FROM ({sql.states(_ANSATZ, 4)})")
def family_eigensolver(spark, sf_dir):
    """Two of four orbitals filled and excited together, angles from the mean keys of a region's nations."""
    rows = table(spark, sf_dir, "nation").groupBy("n_regionkey").agg((F.avg("n_nationkey") / 20).alias("a")).collect()
    angle = {r.n_regionkey: r.a for r in rows}
    return _simulate_family(spark, families.eigensolver([0, 1], [(x, angle[k % 5]) for k, x in enumerate(_STRINGS)]), 4)
