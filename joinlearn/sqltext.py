"""Plain SQL with the same results as the plans: what a user would write by hand, and the oracle of the tests."""

from __future__ import annotations

from .plans.monomials import Monomial, by_keys
from .workloads import SCALES

STAR = """star AS (
  SELECT l_orderkey AS orderkey, l_partkey AS partkey, l_suppkey AS suppkey, o_custkey AS custkey, l_quantity, l_extendedprice, l_discount, l_tax,
         l_returnflag, l_linestatus, p_brand, p_type, p_name, p_size, p_retailprice, o_orderpriority, o_orderstatus, o_totalprice,
         c_mktsegment, c_acctbal, s_acctbal, s_nationkey
  FROM lineitem JOIN part ON l_partkey = p_partkey JOIN orders ON l_orderkey = o_orderkey
       JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey {where})"""
EVENTS = """star AS (
  SELECT user_id AS custkey, event_type, value, o_orderkey AS orderkey, o_orderpriority, o_orderstatus, o_totalprice, l_extendedprice, l_discount, l_quantity
  FROM events JOIN orders ON user_id = o_custkey JOIN lineitem ON l_orderkey = o_orderkey)"""


def factor(name: str, exponent: int) -> str:
    one = f"CAST(round({name} * {SCALES.get(name, 1)}) AS HUGEINT)"
    return " * ".join([one] * exponent)


def moments_sql(monomials: list[Monomial], source: str) -> str:
    """(monomial, k, value): one grouping for each key set over the source CTE named star."""
    parts = []
    for keys, wanted in by_keys(monomials).items():
        key = f"concat_ws('|', {', '.join(f'CAST({k} AS VARCHAR)' for k in keys)})" if keys else "''"
        sums = [f"CAST(sum({' * '.join(factor(v, e) for v, e in m.cont) or '1'}) AS DOUBLE) AS m{i}" for i, m in enumerate(wanted)]
        pairs = ", ".join(f"{{'monomial': '{m}', 'value': m{i}}}" for i, m in enumerate(wanted))
        group = f" GROUP BY {', '.join(keys)}" if keys else ""
        parts.append(f"SELECT e.monomial AS monomial, k, e.value AS value FROM (SELECT k, unnest([{pairs}]) AS e FROM (SELECT {key} AS k, {', '.join(sums)} FROM star{group}))")
    return f"WITH {source}\n" + "\nUNION ALL\n".join(parts)


def star_moments(monomials: list[Monomial], workload: str = "W2") -> str:
    return moments_sql(monomials, STAR.format(where="WHERE l_orderkey % 5 = 0" if workload == "W1" else ""))
