"""The row clouds of :mod:`frontfill.sources.tables` in DuckDB SQL, and Morton keys."""

from __future__ import annotations


def axis(raw: str, lo: int, span: int) -> str:
    return f"greatest(0, least(16777215, (({raw} - ({lo})) * 16777216) // {span}))::BIGINT"


def cents(c: str) -> str:
    return f"CAST(ROUND({c} * 100 + 0.0) AS BIGINT)"


ORDERS = f"""
SELECT o_orderkey AS id, o_orderpriority AS grp, {axis("date_diff('day', DATE '1995-01-01', o_orderdate::DATE)", 0, 2500)} AS x0,
       {axis(cents('o_totalprice'), 0, 50_000_000)} AS x1 FROM orders"""
LINEITEM = f"""
SELECT l_orderkey * 8 + l_linenumber AS id, l_returnflag AS grp, {axis('CAST(ROUND(l_quantity) AS BIGINT)', 0, 51)} AS x0,
       {axis(cents('l_extendedprice'), 0, 11_000_000)} AS x1, {axis(cents('l_discount'), 0, 11)} AS x2 FROM lineitem"""
EVENTS = f"""
SELECT event_id AS id, event_type AS grp, {axis('((epoch_us(ts) - 1704067200000000) // 1000)', 0, 2_678_400_000)} AS x0,
       {axis(cents('value'), 0, 100_000)} AS x1 FROM events"""
CUSTOMER = f"""
SELECT c_custkey AS id, c_nationkey::VARCHAR AS grp, {axis(cents('c_acctbal'), -100_000, 1_110_000)} AS x0,
       {axis('(((c_custkey * 48271 + 11) % 2147483647) % 10007)', 0, 10_007)} AS x1 FROM customer"""
SUPPLIER = f"""
SELECT s_suppkey AS id, s_nationkey::VARCHAR AS grp, {axis(cents('s_acctbal'), -100_000, 1_110_000)} AS x0,
       {axis('(((s_suppkey * 48271 + 11) % 2147483647) % 10007)', 0, 10_007)} AS x1,
       {axis('(((((s_suppkey * 48271 + 11) % 2147483647) * 48271 + 11) % 2147483647) % 10007)', 0, 10_007)} AS x2 FROM supplier"""
PART = f"""
SELECT p_partkey AS id, p_brand AS grp, {axis('p_size::BIGINT', 0, 51)} AS x0,
       {axis('CAST(ROUND(p_retailprice * 10) AS BIGINT)', 9000, 1000)} AS x1 FROM part"""
PAGES = f"""
SELECT page_id AS id, NULL::VARCHAR AS grp, {axis('length(html)', 0, 100_000)} AS x0, {axis('length(url)', 0, 100)} AS x1 FROM pages"""
DOCUMENTS = f"""
SELECT doc_id AS id, lang AS grp, {axis('n_chars', 0, 200_000)} AS x0, {axis("len(string_split(text, ' '))", 0, 20_001)} AS x1 FROM documents"""
CONVERSATIONS = f"""
SELECT conv_id * 1000 + turn AS id, role AS grp, {axis('turn', 0, 8)} AS x0, {axis('length(text)', 0, 4096)} AS x1 FROM conversations"""
BENCHMARK = f"SELECT item_id AS id, NULL::VARCHAR AS grp, {axis('length(text)', 0, 512)} AS x0 FROM benchmark"


def embeddings(d: int) -> str:
    cols = ", ".join(f"{axis(f'CAST(FLOOR(embedding[{a + 1}]::DOUBLE * 1048576) AS BIGINT)', -(1 << 20), 1 << 21)} AS x{a}" for a in range(d))
    return f"SELECT vec_id AS id, label::VARCHAR AS grp, {cols} FROM embeddings"


def morton(xs: list[str], bits: int) -> str:
    d = len(xs)
    return " + ".join(f"(((({x}) >> {b}) & 1) << {d * b + d - 1 - a})" for b in range(bits) for a, x in enumerate(xs))


def leaves(cloud: str, d: int, limit: int, deep: int) -> str:
    """CTEs ``pts``, ``nodes`` and ``leaves(cell, level, est)`` of the counted tree."""
    key = morton([f"(x{a} >> {24 - deep})" for a in range(d)], deep)
    # counted once at the deepest level; coarser nodes are sums
    return f"""
pts AS MATERIALIZED ({cloud}),
deepest AS MATERIALIZED (SELECT {1 << (d * deep)}::BIGINT + {key} AS cell, count(*)::BIGINT AS est FROM pts WHERE {' AND '.join(f'x{a} IS NOT NULL' for a in range(d))} GROUP BY 1),
nodes AS MATERIALIZED (SELECT level::INT AS level, cell >> ({d} * ({deep} - level))::INT AS cell, sum(est)::BIGINT AS est FROM deepest, range(0, {deep + 1}) r(level) GROUP BY 1, 2),
every AS (SELECT 1::BIGINT AS cell, 0 AS level UNION ALL SELECT cell * {1 << d} + o, level + 1 FROM nodes, range(0, {1 << d}) t(o) WHERE est > {limit} AND level < {deep}),
leaves AS MATERIALIZED (
  SELECT e.cell, e.level::INT AS level, coalesce(n.est, 0)::BIGINT AS est
  FROM every e LEFT JOIN nodes n ON n.cell = e.cell WHERE e.level = {deep} OR coalesce(n.est, 0) <= {limit})
"""


def boxes(d: int, bits: int, source: str = "leaves") -> str:
    """CTE ``boxed(cell, level, c0.., lo0.., side)``."""
    c = [" + ".join(f"(((cell >> {d * b + d - 1 - a}) & 1) << {b})" for b in range(bits)) for a in range(d)]
    cs = ", ".join(f"(({x}) & ((1::BIGINT << level) - 1)) AS c{a}" for a, x in enumerate(c))
    return f"""
boxed AS (SELECT *, {', '.join(f'c{a} * side AS lo{a}' for a in range(d))} FROM (SELECT *, {cs}, 1::BIGINT << (24 - level) AS side FROM {source}))
"""
