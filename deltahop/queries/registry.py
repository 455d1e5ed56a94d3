"""The registry, and SQL fragments of the graphs that oracles share."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame

QUERIES: dict[str, Callable] = {}
ORACLES: dict[str, str] = {}


def query(name: str, oracle: str | None = None) -> Callable:
    """Register fn(spark, sf_dir) under a name, with its SQL where SQL can express it."""

    def add(fn: Callable[..., DataFrame]) -> Callable[..., DataFrame]:
        QUERIES[name] = fn
        if oracle is not None:
            ORACLES[name] = oracle
        return fn

    return add


def mix(a: str, b) -> str:
    return f"((((({a}) % 2147483647)::BIGINT * 1103515245 + ({b}) * 16807 + 7) % 2147483647) * 69621 % 2147483647)"


REL = "CAST((instr('ANR', l_returnflag) - 1) * 2 + instr('FO', l_linestatus) - 1 AS INTEGER)"
CUST_PART = f"SELECT DISTINCT o_custkey * 16 AS src_id, {REL} AS rel_id, l_partkey * 16 + 1 AS dst_id FROM lineitem JOIN orders ON l_orderkey = o_orderkey"
CUST_PART_PLAIN = "SELECT DISTINCT o_custkey * 16 AS src_id, 0 AS rel_id, l_partkey * 16 + 1 AS dst_id FROM lineitem JOIN orders ON l_orderkey = o_orderkey"
PART_SUPP = "SELECT DISTINCT l_partkey * 16 + 1 AS src_id, 6 AS rel_id, l_suppkey * 16 + 2 AS dst_id FROM lineitem"
GEO = """SELECT c_custkey * 16 AS src_id, 7 AS rel_id, CAST(c_nationkey AS BIGINT) * 16 + 3 AS dst_id FROM customer
UNION ALL SELECT s_suppkey * 16 + 2, 8, CAST(s_nationkey AS BIGINT) * 16 + 3 FROM supplier
UNION ALL SELECT CAST(n_nationkey AS BIGINT) * 16 + 3, 9, CAST(n_regionkey AS BIGINT) * 16 + 4 FROM nation"""
TRADE = f"{CUST_PART} UNION ALL {PART_SUPP} UNION ALL {GEO}"
TRADE_CORE = f"{CUST_PART_PLAIN} UNION ALL {PART_SUPP.replace('6 AS rel_id', '0 AS rel_id')}"
COPURCHASE = """SELECT DISTINCT a.l_partkey * 16 + 1 AS src_id, 0 AS rel_id, b.l_partkey * 16 + 1 AS dst_id
FROM (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) a JOIN (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) b ON a.l_orderkey = b.l_orderkey AND a.l_partkey <> b.l_partkey"""
TOKENS = r"SELECT DISTINCT doc_id, t.token FROM documents, LATERAL (SELECT unnest(regexp_split_to_array(lower(text), '[^\p{L}]+')) AS token) t WHERE t.token <> ''"
DOCTOKEN = f"SELECT doc_id * 16 + 5 AS src_id, 0 AS rel_id, token_id * 16 + 6 AS dst_id FROM (SELECT doc_id, dense_rank() OVER (ORDER BY token) - 1 AS token_id FROM ({TOKENS}))"
LINKS = "SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS href FROM pages"
HYPERLINK = f"SELECT page_id * 16 + 7 AS src_id, 0 AS rel_id, target_id * 16 + 8 AS dst_id FROM (SELECT DISTINCT page_id, href, dense_rank() OVER (ORDER BY href) - 1 AS target_id FROM ({LINKS}))"
ADJ = {
    "core": f"SELECT src_id AS node_id, dst_id AS nbr_id FROM ({TRADE_CORE}) UNION SELECT dst_id, src_id FROM ({TRADE_CORE})",
    "copurchase": f"SELECT src_id AS node_id, dst_id AS nbr_id FROM ({COPURCHASE})",
}
