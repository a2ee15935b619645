"""DuckDB SQL for the tensors and the steps that queries share."""

from __future__ import annotations

import math

from ..functions.hashing import hash_sql
from ..operators.bloom import LN2, hashes_for

WEIGHT = "CAST(round(l_extendedprice * 100) AS BIGINT) * (CAST(round(l_discount * 100) AS BIGINT) - 5)"
PARTS = "(SELECT count(*) FROM part)"


def _sum(tensor: str, idx: str, value: str, source: str) -> str:
    return f"SELECT CAST({tensor} AS BIGINT) AS tensor_id, CAST({idx} AS BIGINT) AS idx, CAST(sum({value}) AS BIGINT) AS value FROM {source} GROUP BY 1, 2 HAVING sum({value}) <> 0"


TENSORS = {
    "nation_part": _sum("0", f"s_nationkey * {PARTS} + l_partkey", WEIGHT, "lineitem JOIN supplier ON l_suppkey = s_suppkey"),
    "supp_part": _sum("l_suppkey", "l_partkey", WEIGHT, "lineitem"),
    "cust_part": _sum("0", f"o_custkey * {PARTS} + l_partkey", WEIGHT, "lineitem JOIN orders ON l_orderkey = o_orderkey"),
    "worker8": _sum("l_orderkey % 8", f"s_nationkey * {PARTS} + l_partkey", WEIGHT, "lineitem JOIN supplier ON l_suppkey = s_suppkey"),
    "user_hour": _sum("0", "user_id * 720 + CAST(floor((epoch(ts) - epoch(TIMESTAMP '2024-01-01')) / 3600) AS BIGINT)", "CAST(round(value * 100) AS BIGINT)", "events"),
    "conv": "SELECT CAST(0 AS BIGINT) AS tensor_id, vec_id * 64 + pos - 1 AS idx, CAST(x AS DOUBLE) AS value FROM (SELECT vec_id, unnest(embedding) AS x, unnest(range(1, 65)) AS pos FROM embeddings) WHERE x <> 0",
    "layers": "SELECT CAST(label AS BIGINT) AS tensor_id, nth * 64 + pos - 1 AS idx, CAST(x AS DOUBLE) AS value FROM (SELECT label, nth, unnest(embedding) AS x, unnest(range(1, 65)) AS pos FROM (SELECT *, row_number() OVER (PARTITION BY label ORDER BY vec_id) - 1 AS nth FROM embeddings)) WHERE x <> 0",
    "text": "SELECT doc_id AS tensor_id, CAST('0x' || substr(md5(w), 1, 7) AS BIGINT) % 65536 AS idx, count(*) AS value FROM (SELECT doc_id, unnest(regexp_split_to_array(lower(text), '\\s+')) AS w FROM documents) WHERE w <> '' GROUP BY 1, 2",
}
DIMENSIONS = {"nation_part": f"25 * {PARTS}", "supp_part": PARTS, "cust_part": f"(SELECT count(*) FROM customer) * {PARTS}", "conv": "(SELECT count(*) * 64 FROM embeddings)", "user_hour": "(SELECT (max(user_id) + 1) * 720 FROM events)", "worker8": f"25 * {PARTS}"}


def small(name: str) -> str:
    """The tensor with values divided by 1000 toward zero, exact in 32-bit floats."""
    return f"SELECT tensor_id, idx, value FROM (SELECT tensor_id, idx, CAST(trunc(value / 1000) AS BIGINT) AS value FROM ({TENSORS[name]})) WHERE value <> 0"


def bits(r: str, fpr: float) -> str:
    return f"greatest(1, CAST(ceil({r} * {-math.log(fpr) / LN2**2!r}::DOUBLE - 1e-9) AS BIGINT))"


def pos(idx: str, j: int, m: str, seed: int = 0) -> str:
    return f"{hash_sql(idx, j, seed, duckdb=True)} % {m}"


def filter_ctes(true: str, d: str, fpr: float, seed: int = 0) -> str:
    """CTEs t (true cells), meta, b (set bits) and p (positives)."""
    k = hashes_for(fpr)
    tests = " AND ".join(f"EXISTS (SELECT 1 FROM b WHERE b.tensor_id = u.tensor_id AND b.pos = {pos('u.idx', j, 'u.m', seed)})" for j in range(k))
    sets = " UNION ".join(f"SELECT t.tensor_id, {pos('t.idx', j, 'm', seed)} AS pos FROM t JOIN meta USING (tensor_id)" for j in range(k))
    return (
        f"t AS MATERIALIZED ({true}), meta AS MATERIALIZED (SELECT tensor_id, count(*) AS r, {d} AS d, {bits('count(*)', fpr)} AS m FROM t GROUP BY 1), b AS MATERIALIZED ({sets}), "
        f"u AS (SELECT tensor_id, m, unnest(range(0, d)) AS idx FROM meta), p AS MATERIALIZED (SELECT tensor_id, idx FROM u WHERE {tests})"
    )


def priority(idx: str, seed: int, tag: str) -> str:
    return hash_sql(idx, 0, seed, tag, duckdb=True)


CHOSEN = {
    "p0": "SELECT tensor_id, idx FROM p",
    "p1": "SELECT tensor_id, idx FROM (SELECT p.*, row_number() OVER (PARTITION BY tensor_id ORDER BY {priority}, idx) AS n FROM p) JOIN meta USING (tensor_id) WHERE n <= r",
    "left": "SELECT tensor_id, idx FROM (SELECT p.*, row_number() OVER (PARTITION BY tensor_id ORDER BY idx) AS n FROM p) JOIN meta USING (tensor_id) WHERE n <= r",
    "right": "SELECT tensor_id, idx FROM (SELECT p.*, row_number() OVER (PARTITION BY tensor_id ORDER BY idx DESC) AS n FROM p) JOIN meta USING (tensor_id) WHERE n <= r",
    "middle": "SELECT tensor_id, idx FROM (SELECT p.*, row_number() OVER (PARTITION BY tensor_id ORDER BY idx) AS n, count(*) OVER (PARTITION BY tensor_id) AS c FROM p) JOIN meta USING (tensor_id) WHERE n > (c - r) // 2 AND n <= (c - r) // 2 + r",
}


def chosen(policy: str, seed: int = 0) -> str:
    return CHOSEN[policy].format(priority=priority("idx", seed, "p1"))


def decoded(policy: str, seed: int = 0) -> str:
    """Rows rebuilt by the receiver, over the CTEs of filter_ctes."""
    if policy == "naive":
        return (
            "SELECT k.tensor_id, k.idx, v.value FROM (SELECT tensor_id, idx, row_number() OVER (PARTITION BY tensor_id ORDER BY idx) AS n FROM p) k "
            "JOIN (SELECT tensor_id, value, row_number() OVER (PARTITION BY tensor_id ORDER BY idx) AS n FROM t) v USING (tensor_id, n)"
        )
    return f"SELECT c.tensor_id, c.idx, coalesce(t.value, 0) AS value FROM ({chosen(policy, seed)}) c LEFT JOIN t ON t.tensor_id = c.tensor_id AND t.idx = c.idx"


def gaps(cells: str) -> str:
    return f"SELECT tensor_id, idx, idx - lag(idx, 1, -1) OVER (PARTITION BY tensor_id ORDER BY idx) AS gap FROM ({cells})"


def huffman_cost(counts: str, name: str = "h") -> str:
    """CTEs ending in {name}_cost (tensor_id, bits, symbols): bits of an optimal prefix code over (tensor_id, n) counts.

    Merging the two smallest counts, again and again, adds up to the length of the coded text, however ties fall.
    """
    return (
        f"{name}_0 AS MATERIALIZED (SELECT tensor_id, list(n ORDER BY n) AS w FROM ({counts}) GROUP BY 1), "
        f"{name} AS (SELECT tensor_id, w, CAST(CASE WHEN len(w) = 1 THEN w[1] ELSE 0 END AS BIGINT) AS bits, len(w) AS symbols FROM {name}_0 "
        f"UNION ALL SELECT tensor_id, list_sort(list_append(w[3:], w[1] + w[2])), bits + w[1] + w[2], symbols FROM {name} WHERE len(w) > 1), "
        f"{name}_cost AS MATERIALIZED (SELECT tensor_id, bits, symbols FROM {name} WHERE len(w) = 1)"
    )


def gap_byte_counts(cells: str) -> str:
    """(tensor_id, n): how often each byte value occurs in the gaps, each in as few bytes as it needs."""
    size = "CASE WHEN gap < 256 THEN 1 WHEN gap < 65536 THEN 2 WHEN gap < 16777216 THEN 3 ELSE 4 END"
    return f"SELECT tensor_id, count(*) AS n FROM (SELECT tensor_id, unnest([(gap >> (8 * k)) & 255 FOR k IN range(0, {size})]) AS byte FROM ({gaps(cells)})) GROUP BY tensor_id, byte"


def delta_huffman_bits(cells: str) -> str:
    """CTEs ending in dh (tensor_id, bits): coded gap bytes, two bits a key, and two bytes a byte value."""
    return f"{huffman_cost(gap_byte_counts(cells), 'g')}, dh AS (SELECT tensor_id, bits + 2 * r + 16 * symbols AS bits FROM g_cost JOIN (SELECT tensor_id, count(*) AS r FROM ({cells}) GROUP BY 1) USING (tensor_id))"
