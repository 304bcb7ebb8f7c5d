"""SQL that checks the engine: common table expressions over the given tables, put together by name."""

from __future__ import annotations

import re

#: Lattice over `part`, sparse, dense, medium and many-tag layers, tiles, query log. Column orders are fixed.
CTE: dict[str, str] = {
    "dims": "SELECT CAST(count(*) AS BIGINT) AS n, CAST(ceil(sqrt(count(*))) AS BIGINT) AS wide FROM part",
    "vertices": "SELECT p_partkey AS v, 10 * (p_partkey % wide) AS x, 10 * CAST(floor(p_partkey / wide) AS BIGINT) AS y FROM part, dims",
    "edges": """SELECT a.p_partkey AS u, b.p_partkey AS v, CAST(10 + (a.p_size + b.p_size) % 10 AS BIGINT) AS w FROM part a CROSS JOIN dims JOIN part b ON b.p_partkey = a.p_partkey + 1 WHERE floor(a.p_partkey / wide) = floor(b.p_partkey / wide)
      UNION ALL SELECT a.p_partkey, b.p_partkey, CAST(10 + (a.p_size + b.p_size) % 10 AS BIGINT) FROM part a CROSS JOIN dims JOIN part b ON b.p_partkey = a.p_partkey + wide WHERE a.p_partkey % wide = 0 OR (a.p_partkey * 7919) % 11 <> 0""",
    "arcs": "SELECT u, v, w FROM edges UNION ALL SELECT v, u, w FROM edges",
    "big_dims": "SELECT CAST(count(*) AS BIGINT) AS n, CAST(ceil(sqrt(count(*))) AS BIGINT) AS wide FROM orders",
    "big_edges": """SELECT a.o_orderkey AS u, b.o_orderkey AS v, CAST(10 + (a.o_custkey % 50 + b.o_custkey % 50 + 2) % 10 AS BIGINT) AS w FROM orders a CROSS JOIN big_dims JOIN orders b ON b.o_orderkey = a.o_orderkey + 1 WHERE floor(a.o_orderkey / wide) = floor(b.o_orderkey / wide)
      UNION ALL SELECT a.o_orderkey, b.o_orderkey, CAST(10 + (a.o_custkey % 50 + b.o_custkey % 50 + 2) % 10 AS BIGINT) FROM orders a CROSS JOIN big_dims JOIN orders b ON b.o_orderkey = a.o_orderkey + wide WHERE a.o_orderkey % wide = 0 OR (a.o_orderkey * 7919) % 11 <> 0""",
    "suppliers": "SELECT s_suppkey AS poi, (s_suppkey * 613 + 17) % n AS v, n_name AS tag, CAST(1 + floor((s_acctbal + 1000) * 90 / 11000) AS BIGINT) AS rating FROM supplier JOIN nation ON s_nationkey = n_nationkey, dims",
    "customers": "SELECT c_custkey AS poi, (c_custkey * 389 + 5) % n AS v, c_mktsegment AS tag, CAST(1 + floor((c_acctbal + 1000) * 90 / 11000) AS BIGINT) AS rating FROM customer, dims",
    "parts": "SELECT p_partkey AS poi, p_partkey AS v, p_brand AS tag, CAST(1 + floor((p_size - 1) * 89 / 49) AS BIGINT) AS rating FROM part WHERE p_partkey % 3 = 0",
    "docs": """SELECT d.doc_id AS poi, d.doc_id % n AS v, t.tag, CAST(1 + 30 * coalesce(l.quality, 0) + d.n_chars % 30 AS BIGINT) AS rating FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id CROSS JOIN dims
      JOIN (SELECT DISTINCT doc_id AS k, lang AS tag FROM documents UNION ALL SELECT DISTINCT doc_id, source FROM documents) t ON t.k = d.doc_id""",
    "cells": "SELECT v, CAST(floor(x / 70) * 1000 + floor(y / 70) AS BIGINT) AS cell FROM vertices",
    "cut": "SELECT e.u, e.v, e.w, a.cell AS cu, b.cell AS cv FROM edges e JOIN cells a ON e.u = a.v JOIN cells b ON e.v = b.v WHERE a.cell <> b.cell",
    "borders": "SELECT DISTINCT cell, v FROM (SELECT cu AS cell, u AS v FROM cut UNION ALL SELECT cv, v FROM cut)",
    "inner_arcs": "SELECT a.u, a.v, a.w, cu.cell FROM arcs a JOIN cells cu ON a.u = cu.v JOIN cells cv ON a.v = cv.v WHERE cu.cell = cv.cell",
    "log": """SELECT event_id AS qid, (user_id * 131 + event_id * 17) % n AS v_q, i AS pos, (event_id * 7 + i * (1 + event_id % 4)) % 25 AS nation FROM events, dims, (SELECT 0 AS i UNION ALL SELECT 1 UNION ALL SELECT 2 UNION ALL SELECT 3)""",
}


def _needs(text: str) -> list[str]:
    return [n for n in CTE if re.search(rf"\b{n}\b", text)]


def with_sql(final: str, extra: dict[str, str] | None = None, recursive: dict[str, str] | None = None) -> str:
    """`final` with the expressions that it names, each after those that it needs. recursive: name and key -> text."""
    have: dict[str, str] = {}
    extra = extra or {}

    def add(name: str) -> None:
        if name in have:
            return
        text = extra.get(name) or CTE[name]
        for n in [*_needs(text), *(e for e in extra if re.search(rf"\b{e}\b", text))]:
            if n != name:
                add(n)
        have[name] = text

    parts = []
    for head, text in (recursive or {}).items():
        for n in [*_needs(text), *(e for e in extra if re.search(rf"\b{e}\b", text))]:
            add(n)
        parts.append((head, text))
    early = dict(have)
    for n in [*_needs(final), *(e for e in extra if re.search(rf"\b{e}\b", final))]:
        add(n)
    listed = [f"{n} AS MATERIALIZED ({early[n]})" for n in early] + [f"{h} AS ({t})" for h, t in parts] + [f"{n} AS MATERIALIZED ({have[n]})" for n in have if n not in early]
    if not listed:
        return final
    return ("WITH RECURSIVE " if parts else "WITH ") + ",\n".join(listed) + "\n" + final


def sssp_sql(sources: str, arcs: str = "arcs", name: str = "sd", limit: str = "") -> dict[str, str]:
    """Recursive expression name(s, v, dist): least distances from every s of `sources`, by keyed recursion."""
    return {
        f"{name}(s, v, dist) USING KEY (s, v)": f"""SELECT s, s AS v, CAST(0 AS BIGINT) AS dist FROM ({sources}) AS src
      UNION SELECT d.s, a.v, min(d.dist + a.w) AS dist FROM {name} d JOIN {arcs} a ON d.v = a.u LEFT JOIN recurring.{name} r ON r.s = d.s AND r.v = a.v
      WHERE (r.dist IS NULL OR d.dist + a.w < r.dist) {limit} GROUP BY d.s, a.v"""
    }
