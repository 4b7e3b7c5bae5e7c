"""DuckDB SQL for the queries: everything is derived from the definitions by substrings, never by the kernels' ways."""

from __future__ import annotations

PASSAGES = "SELECT item_id AS sid, text AS body FROM benchmark"
PARTS = "SELECT p_partkey AS sid, p_name AS body FROM part"
USERS = "SELECT user_id AS sid, string_agg(substr(event_type, 1, 1), '' ORDER BY ts, event_id) AS body FROM events GROUP BY user_id"
ORDERS = "SELECT l_orderkey AS sid, string_agg(l_returnflag || l_linestatus, '' ORDER BY l_linenumber, l_returnflag || l_linestatus) AS body FROM lineitem GROUP BY l_orderkey"


def factors(source: str, overlap: bool = True) -> str:
    """CTEs up to ``f(sid, pos, lpf_raw)`` and ``r(sid, reach, n)``: reach is the list of all reaches of a string."""
    limit = "g.first < g.pos" if overlap else "g.first + g.size <= g.pos"
    return f"""
s AS MATERIALIZED ({source}),
g0 AS (SELECT sid, p.pos, z.size, substr(body, p.pos, z.size) AS gram
  FROM s, LATERAL (SELECT unnest(range(1, length(body) + 1)) AS pos) p, LATERAL (SELECT unnest(range(1, length(body) - p.pos + 2)) AS size) z),
g AS (SELECT sid, pos, size, min(pos) OVER (PARTITION BY sid, gram) AS first FROM g0),
f AS MATERIALIZED (SELECT sid, pos, CAST(coalesce(max(size) FILTER (WHERE {limit}), 0) AS BIGINT) AS lpf_raw FROM g GROUP BY sid, pos),
r AS MATERIALIZED (SELECT sid, list(pos + greatest(lpf_raw, 1) ORDER BY pos) AS reach, max(pos) AS n FROM f GROUP BY sid)"""


WALK = """
w AS MATERIALIZED (SELECT sid, CAST(1 AS BIGINT) AS ord, CAST(1 AS BIGINT) AS lo, CAST(reach[1] - 1 AS BIGINT) AS hi, reach, n FROM r
  UNION ALL SELECT sid, ord + 1, hi + 1, CAST(reach[hi + 1] - 1 AS BIGINT), reach, n FROM w WHERE hi < n)"""


def phrases(source: str, then: str, overlap: bool = True) -> str:
    """``then`` reads ``w(sid, ord, lo, hi)`` and the CTEs of ``factors``."""
    return f"WITH RECURSIVE {factors(source, overlap)},{WALK} {then}"


def lpf(source: str, then: str) -> str:
    return f"WITH {factors(source)} {then}"


def edited(edits: int, kinds: tuple[str, ...], alphabet: str = "aeinrst", names: str = PARTS) -> str:
    """A source of all versions: ``sid`` packs the string's id and the edit's number as ``sid * 100 + seq``."""
    parts = [f"v0 AS (SELECT sid, body, greatest(length(body) - {edits}, 1) AS n FROM ({names}) WHERE length(body) > {edits})"]
    for q in range(1, edits + 1):
        op, pos, sym = kinds[q % len(kinds)], f"(1 + (7 * sid + {13 * q}) % n)", f"substr('{alphabet}', CAST((sid + {q}) % {len(alphabet)} AS INTEGER) + 1, 1)"
        tail = f"{pos} + {0 if op == 'ins' else 1}"
        parts.append(f"v{q} AS (SELECT sid, left(body, CAST({pos} - 1 AS INTEGER)) || {sym if op != 'del' else chr(39) * 2} || substr(body, CAST({tail} AS INTEGER)) AS body, n FROM v{q - 1})")
    union = " UNION ALL ".join(f"SELECT sid * 100 + {q} AS sid, body FROM v{q}" for q in range(1, edits + 1))
    return f"WITH {', '.join(parts)} {union}"


def edited_counts(edits: int, kinds: tuple[str, ...]) -> str:
    return phrases(edited(edits, kinds), "SELECT sid // 100 AS sid, sid % 100 AS seq, CAST(max(n) AS BIGINT) AS n, count(*) AS phrases FROM w GROUP BY sid")


def patterns(d: int) -> str:
    value = " + ".join(f"(CASE WHEN embedding[{j}] > 0 THEN {1 << (d - j)} ELSE 0 END)" for j in range(1, d + 1))
    return f"p AS (SELECT vec_id % 2 AS side, CAST({value} AS BIGINT) AS bits FROM embeddings), a AS (SELECT bits AS v, count(*) AS copies FROM p WHERE side = 0 GROUP BY bits), b AS (SELECT bits AS u, count(*) AS copies FROM p WHERE side = 1 GROUP BY bits)"
