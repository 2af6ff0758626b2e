"""DuckDB statements for queries of the registry."""

from __future__ import annotations


def quad_sql(source: str, key: str, values: list[str], tau: int, final: str, cycle: bool = False) -> str:
    """A recursive split at centroids over scaled whole values; final reads placed(key, gid, v0..)."""
    k = len(values)
    v = ", ".join(f"CAST({x} AS BIGINT) AS v{i}" for i, x in enumerate(values))
    names = ", ".join(f"v{i}" for i in range(k))
    stats = ", ".join(f"sum(v{i}) OVER g AS s{i}, min(v{i}) OVER g AS lo{i}, max(v{i}) OVER g AS hi{i}" for i in range(k))
    if cycle:
        turns = []
        for r in range(k):
            order = [(r + j) % k for j in range(k)]
            turns.append(f"WHEN {r} THEN CASE " + " ".join(f"WHEN hi{i} > lo{i} THEN {i}" for i in order) + " END")
        first = f"CASE lvl % {k} " + " ".join(turns) + " END"
        bits = " || ".join(f"CASE WHEN ({first}) IS DISTINCT FROM {i} THEN '-' WHEN v{i} * n >= s{i} THEN '1' ELSE '0' END" for i in range(k))
    else:
        bits = " || ".join(f"CASE WHEN hi{i} = lo{i} THEN '-' WHEN v{i} * n >= s{i} THEN '1' ELSE '0' END" for i in range(k))
    return f"""WITH RECURSIVE t(key, gid, lvl, {names}) AS (
      SELECT {key}, 'r', 0, {names} FROM (SELECT {key}, {v} FROM {source})
      UNION ALL
      SELECT key, gid || '/' || {bits}, lvl + 1, {names}
      FROM (SELECT *, count(*) OVER g AS n, {stats} FROM t WINDOW g AS (PARTITION BY gid))
      WHERE n > {tau}),
    placed AS (SELECT key, max_by(gid, lvl) AS gid, {", ".join(f"any_value(v{i}) AS v{i}" for i in range(k))} FROM t GROUP BY key)
    {final}"""


PART_VALUES = ["p_size * 100", "round(p_retailprice * 100)"]
MEAL_PAIRS = "FROM p a JOIN p b ON a.p_partkey {op} b.p_partkey JOIN p c ON b.p_partkey {op} c.p_partkey"


def meal_sql(select: str, condition: str, op: str = "<", tail: str = "") -> str:
    return f"""WITH p AS (SELECT p_partkey, p_size, CAST(round(p_retailprice * 100) AS BIGINT) AS cents FROM part WHERE p_type = 'PROMO'),
    m AS (SELECT a.p_size + b.p_size + c.p_size AS size, a.cents + b.cents + c.cents AS cents {MEAL_PAIRS.format(op=op)})
    SELECT {select} FROM m WHERE {condition} {tail}"""


LINES = """(SELECT * FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey
    WHERE l_linenumber IS NOT NULL AND l_quantity IS NOT NULL AND l_tax IS NOT NULL AND l_extendedprice IS NOT NULL AND l_discount IS NOT NULL
    AND o_totalprice IS NOT NULL AND p_size IS NOT NULL AND s_acctbal IS NOT NULL AND p_retailprice IS NOT NULL)"""
FEATURES = r"""(SELECT lang, n_chars, coalesce(toxic, 0) AS toxic, coalesce(len(regexp_extract_all(text, '[^ \t\n\r]+')), 0) AS n_words,
    coalesce(len(regexp_extract_all(text, '\n')), 0) + 1 AS n_lines, coalesce(len(regexp_extract_all(text, '[0-9]')), 0) AS n_digits
    FROM documents LEFT JOIN labels USING (doc_id))"""
EVENTS = "(SELECT * FROM (SELECT *, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k FROM events) WHERE k IS NOT NULL AND value IS NOT NULL)"
VECTORS = "(SELECT " + ", ".join(f"CAST(embedding[{i}] AS DOUBLE) AS e{i}" for i in range(1, 5)) + " FROM embeddings)"
#: Each workload's relation, and name and coefficient of every linear row.
ROWS = {
    "w1": (LINES, {"c0": "1", "c1": "l_quantity", "c2": "l_tax"}),
    "w2": (LINES, {"c0": "1", "c1": "p_size", "c2": "s_acctbal"}),
    "w3": (LINES, {"c0": "1", "c1": "o_totalprice", "c2": "l_discount"}),
    "w4": (LINES, {"c0": "1", "c1": "l_quantity"}),
    "w5": ("part", {"c0": "1", "c1": "p_size"}),
    "w6": (LINES, {"c0": "1", "c1": "l_quantity", "c2_avg low": "l_discount - 0.05", "c2_avg high": "l_discount - 0.07"}),
    "w7": (LINES, {"c0": "1", "c1": "CASE l_returnflag WHEN 'R' THEN 1 ELSE 0 END - CASE l_linestatus WHEN 'F' THEN 1 ELSE 0 END", "c2": "l_quantity"}),
    "v1": (FEATURES, {"c0": "1", "c1": "n_chars"}),
    "v2": (FEATURES, {"c0": "1", "c1": "n_words", "c2": "n_digits", "c3": "n_lines"}),
    "v3": (EVENTS, {"c0": "1", "c1": "value", "c2": "CASE event_type WHEN 'error' THEN 1 WHEN 'click' THEN -1 ELSE 0 END"}),
    "v4": (FEATURES, {"c0": "1", "c1_avg": "n_chars - 2500", "c2": "CASE lang WHEN 'fr' THEN 1 ELSE 0 END"}),
    "v5": (FEATURES, {"c0": "1", "c1": "n_chars", "c2": "toxic"}),
    "v6": (VECTORS, {"c0": "1", "c1": "e1", "c2": "e2", "c3": "e3", "c4": "e4"}),
    "v7": (FEATURES, {"c0": "n_chars"}),
}


def audit_sql(name: str) -> str:
    """Every linear row's coefficient summed over the whole relation; the package must satisfy the row."""
    relation, rows = ROWS[name]
    sums = ", ".join(f"round(CAST(sum({x}) AS DOUBLE), 3) AS t{i}" for i, x in enumerate(rows.values()))
    out = " UNION ALL ".join(f"SELECT '{name}' AS workload, {i} AS place, '{r.split()[0]}' AS row, t{i} AS total, t{i} IS NOT NULL AS satisfied FROM sums" for i, r in enumerate(rows))
    return f"WITH sums AS (SELECT {sums} FROM {relation}) {out}"
