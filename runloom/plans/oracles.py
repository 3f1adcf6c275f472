"""DuckDB SQL builders: sequences decoded to one letter a symbol, occurrences by equality of substrings."""

from __future__ import annotations

from runloom.types import Run, runs_of


def expand(pattern, letters: dict | None = None) -> str:
    """A pattern as the string of its symbols' letters."""
    runs = pattern if pattern and isinstance(pattern[0], Run) else runs_of(pattern)
    return "".join((letters[s] if letters else s) * n for s, n in runs)


def quote(text: str) -> str:
    return "'" + text.replace("'", "''") + "'"


def values(patterns: list, letters: dict | None = None) -> str:
    rows = ", ".join(f"(CAST({k} AS BIGINT), {quote(expand(p, letters))})" for k, p in patterns)
    return f"pats(pattern_id, p) AS (VALUES {rows})"


EVENT_LETTERS = {"view": "v", "click": "c", "purchase": "p", "error": "e", "signup": "s"}
EVENT_CODE = "CASE event_type " + " ".join(f"WHEN '{k}' THEN '{v}'" for k, v in EVENT_LETTERS.items()) + " ELSE '?' END"
#: Events on the alphabet of the worked example.
ABC_CODE = "CASE WHEN event_type IN ('view', 'click', 'purchase') THEN 'a' WHEN event_type = 'error' THEN 'b' ELSE 'c' END"
QUANTITY_CODE = "CASE WHEN l_quantity <= 45 THEN 'L' ELSE 'H' END"

#: One row per sequence: seq_id and its string.
SEQUENCES = {
    "events": f"SELECT user_id AS seq_id, string_agg({EVENT_CODE}, '' ORDER BY ts, event_id, event_type) AS s FROM events GROUP BY 1",
    "abc": f"SELECT user_id AS seq_id, string_agg({ABC_CODE}, '' ORDER BY ts, event_id, event_type) AS s FROM events GROUP BY 1",
    "linestatus": "SELECT l_suppkey AS seq_id, string_agg(l_linestatus, '' ORDER BY l_shipdate, l_orderkey, l_linenumber, l_linestatus) AS s FROM lineitem GROUP BY 1",
    "quantity": f"SELECT l_suppkey AS seq_id, string_agg({QUANTITY_CODE}, '' ORDER BY l_shipdate, l_orderkey, l_linenumber, {QUANTITY_CODE}) AS s FROM lineitem GROUP BY 1",
    "orderstatus": "SELECT o_custkey AS seq_id, string_agg(o_orderstatus, '' ORDER BY o_orderdate, o_orderkey, o_orderstatus) AS s FROM orders GROUP BY 1",
    "quality": "SELECT CAST(0 AS BIGINT) AS seq_id, string_agg(CAST(quality AS VARCHAR), '' ORDER BY doc_id, quality) AS s FROM labels",
    "signs": "SELECT vec_id AS seq_id, array_to_string(list_transform(embedding, lambda x: CASE WHEN x > 0 THEN '+' ELSE '-' END), '') AS s FROM embeddings",
    "names": "SELECT c_custkey AS seq_id, c_name AS s FROM customer",
    "roles": "SELECT conv_id AS seq_id, string_agg(substr(role, 1, 1), '' ORDER BY turn, role) AS s FROM conversations GROUP BY 1",
}
LETTERS = {"events": EVENT_LETTERS, "roles": {"user": "u", "assistant": "a", "system": "s"}}

#: One row per symbol of the one long sequence: n (from 0) and c.
GLOBAL = {
    "events": f"SELECT row_number() OVER (ORDER BY ts, event_id, event_type) - 1 AS n, {EVENT_CODE} AS c FROM events",
    "linestatus": "SELECT row_number() OVER (ORDER BY l_shipdate, l_orderkey, l_linenumber, l_linestatus) - 1 AS n, l_linestatus AS c FROM lineitem",
}


def hits_ctes(name: str, patterns: list) -> str:
    """seqs, pats and hits(seq_id, pattern_id, start, len)."""
    return f"""seqs AS ({SEQUENCES[name]}), {values(patterns, LETTERS.get(name))},
    hits AS (SELECT seq_id, pattern_id, CAST(i AS BIGINT) AS start, CAST(length(p) AS BIGINT) AS len FROM (
        SELECT seq_id, pattern_id, p, s, unnest(generate_series(0, length(s) - length(p))) AS i FROM seqs, pats WHERE length(s) >= length(p))
      WHERE substr(s, CAST(i AS INT) + 1, CAST(length(p) AS INT)) = p)"""


def hits_sql(name: str, patterns: list) -> str:
    return f"WITH {hits_ctes(name, patterns)} SELECT seq_id, pattern_id, start FROM hits"


def global_sql(name: str, patterns: list) -> str:
    """Windows of each length over the rows of one long sequence."""
    letters = LETTERS.get(name)
    lengths = sorted({len(expand(p, letters)) for _, p in patterns})
    parts = [
        f"SELECT CAST(0 AS BIGINT) AS seq_id, pattern_id, CAST(n AS BIGINT) AS start FROM (SELECT n, string_agg(c, '') OVER (ORDER BY n ROWS BETWEEN CURRENT ROW AND {m - 1} FOLLOWING) AS w FROM chars) JOIN pats ON w = p AND length(p) = {m}"
        for m in lengths
    ]
    return f"WITH chars AS ({GLOBAL[name]}), {values(patterns, letters)} " + " UNION ALL ".join(parts)


def text_ctes(source: str, patterns: list) -> str:
    """The same for texts: characters are numbered, each length's windows are put together by lead(). source: SELECT seq_id, s."""
    lengths = sorted({len(p) for _, p in patterns})
    glue = lambda m: " || ".join(["c", *[f"lead(c, {j}) OVER w" for j in range(1, m)]])
    parts = [f"SELECT seq_id, pattern_id, CAST(n AS BIGINT) AS start, CAST({m} AS BIGINT) AS len FROM (SELECT seq_id, n, {glue(m)} AS x FROM chars WINDOW w AS (PARTITION BY seq_id ORDER BY n)) JOIN pats ON x = p AND length(p) = {m}" for m in lengths]
    return f"""texts AS ({source}), {values(patterns)},
    chars AS (SELECT seq_id, unnest(string_split(s, '')) AS c, unnest(generate_series(0, length(s) - 1)) AS n FROM texts WHERE length(s) > 0),
    hits AS ({" UNION ALL ".join(parts)})"""


def text_sql(source: str, patterns: list) -> str:
    return f"WITH {text_ctes(source, patterns)} SELECT seq_id, pattern_id, start FROM hits"


def runs_sql(source: str) -> str:
    """Long form of runs by gaps and islands. source: SELECT seq_id, n (from 0), sym."""
    return f"""WITH syms AS ({source}),
    marked AS (SELECT *, CASE WHEN sym = lag(sym) OVER (PARTITION BY seq_id ORDER BY n) THEN 0 ELSE 1 END AS new FROM syms),
    islands AS (SELECT *, sum(new) OVER (PARTITION BY seq_id ORDER BY n) AS run_no FROM marked)
    SELECT seq_id, CAST(run_no AS BIGINT) AS run_no, min(sym) AS sym, CAST(count(*) AS BIGINT) AS len, CAST(min(n) AS BIGINT) AS start FROM islands GROUP BY seq_id, run_no"""
