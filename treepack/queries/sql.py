"""Parts of oracle SQL (DuckDB)."""

from __future__ import annotations

#: stream -> SELECT of (value_id, t): the text whose UTF-8 bytes are the value.
TEXT = {
    **{f"doc_{x}": f"SELECT doc_id AS value_id, text AS t FROM documents WHERE lang = '{x}' AND text IS NOT NULL" for x in ("en", "de", "fr", "es")},
    "html": "SELECT page_id AS value_id, html AS t FROM pages WHERE html IS NOT NULL",
    "letters": r"SELECT doc_id AS value_id, regexp_replace(lower(text), '[^a-z .,\n]', '', 'g') AS t FROM documents WHERE lang = 'en' AND text IS NOT NULL",
}


def rows(streams) -> str:
    """SELECT of (stream_id, value_id, pos, sym), one row per byte."""
    parts = " UNION ALL ".join(f"SELECT '{s}' AS stream_id, * FROM ({TEXT[s]})" for s in streams)
    return f"SELECT stream_id, value_id, u.i AS pos, ('0x' || substr(h, 2 * u.i + 1, 2))::INT AS sym FROM (SELECT stream_id, value_id, hex(encode(t)) AS h, strlen(t) AS n FROM ({parts})) x, unnest(range(x.n)) AS u(i)"


def numbers(stream: str, table: str, column: str, size: int) -> str:
    """SELECT of (stream_id, sym): little-endian bytes of an integer column."""
    return f"SELECT '{stream}' AS stream_id, (({column} >> (8 * k)) & 255)::INT AS sym FROM {table}, range({size}) r(k)"


def hist(source: str) -> str:
    return f"SELECT stream_id, sym, count(*) AS cnt FROM ({source}) GROUP BY ALL"


def codes(hist_sql: str) -> str:
    """CTEs hist, lifted (no count under a 4096th), lens(stream_id, sym, len) and codes(stream_id, sym, len, code): recursive merging of the two rarest subtrees, then a running sum of code space."""
    return f"""hist AS MATERIALIZED ({hist_sql}),
lifted AS MATERIALIZED (SELECT stream_id, sym, greatest(cnt, (sum(cnt) OVER (PARTITION BY stream_id) // 4096)::BIGINT) AS cnt FROM hist),
merge_(stream_id, items, merged) AS (
  SELECT stream_id, list_sort(list({{'c': cnt, 'm': sym, 's': [sym]}})), NULL::INT[] FROM lifted GROUP BY stream_id
  UNION ALL
  SELECT stream_id, list_sort(list_append(items[3:], {{'c': items[1].c + items[2].c, 'm': least(items[1].m, items[2].m), 's': list_concat(items[1].s, items[2].s)}})), list_concat(items[1].s, items[2].s)
  FROM merge_ WHERE len(items) > 1),
lens AS MATERIALIZED (SELECT stream_id, sym, count(*)::INT AS len FROM (SELECT stream_id, unnest(merged) AS sym FROM merge_ WHERE merged IS NOT NULL) GROUP BY ALL),
codes AS MATERIALIZED (SELECT stream_id, sym, len, lpad(bin((coalesce(sum((1::BIGINT << (15 - len))) OVER (PARTITION BY stream_id ORDER BY len, sym ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT >> (15 - len))), len, '0') AS code FROM lens)"""


#: CTE nodes_(stream_id, prefix, depth, n, n_right), from hist and codes.
NODES = """nodes_ AS MATERIALIZED (SELECT stream_id, left(code, d.d) AS prefix, d.d::INT AS depth, sum(cnt)::BIGINT AS n, sum(CASE WHEN substr(code, d.d + 1, 1) = '1' THEN cnt ELSE 0 END)::BIGINT AS n_right
FROM hist JOIN codes USING (stream_id, sym), unnest(range(len)) AS d(d) GROUP BY ALL)"""


def md5_of(streams) -> str:
    parts = " UNION ALL ".join(f"SELECT '{s}' AS stream_id, * FROM ({TEXT[s]})" for s in streams)
    return f"SELECT stream_id, value_id, strlen(t)::BIGINT AS n_bytes, md5(t) AS digest FROM ({parts})"
