"""Pieces of key-free SQL for the oracles: signatures, pairs by shared elements, clusterings by walking the arrivals."""

from __future__ import annotations


def _finish(inner: str, order: str = "item_id") -> str:
    return f"""sig AS (SELECT row_number() OVER (ORDER BY {order})::BIGINT AS ordinal, item_id, len(s)::INT AS size, s AS sig
        FROM (SELECT *, list_slice(sig, 1, 10) AS s FROM ({inner})) WHERE len(s) >= 2)"""


def _keywords(rows: str, total: str, floor: int = 0) -> str:
    return f"""tok AS (SELECT * FROM ({rows}) WHERE length(token) >= 4),
        tf AS (SELECT item_id, token, count(*) AS tf FROM tok GROUP BY 1, 2),
        df AS (SELECT token, count(*) AS df FROM tf GROUP BY 1 HAVING count(*) >= 2 AND count(*) <= greatest(({total}) // 10, {floor})),
        best AS (SELECT item_id, token, row_number() OVER (PARTITION BY item_id ORDER BY tf DESC, df, token) AS r FROM tf JOIN df USING (token)),
        """ + _finish("SELECT item_id, list_sort(list(token)) AS sig FROM best WHERE r <= 10 GROUP BY 1")


_SPLIT = "unnest(string_split_regex(lower({}), '[^a-z0-9À-ÿ]+'))"

SIG = {
    "docs": _keywords(f"SELECT doc_id AS item_id, {_SPLIT.format('text')} AS token FROM documents", "SELECT count(*) FROM documents"),
    "pages": _keywords(f"SELECT page_id AS item_id, {_SPLIT.format(chr(32).join(['regexp_replace(regexp_replace(html,', chr(39) + '(?s)<(script|style)[^>]*>.*?</(script|style)>' + chr(39) + ',', chr(39) + ' ' + chr(39) + ',', chr(39) + 'g' + chr(39) + '),', chr(39) + '<[^>]*>' + chr(39) + ',', chr(39) + ' ' + chr(39) + ',', chr(39) + 'g' + chr(39) + ')']))} AS token FROM pages", "SELECT count(*) FROM pages", 2),
    "conversations": _keywords(f"SELECT conv_id AS item_id, {_SPLIT.format('text')} AS token FROM conversations", "SELECT count(DISTINCT conv_id) FROM conversations"),
    "orders": _finish("SELECT l_orderkey AS item_id, list_sort(list(DISTINCT p_brand)) AS sig FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1"),
    "ordersupp": _finish("SELECT l_orderkey AS item_id, list_sort(list(DISTINCT l_suppkey::VARCHAR)) AS sig FROM lineitem GROUP BY 1"),
    "userday": _finish("SELECT ts::DATE AS day, user_id AS item_id, list_sort(list(DISTINCT event_type || ':' || (json_extract_string(props, '$.k')::INT // 20))) AS sig FROM events GROUP BY 1, 2", "day, item_id"),
    "part": _finish("SELECT p_partkey AS item_id, list_sort(list_distinct(list_concat(string_split(p_name, ' '), [p_brand, p_type, 'sz' || (p_size // 10)]))) AS sig FROM part"),
    "customer": _finish("SELECT c_custkey AS item_id, list_sort(list_distinct(['N' || n_nationkey, 'R' || n_regionkey, c_mktsegment, 'B' || floor(c_acctbal / 1000)::INT])) AS sig FROM customer JOIN nation ON c_nationkey = n_nationkey"),
    "supplier": _finish("SELECT s_suppkey AS item_id, list_sort(list_distinct(['N' || n_nationkey, 'R' || n_regionkey, 'B' || floor(s_acctbal / 2000)::INT])) AS sig FROM supplier JOIN nation ON s_nationkey = n_nationkey"),
    "embeddings": _finish("SELECT vec_id AS item_id, list_sort(list_distinct(list_transform(range(0, 8), lambda b: 'b' || b || '.' || (list_position(list_slice(embedding, b * 8 + 1, b * 8 + 8), list_max(list_slice(embedding, b * 8 + 1, b * 8 + 8))) - 1)))) AS sig FROM embeddings"),
}

HOLDS = {
    "jaccard": "o * ({d} + {n}) >= {n} * (x + y)", "dice": "o * 2 * {d} >= {n} * (x + y)", "cosine": "o * o * {d} * {d} >= x * y * {n} * {n}",
    "overlap": "o * {d} >= {n} * least(x, y)", "contain": "o * {d} >= {n} * x", "hamming": "o * 2 * {d} + {n} >= {d} * (x + y)",
}


def pairs(n: int = 3, d: int = 5, kind: str = "jaccard", source: str = "sig") -> str:
    """pairs(earlier, later, overlap, y, x): x is the later item's size, the one that probes."""
    return f"""flat AS (SELECT ordinal, size, unnest(sig) AS e FROM {source}),
        shared AS (SELECT a.ordinal AS earlier, b.ordinal AS later, a.size AS y, b.size AS x, count(*) AS o FROM flat a JOIN flat b ON a.e = b.e AND a.ordinal < b.ordinal GROUP BY ALL),
        pairs AS MATERIALIZED (SELECT earlier, later, o AS overlap, x, y FROM shared WHERE {HOLDS[kind].format(n=n, d=d)})"""


LEADER = """adj AS MATERIALIZED (SELECT later AS i, list(earlier) AS e FROM pairs GROUP BY 1),
        walk AS (SELECT 0::BIGINT AS i, []::BIGINT[] AS led, NULL::BIGINT AS c UNION ALL
            SELECT i + 1, CASE WHEN f IS NULL THEN list_append(led, i + 1) ELSE led END, coalesce(f, i + 1)
            FROM (SELECT w.i, w.led, list_min(list_intersect(coalesce(a.e, []::BIGINT[]), w.led)) AS f FROM walk w LEFT JOIN adj a ON a.i = w.i + 1 WHERE w.i < (SELECT max(ordinal) FROM sig))),
        clusters AS MATERIALIZED (SELECT c AS cluster_id, i AS ordinal FROM walk WHERE i > 0)"""

CHAIN = """adj AS MATERIALIZED (SELECT later AS i, list(earlier) AS e FROM pairs GROUP BY 1),
        walk AS (SELECT 0::BIGINT AS i, []::BIGINT[] AS lab UNION ALL
            SELECT i + 1, list_append(lab, coalesce(f, i + 1))
            FROM (SELECT w.i, w.lab, list_min(list_select(w.lab, coalesce(a.e, []::BIGINT[]))) AS f FROM walk w LEFT JOIN adj a ON a.i = w.i + 1 WHERE w.i < (SELECT max(ordinal) FROM sig))),
        clusters AS MATERIALIZED (SELECT lab[ordinal] AS cluster_id, ordinal FROM sig, (SELECT lab FROM walk ORDER BY i DESC LIMIT 1))"""

REACH = """both_ways AS (SELECT earlier AS a, later AS b FROM pairs UNION ALL SELECT later, earlier FROM pairs),
        reach AS (SELECT ordinal AS a, ordinal AS b FROM sig UNION SELECT r.a, p.b FROM reach r JOIN both_ways p ON r.b = p.a),
        clusters AS (SELECT a AS ordinal, min(b) AS cluster_id FROM reach GROUP BY 1)"""


def renamed(ctes: str, suffix: str, **other: str) -> str:
    """The pieces above under names of their own, over other tables where ``other`` names them."""
    import re

    for name in ("flat", "shared", "pairs", "adj", "walk", "clusters", "sig"):
        new = other.get(name, name if name == "sig" else f"{name}_{suffix}")
        pattern = rf"(?<=FROM ){name}\b" if name == "sig" else rf"\b{name}\b"
        ctes = re.sub(pattern, new, ctes)
    return ctes


def query(sig: str | None, ctes: list[str], body: str) -> str:
    parts = [] if sig is None else [SIG[sig]]
    return "WITH RECURSIVE " + ",\n".join([*parts, *ctes]) + "\n" + body
