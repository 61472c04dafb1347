"""DuckDB SQL that recomputes encodings, levels and measures: what the registered queries are held against."""

from __future__ import annotations

LINES = "lineitem JOIN part ON l_partkey = p_partkey"
ORDERS = "JOIN orders ON l_orderkey = o_orderkey"


def _two(key: str, label: str, source: str) -> str:
    return f"SELECT DISTINCT ({key})::VARCHAR AS key, ({label})::VARCHAR AS label FROM {source} WHERE ({key}) IS NOT NULL AND ({label}) IS NOT NULL"


def _words(key: str, table: str) -> str:
    return f"SELECT DISTINCT {key}::VARCHAR AS key, w AS label FROM (SELECT {key}, unnest(string_split_regex(lower(text), '[^\\p{{L}}]+')) AS w FROM {table}) WHERE w <> ''"


def _attributes(key: str, source: str, items: list[str]) -> str:
    return f"SELECT DISTINCT key, label FROM (SELECT {key} AS key, unnest([{', '.join(items)}]) AS label FROM {source}) WHERE label IS NOT NULL"


ENCODINGS = {
    "e1": _two("l_orderkey", "l_partkey", "lineitem"),
    "e2": _two("l_orderkey", "p_brand", LINES),
    "e2b": _two("l_orderkey", "p_type", LINES),
    "e2c": _two("o_custkey", "p_brand", f"{LINES} {ORDERS}"),
    "e3": _attributes(
        "concat_ws('|', l_orderkey, l_linenumber, l_partkey, l_suppkey)",
        "lineitem",
        ["'rf=' || l_returnflag", "'ls=' || l_linestatus", "'ln=' || l_linenumber", "'q=' || floor(l_quantity / 10)::BIGINT", "'d=' || round(l_discount * 100)::INT", "'tx=' || round(l_tax * 100)::INT", "'y=' || year(l_shipdate)"],
    ),
    "e4": _words("doc_id", "documents"),
    "e5": _two("user_id || '|' || strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M')", "event_type", "events"),
    "e6": "SELECT vec_id::VARCHAR AS key, (i - 1)::VARCHAR AS label FROM (SELECT vec_id, embedding, unnest(range(1, len(embedding) + 1)) AS i FROM embeddings) WHERE embedding[i] > 0",
    "e7": _two("o_custkey", "l_suppkey", f"lineitem {ORDERS}"),
    "e8": "SELECT DISTINCT page_id::VARCHAR AS key, w AS label FROM (SELECT page_id, unnest(regexp_extract_all(lower(html), '<([a-z][a-z0-9]*)', 1)) AS w FROM pages)",
    "e9": _words("conv_id", "conversations"),
    "e10": _attributes("doc_id::VARCHAR", "labels JOIN documents USING (doc_id)", ["'quality=' || quality", "'toxic=' || toxic", "'lang=' || lang", "'source=' || source"]),
}


def levels(enc: str, theta: str, top: int, ids: bool = False) -> str:
    """WITH clause: p, n(n, s_min), f, b, and l1 .. l<top> (its, c): frequent itemsets by size, as sorted lists of labels,
    or of item numbers (by falling frequency, then label)."""
    name = "(row_number() OVER (ORDER BY count(*) DESC, label) - 1)::INT" if ids else "label"
    out = [
        f"WITH p AS ({ENCODINGS[enc]})",
        f"n AS (SELECT count(DISTINCT key) AS n, greatest(1, ceil({theta}::DECIMAL(18, 12) * count(DISTINCT key)))::BIGINT AS s_min FROM p)",
        f"f AS (SELECT label, {name} AS item, count(*) AS s FROM p GROUP BY label HAVING count(*) >= (SELECT s_min FROM n))",
        "b AS (SELECT key, item FROM p JOIN f USING (label))",
        "r1 AS (SELECT key, [item] AS its, item AS last FROM b)",
    ]
    for k in range(1, top + 1):
        if k > 1:
            out.append(f"r{k} AS (SELECT a.key, list_append(a.its, b.item) AS its, b.item AS last FROM (SELECT * FROM r{k - 1} SEMI JOIN l{k - 1} USING (its)) a JOIN b ON a.key = b.key AND b.item > a.last)")
        out.append(f"l{k} AS (SELECT its, count(*) AS c FROM r{k} GROUP BY its HAVING count(*) >= (SELECT s_min FROM n))")
    return ",\n".join(out)


def mined(enc: str, theta: str, top: int) -> str:
    return levels(enc, theta, top) + "\n" + " UNION ALL ".join(f"SELECT {k}::INT AS level, array_to_string(its, ',') AS itemset, c AS support FROM l{k}" for k in range(1, top + 1))


def all_levels(top: int) -> str:
    return ", a AS (" + " UNION ALL ".join(f"SELECT {k} AS level, its, c FROM l{k}" for k in range(1, top + 1)) + ")"


def compatible(k: int) -> str:
    """A subquery of the unordered compatible pairs of l<k>: its (sorted union), x, y."""
    return f"(SELECT list_sort(list_distinct(list_concat(x.its, y.its))) AS its, x.its AS x, y.its AS y FROM l{k} x JOIN l{k} y ON x.its < y.its AND len(list_distinct(list_concat(x.its, y.its))) = {k + 1})"


def text(column: str) -> str:
    return f"array_to_string({column}, ',')"
