"""DuckDB SQL of the corpora, clusters and indexes, from which the oracles are put together."""

from __future__ import annotations

_L = "concat_ws('|', l_orderkey, l_linenumber, l_partkey, l_suppkey, round(l_quantity)::BIGINT, round(l_extendedprice * 100)::BIGINT, round(l_discount * 100)::BIGINT, round(l_tax * 100)::BIGINT, l_returnflag, l_linestatus, strftime(l_shipdate, '%Y-%m-%d'))"
_O = "concat_ws('|', o_orderkey, o_custkey, o_orderstatus, round(o_totalprice * 100)::BIGINT, strftime(o_orderdate, '%Y-%m-%d'), o_orderpriority)"
_C = "concat_ws('|', c_custkey, c_name, c_nationkey, round(c_acctbal * 100)::BIGINT, c_mktsegment)"
_S = "concat_ws('|', s_suppkey, s_name, s_nationkey, round(s_acctbal * 100)::BIGINT)"
_P = "concat_ws('|', p_partkey, p_name, p_brand, p_type, p_size, round(p_retailprice * 100)::BIGINT)"
_LINES = f"(SELECT l_orderkey, l_partkey, l_suppkey, t AS text, l_orderkey * 1000 + row_number() OVER (PARTITION BY l_orderkey ORDER BY t) AS pair_ord FROM (SELECT l_orderkey, l_partkey, l_suppkey, {_L} AS t FROM lineitem))"
_VECTOR = "(SELECT vec_id, label, list_aggregate(list_transform(embedding, lambda x: round(x::DOUBLE * 1000000)::BIGINT::VARCHAR), 'string_agg', ',') AS media FROM embeddings)"
_TEXTS = "(SELECT text AS media, min(doc_id) AS src_id, length(text) AS n FROM documents GROUP BY text)"


def _captions(count: str, width: int) -> str:
    return f"SELECT src_id * 1000 + j AS pair_ord, media, j || ':' || substr(media, (1 + ((j - 1) * n) // k)::BIGINT, {width}) AS text FROM (SELECT *, {count} AS k FROM {_TEXTS}), range(1, 26) r(j) WHERE j <= k"


PAIRS: dict[str, str] = {
    "region_nations": "SELECT n_nationkey::BIGINT AS pair_ord, r_name AS media, n_name AS text FROM nation JOIN region ON n_regionkey = r_regionkey",
    "doc_cap5": _captions("5", 60),
    "doc_cap20": _captions("20", 48),
    "doc_caphyb": _captions("1 + n % 25", 48),
    "page_links": """SELECT page_id * 1000 + pos AS pair_ord, html AS media, link AS text FROM (SELECT page_id, html, unnest(links) AS link, generate_subscripts(links, 1) AS pos FROM (SELECT page_id, html, regexp_extract_all(html, 'href="([^"]*)"', 1) AS links FROM pages))""",
    "orders_lineitems": f"SELECT l.pair_ord, o.media, l.text FROM (SELECT o_orderkey, {_O} AS media FROM orders) o JOIN {_LINES} l ON o_orderkey = l_orderkey",
    "customer_orders": f"SELECT o_orderkey AS pair_ord, {_C} AS media, {_O} AS text FROM orders JOIN customer ON o_custkey = c_custkey",
    "part_lineitems": f"SELECT l.pair_ord, {_P} AS media, l.text FROM {_LINES} l JOIN part ON l_partkey = p_partkey",
    "supplier_lineitems": f"SELECT l.pair_ord, {_S} AS media, l.text FROM {_LINES} l JOIN supplier ON l_suppkey = s_suppkey",
    "user_events": "SELECT event_id AS pair_ord, 'user-' || user_id AS media, concat_ws('|', event_id, event_type, props) AS text FROM events",
    "conv_turns": "SELECT c.conv_id * 1000 + c.turn AS pair_ord, m.media, c.text FROM conversations c JOIN (SELECT conv_id, string_agg(text, chr(10) ORDER BY turn) AS media FROM conversations WHERE role = 'assistant' GROUP BY conv_id) m ON c.conv_id = m.conv_id WHERE c.role <> 'assistant'",
    "doc_copies": "SELECT doc_id AS pair_ord, text AS media, concat_ws('/', source, lang, doc_id) AS text FROM documents",
    "doc_labels": "SELECT d.doc_id AS pair_ord, d.text AS media, 'q' || quality || 't' || toxic AS text FROM documents d JOIN labels l ON d.doc_id = l.doc_id",
    "bench_hits": "SELECT doc_id * 1000 + item_id AS pair_ord, d.text AS media, b.text AS text FROM documents d JOIN benchmark b ON contains(d.text, b.text)",
    "pages_url": "SELECT page_id AS pair_ord, html AS media, url AS text FROM pages",
    "vec_label": f"SELECT vec_id AS pair_ord, media, label::VARCHAR AS text FROM {_VECTOR}",
    "docs_uni": "SELECT min(doc_id) AS pair_ord, text AS media, NULL::VARCHAR AS text FROM documents GROUP BY documents.text",
    "bench_uni": "SELECT min(item_id) AS pair_ord, text AS media, NULL::VARCHAR AS text FROM benchmark GROUP BY benchmark.text",
    "vec_uni": f"SELECT min(vec_id) AS pair_ord, media, NULL::VARCHAR AS text FROM {_VECTOR} GROUP BY media",
}


def clusters(name: str) -> str:
    return f"SELECT md5(media) AS fingerprint, strlen(media)::BIGINT AS media_bytes, min(pair_ord)::BIGINT AS rep_ord, count(text)::BIGINT AS n_texts, coalesce(sum(strlen(text)), 0)::BIGINT AS text_bytes, count(*)::BIGINT AS n_copies FROM ({PAIRS[name]}) GROUP BY 1, 2"


_LEN = "(8 + media_bytes + text_bytes + 4 * n_texts)"


def index(name: str, order: str = "rep_ord, fingerprint") -> str:
    uni = name.endswith("_uni")
    owned = "1" if uni else "n_texts"
    w = f"OVER (ORDER BY {order} ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)"
    return f"SELECT *, (row_number() OVER (ORDER BY {order}) - 1)::BIGINT AS bundle_id, (sum({owned}) {w} - {owned})::BIGINT AS start_idx, (sum({owned}) {w} - 1)::BIGINT AS end_idx, (sum({_LEN}) {w} - {_LEN})::BIGINT AS byte_offset, {_LEN}::BIGINT AS byte_len FROM ({clusters(name)})"


def stats(names) -> str:
    one = f"SELECT '{{n}}' AS corpus, CASE WHEN max(n_texts) = 0 THEN 'uni_modal' WHEN min(n_texts) = 1 AND max(n_texts) = 1 THEN 'one_to_one' WHEN min(n_texts) = max(n_texts) THEN 'fixed' ELSE 'hybrid' END AS kind, (CASE WHEN max(n_texts) = 0 THEN count(*) ELSE sum(n_texts) END)::BIGINT AS n_pairs, count(*)::BIGINT AS n_bundles, sum(media_bytes)::BIGINT AS media_bytes, sum(text_bytes)::BIGINT AS text_bytes, sum(greatest(n_texts, 1) * media_bytes)::BIGINT AS dup_bytes, sum({_LEN})::BIGINT AS body_bytes, sum(greatest(n_texts, 1) * {_LEN})::BIGINT AS touched_bytes FROM ({{c}})"
    return " UNION ALL ".join(one.format(n=n, c=clusters(n)) for n in names)


_W = "(CASE WHEN kind = 'hybrid' THEN 16 ELSE 4 END)"


def storage(names, scale: int = 1) -> str:
    return f"""SELECT corpus, n_pairs, media_bytes, dup_bytes, text_bytes, layout, files, (body + files * 4096)::BIGINT AS storage_bytes, body::BIGINT AS body FROM (
SELECT *, unnest(['loose', 'path_table', 'pair_record', 'bundle']) AS layout,
  unnest([n_pairs * 2, n_bundles + 1, 1, 1]) AS files,
  unnest([dup_bytes * {scale} + text_bytes, media_bytes * {scale} + text_bytes, dup_bytes * {scale} + text_bytes + n_pairs * 4, media_bytes * {scale} + text_bytes + n_bundles * {_W}]) AS body
FROM ({stats(names)}))"""


def index_bytes(names) -> str:
    return f"""SELECT corpus, kind, n_pairs, n_bundles, unnest(['loose', 'path_table', 'pair_record', 'bundle', 'bundle_hash']) AS layout,
  unnest([0, text_bytes + n_pairs * 4, n_pairs * 4, n_bundles * {_W}, n_pairs * 8 + n_bundles * 4])::BIGINT AS index_bytes FROM ({stats(names)})"""


def load_rate(names, scale: int = 1, cached: bool = True, fetch: str = "object", shares: str = "range(10, 101, 10)") -> str:
    """The default profile: 0.5 ms to open, 0.1 ms to seek, 500 and 8000 MB a second."""
    d = f"(dup_bytes * {scale})"
    pair = f"({d} + text_bytes) / n_pairs"
    grown = f"(touched_bytes + dup_bytes * {scale - 1}) / n_pairs" if fetch == "object" else pair
    reuse = "(1 - n_bundles / n_pairs)"
    hits = f"[0.0, share / 100 * {reuse}, 0.0, {'share / 100 * ' + reuse if fetch == 'object' else '0.0'}]" if cached else "[0.0, 0.0, 0.0, 0.0]"
    return f"""SELECT corpus, kind, n_pairs, n_bundles, share, layout, 1000 / (opens * 0.5 + (1 - hit) * (0.1 + mb / 500.0 * 1000) + hit * (mb / 8000.0 * 1000)) AS rate FROM (
SELECT corpus, kind, n_pairs, n_bundles, share, unnest(['loose', 'path_table', 'pair_record', 'bundle']) AS layout, unnest([2, 1, 0, 0]) AS opens, unnest({hits}::DOUBLE[]) AS hit,
  unnest([{pair}, {d} / n_pairs, {pair}, {grown}]::DOUBLE[]) / 1000000 AS mb FROM ({stats(names)}), {shares} s(share))"""


def write_rate(names, scale: int = 1) -> str:
    return f"SELECT corpus, layout, files, body, n_pairs, n_pairs / (files * 5.0 / 1000 + body / 1e6 / 200.0) AS rate FROM ({storage(names, scale)})"


def samples(name: str, order: str = "rep_ord, fingerprint") -> str:
    """sample_id, bundle_id, text_pos, offsets."""
    return f"SELECT start_idx + p AS sample_id, bundle_id, p AS text_pos, byte_offset, byte_len FROM ({index(name, order)}), range(0, 2000) r(p) WHERE p <= end_idx - start_idx"


def epoch(name: str, order: str = "rep_ord, fingerprint", seed: int = 42, number: int = 0) -> str:
    return f"SELECT (row_number() OVER (ORDER BY md5('{seed}|{number}|' || sample_id), sample_id) - 1)::BIGINT AS step, * FROM ({samples(name, order)})"


def distances(name: str, order: str = "fingerprint, media_bytes") -> str:
    """Recency distances of bundles over a shuffled epoch, by definition."""
    return f"""SELECT a.step, a.bundle_id, a.byte_len, CASE WHEN a.prev IS NOT NULL THEN coalesce((SELECT sum(b.byte_len) FROM acc b WHERE b.step > a.prev AND b.step < a.step AND coalesce(b.prev, -1) <= a.prev), 0) END AS distance
FROM acc a""", f"acc AS (SELECT step, bundle_id, byte_len, lag(step) OVER (PARTITION BY bundle_id ORDER BY step) AS prev FROM ({epoch(name, order)}))"
