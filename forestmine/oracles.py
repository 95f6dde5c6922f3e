"""DuckDB SQL for the registered queries: forests by windows, mining by explicit occurrences.

The mining SQL keeps one row for each occurrence with the path's upper bounds as a
list and never merges, so it checks the record joins from another side.
"""

from __future__ import annotations

from . import pattern as pt
from .sources.generator import INCREMENT, MODULUS, MULTIPLIER, level_sizes
from .sources.tables import EVENT_RANKS, ITEM_ORDER, LEAVES

_ITEMS = f"(SELECT *, row_number() OVER (PARTITION BY l_orderkey ORDER BY {', '.join(ITEM_ORDER)}) AS pos FROM lineitem)"


def _numbered(rows: str, order: str, depth: str = "level", levels: int = 7) -> str:
    """Scopes of rows (tree_id, level, label, order columns): a scope ends before the next row of a level not above its own."""
    ends = " ".join(f"WHEN {d} THEN min(CASE WHEN level <= {d} THEN lo END) OVER later" for d in range(levels))
    counted = "level" if depth == "level" else "lo - (SELECT count(*) FROM e f WHERE f.tree_id = e.tree_id AND f.hi < e.lo)"
    return f"""(WITH r AS ({rows}), n AS (SELECT *, row_number() OVER (PARTITION BY tree_id ORDER BY {order}) - 1 AS lo, count(*) OVER (PARTITION BY tree_id) AS size FROM r),
 e AS (SELECT tree_id, lo, coalesce(CASE level {ends} END - 1, size - 1) AS hi, level, label FROM n WINDOW later AS (PARTITION BY tree_id ORDER BY lo ROWS BETWEEN 1 FOLLOWING AND UNBOUNDED FOLLOWING))
 SELECT CAST(tree_id AS BIGINT) AS tree_id, CAST(lo AS INTEGER) AS lo, CAST(hi AS INTEGER) AS hi, CAST({counted} AS INTEGER) AS depth, label FROM e)"""


_SESSION_EVENTS = """(SELECT *, last_value(first IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS tree_id FROM
 (SELECT *, CASE WHEN lag(ts) OVER u IS NULL OR epoch_us(ts) - epoch_us(lag(ts) OVER u) > 86400000000 THEN event_id END AS first FROM events WINDOW u AS (PARTITION BY user_id ORDER BY ts, event_id)))"""
_RANKS = " ".join(f"WHEN '{k}' THEN {v}" for k, v in EVENT_RANKS.items())
_SESSIONS = f"""SELECT tree_id, ts, -1 AS event_id, 'session' AS label, 'infinity'::DOUBLE AS value, 0 AS level FROM {_SESSION_EVENTS} WHERE first IS NOT NULL
 UNION ALL SELECT tree_id, ts, event_id, event_type, value, CASE event_type {_RANKS} ELSE 6 END FROM {_SESSION_EVENTS}"""
_USER_EVENTS = "(SELECT *, first_value(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS tree_id FROM events)"
_LEAVES = ", ".join(f"'{x}'" for x in LEAVES)

_URL = r"^https?://(?:([^./]+)\.)?([^./]+\.example\.[a-z]+)/([^/?#]*)"
_PAGES = f"""(SELECT page_id, regexp_extract(url, '{_URL}', 1) AS host, regexp_extract(url, '{_URL}', 3) AS lang, min(page_id) OVER (PARTITION BY regexp_extract(url, '{_URL}', 2)) AS tree_id,
 CASE WHEN contains(url, '#') THEN 'anchor' WHEN contains(url, '?') THEN 'query' WHEN ends_with(url, '.html') THEN 'html' WHEN ends_with(url, '/') THEN 'slash' ELSE 'plain' END AS kind FROM pages WHERE regexp_matches(url, '{_URL}'))"""

FORESTS = {
    "urls": _numbered(
        f"""SELECT DISTINCT tree_id, '' AS host, '' AS lang, -1 AS page, 0 AS level, 'site' AS label FROM {_PAGES}
 UNION ALL SELECT DISTINCT tree_id, host, '', -1, 1, 'host:' || host FROM {_PAGES}
 UNION ALL SELECT DISTINCT tree_id, host, lang, -1, 2, 'lang:' || lang FROM {_PAGES}
 UNION ALL SELECT tree_id, host, lang, page_id, 3, 'page:' || kind FROM {_PAGES}""",
        "host, lang, page, level",
    ),
    "orders": _numbered(
        f"""SELECT o_orderkey AS tree_id, 0 AS pos, 0 AS level, 'O:' || o_orderstatus AS label FROM orders
 UNION ALL SELECT l_orderkey, pos, 1, 'F:' || l_returnflag FROM {_ITEMS} WHERE l_orderkey IN (SELECT o_orderkey FROM orders)
 UNION ALL SELECT l_orderkey, pos, 2, 'T:' || p_type FROM {_ITEMS} JOIN part ON l_partkey = p_partkey WHERE l_orderkey IN (SELECT o_orderkey FROM orders)""",
        "pos, level",
    ),
    "customers": _numbered(
        f"""SELECT c_custkey AS tree_id, -1 AS o, 0 AS pos, 0 AS level, 'C:' || c_mktsegment AS label FROM customer
 UNION ALL SELECT o_custkey, o_orderkey, 0, 1, 'O:' || o_orderstatus FROM orders JOIN customer ON o_custkey = c_custkey
 UNION ALL SELECT o_custkey, o_orderkey, pos, 2, 'F:' || l_returnflag || l_linestatus FROM {_ITEMS} JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey""",
        "o, pos",
    ),
    "regions": _numbered(
        """SELECT r_regionkey AS tree_id, -1 AS k1, -1 AS k2, -1 AS k3, 0 AS level, 'R' AS label FROM region
 UNION ALL SELECT n_regionkey, n_nationkey, -1, -1, 1, 'nation' FROM nation JOIN region ON n_regionkey = r_regionkey
 UNION ALL SELECT n_regionkey, n_nationkey, c_custkey, -1, 2, 'C:' || c_mktsegment FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey
 UNION ALL SELECT n_regionkey, n_nationkey, c_custkey, o_orderkey, 3, 'O:' || o_orderstatus FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey""",
        "k1, k2, k3",
    ),
    "library": _numbered(
        f"""SELECT c_custkey AS tree_id, -1 AS o, 0 AS pos, 0 AS level, 'customer' AS label FROM customer
 UNION ALL SELECT o_custkey, o_orderkey, 0, 1, 'order' FROM orders JOIN customer ON o_custkey = c_custkey
 UNION ALL SELECT o_custkey, o_orderkey, pos, 2, 'T:' || p_type FROM {_ITEMS} JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN part ON l_partkey = p_partkey
 UNION ALL SELECT o_custkey, o_orderkey, pos, 3, 'B:' || replace(p_brand, '#', '') FROM {_ITEMS} JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN part ON l_partkey = p_partkey""",
        "o, pos, level",
    ),
    "sessions_rank": _numbered(_SESSIONS, "ts, event_id", "count"),
    "users": _numbered(
        f"""SELECT tree_id, ts, -1 AS event_id, 'session' AS label, 0 AS level FROM {_USER_EVENTS} WHERE event_id = tree_id
 UNION ALL SELECT tree_id, ts, event_id, event_type, CASE event_type {_RANKS} ELSE 6 END FROM {_USER_EVENTS}""",
        "ts, event_id", "count",
    ),
    "sessions_value": f"""(WITH r AS ({_SESSIONS}), n AS (SELECT *, row_number() OVER (PARTITION BY tree_id ORDER BY ts, event_id) - 1 AS lo, count(*) OVER (PARTITION BY tree_id) AS size FROM r),
 e AS (SELECT a.tree_id, a.lo, a.label, coalesce(min(b.lo) - 1, any_value(a.size) - 1) AS hi FROM n a LEFT JOIN n b ON a.tree_id = b.tree_id AND b.lo > a.lo AND b.value >= a.value GROUP BY a.tree_id, a.lo, a.label)
 SELECT CAST(tree_id AS BIGINT) AS tree_id, CAST(lo AS INTEGER) AS lo, CAST(hi AS INTEGER) AS hi, CAST(lo - (SELECT count(*) FROM e f WHERE f.tree_id = e.tree_id AND f.hi < e.lo) AS INTEGER) AS depth, label FROM e)""",
    "conversations": _numbered(
        """SELECT DISTINCT conv_id AS tree_id, -1 AS turn, 0 AS level, 'conv' AS label FROM conversations
 UNION ALL SELECT conv_id, turn, CASE role WHEN 'assistant' THEN 2 ELSE 1 END, role FROM conversations""",
        "turn, level, label", "count",
    ),
    "pages_flat": rf"""(WITH h AS (SELECT page_id AS tree_id, regexp_extract_all(regexp_replace(regexp_replace(regexp_replace(lower(html), '<!--.*?-->', '', 'gs'), '(<script[^>]*>).*?(</script>)', '\1\2', 'gs'), '(<style[^>]*>).*?(</style>)', '\1\2', 'gs'), '</?[a-z][a-z0-9]*') AS tags FROM pages),
 u AS (SELECT tree_id, unnest(tags) AS tag, unnest(range(len(tags))) AS pos FROM h),
 t AS (SELECT tree_id, pos, regexp_replace(tag, '[</]', '', 'g') AS label, starts_with(tag, '</') AS closing FROM u),
 k AS (SELECT *, CASE WHEN closing THEN 'close' WHEN label IN ({_LEAVES}) THEN 'leaf' ELSE 'open' END AS kind FROM t WHERE NOT (closing AND label IN ({_LEAVES}))),
 s AS (SELECT *, sum(CASE kind WHEN 'open' THEN 1 WHEN 'close' THEN -1 ELSE 0 END) OVER up AS nest, sum(CASE WHEN kind <> 'close' THEN 1 ELSE 0 END) OVER up AS seen, sum(CASE WHEN kind <> 'close' THEN 1 ELSE 0 END) OVER (PARTITION BY tree_id) AS n
  FROM k WINDOW up AS (PARTITION BY tree_id ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)),
 l AS (SELECT *, CASE kind WHEN 'close' THEN nest + 1 WHEN 'open' THEN nest ELSE -pos - 1 END AS level FROM s),
 c AS (SELECT *, lead(seen) OVER (PARTITION BY tree_id, level ORDER BY pos) AS ends FROM l)
 SELECT CAST(tree_id AS BIGINT) AS tree_id, CAST(seen - 1 AS INTEGER) AS lo, CAST(CASE WHEN kind = 'leaf' THEN seen - 1 ELSE coalesce(ends - 1, n - 1) END AS INTEGER) AS hi, CAST(CASE WHEN kind = 'leaf' THEN nest ELSE nest - 1 END AS INTEGER) AS depth, label FROM c WHERE kind <> 'close')""",
    "outlines": _numbered(
        r"""SELECT doc_id AS tree_id, -1 AS i, -1 AS j, 0 AS level, 'doc:' || lang AS label FROM documents
 UNION ALL SELECT doc_id, i, -1, 1, 'line:' || CASE WHEN length(line) = 0 THEN 'empty' WHEN length(line) < 40 THEN 'short' WHEN length(line) < 200 THEN 'mid' ELSE 'long' END FROM
  (SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line, unnest(range(len(string_split(coalesce(text, ''), chr(10))))) AS i FROM documents)
 UNION ALL SELECT doc_id, i, j, 2, 'sent:' || CASE WHEN length(s) < 20 THEN 'short' WHEN length(s) < 60 THEN 'mid' ELSE 'long' END FROM
  (SELECT doc_id, i, unnest(string_split(line, '.')) AS s, unnest(range(len(string_split(line, '.')))) AS j FROM
   (SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line, unnest(range(len(string_split(coalesce(text, ''), chr(10))))) AS i FROM documents)) WHERE trim(s, ' ') <> ''""",
        "i, j",
    ),
}


def _hashed(*values: str) -> str:
    h = "CAST(17 AS BIGINT)"
    for v in values:
        for _ in range(2):
            h = f"((({h} + {v}) * {MULTIPLIER} + {INCREMENT}) % {MODULUS})"
        h = f"(({h} >> 3) + ({h} % 8) * {MODULUS // 8})"
    return h


def master(n_labels: int, vertices: int, depth: int, fan_out: int, seed: int = 1) -> str:
    """The synthetic master tree: id, parent, slot, depth, label."""
    sizes = level_sizes(vertices, depth, fan_out)
    rows = ", ".join(f"({d}, {sum(sizes[:d])}, {n}, {sum(sizes[: d - 1]) if d else 0}, {(sizes[d - 1] if d else 1) * fan_out})" for d, n in enumerate(sizes))
    return f"""SELECT id, CASE WHEN depth > 0 THEN above + place // {fan_out} END AS parent, CAST(CASE WHEN depth > 0 THEN place % {fan_out} ELSE 0 END AS INTEGER) AS slot, depth, 's' || ({_hashed(str(seed + 1), 'id')} % {n_labels}) AS label
FROM (SELECT *, (i * slots * 1024 + {_hashed(str(seed), 'id')} % 1024 * (slots - size)) // (size * 1024) AS place FROM
 (SELECT CAST(depth AS INTEGER) AS depth, CAST(size AS BIGINT) AS size, CAST(above AS BIGINT) AS above, CAST(slots AS BIGINT) AS slots, CAST(unnest(range(size)) AS BIGINT) AS i, CAST(first + unnest(range(size)) AS BIGINT) AS id FROM (VALUES {rows}) l(depth, first, size, above, slots)))"""


def master_of(table: str, key: str, n_labels: int, depth: int, fan_out: int, seed: int = 1) -> str:
    """A master tree of a table's rows: id, parent, slot, depth, label."""
    hashed = lambda x: f"(({_hashed(str(x), f'(key % {MODULUS})')}) % {{0}} + {{0}}) % {{0}}"
    return f"""SELECT id, CASE WHEN depth > 0 THEN above + place // fan END AS parent, CAST(CASE WHEN depth > 0 THEN place % fan ELSE 0 END AS INTEGER) AS slot, depth, 's' || ({hashed(seed + 1).format(n_labels)}) AS label FROM
 (WITH RECURSIVE k AS MATERIALIZED (SELECT CAST({key} AS BIGINT) AS key, CAST(row_number() OVER (ORDER BY {key}) - 1 AS BIGINT) AS id FROM {table} WHERE {key} IS NOT NULL), n AS (SELECT count(*) AS n FROM k),
 b AS (SELECT 0 AS i, CAST(0 AS DOUBLE) AS low, CAST(greatest(n, {fan_out}) AS DOUBLE) AS high FROM n
  UNION ALL SELECT i + 1, CASE WHEN less THEN ratio ELSE low END, CASE WHEN less THEN high ELSE ratio END FROM (SELECT i, low, high, (low + high) / 2 AS ratio, list_sum(list_transform(range({depth + 1}), lambda d: pow((low + high) / 2, d))) < n AS less FROM b, n WHERE i < 80)),
 z AS (SELECT CAST(d AS INTEGER) AS depth, greatest(1, CAST(floor(pow(high, d) + 0.5) AS BIGINT)) AS size FROM (SELECT high FROM b WHERE i = 80), range({depth}) r(d)),
 s AS (SELECT * FROM z UNION ALL SELECT {depth}, CAST(greatest(1, n - (SELECT coalesce(sum(size), 0) FROM z)) AS BIGINT) FROM n),
 l AS (SELECT *, CAST(coalesce(sum(size) OVER (ORDER BY depth ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS first, lag(size, 1, CAST(1 AS BIGINT)) OVER (ORDER BY depth) AS up FROM s),
 f AS (SELECT *, greatest({fan_out}, (size + up - 1) // up) AS fan, coalesce(lag(first) OVER (ORDER BY depth), 0) AS above FROM l)
 SELECT id, key, depth, fan, above, ((id - first) * up * fan * 1024 + {hashed(seed).format(1024)} * (up * fan - size)) // (size * 1024) AS place FROM k JOIN f ON id >= first AND id < first + size)"""


def browsing(tree: str, depth: int, n_trees: int, keep_percent: int, seed: int = 7) -> str:
    """Subtrees of the master as a numbered forest."""
    rows = f"""WITH RECURSIVE mt AS MATERIALIZED ({tree}), bt AS (SELECT t.tree_id, id, label, [slot] AS path, 0 AS level FROM mt, (SELECT unnest(range({n_trees})) AS tree_id) t WHERE depth = 0
 UNION ALL SELECT bt.tree_id, mt.id, mt.label, list_append(bt.path, mt.slot), bt.level + 1 FROM bt JOIN mt ON mt.parent = bt.id WHERE {_hashed(str(seed), 'bt.tree_id', 'mt.id')} % 100 < {keep_percent})
 SELECT tree_id, path, level, label FROM bt"""
    return f"SELECT * FROM {_numbered(rows, 'path', levels=depth + 1)}"


def forest(name: str) -> str:
    return f"SELECT * FROM {FORESTS[name]}"


def stats(name: str) -> str:
    return f"""WITH v AS MATERIALIZED ({forest(name)}), t AS (SELECT tree_id, count(*) AS n, max(depth) AS d FROM v GROUP BY tree_id)
SELECT count(*) AS n_trees, CAST(sum(n) AS BIGINT) AS n_vertices, max(n) AS max_size, CAST(max(d) AS BIGINT) AS max_depth, 2 * max(n) - 1 AS max_encoded, CAST(sum(2 * n - 1) AS BIGINT) AS sum_encoded, (SELECT count(DISTINCT label) FROM v) AS n_labels FROM t"""


def _safe(label: str = "label") -> str:
    return f"replace(replace(replace({label}, '%', '%25'), ' ', '%20'), '@', '%40')"


def minsup_sql(minsup: int | tuple[int, int]) -> str:
    return str(minsup) if isinstance(minsup, int) else f"(SELECT greatest(1, count(DISTINCT tree_id) * {minsup[0]} // {minsup[1]}) FROM v)"


def occurrences(source: str, minsup: int | tuple[int, int], k: int, rule: str = "prefix", support: str = "occurrence") -> str:
    """CTEs o1..ok (one row an occurrence: tree_id, lo, hi, rp, code, prefix) and f1..fk (frequent codes)."""
    measure = "tree_support" if support == "tree" else "support"
    out = f"WITH v AS MATERIALIZED ({source}), m AS (SELECT {minsup_sql(minsup)} AS minsup),\nb1 AS (SELECT tree_id, lo, hi, [hi] AS rp, {_safe()} || '@0' AS code, '' AS prefix, {_safe()} AS last, 0 AS c FROM v)"
    for n in range(1, k + 1):
        if n > 1:
            out += f""",\nb{n} AS (SELECT tree_id, lo, hi, list_append(rp[1:c], hi) AS rp, prefix || ' ' || last || '@' || c AS code, prefix, last, c - 1 AS c FROM
 (SELECT o.tree_id, x.lo, x.hi, o.rp, o.code AS prefix, {_safe('x.label')} AS last, len(list_filter(o.rp, lambda u: u >= x.lo)) AS c FROM o{n - 1} o JOIN v x ON x.tree_id = o.tree_id AND x.lo > o.lo AND x.lo <= o.rp[1] JOIN f1 ON f1.code = {_safe('x.label')} || '@0'))"""
        keep = ""
        if n == 3 and rule == "class":
            keep = " AND split_part(code, ' ', 1) || ' ' || last || '@1' IN (SELECT code FROM f2)"
        if n == 3 and rule == "all":
            keep = " AND split_part(code, ' ', 1) || ' ' || last || '@1' IN (SELECT code FROM f2) AND (c = 0 OR replace(split_part(code, ' ', 2), '@1', '@0') || ' ' || last || '@1' IN (SELECT code FROM f2))"
        out += f""",\nf{n} AS MATERIALIZED (SELECT code, count(*) AS support, count(DISTINCT tree_id) AS tree_support FROM b{n} WHERE true{keep} GROUP BY code HAVING {measure} >= (SELECT minsup FROM m)),
o{n} AS (SELECT * FROM b{n} WHERE code IN (SELECT code FROM f{n}))"""
    return out


def mine(source: str, minsup: int | tuple[int, int], k: int, rule: str = "prefix", support: str = "occurrence") -> str:
    rows = " UNION ALL ".join(f"SELECT CAST({n} AS BIGINT) AS size, code, CAST(support AS BIGINT) AS support, CAST(tree_support AS BIGINT) AS tree_support FROM f{n}" for n in range(1, k + 1))
    return f"{occurrences(source, minsup, k, rule, support)}\n{rows}"


def records_of(source: str, minsup: int | tuple[int, int], k: int) -> str:
    """All canonical records of frequent patterns."""
    rows = " UNION ALL ".join(f"SELECT code, tree_id, CAST(lo AS BIGINT) AS lo, CAST(hi AS BIGINT) AS hi, array_to_string(rp, ',') AS rp, count(*) AS mult FROM o{n} GROUP BY ALL" for n in range(1, k + 1))
    return f"{occurrences(source, minsup, k)}\n{rows}"


def count_pattern(source: str, code: str, edges: str = "embedded") -> str:
    """(tree_id, n_occ) by a join of all vertices of a pattern; edges: 'embedded', 'isomorphic' or 'homomorphic'."""
    nodes = pt.parse(code)
    parent = {i: pt.rightmost_path(nodes[: i + 1])[-2] for i in range(1, len(nodes))}
    above = {i: pt.rightmost_path(nodes[: i + 1])[:-1] for i in range(len(nodes))}
    frm, where = [], []
    for i, (label, _) in enumerate(nodes):
        frm.append(f"v v{i}")
        where.append(f"v{i}.label = '{pt.unescape(label)}'")
        if i:
            where.append(f"v{i}.tree_id = v0.tree_id")
            if edges == "homomorphic":
                where.append(f"v{i}.lo >= v{i - 1}.lo")
            else:
                where += [f"v{i}.lo > v{i - 1}.lo", *(f"v{i}.lo {'<=' if a in above[i] else '>'} v{a}.hi" for a in range(i))]
            if edges != "embedded":
                p = parent[i]
                where.append(f"v{i}.lo > v{p}.lo AND v{i}.hi <= v{p}.hi AND v{i}.depth = v{p}.depth + 1")
    return f"WITH v AS MATERIALIZED ({source}) SELECT v0.tree_id AS tree_id, count(*) AS n_occ FROM {', '.join(frm)} WHERE {' AND '.join(where)} GROUP BY v0.tree_id"
