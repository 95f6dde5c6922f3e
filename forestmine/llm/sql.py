"""DuckDB SQL for the operators of this folder that SQL can express."""

from __future__ import annotations

from .mixing import DIMENSIONS, SWEEPS, TEMPER

_WORDS = r"list_filter(regexp_split_to_array({text}, '[\x20\x09-\x0D]+'), lambda x: x <> '')"


def _lower(text: str) -> str:
    return f"translate({text}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"


NEAR_DUP = f"""
WITH RECURSIVE w AS (SELECT doc_id, {_WORDS.format(text=_lower("coalesce(text, '')"))} AS w FROM documents),
s AS (SELECT doc_id, CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 4 THEN [array_to_string(w, ' ')]
      ELSE list_distinct(list_transform(range(1, len(w) - 2), lambda i: array_to_string(w[i:i + 3], ' '))) END AS s FROM w),
n AS (SELECT doc_id, CAST(len(s) AS BIGINT) AS n FROM s),
e AS (SELECT doc_id, n, unnest(s) AS g FROM s JOIN n USING (doc_id)),
p AS (SELECT a.doc_id AS x, b.doc_id AS y FROM e a JOIN e b ON a.g = b.g AND a.doc_id < b.doc_id
      GROUP BY a.doc_id, b.doc_id, a.n, b.n HAVING 100 * count(*) >= 80 * (a.n + b.n - count(*))),
l AS (SELECT x, y FROM p UNION SELECT y, x FROM p),
r AS (SELECT doc_id AS a, doc_id AS b FROM n UNION SELECT r.a, l.y FROM r JOIN l ON r.b = l.x)
SELECT n.doc_id, n.n AS n_shingles, c.b AS component_id, n.doc_id = c.b AS kept
FROM n JOIN (SELECT a, min(b) AS b FROM r GROUP BY a) c ON n.doc_id = c.a
"""

SUBSTRING_DEDUP = f"""
WITH w AS (SELECT doc_id, {_WORDS.format(text="coalesce(text, '')")} AS w FROM documents),
v AS (SELECT doc_id, unnest(range(1, len(w) - 11)) AS i, w FROM w WHERE len(w) >= 13),
g AS (SELECT doc_id, i, array_to_string(w[i:i + 12], ' ') AS g FROM v),
f AS (SELECT g, min(doc_id) AS least FROM g GROUP BY g HAVING min(doc_id) < max(doc_id)),
c AS (SELECT DISTINCT doc_id, unnest(range(i, i + 13)) AS j FROM g JOIN f USING (g) WHERE doc_id > least),
r AS (SELECT doc_id, list(j) AS gone FROM c GROUP BY doc_id),
k AS (SELECT w.doc_id, len(w.w) AS n, coalesce(len(r.gone), 0) AS gone,
      array_to_string(list_transform(list_filter(range(1, len(w.w) + 1), lambda j: NOT list_contains(coalesce(r.gone, []), j)), lambda j: w.w[j]), ' ') AS kept
      FROM w LEFT JOIN r ON w.doc_id = r.doc_id)
SELECT doc_id, CAST(n AS BIGINT) AS n_words, CAST(gone AS BIGINT) AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256 FROM k
"""

TOP_K = """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(64 * CAST(x AS DOUBLE)) AS BIGINT)) AS v FROM embeddings
  WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (SELECT q.vec_id AS query_id, c.vec_id, CAST(list_sum(list_transform(range(1, len(q.v) + 1), lambda i: q.v[i] * c.v[i])) AS BIGINT) AS score
  FROM v q JOIN v c ON q.vec_id <> c.vec_id WHERE q.vec_id % 20 = 0),
r AS (SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank, vec_id, score FROM s)
SELECT * FROM r WHERE rank <= 20
"""


def mixing_sql() -> str:
    """The raking rounds, unrolled."""
    text = "coalesce(text, '')"
    of = lambda characters: f"(length({text}) - length(translate({text}, '{characters}', '')))"
    out = f"""WITH d AS (SELECT doc_id, coalesce(source, '') AS source, coalesce(lang, '') AS lang,
CASE WHEN 20 * {of('#*$%&|<>')} > length({text}) THEN 'symbols' WHEN 20 * {of('0123456789')} > length({text}) THEN 'numbers'
WHEN 10 * {of('ABCDEFGHIJKLMNOPQRSTUVWXYZ')} > 4 * length({text}) THEN 'headline' ELSE 'prose' END AS topic,
CAST(len({_WORDS.format(text=text)}) AS BIGINT) AS n_tokens FROM documents),
c AS (SELECT source, lang, topic, CAST(sum(n_tokens) AS DOUBLE) AS weight FROM d GROUP BY ALL)"""
    now = {}
    for d in DIMENSIONS:
        out += f",\nt_{d} AS (SELECT {d}, p / sum(p) OVER () AS share FROM (SELECT {d}, CASE WHEN sum(weight) > 0 THEN pow(sum(weight), {TEMPER[d]}) ELSE 0 END AS p FROM c GROUP BY {d}))"
        out += f",\nf_{d} AS (SELECT DISTINCT {d}, 1.0::DOUBLE AS f FROM c)"
        now[d] = f"f_{d}"
    for k in range(SWEEPS):
        for d in DIMENSIONS:
            a, b = (e for e in DIMENSIONS if e != d)
            out += f""",
f_{d}_{k} AS MATERIALIZED (SELECT s.{d}, CASE WHEN s.w > 0 THEN t.share / s.w ELSE 0 END AS f FROM
 (SELECT c.{d}, sum(c.weight * a.f * b.f) AS w FROM c JOIN {now[a]} a ON c.{a} = a.{a} JOIN {now[b]} b ON c.{b} = b.{b} GROUP BY c.{d}) s JOIN t_{d} t ON s.{d} = t.{d})"""
            now[d] = f"f_{d}_{k}"
    x, y, z = DIMENSIONS
    return out + f""",
r AS (SELECT c.{x}, c.{y}, c.{z}, CASE WHEN c.weight > 0 THEN a.f * b.f * e.f END AS p FROM c JOIN {now[x]} a ON c.{x} = a.{x} JOIN {now[y]} b ON c.{y} = b.{y} JOIN {now[z]} e ON c.{z} = e.{z}),
o AS (SELECT d.*, CAST(round(coalesce(r.p, 0) / (SELECT max(p) FROM r) * 1000000) AS BIGINT) AS ppm FROM d JOIN r USING ({x}, {y}, {z}))
SELECT doc_id, {x}, {y}, {z}, n_tokens, ppm, CAST('0x' || substr(md5(CAST(doc_id AS VARCHAR)), 1, 8) AS BIGINT) % 1000000 < ppm AS selected FROM o"""


#: The base columns of operators whose other columns SQL can't express.
LICENSE_BASE = f"""
WITH w AS (SELECT doc_id, regexp_extract_all({_lower("coalesce(text, '')")}, '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+') AS w FROM documents),
p AS (SELECT doc_id, w, list_filter(range(1, len(w) + 1), lambda i: w[i] = 'mit' AND coalesce(w[i + 1] = 'license', false)) AS mit,
      list_filter(range(1, len(w) + 1), lambda i: w[i] = 'apache' AND coalesce(w[i + 1] = 'license', false)) AS apache,
      list_filter(range(1, len(w) + 1), lambda i: w[i] = 'general' AND coalesce(w[i + 1] = 'public' AND w[i + 2] = 'license', false)) AS gpl FROM w)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(len(mit) + len(apache) + len(gpl) AS BIGINT) AS n_base, list_min(list_concat(mit, apache, gpl)) - 1 AS first_word, list_max(list_concat(mit, apache, gpl)) - 1 AS last_word,
 array_to_string(list_filter([CASE WHEN len(apache) > 0 THEN 'apache' END, CASE WHEN len(gpl) > 0 THEN 'gpl' END, CASE WHEN len(mit) > 0 THEN 'mit' END], lambda x: x IS NOT NULL), ',') AS base_labels FROM p
"""

_CRC = """CAST(xor(list_reduce(list_prepend(4294967295::BIGINT, list_transform(string_split({text}, ''), lambda c: CAST(ascii(c) AS BIGINT))), lambda a, c: xor(a >> 8, t[(xor(a, c) & 255) + 1])), 4294967295::BIGINT) AS BIGINT)"""

LM_BASE = f"""
WITH t AS (SELECT list_transform(range(256), lambda i: list_reduce([CAST(i AS BIGINT), 0, 0, 0, 0, 0, 0, 0, 0], lambda a, b: xor(a >> 1, 3988292384::BIGINT * (a & 1)))) AS t),
d AS (SELECT doc_id, {_CRC.format(text="CAST(doc_id AS VARCHAR)")} % 7 = 2 AS held_out, list_append({_WORDS.format(text=_lower("coalesce(text, '')"))}, ' ') AS w FROM documents, t),
k AS (SELECT doc_id, held_out, unnest(w) AS token FROM d), c AS (SELECT token, count(*) AS c FROM k WHERE NOT held_out GROUP BY token), n AS (SELECT sum(c) AS n, count(*) AS v FROM c)
SELECT doc_id, held_out, count(*) AS n_tokens, count(c.c) AS n_known, CAST((SELECT n FROM n) AS BIGINT) AS train_tokens, round(sum(log10((coalesce(c.c, 0) + 1) / ((SELECT n + v FROM n) + 1.0))), 4) AS base_score
FROM k LEFT JOIN c USING (token) GROUP BY doc_id, held_out
"""

TOKEN_BYTES = "SELECT doc_id, CAST(strlen(coalesce(text, '')) AS BIGINT) AS n_bytes FROM documents"

QUALITY_BASE = f"""
WITH w AS (SELECT doc_id, coalesce(text, '') AS text, {_WORDS.format(text="coalesce(text, '')")} AS w FROM documents),
v AS (SELECT doc_id, unnest(range(1, len(w) - 3)) AS i, w FROM w WHERE len(w) >= 5), g AS (SELECT doc_id, i, array_to_string(w[i:i + 4], ' ') AS g FROM v),
r AS (SELECT doc_id, count(DISTINCT j) AS n FROM (SELECT doc_id, unnest(range(i, i + 5)) AS j FROM (SELECT *, count(*) OVER (PARTITION BY doc_id, g) AS k FROM g) WHERE k > 1) GROUP BY doc_id),
l AS (SELECT *, list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^\\x20\\x09-\\x0D]')) AS lines FROM w),
s AS (SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(list_sum(list_transform(w, lambda x: length(x))), 0) AS BIGINT) AS word_chars, CAST(length(regexp_replace(text, '[^#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols,
      CAST(len(lines) - len(list_distinct(lines)) AS BIGINT) AS n_dup_lines, CAST(coalesce(r.n, 0) AS BIGINT) AS n_repeat_words FROM l LEFT JOIN r USING (doc_id))
SELECT *, n_words < 10 OR 100 * n_repeat_words > 20 * n_words AS base_failed FROM s
"""

_DIGITS = "regexp_replace(m, '[^0-9]', '', 'g')"
_LUHN = f"list_sum(list_transform(range(1, length({_DIGITS}) + 1), lambda i: CASE WHEN i % 2 = 1 THEN CAST(substr(reverse({_DIGITS}), i, 1) AS INTEGER) WHEN CAST(substr(reverse({_DIGITS}), i, 1) AS INTEGER) > 4 THEN 2 * CAST(substr(reverse({_DIGITS}), i, 1) AS INTEGER) - 9 ELSE 2 * CAST(substr(reverse({_DIGITS}), i, 1) AS INTEGER) END)) % 10 = 0"
#: The base patterns, and what confirms a match m.
_PII = [
    ("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "true"),
    ("ip", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "len(list_filter(string_split(m, '.'), lambda x: length(ltrim(x, '0')) > 3 OR CAST('0' || right(x, 3) AS INTEGER) > 255)) = 0"),
    ("card", r"[0-9]([\x20-]?[0-9])+", f"length({_DIGITS}) BETWEEN 14 AND 19 AND {_LUHN}"),
    ("phone", r"\+[0-9][\x20().0-9-]+[0-9]", f"length({_DIGITS}) BETWEEN 10 AND 15"),
]


def _found(order: int, kind: str, pattern: str, confirmed: str) -> str:
    """Confirmed spans of a kind: a match begins after all text between matches and all matches before it."""
    lengths = "coalesce(list_sum(list_transform({}, lambda x: length(x))), 0)"
    at = f"list_transform(range(1, len(ms) + 1), lambda k: {lengths.format('parts[1:k]')} + {lengths.format('ms[1:k - 1]')})"
    return f"SELECT doc_id, {order} AS o, '{kind}' AS kind, CAST(s AS BIGINT) AS s, CAST(s + length(m) AS BIGINT) AS e FROM (SELECT doc_id, unnest(ms) AS m, unnest({at}) AS s FROM (SELECT doc_id, regexp_extract_all(text, '{pattern}') AS ms, regexp_split_to_array(text, '{pattern}') AS parts FROM documents WHERE text IS NOT NULL)) WHERE {confirmed}"


PERSONAL_DATA_BASE = f"""
WITH f AS ({" UNION ALL ".join(_found(i, *x) for i, x in enumerate(_PII))}),
g AS (SELECT doc_id, {", ".join(f"count(*) FILTER (kind = '{k}') AS n_{k}" for k, *_ in _PII)}, string_agg(kind || ':' || s || ':' || e, ',' ORDER BY s, o) AS spans FROM f GROUP BY doc_id)
SELECT doc_id, {", ".join(f"coalesce(n_{k}, 0) AS n_{k}" for k, *_ in _PII)}, sha256(coalesce(spans, '')) AS base_sha256 FROM documents LEFT JOIN g USING (doc_id)
"""
