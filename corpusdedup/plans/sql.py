"""DuckDB building blocks of the oracles, phrased apart from the Spark plans.

Segmentation marks every boundary, splits there and folds short pieces from left to
right; Spark's one lazy pattern must give the same chunks.
"""

from __future__ import annotations

from ..functions.retention import FULL_LENGTH, N_SHARDS
from ..functions.text import NUMBER, STOPS, TYPED, WIDE_STOPS

WS = r"[ \t\n\r\f\x0B]"
CUTS = {
    "line": rf"{WS}*\n{WS}*",
    "paragraph": rf"{WS}*\n[ \t\r\f\x0B]*\n{WS}*",
    "sentence": rf"[{STOPS}]+{WS}+|[{WIDE_STOPS}]+{WS}*",
}


def quoted(text: str) -> str:
    return "'" + text.replace("'", "''") + "'"


def normal(col: str, placeholders: str | None = "single") -> str:
    if placeholders == "single":
        return f"regexp_replace({col}, {quoted(NUMBER)}, '<NUM>', 'g')"
    if placeholders == "typed":
        for pattern, mark in TYPED:
            col = f"regexp_replace({col}, {quoted(pattern)}, '{mark}', 'g')"
    return col


def chunk_ctes(source: str = "SELECT doc_id, text FROM documents", tau: int = 32, kinds: tuple[str, ...] = ("line", "sentence")) -> str:
    """src, pieces and chunk(doc_id, pos, text)."""
    cut = "(" + "|".join(CUTS[k] for k in kinds) + ")"
    tau = max(1, tau)
    return f"""src AS ({source}),
marked AS (SELECT doc_id, list_filter(string_split(regexp_replace(text, {quoted(cut)}, '\\1' || chr(1), 'g'), chr(1)), lambda x: x <> '') AS p FROM src WHERE text <> ''),
folded AS (SELECT doc_id, string_split(list_reduce(p, lambda a, x: CASE WHEN length(string_split(a, chr(2))[-1]) >= {tau} THEN a || chr(2) || x ELSE a || x END), chr(2)) AS c FROM marked),
chunk AS MATERIALIZED (SELECT doc_id, unnest(c) AS text, generate_subscripts(c, 1) - 1 AS pos FROM folded)"""


def brace_spans_cte() -> str:
    """span(doc_id, s, e) of src: outermost pairs of braces with the start of their line, for texts whose braces are balanced."""
    return """br AS (SELECT doc_id, text, p, sum(CASE c WHEN '{' THEN 1 ELSE -1 END) OVER (PARTITION BY doc_id ORDER BY p) AS depth, c FROM (SELECT doc_id, text, p, substr(text, p, 1) AS c FROM (SELECT doc_id, text, unnest(range(1, length(text) + 1)) AS p FROM src)) WHERE c IN ('{', '}')),
op AS (SELECT doc_id, text, p - 1 AS a, row_number() OVER (PARTITION BY doc_id ORDER BY p) AS k FROM br WHERE c = '{' AND depth = 1),
cl2 AS (SELECT doc_id, p AS e, row_number() OVER (PARTITION BY doc_id ORDER BY p) AS k FROM br WHERE c = '}' AND depth = 0),
pr AS (SELECT doc_id, a, e, CASE WHEN contains(substr(text, 1, a), chr(10)) THEN a - strpos(reverse(substr(text, 1, a)), chr(10)) + 1 ELSE 0 END AS line FROM op JOIN cl2 USING (doc_id, k)),
span AS (SELECT doc_id, greatest(line, coalesce(lag(e) OVER (PARTITION BY doc_id ORDER BY a), 0)) AS s, e FROM pr)"""


def spanned_chunk_ctes(source: str, spans: str, tau: int = 32) -> str:
    """src, span and chunk(doc_id, pos, text, kind): no cut inside a span, a cut at each of its ends, short pieces folded."""
    cut = "(" + "|".join(CUTS[k] for k in ("line", "sentence")) + ")"
    return f"""src AS ({source}), {spans},
pc AS (SELECT doc_id, unnest(q) AS x, generate_subscripts(q, 1) AS k FROM (SELECT doc_id, list_filter(string_split(regexp_replace(text, {quoted(cut)}, '\\1' || chr(1), 'g'), chr(1)), lambda x: x <> '') AS q FROM src WHERE text <> '')),
ends AS (SELECT doc_id, sum(length(x)) OVER (PARTITION BY doc_id ORDER BY k)::BIGINT AS c FROM pc),
bound AS (SELECT doc_id, c FROM ends WHERE NOT EXISTS (SELECT 1 FROM span WHERE span.doc_id = ends.doc_id AND span.s < ends.c AND ends.c < span.e)
UNION SELECT doc_id, s::BIGINT FROM span WHERE s > 0 UNION SELECT doc_id, e::BIGINT FROM span UNION SELECT doc_id, length(text) FROM src WHERE text <> ''),
fold AS (SELECT doc_id, list_reduce(list_prepend([0::BIGINT], list_transform(list_sort(list(c)), lambda c: [c])), lambda a, x: CASE WHEN x[1] - a[-1] >= {max(1, tau)} THEN list_concat(a, x) ELSE a END) AS edges, max(c) AS n FROM bound GROUP BY doc_id),
whole AS (SELECT doc_id, CASE WHEN edges[-1] < n THEN list_append(edges, n) ELSE edges END AS edges FROM fold),
cell AS (SELECT doc_id, unnest(range(1, len(edges))) AS k, edges FROM whole),
chunk AS MATERIALIZED (SELECT cell.doc_id, k - 1 AS pos, substr(src.text, edges[k] + 1, edges[k + 1] - edges[k]) AS text, CASE WHEN EXISTS (SELECT 1 FROM span WHERE span.doc_id = cell.doc_id AND span.s < edges[k + 1] AND span.e > edges[k]) THEN 'code' ELSE 'prose' END AS kind FROM cell JOIN src USING (doc_id))"""


def code_occ_ctes(source: str, spans: str) -> str:
    """chunk with its kind, then occ and grp; code is hashed as it is."""
    return f"""{spanned_chunk_ctes(source, spans)},
normed AS (SELECT doc_id, pos, text, kind, CASE kind WHEN 'code' THEN text ELSE {normal('text')} END AS norm FROM chunk),
occ AS MATERIALIZED (SELECT doc_id, pos, md5(norm) AS h, length(norm) AS norm_len, length(text) AS raw_len, text, kind FROM normed),
grp AS (SELECT h, norm_len, count(*) AS freq FROM occ GROUP BY ALL)"""


def occ_ctes(placeholders: str | None = "single", **options) -> str:
    """chunk, then occ(doc_id, pos, h, norm_len, raw_len, text) and grp(h, norm_len, freq)."""
    return f"""{chunk_ctes(**options)},
normed AS (SELECT doc_id, pos, text, {normal('text', placeholders)} AS norm FROM chunk),
occ AS MATERIALIZED (SELECT doc_id, pos, md5(norm) AS h, length(norm) AS norm_len, length(text) AS raw_len, text FROM normed),
grp AS (SELECT h, norm_len, count(*) AS freq FROM occ GROUP BY ALL)"""


def g(freq: str, n: float | str = N_SHARDS) -> str:
    return f"({freq} * pow(1.0::DOUBLE - 1.0::DOUBLE / {n!r}::DOUBLE, {freq} - 1))" if not isinstance(n, str) else f"({freq} * pow(1.0::DOUBLE - 1.0::DOUBLE / {n}, {freq} - 1))"


def alpha(length: str, full: float | str = FULL_LENGTH) -> str:
    return f"greatest(0.0::DOUBLE, 1.0::DOUBLE - {length} / {full}::DOUBLE)"


def budget(freq: str = "freq", length: str = "norm_len", n: float | str = N_SHARDS, full: float | str = FULL_LENGTH, length_aware: bool = True) -> str:
    a = alpha(length, full) if length_aware else "1.0::DOUBLE"
    return f"least({freq}, greatest(1, ceil(1.0::DOUBLE + ({g(freq, n)} - 1) * {a})::BIGINT))"


def decision_ctes(budget_sql: str | None = None, ties: str = "document", occ: str | None = None, **options) -> str:
    """occ and grp, then cand(doc_id, pos, raw_len, ...) and runs(doc_id, first_pos, last_pos, run_chars)."""
    order = "rank() OVER (PARTITION BY h, norm_len ORDER BY doc_id)" if ties == "document" else "row_number() OVER (PARTITION BY h, norm_len ORDER BY doc_id, pos)"
    return f"""{occ or occ_ctes(**options)},
dec AS (SELECT *, {order} AS place, row_number() OVER (PARTITION BY h, norm_len ORDER BY doc_id, pos) AS seat FROM (SELECT *, {budget_sql or budget()} AS budget FROM occ JOIN grp USING (h, norm_len))),
cand AS (SELECT * FROM dec WHERE place > budget),
isles AS (SELECT *, pos - row_number() OVER (PARTITION BY doc_id ORDER BY pos) AS isle FROM cand),
runs AS (SELECT doc_id, min(pos) AS first_pos, max(pos) AS last_pos, sum(raw_len)::BIGINT AS run_chars FROM isles GROUP BY doc_id, isle)"""


def rebuilt_ctes(tau_del: int = 100, **options) -> str:
    """... and kept(doc_id, text) of documents that have text left."""
    return f"""{decision_ctes(**options)},
kept AS (SELECT c.doc_id, string_agg(c.text, '' ORDER BY c.pos) AS text FROM occ c
         WHERE NOT EXISTS (SELECT 1 FROM runs r WHERE r.doc_id = c.doc_id AND c.pos BETWEEN r.first_pos AND r.last_pos AND r.run_chars >= {tau_del}) GROUP BY c.doc_id)"""


def words(col: str = "text") -> str:
    return f"list_filter(regexp_split_to_array(lower({col}), '{WS}+'), lambda x: x <> '')"


def shingle_ctes(source: str = "documents", n: int = 5) -> str:
    """sh(doc_id, base): distinct word n-grams as 60-bit hashes."""
    return f"""wd AS (SELECT doc_id, {words()} AS w FROM {source}),
gr AS (SELECT doc_id, unnest(list_transform(range(1, greatest(1, len(w) - {n - 1}) + 1), lambda i: array_to_string(w[i:i + {n - 1}], ' '))) AS s FROM wd WHERE len(w) > 0),
sh AS MATERIALIZED (SELECT DISTINCT doc_id, ('0x' || substr(md5(s), 1, 15))::BIGINT AS base FROM gr)"""


def signature_cte(perms: int = 128) -> str:
    from ..operators.documents import PRIME, permutations

    a, b = permutations(perms)
    slots = ", ".join(f"min(({x} * (base % {PRIME}) + {y}) % {PRIME})" for x, y in zip(a, b, strict=True))
    return f"sg AS MATERIALIZED (SELECT doc_id, [{slots}] AS sig FROM sh GROUP BY doc_id)"


def pair_ctes(bands: int, rows: int, perms: int = 128) -> str:
    """cp(a, b): pairs that share a bucket; vp(a, b, similarity): those with enough equal slots."""
    return f"""bk AS MATERIALIZED (SELECT doc_id, band, md5(array_to_string(sig[band * {rows} + 1:band * {rows} + {rows}], ',')) AS key FROM sg, range({bands}) r(band)),
cp AS MATERIALIZED (SELECT DISTINCT x.doc_id AS a, y.doc_id AS b FROM bk x JOIN bk y ON x.band = y.band AND x.key = y.key AND x.doc_id < y.doc_id),
vp AS MATERIALIZED (SELECT * FROM (SELECT a, b, len(list_filter(range(1, {perms + 1}), lambda i: x.sig[i] = y.sig[i])) / {perms}.0::DOUBLE AS similarity FROM cp JOIN sg x ON x.doc_id = a JOIN sg y ON y.doc_id = b) WHERE similarity >= 0.7)"""


def cluster_ctes() -> str:
    """cl(doc_id, component) from vp, as a recursive reach."""
    return """ed AS (SELECT a, b FROM vp UNION ALL SELECT b, a FROM vp),
rc AS (SELECT a AS node, a AS seen FROM ed UNION SELECT rc.node, ed.b FROM rc JOIN ed ON ed.a = rc.seen),
cl AS MATERIALIZED (SELECT node AS doc_id, min(seen) AS component FROM rc GROUP BY node)"""


def survivor_ctes(bands: int = 32, rows: int = 4) -> str:
    """surv(doc_id, text): documents left by MinHash. Needs WITH RECURSIVE."""
    return f"""{shingle_ctes()}, {signature_cte()}, {pair_ctes(bands, rows)}, {cluster_ctes()},
surv AS MATERIALIZED (SELECT d.* FROM documents d WHERE NOT EXISTS (SELECT 1 FROM cl WHERE cl.doc_id = d.doc_id AND cl.component <> d.doc_id))"""


def tokens(col: str = "text") -> str:
    trimmed = f"regexp_replace({col}, '^{WS}+|{WS}+$', '', 'g')"
    return f"CASE WHEN length({trimmed}) > 0 THEN len(regexp_split_to_array({trimmed}, '{WS}+')) ELSE 0 END"


def shard(n: int, by: str = "hash") -> str:
    key = "'0-' || doc_id::VARCHAR" if by == "hash" else "coalesce(source, '')"
    return f"(('0x' || substr(md5({key}), 1, 8))::BIGINT % {n})"


def kgram_ctes(source: str = "documents", k: int = 50, shard_sql: str = "0", keep_first: bool = False) -> str:
    """sp(doc_id, start, stop): merged spans of k-grams that occur twice or more in a shard."""
    first = "AND (g.doc_id, g.pos) <> (n.d, n.p)" if keep_first else ""
    return f"""kg AS (SELECT shard, doc_id, pos, md5(substr(text, pos, {k})) AS gram FROM (SELECT {shard_sql} AS shard, doc_id, text, unnest(range(1, length(text) - {k} + 2)) AS pos FROM {source} WHERE length(text) >= {k})),
kn AS (SELECT shard, gram, min((doc_id, pos)) AS f FROM kg GROUP BY shard, gram HAVING count(*) > 1),
hit AS (SELECT g.doc_id, g.pos - 1 AS a, g.pos - 1 + {k} AS b FROM kg g JOIN (SELECT shard, gram, f[1] AS d, f[2] AS p FROM kn) n ON g.shard = n.shard AND g.gram = n.gram {first}),
fl AS (SELECT *, CASE WHEN a <= max(b) OVER (PARTITION BY doc_id ORDER BY a ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) THEN 0 ELSE 1 END AS fresh FROM hit),
il AS (SELECT *, sum(fresh) OVER (PARTITION BY doc_id ORDER BY a ROWS UNBOUNDED PRECEDING) AS isle FROM fl),
sp AS MATERIALIZED (SELECT doc_id, min(a)::BIGINT AS start, max(b)::BIGINT AS stop FROM il GROUP BY doc_id, isle)"""


def cut_cte(source: str = "documents") -> str:
    """cutdoc(doc_id, text): characters outside the spans."""
    return f"""gaps AS (SELECT doc_id, coalesce(lag(stop) OVER w, 0) AS a, start AS b FROM sp WINDOW w AS (PARTITION BY doc_id ORDER BY start)
UNION ALL SELECT d.doc_id, coalesce(max(stop), 0), length(any_value(d.text)) FROM {source} d LEFT JOIN sp ON sp.doc_id = d.doc_id GROUP BY d.doc_id),
cutdoc AS (SELECT d.doc_id, string_agg(substr(d.text, (a + 1)::BIGINT, (b - a)::BIGINT), '' ORDER BY a) AS text FROM gaps JOIN {source} d ON d.doc_id = gaps.doc_id GROUP BY d.doc_id)"""
