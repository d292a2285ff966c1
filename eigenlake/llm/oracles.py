"""DuckDB SQL for the queries of this subpackage that SQL can express."""

from __future__ import annotations

from string import ascii_lowercase, ascii_uppercase

from . import jaccard, licenses, secrets

_WORDS = r"regexp_extract_all({text}, '[^ \t\n\v\f\r]+')"
_LOW = f"translate(coalesce(text, ''), '{ascii_uppercase}', '{ascii_lowercase}')"


def _quoted(text: str) -> str:
    return "'" + text.replace("'", "''") + "'"


def _licenses() -> str:
    """Base columns by comparing slices of the words with the phrases; other spans by votes, their order by dynamic programming."""
    rows = ", ".join(f"({t}, {_quoted(x.label)}, {str(x.base).lower()}, {_quoted(x.text)})" for t, x in enumerate(licenses.TEMPLATES))
    return f"""
    WITH RECURSIVE t(t, label, base, txt) AS (VALUES {rows}),
    tw AS (SELECT t, label, base, string_split(txt, ' ') AS p FROM t),
    d AS MATERIALIZED (SELECT doc_id, regexp_extract_all({_LOW}, '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+') AS w FROM documents),
    phrase AS (SELECT doc_id, label, k - 1 AS start FROM d, tw, unnest(range(1, len(w) - len(p) + 2)) x(k) WHERE base AND list_has_all(w, p) AND w[k : k + len(p) - 1] = p),
    b AS (SELECT doc_id, count(*) AS n_base, min(start) AS first_word, max(start) AS last_word, string_agg(DISTINCT label, ',' ORDER BY label) AS base_labels FROM phrase GROUP BY doc_id),
    tg AS (SELECT t, k - 1 AS place, p[k] || ' ' || p[k + 1] || ' ' || p[k + 2] AS gram, len(p) - 2 AS grams FROM tw, unnest(range(1, len(p) - 1)) x(k) WHERE NOT base),
    g AS (SELECT doc_id, k - 1 AS pos, w[k] || ' ' || w[k + 1] || ' ' || w[k + 2] AS gram FROM d, unnest(range(1, len(w) - 1)) x(k)),
    votes AS MATERIALIZED (SELECT DISTINCT doc_id, t, grams, pos - place AS diagonal, pos, place FROM g JOIN tg USING (gram)),
    lines AS (SELECT doc_id, t, grams, diagonal, count(*) AS n, min(pos) AS lo, max(pos) AS hi FROM votes GROUP BY ALL),
    marked AS (SELECT *, n = grams AS whole, lag(diagonal) OVER w AS ld, lag(hi) OVER w AS lh, lag(n = grams) OVER w AS lw FROM lines WINDOW w AS (PARTITION BY doc_id, t ORDER BY lo, diagonal)),
    runs AS MATERIALIZED (SELECT *, sum(coalesce((abs(diagonal - ld) > {licenses.SHIFT} OR lo - lh > {licenses.GAP} OR whole OR lw)::INT, 1)) OVER (PARTITION BY doc_id, t ORDER BY lo, diagonal ROWS UNBOUNDED PRECEDING) AS span FROM marked),
    merged AS MATERIALIZED (SELECT doc_id, t, grams, span, min(lo) AS first_word, max(hi) + 2 AS last_word, count(*) AS n_lines, sum(n) AS n FROM runs GROUP BY doc_id, t, grams, span HAVING sum(n) / grams >= {licenses.SHARE}),
    chain(doc_id, t, span, v, i, best) AS (
      SELECT doc_id, t, span, list(struct_pack(pos, place) ORDER BY pos, place DESC), 1, list_transform(range(any_value(grams)), lambda x: 0::BIGINT)
      FROM merged JOIN runs USING (doc_id, t, grams, span) JOIN votes USING (doc_id, t, grams, diagonal) WHERE n_lines > 1 GROUP BY doc_id, t, span
      UNION ALL SELECT doc_id, t, span, v, i + 1, list_transform(best, lambda x, k: CASE WHEN k = v[i].place + 1 THEN greatest(x, 1 + coalesce(list_max(best[1 : v[i].place]), 0)) ELSE x END) FROM chain WHERE i <= len(v)),
    ordered AS (SELECT doc_id, t, span, list_max(best) AS m FROM chain WHERE i > len(v)),
    every AS (SELECT * FROM (SELECT doc_id, t, first_word, last_word, coalesce(m, n)::DOUBLE / grams AS share FROM merged LEFT JOIN ordered USING (doc_id, t, span)) WHERE share >= {licenses.SHARE}),
    reached AS (SELECT *, max(last_word) OVER (PARTITION BY doc_id ORDER BY first_word, t, last_word ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS reach FROM every),
    islands AS (SELECT *, sum(coalesce((first_word > reach)::INT, 1)) OVER (PARTITION BY doc_id ORDER BY first_word, t, last_word ROWS UNBOUNDED PRECEDING) AS island FROM reached),
    chosen AS (SELECT doc_id, label, share FROM (SELECT *, max(share) OVER (PARTITION BY doc_id, island) AS best FROM islands) JOIN tw USING (t) WHERE share = best UNION ALL SELECT doc_id, label, 1.0 FROM phrase),
    found AS (SELECT doc_id, string_agg(DISTINCT label, ',' ORDER BY label) AS labels, max(share) AS score FROM chosen GROUP BY doc_id)
    SELECT d.doc_id, len(w) AS n_words, coalesce(n_base, 0) AS n_base, first_word, last_word, coalesce(base_labels, '') AS base_labels, coalesce(labels, '') AS labels, coalesce(score, 0.0)::DOUBLE AS score FROM d LEFT JOIN b USING (doc_id) LEFT JOIN found USING (doc_id)"""


def _needed(rule: secrets.Rule) -> str:
    """A pattern that every text with a match of the rule holds."""
    return f"{rule.pattern[:-1]}{{{rule.least}}}" if rule.pattern.startswith("[") and rule.pattern.endswith("]+") else rule.pattern


def _secrets() -> str:
    parts = " UNION ALL ".join(
        f"SELECT doc_id, {rank} AS rank, {_quoted(r.kind)} AS kind, {r.least} AS least, {str(r.base).lower()} AS base, string_split_regex(text, {_quoted(r.pattern)}) AS gaps, regexp_extract_all(text, {_quoted(r.pattern)}) AS m, regexp_extract_all(text, {_quoted(r.pattern)}, {r.group}) AS p FROM documents WHERE regexp_matches(text, {_quoted(_needed(r))})"
        for rank, r in enumerate(secrets.RULES)
    )
    return f"""
    WITH f AS ({parts}), each AS (SELECT doc_id, rank, kind, base, k, length(m[k]) AS size, length(p[k]) >= least AS good, sum(length(gaps[k]) + length(m[k])) OVER (PARTITION BY doc_id, kind ORDER BY k ROWS UNBOUNDED PRECEDING)::BIGINT AS stop FROM f, unnest(range(1, len(m) + 1)) x(k)),
    spans AS (SELECT *, stop - size AS start, kind || ':' || (stop - size) || ':' || stop AS span FROM each WHERE good),
    s AS (SELECT doc_id, count(*) FILTER (kind = 'assign') AS n_assign, count(*) FILTER (kind = 'access') AS n_access, count(*) FILTER (kind = 'hex') AS n_hex, string_agg(span, ',' ORDER BY start, rank) FILTER (base) AS b, string_agg(span, ',' ORDER BY start, rank) AS spans FROM spans GROUP BY doc_id)
    SELECT doc_id, coalesce(n_assign, 0) AS n_assign, coalesce(n_access, 0) AS n_access, coalesce(n_hex, 0) AS n_hex, sha256(coalesce(b, '')) AS base_sha256, coalesce(spans, '') AS spans FROM documents LEFT JOIN s USING (doc_id)"""


_TOPK = """
    WITH e AS (SELECT vec_id, list_transform(embedding, lambda x: floor(256 * x::DOUBLE)) AS v FROM embeddings WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0)
    SELECT query_id, rank, vec_id, score FROM (SELECT q.vec_id AS query_id, c.vec_id, list_dot_product(q.v, c.v)::BIGINT AS score, row_number() OVER (PARTITION BY q.vec_id ORDER BY list_dot_product(q.v, c.v) DESC, c.vec_id)::INT AS rank
      FROM e q JOIN e c ON q.vec_id != c.vec_id WHERE q.vec_id % 50 = 0) WHERE rank <= 5"""

_REPEATS = f"""
    WITH d AS MATERIALIZED (SELECT doc_id, {_WORDS.format(text="coalesce(text, '')")} AS w FROM documents),
    win AS (SELECT doc_id, k, array_to_string(w[k : k + 19], ' ') AS g FROM d, unnest(range(1, len(w) - 18)) x(k)),
    late AS (SELECT doc_id, k FROM (SELECT doc_id, k, min((doc_id, k)) OVER (PARTITION BY g) AS first FROM win) WHERE (doc_id, k) != first),
    gone AS (SELECT DISTINCT doc_id, k + o AS k FROM late, range(20) r(o)),
    words AS (SELECT doc_id, k, w[k] AS word FROM d, unnest(range(1, len(w) + 1)) x(k)),
    kept AS (SELECT doc_id, string_agg(word, ' ' ORDER BY k) AS kept FROM words ANTI JOIN gone USING (doc_id, k) GROUP BY doc_id),
    lost AS (SELECT doc_id, count(*) AS n FROM gone GROUP BY doc_id)
    SELECT doc_id, len(w) AS n_words, coalesce(n, 0) AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256 FROM d LEFT JOIN kept USING (doc_id) LEFT JOIN lost USING (doc_id)"""

_CLASSES = f"""
    WITH RECURSIVE d AS MATERIALIZED (SELECT doc_id, {_WORDS.format(text=_LOW)} AS w FROM documents),
    s AS MATERIALIZED (SELECT DISTINCT doc_id, array_to_string(w[k : k + {jaccard.SHINGLE - 1}], ' ') AS g FROM d, unnest(range(1, greatest(len(w) - {jaccard.SHINGLE - 2}, 2))) x(k) WHERE len(w) > 0),
    n AS MATERIALIZED (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
    common AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM s a JOIN s b ON a.g = b.g AND a.doc_id != b.doc_id GROUP BY ALL),
    link AS MATERIALIZED (SELECT a, b FROM common JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * c >= {jaccard.PER_CENT} * (x.n + y.n - c)),
    reach(a, b) AS (SELECT doc_id, doc_id FROM d UNION SELECT reach.a, link.b FROM reach JOIN link ON reach.b = link.a),
    comp AS (SELECT a AS doc_id, min(b) AS component_id FROM reach GROUP BY a)
    SELECT d.doc_id, coalesce(n, 0) AS n_shingles, component_id FROM d LEFT JOIN n USING (doc_id) JOIN comp ON comp.doc_id = d.doc_id"""

ORACLES: dict[str, str] = {
    "op1_license_scan": _licenses(),
    "op2_secret_scan": _secrets(),
    "op4_exact_topk": _TOPK,
    "op7_substring_dedup": _REPEATS,
    "op10_ngram_jaccard_join": _CLASSES,
}
