"""DuckDB SQL that says what the operators' queries return, by plain joins on whole tables instead of the operators' methods. For small tables."""

from __future__ import annotations

from . import quality_rules as Q

_WORDS = r"regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')"
_HAS_WORD = r"regexp_matches(line, '[^\x20\x09-\x0D]')"


def _repeats(units: str, width: int, windows: str) -> str:
    """CTEs up to c (doc_id, p, u, gone): every unit of every document and whether a window over it also starts in an earlier document. ``units`` gives d (doc_id, w), ``windows`` (doc_id, i, k)."""
    return f"""{units},
cells AS (SELECT doc_id, unnest(range(1, len(w) + 1)) AS p, unnest(w) AS u FROM d),
windows AS ({windows}),
firsts AS (SELECT k, min(doc_id) AS least FROM windows GROUP BY k),
hits AS (SELECT doc_id, i FROM windows JOIN firsts USING (k) WHERE least < doc_id),
marked AS (SELECT cells.doc_id, p, u, i FROM cells LEFT JOIN hits ON hits.doc_id = cells.doc_id AND hits.i = p),
c AS (SELECT doc_id, p, u, count(i) OVER (PARTITION BY doc_id ORDER BY p ROWS BETWEEN {width - 1} PRECEDING AND CURRENT ROW) > 0 AS gone FROM marked)"""


#: Cut from blocks of a thousand bytes, as a cut far into a long string is slow.
_BYTE_WINDOWS = """SELECT doc_id, b * 1000 + j AS i, substr(block, 2 * j - 1, 100) AS k FROM (SELECT doc_id, b, block, unnest(range(1, least(1000, n - 49 - b * 1000) + 1)) AS j
  FROM (SELECT doc_id, len(w) AS n, b, substr(s, b * 2000 + 1, 2098) AS block FROM (SELECT doc_id, w, s, unnest(range(0, (len(w) + 999) // 1000)) AS b FROM d)))"""

OP9 = (
    "WITH "
    + _repeats(f"d AS (SELECT doc_id, {_WORDS} AS w FROM documents)", 13, "SELECT doc_id, i, array_to_string(w[i:i + 12], ' ') AS k FROM (SELECT doc_id, w, unnest(range(1, len(w) - 11)) AS i FROM d)")
    + """
SELECT d.doc_id, len(w)::BIGINT AS n_words, coalesce(n, 0) AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256
FROM d LEFT JOIN (SELECT doc_id, count(*) FILTER (gone) AS n, string_agg(u, ' ' ORDER BY p) FILTER (NOT gone) AS kept FROM c GROUP BY doc_id) USING (doc_id)"""
)

OP6 = (
    "WITH "
    + _repeats("d AS (SELECT doc_id, regexp_extract_all(s, '..') AS w, s FROM (SELECT doc_id, hex(encode(coalesce(text, ''))) AS s FROM documents))", 50, _BYTE_WINDOWS)
    + """,
runs AS (SELECT *, gone AND NOT coalesce(lag(gone) OVER (PARTITION BY doc_id ORDER BY p), false) AS opens FROM c)
SELECT d.doc_id, len(w)::BIGINT AS n_bytes, coalesce(n, 0) AS n_removed, coalesce(spans, 0) AS n_spans, sha256(unhex(coalesce(kept, ''))) AS kept_sha256
FROM d LEFT JOIN (SELECT doc_id, count(*) FILTER (gone) AS n, count(*) FILTER (opens) AS spans, string_agg(u, '' ORDER BY p) FILTER (NOT gone) AS kept FROM runs GROUP BY doc_id) USING (doc_id)"""
)

#: Links as l (a, b) in both directions to the smallest id that can be reached.
_REACH = "reach(a, b) AS (SELECT a, a FROM (SELECT DISTINCT a FROM l) UNION SELECT r.a, l.b FROM reach r JOIN l ON l.a = r.b), classes AS (SELECT a, min(b) AS least FROM reach GROUP BY a)"

OP3 = f"""WITH RECURSIVE v AS (SELECT vec_id, label, list_transform(embedding, lambda x: x::DOUBLE) AS x FROM embeddings),
u AS (SELECT * FROM v WHERE label IS NOT NULL AND x IS NOT NULL AND len(list_filter(x, lambda c: c IS NULL OR NOT isfinite(c))) = 0 AND len(list_filter(x, lambda c: c <> 0)) > 0),
l AS (SELECT p.vec_id AS a, q.vec_id AS b FROM u p JOIN u q ON p.label = q.label AND p.vec_id <> q.vec_id AND len(p.x) = len(q.x) WHERE list_cosine_similarity(p.x, q.x) >= 0.93),
{_REACH}
SELECT vec_id, (SELECT count(*) FROM l WHERE l.a = vec_id) AS n_links, coalesce(least, vec_id) AS component_id, coalesce(least, vec_id) = vec_id AS kept FROM v LEFT JOIN classes ON a = vec_id"""

OP4 = f"""WITH RECURSIVE d AS (SELECT doc_id, {_WORDS} AS w FROM documents),
s AS (SELECT doc_id, k, count(*) AS c FROM (SELECT doc_id, array_to_string(w[i:i + 4], ' ') AS k FROM (SELECT doc_id, w, unnest(range(1, greatest(2, len(w) - 3))) AS i FROM d WHERE len(w) > 0)) GROUP BY 1, 2),
n AS (SELECT doc_id, sum(c) AS n FROM s GROUP BY doc_id),
o AS (SELECT x.doc_id AS a, y.doc_id AS b, sum(least(x.c, y.c)) AS common FROM s x JOIN s y ON x.k = y.k AND x.doc_id <> y.doc_id GROUP BY 1, 2),
l AS (SELECT a, b FROM o JOIN n p ON p.doc_id = a JOIN n q ON q.doc_id = b WHERE common / (p.n + q.n - common)::DOUBLE >= 0.8),
{_REACH}
SELECT doc_id, coalesce(least, doc_id) AS component_id, coalesce(least, doc_id) = doc_id AS kept FROM documents LEFT JOIN classes ON a = doc_id"""

#: Prefixes are of words in the order of their counts of lines; pairs that share one are compared whole.
OP8 = rf"""WITH parts AS (SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line, unnest(range(0, len(string_split(coalesce(text, ''), chr(10))))) AS pos FROM documents),
worded AS (SELECT doc_id, pos, list_sort(list_distinct(regexp_extract_all(line, '[^\x20\x09-\x0D]+'))) AS w, row_number() OVER (ORDER BY doc_id, pos) AS r FROM parts WHERE {_HAS_WORD}),
sets AS (SELECT w, min(r) AS r FROM worded GROUP BY w),
e AS (SELECT r, w, unnest(w) AS x FROM sets),
df AS (SELECT x, count(*) AS f FROM e GROUP BY x),
ranked AS (SELECT r, w, x, row_number() OVER (PARTITION BY r ORDER BY f, x) AS place FROM e JOIN df USING (x)),
prefixes AS (SELECT r, w, x FROM ranked WHERE place <= len(w) - (4 * len(w) + 4) // 5 + 1),
pairs AS (SELECT DISTINCT p.r AS a, q.r AS b FROM prefixes p JOIN prefixes q ON p.x = q.x AND q.r < p.r AND 5 * len(q.w) >= 4 * len(p.w) AND 5 * len(p.w) >= 4 * len(q.w)),
alike AS (SELECT DISTINCT a FROM pairs JOIN sets p ON p.r = a JOIN sets q ON q.r = b WHERE 9 * len(list_intersect(p.w, q.w)) >= 4 * (len(p.w) + len(q.w))),
judged AS (SELECT doc_id, pos, worded.r <> sets.r OR sets.r IN (SELECT a FROM alike) AS gone FROM worded JOIN sets USING (w))
SELECT d.doc_id, count(gone) AS n_lines, count(*) FILTER (gone) AS n_removed, sha256(coalesce(string_agg(line, chr(10) ORDER BY parts.pos) FILTER (NOT coalesce(gone, false)), '')) AS kept_sha256
FROM documents d JOIN parts USING (doc_id) LEFT JOIN judged ON judged.doc_id = parts.doc_id AND judged.pos = parts.pos GROUP BY d.doc_id"""


def _op1() -> str:
    """Counts, the votes of ``quality_rules.RULES`` (whose limits stand here again), and its rounds of expectation and maximisation over vote patterns."""
    share = lambda top, bottom: f"(CASE WHEN {bottom} > 0 THEN {top}::DOUBLE / {bottom} ELSE 0 END)"
    repeats, stops = share("n_repeat_words", "n_words"), share("n_stops", "n_words")
    votes = [
        f"CASE WHEN {repeats} > 0.18 THEN -1 WHEN {repeats} <= 0.03 THEN 1 ELSE 0 END",
        f"CASE WHEN n_stops = 0 AND n_words > 60 THEN -1 WHEN {stops} BETWEEN 0.02 AND 0.34 THEN 1 ELSE 0 END",
        f"CASE WHEN {share('n_dup_lines', 'n_lines')} > 0.4 THEN -1 ELSE 0 END",
        f"CASE WHEN {share('n_symbols', 'word_chars')} > 0.02 THEN -1 ELSE 0 END",
        f"CASE WHEN {share('word_chars', 'n_words')} NOT BETWEEN 2 AND 14 THEN -1 ELSE 0 END",
        f"CASE WHEN {share('n_upper', 'word_chars')} > 0.3 THEN -1 ELSE 0 END",
        f"CASE WHEN {share('n_shouts', 'n_words')} > 0.15 THEN -1 ELSE 0 END",
        f"CASE WHEN {share('n_digits', 'word_chars')} > 0.25 THEN -1 ELSE 0 END",
        "CASE WHEN n_words < 10 THEN -1 ELSE 0 END",
    ]
    count = lambda pattern, text="t": f"len(regexp_extract_all({text}, '{pattern}'))::BIGINT"
    # sound for a rule: the other rules that can speak for a document do
    sound = "CASE j WHEN 1 THEN v[2] = 1 WHEN 2 THEN v[1] = 1 ELSE v[1] = 1 AND v[2] = 1 END"
    return rf"""WITH RECURSIVE d AS (SELECT doc_id, coalesce(text, '') AS t, {_WORDS} AS w, list_filter(string_split(coalesce(text, ''), chr(10)), lambda line: {_HAS_WORD}) AS lines FROM documents),
five AS (SELECT doc_id, i, array_to_string(w[i:i + 4], ' ') AS k FROM (SELECT doc_id, w, unnest(range(1, len(w) - 3)) AS i FROM d)),
twice AS (SELECT doc_id, i FROM five JOIN (SELECT doc_id, k FROM five GROUP BY 1, 2 HAVING count(*) > 1) USING (doc_id, k)),
steps AS (SELECT doc_id, least(5, i - coalesce(lag(i) OVER (PARTITION BY doc_id ORDER BY i), -10)) AS n FROM twice),
f AS (SELECT doc_id, len(w)::BIGINT AS n_words, len(array_to_string(w, ''))::BIGINT AS word_chars, {count('[#*$%&|<>]')} AS n_symbols, (len(lines) - len(list_distinct(lines)))::BIGINT AS n_dup_lines,
  coalesce((SELECT sum(n) FROM steps WHERE steps.doc_id = d.doc_id), 0)::BIGINT AS n_repeat_words, len(lines) AS n_lines, {count(r'\p{Lu}')} AS n_upper, {count('[!?.,;:]{2}')} AS n_shouts, {count(r'\p{N}')} AS n_digits,
  {count(r'[.!?][\x20\x09-\x0D]', "t || ' '")} AS n_stops FROM d),
voted AS (SELECT *, [{", ".join(votes)}] AS v FROM f),
patterns AS (SELECT v, count(*)::DOUBLE AS n FROM voted GROUP BY v),
cells AS MATERIALIZED (SELECT v, n, j.range AS j, v[j.range] = -1 AS bad, {sound.replace("j WHEN", "j.range WHEN")} AS sound FROM patterns, range(1, {len(votes) + 1}) j),
em(i, j, wrong, good, junk) AS (
  SELECT 0, range, {Q.DOUBT}::DOUBLE, 0.9::DOUBLE, 0.5::DOUBLE FROM range(1, {len(votes) + 1})
  UNION ALL
  SELECT i, j, wrong, good, least(junk, {Q.APART}::DOUBLE * good) FROM (
    SELECT i + 1 AS i, j, (sum(CASE WHEN bad THEN n * p ELSE 0 END) + {Q.TRUST * Q.DOUBT / 100!r}::DOUBLE) / (sum(CASE WHEN bad THEN n * p ELSE 0 END) + sum(n * p * odds) + {Q.TRUST}::DOUBLE) AS wrong,
      (sum(CASE WHEN sound THEN n * p ELSE 0 END) + 0.9) / (sum(n * p) + 1) AS good, (sum(CASE WHEN sound THEN n * p * odds ELSE 0 END) + 0.5) / (sum(n * p * odds) + 1) AS junk
    FROM (SELECT *, 1 / (1 + sum(odds) OVER (PARTITION BY v)) AS p FROM (SELECT i, c.*, CASE WHEN bad THEN (1 - wrong) / wrong * CASE WHEN sound THEN junk / good ELSE (1 - junk) / (1 - good) END ELSE 0 END AS odds FROM em JOIN cells c USING (j) WHERE i < 40))
    GROUP BY i, j)),
judged AS (SELECT v, 1 / (1 + sum(CASE WHEN bad THEN (1 - wrong) / wrong * CASE WHEN sound THEN junk / good ELSE (1 - junk) / (1 - good) END ELSE 0 END)) AS quality FROM cells JOIN em USING (j) WHERE i = 40 GROUP BY v)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_words < 10 OR 100 * n_repeat_words > 20 * n_words AS base_failed,
  NOT (n_words < 10 OR 100 * n_repeat_words > 20 * n_words) AND quality >= 0.5 AS kept FROM voted JOIN judged USING (v)"""


OP1 = _op1()
