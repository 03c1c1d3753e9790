"""SQL for another engine with the meaning of the queries that SQL can express on whole tables."""

from __future__ import annotations

from .license_scan import COPYRIGHT_LINE, LINE_ENDS, NOT_WORD, SPELLINGS, catalogue
from .quality_rules import POLICIES, RULES

WORD = r"[^\x20\x09-\x0D]+"
_WORDS = f"regexp_extract_all(coalesce(text, ''), '{WORD}')"


def substring_dedup() -> str:
    return f"""WITH d AS (SELECT doc_id, {_WORDS} AS w FROM documents),
        s AS (SELECT doc_id, i, w[i:i + 12] AS run FROM (SELECT doc_id, w, unnest(range(1, len(w) - 11)) AS i FROM d WHERE len(w) >= 13)),
        f AS (SELECT run, min(doc_id) AS first FROM s GROUP BY 1),
        gone AS (SELECT DISTINCT doc_id, i + k AS i FROM s JOIN f USING (run), range(13) r(k) WHERE first < doc_id),
        x AS (SELECT doc_id, unnest(w) AS word, unnest(range(1, len(w) + 1)) AS i FROM d),
        kept AS (SELECT x.doc_id, string_agg(word, ' ' ORDER BY x.i) AS t, count(*) AS n FROM x ANTI JOIN gone USING (doc_id, i) GROUP BY 1)
        SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(len(w) - coalesce(n, 0) AS BIGINT) AS n_removed, sha256(coalesce(t, '')) AS kept_sha256 FROM d LEFT JOIN kept USING (doc_id)"""


def topk_search() -> str:
    return """WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(256 * CAST(x AS DOUBLE))) AS vec FROM embeddings),
        s AS (SELECT q.vec_id AS query_id, v.vec_id, CAST(list_dot_product(q.vec, v.vec) AS BIGINT) AS score FROM v q JOIN v ON q.vec_id != v.vec_id WHERE q.vec_id % 50 = 0),
        r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS k FROM s)
        SELECT query_id, CAST(k AS INT) AS rank, vec_id, score FROM r WHERE k <= 5"""


def quality_rules() -> str:
    fails = " OR ".join(f"({c})" for name, c in RULES if name in POLICIES["v1"])
    base = " OR ".join(f"({c})" for name, c in RULES if name in POLICIES["base"])
    return f"""WITH d AS (SELECT doc_id, coalesce(text, '') AS text, {_WORDS} AS w, list_filter(string_split(coalesce(text, ''), chr(10)), lambda l: regexp_matches(l, '{WORD}')) AS l FROM documents),
        g AS (SELECT doc_id, i, w[i:i + 2] AS run FROM (SELECT doc_id, w, unnest(range(1, len(w) - 1)) AS i FROM d WHERE len(w) >= 3)),
        t AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, run) AS n FROM g) WHERE n > 1),
        c AS (SELECT doc_id, count(DISTINCT i + k) AS n FROM t, range(3) r(k) GROUP BY 1),
        m AS (SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(length(array_to_string(w, '')) AS BIGINT) AS word_chars, CAST(length(regexp_replace(text, '[^#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols,
            CAST(len(l) - len(list_distinct(l)) AS BIGINT) AS n_dup_lines, CAST(coalesce(c.n, 0) AS BIGINT) AS n_repeat_words, len(l) AS n_lines,
            length(regexp_replace(text, '\\P{{Lu}}', '', 'g')) AS n_upper, length(regexp_replace(text, '\\P{{L}}', '', 'g')) AS n_letters FROM d LEFT JOIN c USING (doc_id))
        SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, ({base}) AS base_failed, NOT ({fails}) AS kept FROM m"""


def url_rules(rules) -> str:
    listed = ", ".join(f"('{h}', '{p}', '{v}')" for h, p, v in rules)
    part = "regexp_extract(coalesce(url, ''), '://([^/?#]*)([^?#]*)', {})"
    return f"""WITH p AS (SELECT page_id, translate({part.format(1)}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, {part.format(2)} AS path FROM pages),
        r(h, s, verdict) AS (VALUES {listed}),
        m AS (SELECT page_id, h || s AS rule, verdict, row_number() OVER (PARTITION BY page_id ORDER BY length(h || s) DESC) AS k FROM p JOIN r ON (host = h OR ends_with(host, '.' || h)) AND starts_with(path, s))
        SELECT p.page_id, host, path, rule, coalesce(verdict, 'allow') AS verdict FROM p LEFT JOIN m ON p.page_id = m.page_id AND k = 1"""


def _quoted(x: str) -> str:
    return "'" + x.replace("'", "''") + "'"


def _respelled(x: str) -> str:
    for old, new in SPELLINGS:
        x = f"replace({x}, ' {old.replace(' ', '  ')} ', ' {new.replace(' ', '  ')} ')"
    return f"regexp_replace({x}, ' v([0-9])', ' version  \\1', 'g')"


def _lined(x: str) -> str:
    x = f"regexp_replace(lower(coalesce({x}, '')), {_quoted(COPYRIGHT_LINE)}, ' ', 'g')"
    x = f"regexp_replace(replace({x}, '&', ' and '), {_quoted(NOT_WORD)}, '  ', 'g')"
    return _respelled(f"concat(' ', replace({x}, chr(10), concat(' ', chr(10), ' ')), ' ')")


def _squeezed(x: str) -> str:
    return f"trim(regexp_replace({x}, '[ \\n]+', ' ', 'g'))"


def license_scan() -> str:
    whole = _squeezed(_respelled(f"regexp_replace(l, {_quoted(LINE_ENDS)}, '  ', 'g')"))
    listed = ", ".join(f"({_quoted(a)}, {_quoted(b)}, {part})" for a, b, part in catalogue())
    return f"""WITH d AS (SELECT doc_id, {_lined('text')} AS l FROM documents), n(license, notice, part) AS (VALUES {listed}), k AS (SELECT license, part, {_lined('notice')} AS l FROM n),
        known AS (SELECT {whole} AS c, min(license) AS license, bool_or(part) AS part FROM k GROUP BY 1), w AS (SELECT doc_id, l, {whole} AS c FROM d),
        parts AS (SELECT doc_id, {_squeezed('line')} AS c FROM (SELECT doc_id, unnest(string_split(l, chr(10))) AS line FROM d)
            UNION SELECT doc_id, {whole} AS c FROM (SELECT doc_id, unnest(string_split_regex(l, '\n[ \n]*\n')) AS l FROM d) WHERE length(l) < 10000),
        found AS (SELECT doc_id, string_agg(DISTINCT license, ',' ORDER BY license) AS notices FROM parts JOIN known USING (c) WHERE part GROUP BY 1)
        SELECT w.doc_id, sha256(w.c) AS digest, known.license, coalesce(notices, '') AS notices FROM w LEFT JOIN known USING (c) LEFT JOIN found ON w.doc_id = found.doc_id"""
