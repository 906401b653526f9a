"""SQL that must give the rows of the queries which SQL can express: words, repeats, linked documents, removed bytes."""

from __future__ import annotations

from liveindex.llm import quality

#: Words of the documents' texts; white space is that of the word rule alone.
_WORDS = "regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+')"


def _ngrams(n: int) -> str:
    return f"g{n} AS (SELECT doc_id, p, list_slice(w, p, p + {n - 1}) AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - {n - 2})) AS p FROM d WHERE len(w) >= {n})), c{n} AS MATERIALIZED (SELECT doc_id, p, count(*) OVER (PARTITION BY doc_id, g) AS times, row_number() OVER (PARTITION BY doc_id, g ORDER BY p) AS nth FROM g{n})"


def repetition() -> str:
    """Every measure of a document by its own words and lines."""
    parts = [f"d AS MATERIALIZED (SELECT doc_id, coalesce(text, '') AS text, {_WORDS} AS w FROM documents)", "x AS MATERIALIZED (SELECT doc_id, p, length(w[p]) AS chars FROM (SELECT doc_id, w, unnest(range(1, len(w) + 1)) AS p FROM d))",
             "l AS (SELECT doc_id, k, l FROM (SELECT doc_id, ls, unnest(range(1, len(ls) + 1)) AS k, unnest(ls) AS l FROM (SELECT doc_id, string_split(text, chr(10)) AS ls FROM d)) WHERE regexp_matches(l, '[^\\x20\\x09-\\x0D]'))",
             "lc AS (SELECT doc_id, length(l) AS chars, row_number() OVER (PARTITION BY doc_id, l ORDER BY k) > 1 AS again FROM l)",
             "lines AS (SELECT doc_id, count(*) AS lines, count_if(again) AS dups, sum(chars) AS chars, sum(CASE WHEN again THEN chars ELSE 0 END) AS dup_chars FROM lc GROUP BY doc_id)",
             "base AS (SELECT d.doc_id, len(d.w)::BIGINT AS n_words, coalesce((SELECT sum(chars) FROM x WHERE x.doc_id = d.doc_id), 0)::BIGINT AS word_chars, len(regexp_extract_all(d.text, '[#*$%&|<>]'))::BIGINT AS n_symbols FROM d)",
             *[_ngrams(n) for n in (*quality.MOST_FREQUENT, *quality.REPEATED)]]
    columns, joins, bad = [], [], []
    covered = lambda n, which: f"(SELECT doc_id, sum(chars) AS chars, count(*) AS words FROM x WHERE EXISTS (SELECT 1 FROM c{n} c WHERE c.doc_id = x.doc_id AND {which} AND x.p BETWEEN c.p AND c.p + {n - 1}) GROUP BY doc_id)"
    share = lambda a: f"(coalesce({a}, 0) / greatest(b.word_chars, 1))::DOUBLE"
    for n, most in quality.REPEATED.items():
        parts.append(f"r{n} AS (SELECT c.doc_id, x.p, any_value(x.chars) AS chars FROM c{n} c JOIN (SELECT unnest(range(0, {n})) AS k) o ON c.nth > 1 JOIN x ON x.doc_id = c.doc_id AND x.p = c.p + o.k GROUP BY c.doc_id, x.p), s{n} AS (SELECT doc_id, sum(chars) AS chars FROM r{n} GROUP BY doc_id)")
        columns.append(f"{share(f's{n}.chars')} AS repeated_{n}")
        joins.append(f"LEFT JOIN s{n} ON s{n}.doc_id = b.doc_id")
        bad.append(f"{share(f's{n}.chars')} > {most}")
    for n, most in quality.MOST_FREQUENT.items():
        width = " + ".join(f"length(w[p + {k}])" for k in range(n))
        parts.append(f"t{n} AS (SELECT doc_id, max(times * chars) AS chars FROM (SELECT c.doc_id, c.times, {width} AS chars FROM c{n} c JOIN d ON d.doc_id = c.doc_id WHERE c.times >= {quality.LEAST_TIMES}) GROUP BY doc_id)")
        columns.append(f"least({share(f't{n}.chars')}, 1.0)::DOUBLE AS top_{n}")
        joins.append(f"LEFT JOIN t{n} ON t{n}.doc_id = b.doc_id")
        bad.append(f"least({share(f't{n}.chars')}, 1.0) > {most}")
    parts.append("q5 AS (SELECT doc_id, count(*) AS words FROM (SELECT DISTINCT c.doc_id, c.p + o.k AS p FROM c5 c JOIN (SELECT unnest(range(0, 5)) AS k) o ON c.times > 1) GROUP BY doc_id)")
    dups, dup_chars = "(coalesce(n.dups, 0) / greatest(coalesce(n.lines, 0), 1))::DOUBLE", "(coalesce(n.dup_chars, 0) / greatest(coalesce(n.chars, 0), 1))::DOUBLE"
    bad += [f"({dups} > {quality.LINES} AND coalesce(n.lines, 0) >= {quality.LEAST_LINES})", f"{dup_chars} > {quality.LINE_CHARS}"]
    failed = "(b.n_words < 10 OR 100 * coalesce(q5.words, 0) > 20 * b.n_words)"
    return (f"WITH {', '.join(parts)} SELECT b.doc_id, b.n_words, b.word_chars, b.n_symbols, coalesce(n.dups, 0)::BIGINT AS n_dup_lines, coalesce(q5.words, 0)::BIGINT AS n_repeat_words, {failed} AS base_failed, NOT {failed} AND NOT ({' OR '.join(bad)}) AS kept, "
            f"{', '.join(columns)}, {dups} AS dup_lines, {dup_chars} AS dup_line_chars FROM base b LEFT JOIN lines n ON n.doc_id = b.doc_id LEFT JOIN q5 ON q5.doc_id = b.doc_id {' '.join(joins)}")


def near_duplicates(width: int = 4, percent: int = 80) -> str:
    """Links from shared shingles of all pairs of sets, components by spreading the smallest doc_id."""
    lower = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
    sets = f"CASE WHEN len(w) >= {width} THEN list_distinct(list_transform(range(1, len(w) - {width - 2}), lambda i: list_slice(w, i, i + {width - 1}))) WHEN len(w) > 0 THEN [w] ELSE [] END"
    return f"""WITH RECURSIVE d AS MATERIALIZED (SELECT doc_id, {_WORDS.replace("coalesce(text, '')", lower)} AS w FROM documents), s AS MATERIALIZED (SELECT doc_id, {sets} AS g FROM d),
k AS MATERIALIZED (SELECT min(doc_id) AS a, g, len(g) AS n FROM (SELECT doc_id, list_sort(g) AS g FROM s) WHERE len(g) > 0 GROUP BY g), e AS MATERIALIZED (SELECT a, n, unnest(g) AS x FROM k),
p AS MATERIALIZED (SELECT u.a, v.a AS b FROM e u JOIN e v ON u.x = v.x AND u.a < v.a GROUP BY u.a, v.a, u.n, v.n HAVING 100 * count(*) >= {percent} * (u.n + v.n - count(*))),
edge AS MATERIALIZED (SELECT a, b FROM p UNION SELECT b, a FROM p), reach AS (SELECT a, a AS b FROM k UNION SELECT r.a, e.b FROM reach r JOIN edge e ON e.a = r.b),
c AS (SELECT a, min(b) AS component FROM reach GROUP BY a), m AS (SELECT s.doc_id, len(s.g) AS n, c.component FROM s LEFT JOIN k ON k.g = list_sort(s.g) AND len(s.g) > 0 LEFT JOIN c ON c.a = k.a)
SELECT doc_id, n::BIGINT AS n_shingles, coalesce(component, doc_id) AS component_id, coalesce(component, doc_id) = doc_id AS kept FROM m"""


def repeated_spans(width: int = 100) -> str:
    """Every string of `width` bytes with its first place, the bytes that later ones cover, and what is left."""
    return f"""WITH d AS MATERIALIZED (SELECT doc_id, hex(encode(coalesce(text, ''))) AS h FROM documents), w AS (SELECT doc_id, p, substr(h, 2 * p + 1, {2 * width}) AS s FROM (SELECT doc_id, h, unnest(range(0, len(h) // 2 - {width - 1})) AS p FROM d WHERE len(h) >= {2 * width})),
n AS MATERIALIZED (SELECT doc_id, p, row_number() OVER (PARTITION BY s ORDER BY doc_id, p) AS nth FROM w), g AS (SELECT doc_id, p, p - lag(p) OVER (PARTITION BY doc_id ORDER BY p) > {width} AS far FROM n WHERE nth > 1),
i AS (SELECT doc_id, p, sum(CASE WHEN far IS NULL OR far THEN 1 ELSE 0 END) OVER (PARTITION BY doc_id ORDER BY p) AS run FROM g), r AS MATERIALIZED (SELECT doc_id, run, min(p) AS low, max(p) + {width} AS high FROM i GROUP BY doc_id, run),
k AS (SELECT doc_id, sum(high - low) AS removed, count(*) AS spans FROM r GROUP BY doc_id),
edges AS (SELECT doc_id, low AS stop, coalesce(lag(high) OVER (PARTITION BY doc_id ORDER BY low), 0) AS start FROM r UNION ALL SELECT d.doc_id, len(d.h) // 2, max(r.high) FROM d JOIN r ON r.doc_id = d.doc_id GROUP BY d.doc_id, d.h),
left_ AS (SELECT e.doc_id, string_agg(substr(d.h, 2 * e.start + 1, 2 * (e.stop - e.start)), '' ORDER BY e.start) AS h FROM edges e JOIN d ON d.doc_id = e.doc_id GROUP BY e.doc_id)
SELECT d.doc_id, (len(d.h) // 2)::BIGINT AS n_bytes, coalesce(k.removed, 0)::BIGINT AS n_removed, coalesce(k.spans, 0)::BIGINT AS n_spans, sha256(unhex(coalesce(l.h, d.h))) AS kept_sha256 FROM d LEFT JOIN k ON k.doc_id = d.doc_id LEFT JOIN left_ l ON l.doc_id = d.doc_id"""
