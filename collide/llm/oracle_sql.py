"""DuckDB SQL of those operators that SQL can express; it gives the rows of the registered queries."""

from __future__ import annotations

from . import bm25_search, line_dedup, quality_rules, secret_scan, substring_dedup

SPACE = r"[\x20\x09-\x0D]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def words(text: str = "coalesce(text, '')") -> str:
    return f"list_filter(regexp_split_to_array({text}, '{SPACE}'), lambda x: x <> '')"


def folded(column: str = "text") -> str:
    return f"translate(coalesce({column}, ''), '{UPPER}', '{LOWER}')"


def _secrets() -> str:
    each = []
    for rank, r in enumerate(secret_scan.RULES):
        p = r.pattern.replace("'", "''")
        each.append(f"""SELECT doc_id, '{r.kind}' AS kind, {rank} AS rank, unnest(regexp_extract_all(t, '{p}')) AS m, unnest(regexp_extract_all(t, '{p}', {r.group})) AS g,
          unnest(regexp_split_to_array(t, '{p}')[1:len(regexp_extract_all(t, '{p}'))]) AS b, generate_subscripts(regexp_extract_all(t, '{p}'), 1) AS k, {r.least} AS least FROM d WHERE regexp_matches(t, '{p}')""")
    kinds = ", ".join(f"'{r.kind}'" for r in secret_scan.BASE)
    return f"""WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents), f AS ({' UNION ALL '.join(each)}),
      e AS (SELECT *, sum(length(b) + length(m)) OVER (PARTITION BY doc_id, kind ORDER BY k) AS stop FROM f),
      s AS (SELECT doc_id, kind, rank, CAST(stop - length(m) AS BIGINT) AS start, CAST(stop AS BIGINT) AS stop, kind || ':' || CAST(stop - length(m) AS BIGINT) || ':' || CAST(stop AS BIGINT) AS w FROM e WHERE length(g) >= least)
      SELECT d.doc_id, {', '.join(f"count(*) FILTER (WHERE kind = '{r.kind}') AS n_{r.kind}" for r in secret_scan.BASE)}, sha256(coalesce(string_agg(w, ',' ORDER BY start, rank) FILTER (WHERE kind IN ({kinds})), '')) AS base_sha256,
      coalesce(string_agg(w, ',' ORDER BY start, rank), '') AS spans, count(kind) AS n_spans FROM d LEFT JOIN s USING (doc_id) GROUP BY d.doc_id"""


def _lines() -> str:
    run, long = line_dedup.RUN, line_dedup.LONG
    return f"""WITH d AS (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS ls FROM documents),
      l AS (SELECT doc_id, x, i, regexp_matches(x, '[^\\x20\\x09-\\x0D]') AS ok, len({words('x')}) AS n FROM (SELECT doc_id, unnest(ls) AS x, generate_subscripts(ls, 1) AS i FROM d)),
      o AS (SELECT *, row_number() OVER (PARTITION BY doc_id ORDER BY i) AS r FROM l WHERE ok),
      w AS (SELECT a.doc_id, a.i, 'r' || a.x || chr(10) || b.x AS name, [a.i, b.i] AS js FROM o a JOIN o b ON a.doc_id = b.doc_id AND b.r = a.r + {run - 1}
        UNION ALL SELECT doc_id, i, 'l' || x, [i] FROM o WHERE n >= {long}),
      later AS (SELECT * FROM w QUALIFY row_number() OVER (PARTITION BY name ORDER BY doc_id, i) > 1),
      gone AS (SELECT DISTINCT doc_id, unnest(js) AS i FROM later)
      SELECT l.doc_id, count(*) AS n_lines, count(g.i) AS n_removed, sha256(coalesce(string_agg(l.x, chr(10) ORDER BY l.i) FILTER (WHERE g.i IS NULL), '')) AS kept_sha256 FROM l LEFT JOIN gone g ON g.doc_id = l.doc_id AND g.i = l.i GROUP BY l.doc_id"""


def _over(x: quality_rules.Limits) -> str:
    return f"(n_symbols > {x.symbols} * word_chars OR n_dup_lines > {x.dup_lines} * n_lines OR n_repeat_words > {x.repeats} * n_words OR (letters >= 20 AND capitals > {x.capitals} * letters))"


def _quality() -> str:
    n = quality_rules.WINDOW
    return f"""WITH d AS (SELECT doc_id, source, coalesce(text, '') AS t, {words()} AS w FROM documents),
      g AS (SELECT doc_id, i, w[i:i + {n - 1}] AS s FROM d, unnest(range(1, len(w) - {n - 2})) AS r(i) WHERE len(w) >= {n}),
      again AS (SELECT doc_id, i FROM g QUALIFY count(*) OVER (PARTITION BY doc_id, s) > 1),
      rep AS (SELECT doc_id, count(DISTINCT j) AS c FROM (SELECT doc_id, unnest(range(i, i + {n})) AS j FROM again) GROUP BY doc_id),
      ln AS (SELECT doc_id, count(*) AS n_lines, count(*) - count(DISTINCT x) AS dup FROM (SELECT doc_id, unnest(string_split(t, chr(10))) AS x FROM d) WHERE regexp_matches(x, '[^\\x20\\x09-\\x0D]') GROUP BY doc_id),
      m AS (SELECT d.doc_id, d.source, CAST(len(w) AS BIGINT) AS n_words, CAST(length(regexp_replace(t, '{SPACE}', '', 'g')) AS BIGINT) AS word_chars, CAST(length(t) - length(translate(t, '{quality_rules.SYMBOLS}', '')) AS BIGINT) AS n_symbols,
        CAST(coalesce(ln.dup, 0) AS BIGINT) AS n_dup_lines, coalesce(ln.n_lines, 0) AS n_lines, CAST(coalesce(rep.c, 0) AS BIGINT) AS n_repeat_words,
        length(regexp_replace(t, '[^A-Z]', '', 'g')) AS capitals, length(regexp_replace(t, '[^A-Za-z]', '', 'g')) AS letters FROM d LEFT JOIN ln USING (doc_id) LEFT JOIN rep USING (doc_id)),
      b AS (SELECT *, n_words < {quality_rules.MIN_WORDS} OR 100 * n_repeat_words > 20 * n_words AS base_failed FROM m),
      f AS (SELECT *, base_failed OR {_over(quality_rules.USUAL)} AS failed FROM b),
      h AS (SELECT source, count(*) AS n, count(*) FILTER (WHERE failed) AS bad FROM f GROUP BY source),
      p AS (SELECT avg(bad / n) AS m, var_pop(bad / n) AS v FROM h),
      q AS (SELECT m, least(greatest(m * (1 - m) / greatest(v, 1e-6) - 1, 2.0), 1000.0) AS s FROM p),
      z AS (SELECT source, m, n + s + 1 AS weight, (bad + m * s) / (n + s) AS rate FROM h, q)
      SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT failed AND NOT (rate - m > {quality_rules.SUSPECT} * sqrt(rate * (1 - rate) / weight) AND {_over(quality_rules.STRICT)}) AS kept, round(rate, 6) AS shrunk_rate FROM f JOIN z ON f.source IS NOT DISTINCT FROM z.source"""


def _search() -> str:
    return f"""WITH t AS (SELECT doc_id, unnest({words(folded())}) AS w FROM documents), tf AS (SELECT doc_id, w, count(*) AS c FROM t GROUP BY ALL), dl AS (SELECT doc_id, count(*) AS l FROM t GROUP BY ALL),
      n AS (SELECT count(*) AS n, (SELECT count(*) FROM t) / CAST(count(*) AS DOUBLE) AS mean FROM documents), q AS (SELECT doc_id AS query_id, w, c AS times FROM tf WHERE doc_id % 20 = 0),
      df AS (SELECT w, count(*) AS df FROM tf WHERE w IN (SELECT w FROM q) GROUP BY w),
      s AS (SELECT query_id, doc_id, round(sum(times * ln(1 + (n - df + 0.5) / (df + 0.5)) * c * {bm25_search.K1 + 1} / (c + {bm25_search.K1} * ({1 - bm25_search.B} + {bm25_search.B} * l / mean))), 6) AS score FROM q JOIN df USING (w) JOIN tf USING (w) JOIN dl USING (doc_id), n GROUP BY ALL)
      SELECT query_id, CAST(rank AS INTEGER) AS rank, doc_id, score FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, doc_id) AS rank FROM s WHERE score > 0) WHERE rank <= {bm25_search.K}"""


def _components() -> str:
    return f"""WITH RECURSIVE d AS (SELECT doc_id, {words(folded())} AS w FROM documents),
      s AS (SELECT DISTINCT doc_id, array_to_string(w[i:i + 3], ' ') AS s FROM d, unnest(range(1, greatest(len(w) - 3, 1) + 1)) AS r(i) WHERE len(w) > 0),
      n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
      e AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS c FROM s a JOIN s b ON a.s = b.s AND a.doc_id <> b.doc_id GROUP BY ALL),
      l AS (SELECT x, y FROM e JOIN n a ON a.doc_id = x JOIN n b ON b.doc_id = y WHERE 100 * c >= 85 * (a.n + b.n - c)),
      r(doc_id, other) AS (SELECT doc_id, doc_id FROM d UNION SELECT r.doc_id, l.y FROM r JOIN l ON l.x = r.other)
      SELECT r.doc_id, CAST(coalesce(any_value(n.n), 0) AS BIGINT) AS n_shingles, min(other) AS component_id FROM r LEFT JOIN n ON n.doc_id = r.doc_id GROUP BY r.doc_id"""


def _substrings() -> str:
    w = substring_dedup.WINDOW
    return f"""WITH d AS (SELECT doc_id, {words()} AS w FROM documents),
      g AS (SELECT doc_id, i, md5(array_to_string(w[i:i + {w - 1}], ' ')) AS h FROM d, unnest(range(1, len(w) - {w - 2})) AS r(i) WHERE len(w) >= {w}),
      again AS (SELECT doc_id, i FROM g QUALIFY count(*) OVER (PARTITION BY h) > 1),
      gone AS (SELECT DISTINCT doc_id, unnest(range(i, i + {w})) AS j FROM again),
      o AS (SELECT doc_id, unnest(w) AS x, generate_subscripts(w, 1) AS j FROM d),
      k AS (SELECT o.doc_id, count(g.j) AS removed, string_agg(o.x, ' ' ORDER BY o.j) FILTER (WHERE g.j IS NULL) AS t FROM o LEFT JOIN gone g ON g.doc_id = o.doc_id AND g.j = o.j GROUP BY o.doc_id)
      SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, coalesce(removed, 0) AS n_removed, sha256(coalesce(t, '')) AS kept_sha256 FROM d LEFT JOIN k USING (doc_id)"""


SQL = {
    "op1_secret_scan": _secrets(),
    "op2_line_dedup": _lines(),
    "op3_quality_rules": _quality(),
    "op6_bm25_topk": _search(),
    "op7_jaccard_join": _components(),
    "op8_substring_dedup": _substrings(),
}
