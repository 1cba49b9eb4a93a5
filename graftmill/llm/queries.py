"""The registered queries of this subpackage and their SQL twins."""

from . import common, html_text, langid, lm_score, mixing, near_dup, packing, quality, repair, search, suffix_dedup


def op2_mix_sources(spark, sf_dir):
    """Every source to the same share, as many rows expected as there are."""
    return mixing.mix_sources(common.documents(spark, sf_dir))


QUERIES = {
    "op1_ngram_jaccard_join": near_dup.op1_ngram_jaccard_join,
    "op2_mix_sources": op2_mix_sources,
    "op3_bm25_search": search.op3_bm25_search,
    "op4_language_id": langid.op4_language_id,
    "op5_best_fit_packing": packing.op5_best_fit_packing,
    "op6_quality_cascade": quality.op6_quality_cascade,
    "op7_repair_ids": repair.op7_repair_ids,
    "op8_suffix_dedup": suffix_dedup.op8_suffix_dedup,
    "op9_stupid_backoff": lm_score.op9_stupid_backoff,
    "op10_html_text": html_text.op10_html_text,
}

ORACLE_SQL = {
    "op2_mix_sources": """
WITH s AS (SELECT source, count(*) AS n FROM documents GROUP BY source),
r AS (SELECT source, (1.0::DOUBLE / count(*) OVER ()) * (sum(n) OVER ())::DOUBLE / n AS rate FROM s),
m AS (SELECT source, rate, greatest(1, ceil(rate / 16.0))::INT AS parts, rate / greatest(1, ceil(rate / 16.0)) AS mean FROM r),
p AS (SELECT source, k, exp(k * ln(mean) - mean - lgamma(k + 1)) AS pk FROM m, range(0, 97) t(k)),
c AS (SELECT source, k, sum(pk) OVER (PARTITION BY source ORDER BY k) AS cdf FROM p),
u AS (SELECT d.doc_id, d.source, ('0x' || substr(md5('17|' || d.doc_id || '|' || j), 1, 13))::UBIGINT::DOUBLE / 4503599627370496.0 AS u
      FROM documents d JOIN m ON d.source IS NOT DISTINCT FROM m.source, range(1, m.parts + 1) t(j)),
n AS (SELECT u.doc_id, count(*) AS copies FROM u JOIN c ON u.source IS NOT DISTINCT FROM c.source AND c.cdf <= u.u GROUP BY u.doc_id)
SELECT d.doc_id, d.text, d.lang, d.source, d.n_chars, g.copy::INT AS copy,
       ('0x' || substr(md5('order17|' || d.doc_id || '|' || g.copy), 1, 15))::UBIGINT::BIGINT AS shuffle_key
FROM documents d JOIN n USING (doc_id), range(1, n.copies + 1) g(copy)
""",
    "op9_stupid_backoff": r"""
WITH d AS (SELECT doc_id, list_filter(regexp_split_to_array(lower(coalesce(text, '')), '\s+'), lambda x: x <> '') AS w FROM documents),
p AS (SELECT doc_id, i, w[i] AS a, CASE WHEN i > 1 THEN w[i-1] || ' ' || w[i] END AS b, CASE WHEN i > 2 THEN w[i-2] || ' ' || w[i-1] || ' ' || w[i] END AS c FROM d, range(1, len(w) + 1) r(i)),
n AS (SELECT *, count(*) OVER (PARTITION BY a) - count(*) OVER (PARTITION BY a, doc_id) AS c1,
             CASE WHEN b IS NULL THEN 0 ELSE count(*) OVER (PARTITION BY b) - count(*) OVER (PARTITION BY b, doc_id) END AS c2,
             CASE WHEN c IS NULL THEN 0 ELSE count(*) OVER (PARTITION BY c) - count(*) OVER (PARTITION BY c, doc_id) END AS c3,
             count(*) OVER () - count(*) OVER (PARTITION BY doc_id) AS others FROM p),
l AS (SELECT *, lag(c1) OVER (PARTITION BY doc_id ORDER BY i) AS p1, lag(c2) OVER (PARTITION BY doc_id ORDER BY i) AS p2 FROM n),
s AS (SELECT doc_id, CASE WHEN c3 > 0 THEN ln(c3) - ln(p2)
                          WHEN c2 > 0 THEN ln(c2) - ln(p1) + least(i - 2, 1) * ln(0.4)
                          ELSE ln(greatest(c1, 1)) - ln(greatest(others, 1)) + (least(i - 1, 2) + (c1 = 0)::INT) * ln(0.4) END AS v FROM l)
SELECT d.doc_id, len(d.w)::BIGINT AS n_words, round(m.v, 6) AS mean_log
FROM d LEFT JOIN (SELECT doc_id, sum(v) / count(*) AS v FROM s GROUP BY doc_id) m USING (doc_id)
""",
    "op3_bm25_search": r"""
WITH t AS (SELECT doc_id, unnest(regexp_extract_all(lower(text), '[\p{L}\p{N}]+')) AS w FROM documents),
n AS (SELECT doc_id, w, count(*) AS tf FROM t GROUP BY ALL),
l AS (SELECT d.doc_id, coalesce(x.dl, 0) AS dl FROM documents d LEFT JOIN (SELECT doc_id, sum(tf) AS dl FROM n GROUP BY doc_id) x USING (doc_id)),
g AS (SELECT count(*) AS docs, avg(dl) AS mean FROM l),
f AS (SELECT w, count(*) AS df FROM n GROUP BY w),
s AS (SELECT q.doc_id AS query_id, n.doc_id, round(sum(q.tf * ln(1 + (docs - df + 0.5) / (df + 0.5)) * (n.tf * 2.2 / (n.tf + 1.2 * (0.25 + 0.75 * dl / mean)))), 6) AS score
      FROM n q JOIN n ON q.w = n.w JOIN f ON f.w = n.w JOIN l ON l.doc_id = n.doc_id, g WHERE q.doc_id % 50 = 0 GROUP BY ALL),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, doc_id) AS rank FROM s WHERE score > 0)
SELECT query_id, rank::INT AS rank, doc_id, score FROM r WHERE rank <= 10
""",
    "op6_quality_cascade": r"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
w AS (SELECT doc_id, t, list_filter(regexp_split_to_array(t, '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws,
             list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS ls FROM d),
g AS (SELECT doc_id, i, ws[i:i+2] AS tri FROM w, range(1, len(ws) - 1) r(i)),
h AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, tri) AS n FROM g) WHERE n > 1),
rep AS (SELECT doc_id, count(DISTINCT p) AS n_repeat_words FROM (SELECT doc_id, unnest([i, i + 1, i + 2]) AS p FROM h) GROUP BY doc_id),
freq AS (SELECT doc_id, max(n) AS top FROM (SELECT doc_id, x, count(*) AS n FROM (SELECT doc_id, unnest(ws) AS x FROM w) GROUP BY ALL) GROUP BY doc_id),
f AS (SELECT w.doc_id, len(ws)::BIGINT AS n_words, coalesce(list_sum(list_transform(ws, lambda x: length(x))), 0)::BIGINT AS word_chars,
             length(regexp_replace(t, '[^#*$%&|<>]', '', 'g'))::BIGINT AS n_symbols,
             (len(ls) - len(list_distinct(ls)))::BIGINT AS n_dup_lines, coalesce(n_repeat_words, 0)::BIGINT AS n_repeat_words,
             len(ls) AS nl, coalesce(top, 0) AS top,
             length(regexp_replace(t, '[^\p{L}]', '', 'g')) AS letters, length(regexp_replace(t, '[^\p{Lu}]', '', 'g')) AS upper_letters,
             len(list_filter(ws, lambda x: regexp_matches(x, '\p{L}'))) AS wordy,
             len(list_filter(ls, lambda x: regexp_matches(x, '(\.\.\.|…)[\x20\x09-\x0D]*$'))) AS dots
      FROM w LEFT JOIN rep USING (doc_id) LEFT JOIN freq USING (doc_id)),
b AS (SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed FROM f)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
       NOT base_failed AND word_chars BETWEEN 2 * n_words AND 14 * n_words AND 10 * n_symbols <= n_words AND 10 * n_dup_lines <= 3 * nl
       AND 2 * upper_letters <= letters AND 10 * wordy >= 6 * n_words AND 10 * top <= 3 * n_words AND 10 * dots <= 3 * nl AS kept
FROM b
""",
}
