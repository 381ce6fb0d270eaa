"""DuckDB SQL of the queries that SQL can express."""

from .quality_rules import FENCE, LEAST_GROUP, LEAST_SPREAD, MEASURES, PART

_WORD = r"[^\x20\x09-\x0D]+"


def measures_sql(docs: str) -> str:
    """CTEs up to ``measured``: every row of ``docs`` (a relation with doc_id, lang, source, text) with counts and measures."""
    return rf"""
rows AS (SELECT row_number() OVER () AS rid, doc_id, lang, source, coalesce(text, '') AS t FROM {docs}),
split_up AS (SELECT *, regexp_extract_all(t, '{_WORD}') AS ws,
    list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS ls FROM rows),
runs AS (SELECT rid, i, array_to_string(ws[i : i + 7], chr(1)) AS run
    FROM (SELECT rid, ws, unnest(range(1, len(ws) - 6)) AS i FROM split_up)),
twice AS (SELECT rid, i, lead(i) OVER (PARTITION BY rid ORDER BY i) AS nxt
    FROM (SELECT rid, i, count(*) OVER (PARTITION BY rid, run) AS c FROM runs) WHERE c > 1),
covered AS (SELECT rid, sum(least(8, coalesce(nxt - i, 8))) AS n FROM twice GROUP BY rid),
counted AS (SELECT s.rid, doc_id, lang, source, t, len(ws)::BIGINT AS n_words, coalesce(list_sum(list_transform(ws, lambda w: length(w))), 0)::BIGINT AS word_chars,
    length(regexp_replace(t, '[^#*$%&|<>]+', '', 'g'))::BIGINT AS n_symbols, (len(ls) - len(list_distinct(ls)))::BIGINT AS n_dup_lines,
    coalesce(n, 0)::BIGINT AS n_repeat_words, len(ls)::BIGINT AS n_lines, length(regexp_replace(t, '[^\p{{Lu}}]+', '', 'g'))::BIGINT AS n_capitals,
    length(regexp_replace(t, '[^!?]+', '', 'g'))::BIGINT AS n_marks,
    len(list_filter(ws, lambda w, i: i > 1 AND ws[i - 1] = w))::BIGINT AS n_stutters
    FROM split_up s LEFT JOIN covered c ON s.rid = c.rid),
measured AS (SELECT *, n_words < 20 OR 100 * n_repeat_words > 30 * n_words AS base_failed,
    CASE WHEN n_words = 0 THEN 0 ELSE 1000 * n_symbols // n_words END AS m_symbols,
    CASE WHEN n_words = 0 THEN 0 ELSE 1000 * n_repeat_words // n_words END AS m_repeats,
    CASE WHEN word_chars = 0 THEN 0 ELSE 1000 * n_capitals // word_chars END AS m_capitals,
    CASE WHEN n_words = 0 THEN 0 ELSE 1000 * n_marks // n_words END AS m_marks,
    CASE WHEN n_lines = 0 THEN 0 ELSE 1000 * n_dup_lines // n_lines END AS m_dup_lines,
    CASE WHEN n_words = 0 THEN 0 ELSE 1000 * n_stutters // n_words END AS m_stutters,
    CASE WHEN n_words = 0 THEN 0 ELSE 1000 * word_chars // n_words END AS m_word_length FROM counted)"""


def verdict_sql(docs: str) -> str:
    """CTEs up to ``judged``: ``measured`` with ``kept``."""
    each = " UNION ALL ".join(f"SELECT lang, source, '{m}' AS measure, m_{m} AS v FROM measured WHERE NOT base_failed" for m in MEASURES)
    fence = f"q3 + {FENCE} * greatest(q3 - q1, q2 // {PART}, {LEAST_SPREAD})"

    def level(name: str, by: str) -> str:
        comma = by + "," if by else ""
        part = f"PARTITION BY {comma} measure"
        return f"""
{name}_b AS (SELECT {comma} measure, bucket, sum(n) AS n FROM sketch GROUP BY {comma} measure, bucket),
{name}_c AS (SELECT *, sum(n) OVER ({part}) AS total, sum(n) OVER ({part} ORDER BY bucket) AS below FROM {name}_b),
{name}_q AS (SELECT {comma} measure, max(total) AS total, min(bucket) FILTER (below * 4 >= total) AS q1, min(bucket) FILTER (below * 4 >= total * 2) AS q2, min(bucket) FILTER (below * 4 >= total * 3) AS q3 FROM {name}_c GROUP BY {comma} measure),
{name}_f AS (SELECT {comma} measure, total, {fence} AS fence FROM {name}_q)"""

    within = " AND ".join(f"coalesce(m_{m} <= (SELECT max(fence) FROM limits f WHERE f.measure = '{m}' AND f.lang IS NOT DISTINCT FROM d.lang AND f.source IS NOT DISTINCT FROM d.source), true)" for m in MEASURES)
    return f"""{measures_sql(docs)},
long_form AS ({each}),
sketch AS (SELECT lang, source, measure, CASE WHEN v < 128 THEN v ELSE (v >> (length(bin(v)) - 7)) << (length(bin(v)) - 7) END AS bucket, count(*) AS n FROM long_form GROUP BY ALL),
{level('own', 'lang, source')},
{level('lng', 'lang')},
{level('whole', '')},
limits AS (SELECT o.lang, o.source, o.measure, CASE WHEN o.total >= {LEAST_GROUP} THEN o.fence WHEN l.total >= {LEAST_GROUP} THEN l.fence ELSE w.fence END AS fence
    FROM own_f o JOIN lng_f l ON o.lang IS NOT DISTINCT FROM l.lang AND o.measure = l.measure JOIN whole_f w ON w.measure = o.measure),
judged AS (SELECT *, NOT base_failed AND {within} AS kept FROM measured d)"""


_OP2 = f"""WITH {verdict_sql('documents')}
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, kept FROM judged"""

_OP7 = rf"""WITH sized AS (SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '{_WORD}'))::BIGINT AS size,
    ('0x' || substr(md5(coalesce(doc_id::VARCHAR, '') || '|' || md5(coalesce(text, ''))), 1, 15))::BIGINT AS key FROM documents),
by_source AS (SELECT source, sum(size)::BIGINT AS source_size FROM sized GROUP BY source),
weighed AS (SELECT *, [3, 1, 2][1 + (row_number() OVER (ORDER BY source COLLATE "C" NULLS LAST) - 1) % 3] AS weight, 2 * source_size AS cap, sum(source_size) OVER () AS total FROM by_source),
filled AS (SELECT *, cap / weight AS fill, (total * 1.5::DOUBLE - coalesce(sum(cap) OVER (ORDER BY cap / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))::DOUBLE
    / (sum(weight) OVER (ORDER BY cap / weight, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING)) AS rate FROM weighed),
goals AS (SELECT source, source_size, least(cap::DOUBLE, coalesce((SELECT arg_min(rate, fill) FROM filled WHERE rate * weight <= cap) * weight, cap::DOUBLE)) AS target FROM filled),
budgets AS (SELECT *, CASE WHEN source_size > 0 THEN floor(target / source_size)::BIGINT ELSE 0 END AS epochs FROM goals),
ordered AS (SELECT s.*, source_size, target, epochs, floor(target)::BIGINT - epochs * source_size AS budget,
    sum(size) OVER (PARTITION BY s.source ORDER BY key RANGE UNBOUNDED PRECEDING) AS upto, sum(size) OVER (PARTITION BY s.source, key) AS tie
    FROM sized s JOIN budgets b ON s.source IS NOT DISTINCT FROM b.source)
SELECT doc_id, source, size, source_size, target, (epochs * size + CASE WHEN upto <= budget THEN size WHEN upto - tie < budget THEN (budget - upto + tie) * size // tie ELSE 0 END)::BIGINT AS taken FROM ordered"""

_OP10 = r"""WITH parts AS (SELECT page_id, coalesce(regexp_extract(url, '(?s)^.*?://(.*)$', 1), '') AS rest FROM pages),
urls AS (SELECT page_id, translate(regexp_extract(rest, '^[^/?#]*', 0), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, regexp_extract(rest, '^[^/?#]*(/[^?#]*)', 1) AS path, row_number() OVER () AS rid FROM parts),
rules(h, p, v) AS (VALUES ('com', '/', 'allow'), ('example.com', '/en/', 'block'), ('www.example.com', '/en/', 'allow'), ('net', '/es/', 'block'), ('net', '/fr/', 'block')),
fits AS (SELECT rid, arg_max(h || p, length(h) * 1000 + length(p)) AS rule, arg_max(v, length(h) * 1000 + length(p)) AS v FROM urls JOIN rules ON (host = h OR ends_with(host, '.' || h)) AND starts_with(path, p) GROUP BY rid)
SELECT page_id, host, path, rule, coalesce(v, CASE WHEN regexp_matches(host, '(^|\.)(ads-track\.example\.org|cheap-pills\.example\.(net|org)|free-bets\.example\.org)$') THEN 'block' ELSE 'allow' END) AS verdict FROM urls LEFT JOIN fits USING (rid)"""

SQL = {"op10_url_filters": _OP10, "op2_quality_rules": _OP2, "op7_mix_sources": _OP7}
