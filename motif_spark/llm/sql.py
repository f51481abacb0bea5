"""SQL counterparts of the native operators, for DuckDB on the same tables."""

from __future__ import annotations

from . import license, mixing, quality

_WORDS = r"list_filter(string_split_regex(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '')"


def _count(text: str, chars: str) -> str:
    chars = chars.replace("'", "''")
    return f"(length({text}) - length(translate({text}, '{chars}', '')))"


_DENSE = "length(regexp_replace(x, '[\\x20\\x09-\\x0D]+', '', 'g'))"
QUALITY = f"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS t, {_WORDS} AS w FROM documents),
win AS (SELECT doc_id, i, hash(w[i], w[i + 1], w[i + 2], w[i + 3], w[i + 4]) AS h FROM (SELECT doc_id, w, unnest(range(1, len(w) - {quality.WINDOW - 2})) AS i FROM d)),
dup AS (SELECT doc_id, i FROM (SELECT *, count(*) OVER (PARTITION BY doc_id, h) AS c FROM win) WHERE c > 1),
rep AS (SELECT doc_id, count(DISTINCT i + k) AS n FROM dup, range({quality.WINDOW}) AS r(k) GROUP BY 1),
l AS (SELECT doc_id, x, i, count(*) OVER (PARTITION BY doc_id) AS lines, len(list_filter(string_split_regex(x, '[\\x20\\x09-\\x0D]+'), lambda y: y <> '')) AS n, {_count('x', quality.MARKS)} AS marks
  FROM (SELECT doc_id, unnest(string_split(t, chr(10))) AS x, unnest(range(len(string_split(t, chr(10))))) AS i FROM d)),
sh AS (SELECT *, n > 0 AND n <= {quality.RUN_WORDS} AND marks = 0 AS short FROM l),
rn AS (SELECT *, sum(CASE WHEN short THEN 0 ELSE 1 END) OVER (PARTITION BY doc_id ORDER BY i) AS part FROM sh),
ru AS (SELECT *, short AND count(CASE WHEN short THEN 1 END) OVER (PARTITION BY doc_id, part) >= {quality.RUN_LINES} AS in_run FROM rn),
j AS (SELECT *, {_DENSE} AS c, n = 0 OR ((n < {quality.LONG_LINE} OR marks > 0) AND marks + {_count('x', quality.SYMBOLS)} <= greatest(4.0, n * {quality.MARKS_PER_WORD})
  AND {_count('x', '|•›»')} <= n * {quality.BARS_PER_WORD} AND NOT in_run AND NOT (n <= {quality.EDGE_WORDS} AND marks = 0 AND (i < {quality.EDGE_LINES} OR i >= lines - {quality.EDGE_LINES}) AND regexp_matches(x, '{quality.MENU}'))
  AND (n > {quality.SHORT_LINE} OR NOT regexp_matches(x, '{quality.BOILERPLATE}'))) AS ok FROM ru),
s AS (SELECT doc_id, CAST(sum(c) AS BIGINT) AS word_chars, sum(CASE WHEN ok THEN c ELSE 0 END) AS kept_chars, sum(CASE WHEN ok THEN n ELSE 0 END) AS kept_words, CAST(sum(CASE WHEN ok THEN 0 ELSE 1 END) AS BIGINT) AS n_failed_lines,
  CAST(count(CASE WHEN n > 0 THEN 1 END) - count(DISTINCT CASE WHEN n > 0 THEN x END) AS BIGINT) AS n_dup_lines FROM j GROUP BY 1),
a AS (SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, word_chars, CAST({_count('t', quality.SYMBOLS)} AS BIGINT) AS n_symbols, n_dup_lines, CAST(coalesce(rep.n, 0) AS BIGINT) AS n_repeat_words,
  CASE WHEN word_chars > 0 THEN 1 - CAST(kept_chars AS DOUBLE) / word_chars ELSE 1.0 END AS lost, kept_words, n_failed_lines FROM d JOIN s USING (doc_id) LEFT JOIN rep USING (doc_id)),
b AS (SELECT *, n_words < {quality.MIN_WORDS} OR 100 * n_repeat_words > {quality.MAX_REPEAT_PERCENT} * n_words AS base_failed FROM a)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND lost <= {quality.MAX_LOST} AND kept_words >= {quality.MIN_WORDS} AS kept, n_failed_lines FROM b
"""


def _license() -> str:
    index = license.rare_index()
    total = {t: sum(x[1] == t for x in index) for t in range(len(license.NOTICES))}
    postings = ", ".join(f"('{w}', {t}, {k})" for w, t, k in index)
    notices = ", ".join(f"({t}, '{label}', {total[t]}, ' {phrase} ')" for t, (label, _, phrase) in enumerate(license.NOTICES))
    base = ", ".join(f"('{label}', {len(p.split())}, '{p}')" for label, p in license.BASE)
    return f"""
WITH d AS (SELECT doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '{license.NO_WORD}'), lambda x: x <> '') AS w FROM documents),
u AS (SELECT doc_id, w, i FROM (SELECT doc_id, w, unnest(range(1, len(w) + 1)) AS i FROM d)),
b AS (SELECT doc_id, label, i - 1 AS i FROM u, (VALUES {base}) AS p(label, n, phrase) WHERE array_to_string(w[i : i + n - 1], ' ') = phrase),
v AS (SELECT doc_id, t, i - k AS shift, count(*) AS c FROM u JOIN (VALUES {postings}) AS q(word, t, k) ON w[i] = word GROUP BY 1, 2, 3),
m AS (SELECT doc_id, t, max(c) AS c FROM v GROUP BY 1, 2),
n AS (SELECT doc_id, label, c / total AS s, c >= {license.AGREE} * total AND contains(' ' || array_to_string(w, ' ') || ' ', phrase) AS ok FROM m JOIN (VALUES {notices}) AS z(t, label, total, phrase) USING (t) JOIN d USING (doc_id)),
x AS (SELECT doc_id, count(*) AS n_base, min(i) AS first_word, max(i) AS last_word, array_to_string(list_sort(list(DISTINCT label)), ',') AS base_labels FROM b GROUP BY 1),
y AS (SELECT doc_id, array_to_string(list_sort(list(DISTINCT label)), ',') AS labels FROM (SELECT doc_id, label FROM b UNION ALL SELECT doc_id, label FROM n WHERE ok) GROUP BY 1),
s AS (SELECT doc_id, max(s) AS score FROM n GROUP BY 1)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, coalesce(n_base, 0) AS n_base, first_word, last_word, coalesce(base_labels, '') AS base_labels, coalesce(labels, '') AS labels, least(1.0, coalesce(score, 0.0)) AS score
FROM d LEFT JOIN x USING (doc_id) LEFT JOIN y USING (doc_id) LEFT JOIN s USING (doc_id)
"""


LICENSE = _license()


def _lague(source: str, group: str) -> str:
    """Rows party, seats_won of rows with party, votes, seats, by highest quotients near the proportional share."""
    by = f"PARTITION BY {group}"
    return f"""SELECT {group}, party, any_value(low) + CAST(sum(CASE WHEN r <= free AND votes > 0 THEN 1 ELSE 0 END) AS BIGINT) AS won FROM (
  SELECT *, row_number() OVER ({by} ORDER BY votes / (2 * k + 1) DESC, party, k) AS r FROM (SELECT *, unnest(range(low, high + 1)) AS k FROM (SELECT *, seats - sum(low) OVER ({by}) AS free FROM (
    SELECT *, CASE WHEN v > 0 THEN greatest(0, CAST(floor(votes * seats / v * (1 - n / greatest(seats, 1))) AS BIGINT) - 1) ELSE 0 END AS low, CASE WHEN v > 0 THEN CAST(ceil(votes * seats / v * (1 + n / greatest(seats, 1))) AS BIGINT) + 1 ELSE 1 END AS high
    FROM (SELECT *, sum(votes) OVER ({by}) AS v, count(*) OVER ({by}) AS n FROM {source}))))) GROUP BY {group}, party"""


MIX = f"""
WITH d AS (SELECT doc_id, source, CAST(len({_WORDS}) AS BIGINT) AS size FROM documents),
p AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM d GROUP BY 1),
q AS (SELECT *, row_number() OVER (ORDER BY source NULLS LAST) - 1 AS sid FROM p),
r AS (SELECT *, [3.0::DOUBLE, 1.0, 2.0][CAST(sid % 3 + 1 AS INT)] AS weight, 2.0::DOUBLE * source_size AS lim FROM q),
s AS (SELECT *, (1.5::DOUBLE * sum(source_size) OVER () - coalesce(sum(lim) OVER f, 0)) / (sum(weight) OVER () - coalesce(sum(weight) OVER f, 0)) AS level FROM r WINDOW f AS (ORDER BY lim / weight, sid ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
t AS (SELECT *, CASE WHEN sum(lim) OVER () <= 1.5 * sum(source_size) OVER () THEN lim ELSE least(lim, max(level) OVER () * weight) END AS target FROM s),
a AS (SELECT 0 AS g, sid AS party, target AS votes, CAST(round(sum(target) OVER () / {mixing.BLOCK}) AS BIGINT) AS seats FROM t),
b AS ({_lague('a', 'g')}),
c AS (SELECT t.*, won AS seats, greatest(1, CAST(ceil(source_size / {mixing.SHARD_WORDS}) AS BIGINT)) AS shards FROM t JOIN b ON party = sid),
h AS (SELECT *, CAST('0x' || substr(place, 1, 8) AS BIGINT) % shards AS shard FROM (SELECT d.*, c.source_size, c.target, c.sid, c.seats, c.shards, md5('7:' || doc_id) AS place FROM d JOIN c ON d.source IS NOT DISTINCT FROM c.source)),
v AS (SELECT sid, shard AS party, seats, sum(size) AS votes FROM h GROUP BY 1, 2, 3),
w AS ({_lague('v', 'sid')}),
x AS (SELECT h.*, won * {mixing.BLOCK} AS quota, sum(size) OVER (PARTITION BY h.sid, shard) AS total, sum(size) OVER (PARTITION BY h.sid, shard ORDER BY place, size ROWS UNBOUNDED PRECEDING) - size AS before FROM h JOIN w ON w.sid = h.sid AND w.party = h.shard),
y AS (SELECT *, CASE WHEN total > 0 THEN least(2, quota // total) ELSE 0 END AS rounds FROM x)
SELECT doc_id, size, source_size, target, CAST(least(rounds * size + greatest(0, least(size, quota - rounds * total - before)), 2 * size) AS BIGINT) AS taken FROM y
"""
