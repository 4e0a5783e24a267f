"""DuckDB SQL of the operators that SQL can express, over whole tables.

op1 has none, as DuckDB has no CRC-32; op9 orders documents by a hash that it lacks; op10 adds what fitted trees choose, and the
pipeline contains op9.  The tests hold these against brute force or their laws.
"""

WORD = r"[^\x20\x09-\x0D]+"
ALNUM = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def _lower(text: str) -> str:
    """A-Z to a-z, and nothing else."""
    return f"translate({text}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"


def _words(text: str, pattern: str = WORD) -> str:
    return f"regexp_extract_all(coalesce({text}, ''), '{pattern}')"


OP2 = f"""
WITH d AS (SELECT doc_id, {_words('text')} AS w FROM documents),
windows AS (SELECT doc_id, p, md5(array_to_string(w[p:p + 49], ' ')) AS h FROM (SELECT doc_id, w, unnest(range(1, len(w) - 48)) AS p FROM d WHERE len(w) >= 50)),
gone AS (SELECT DISTINCT doc_id, p + k AS p FROM (SELECT doc_id, p, min(doc_id) OVER (PARTITION BY h) AS least FROM windows), range(50) AS r(k) WHERE doc_id > least),
lists AS (SELECT doc_id, list(p) AS cut FROM gone GROUP BY doc_id),
kept AS (SELECT d.doc_id, len(w) AS n, coalesce(len(cut), 0) AS c, CASE WHEN cut IS NULL THEN w ELSE [w[i] FOR i IN range(1, len(w) + 1) IF NOT list_contains(cut, i)] END AS k FROM d LEFT JOIN lists ON d.doc_id = lists.doc_id)
SELECT doc_id, n::BIGINT AS n_words, c::BIGINT AS n_removed, sha256(array_to_string(k, ' ')) AS kept_sha256 FROM kept
"""

OP3 = f"""
WITH items AS (SELECT item_id::VARCHAR AS item, {_words(_lower('text'), ALNUM)} AS w FROM benchmark),
patterns AS (SELECT item, least(13, len(w)) AS m, array_to_string(w[p:p + least(13, len(w)) - 1], ' ') AS x FROM (SELECT item, w, unnest(range(1, len(w) - least(13, len(w)) + 2)) AS p FROM items WHERE len(w) > 0)),
sizes AS (SELECT DISTINCT m FROM patterns),
d AS (SELECT doc_id, {_words(_lower('text'), ALNUM)} AS w FROM documents),
windows AS (SELECT doc_id, p, m, array_to_string(w[p:p + m - 1], ' ') AS x FROM (SELECT doc_id, w, m, unnest(range(1, len(w) - m + 2)) AS p FROM d, sizes WHERE len(w) >= m)),
hits AS (SELECT DISTINCT doc_id, p, m, item FROM windows JOIN patterns USING (m, x)),
words AS (SELECT doc_id, count(DISTINCT p + k) AS n FROM hits, range(13) AS r(k) WHERE k < m GROUP BY doc_id),
found AS (SELECT doc_id, list_sort(list(DISTINCT item)) AS items FROM hits GROUP BY doc_id)
SELECT d.doc_id, len(w)::BIGINT AS n_words, coalesce(n, 0)::BIGINT AS n_hit, coalesce(len(items), 0)::BIGINT AS n_items,
  sha256(coalesce(array_to_string(items, ','), '')) AS items_sha256, coalesce(n, 0) > 0 AND 20 * coalesce(n, 0) >= len(w) AS contaminated
FROM d LEFT JOIN words USING (doc_id) LEFT JOIN found USING (doc_id)
"""

_UPPER_HOST = "coalesce(regexp_extract({u}, '(?s)^.*?://([^/?#]*)([^?#]*)', 1), '')"
_HOST = lambda u: _lower(_UPPER_HOST.format(u=u))
_LINK = "(?i)<a\\s[^>]*?href\\s*=\\s*[\"'']?([^\"''\\s>]+)"
#: Rounds after which ranks stand still to nine digits.
_ROUNDS = 140
OP4 = f"""
WITH RECURSIVE p AS (SELECT page_id, html, {_HOST('url')} AS host, coalesce(regexp_extract(url, '(?s)^.*?://([^/?#]*)([^?#]*)', 2), '') AS path FROM pages),
rules AS (SELECT * FROM (VALUES ('block', 'net/', 'net', '/'), ('allow', 'example.net/en/', 'example.net', '/en/'), ('block', 'example.com/de/', 'example.com', '/de/'), ('allow', 'org/fr/', 'org', '/fr/')) AS v(verdict, rule, name, start)),
fits AS (SELECT page_id, max_by(rule, (length(rule), rule)) AS rule, max_by(verdict, (length(rule), rule)) AS verdict FROM p JOIN rules ON (host = name OR ends_with(host, '.' || name)) AND starts_with(path, start) GROUP BY page_id),
shares AS (SELECT host, avg(CASE WHEN verdict = 'allow' THEN 1.0 ELSE 0.0 END) AS allow, avg(CASE WHEN verdict = 'block' THEN 1.0 ELSE 0.0 END) AS block FROM p LEFT JOIN fits USING (page_id) GROUP BY host),
chosen AS (SELECT 'trust' AS kind, host, allow AS s FROM shares WHERE allow > 0 UNION ALL SELECT 'distrust', host, block FROM shares WHERE block > 0),
seeds AS (SELECT kind, host, s / sum(s) OVER (PARTITION BY kind) AS seed FROM chosen),
hrefs AS (SELECT host AS src, unnest(regexp_extract_all(coalesce(html, ''), '{_LINK}', 1)) AS u FROM p),
links AS (SELECT src, dst, count(*) AS n FROM (SELECT src, {_HOST("CASE WHEN starts_with(u, '//') THEN 'http:' || u ELSE u END")} AS dst FROM hrefs WHERE contains(u, '://') OR starts_with(u, '//')) WHERE src <> dst GROUP BY ALL),
edges AS (SELECT 'trust' AS kind, src, dst, n FROM links UNION ALL SELECT 'distrust', dst, src, n FROM links),
weighted AS (SELECT kind, src, dst, n / sum(n) OVER (PARTITION BY kind, src) AS w FROM edges),
nodes AS (SELECT kind, host, coalesce(seed, 0.0) AS seed FROM (SELECT kind, src AS host FROM weighted UNION SELECT kind, dst FROM weighted UNION SELECT kind, host FROM seeds) LEFT JOIN seeds USING (kind, host)),
ranks AS (
  SELECT 0 AS round, kind, host, seed AS rank FROM nodes
  UNION ALL
  SELECT round, kind, host, seed * (1 - 0.85 * sum(inflow) OVER (PARTITION BY kind)) + 0.85 * inflow FROM (
    SELECT r.round + 1 AS round, n.kind, n.host, n.seed, coalesce(sum(w.w * r.rank), 0.0) AS inflow
    FROM nodes n JOIN ranks r ON r.kind = n.kind LEFT JOIN weighted w ON w.kind = n.kind AND w.dst = n.host AND w.src = r.host WHERE r.round < {_ROUNDS} GROUP BY ALL)),
flows AS (SELECT host, coalesce(sum(rank) FILTER (WHERE kind = 'trust'), 0) AS t, coalesce(sum(rank) FILTER (WHERE kind = 'distrust'), 0) AS x FROM ranks WHERE round = {_ROUNDS} GROUP BY host)
SELECT page_id, host, path, rule, coalesce(verdict, CASE WHEN x > 0 AND x > 0.5 * (t + x) THEN 'block' ELSE 'allow' END) AS verdict FROM p LEFT JOIN fits USING (page_id) LEFT JOIN flows USING (host)
"""

OP5 = f"""
WITH lines AS (SELECT doc_id, line, {_words('t')} AS w FROM (SELECT doc_id, unnest(range(len(s))) AS line, unnest(s) AS t FROM (SELECT doc_id, string_split(text, chr(10)) AS s FROM documents WHERE text IS NOT NULL))),
sets AS (SELECT doc_id, line, list_sort(list_distinct(w)) AS s FROM lines WHERE len(w) > 0),
classes AS (SELECT row_number() OVER (ORDER BY min((doc_id, line)), s) AS c, s, len(s) AS n, min((doc_id, line)) AS first FROM sets GROUP BY s),
spread AS (SELECT c, n, unnest(s) AS word FROM classes),
often AS (SELECT word, count(*) AS f FROM spread GROUP BY word),
prefixes AS (SELECT c, n, word FROM (SELECT c, n, word, row_number() OVER (PARTITION BY c ORDER BY f, word) AS pos FROM spread JOIN often USING (word)) WHERE pos <= n - ceil(0.75 * n) + 1),
pairs AS (SELECT DISTINCT a.c AS a, b.c AS b FROM prefixes a JOIN prefixes b ON a.word = b.word AND a.c > b.c AND 4 * least(a.n, b.n) >= 3 * greatest(a.n, b.n)),
gone AS (SELECT DISTINCT a FROM (SELECT a, len(list_intersect(x.s, y.s)) AS k, x.n + y.n AS t FROM pairs JOIN classes x ON x.c = a JOIN classes y ON y.c = b) WHERE 100 * k >= 75 * (t - k)),
judged AS (SELECT sets.doc_id, line, a IS NOT NULL OR (sets.doc_id, line) > first AS removed FROM sets JOIN classes USING (s) LEFT JOIN gone ON a = c)
SELECT d.doc_id, count(line)::BIGINT AS n_lines, count(line) FILTER (WHERE removed)::BIGINT AS n_removed, coalesce(string_agg(line::VARCHAR, ',' ORDER BY line) FILTER (WHERE removed), '') AS removed_lines
FROM documents d LEFT JOIN judged j ON d.doc_id = j.doc_id GROUP BY d.doc_id
"""


def _spans(kind: str, pattern: str, rank: int, check: str = "true", gate: str = "true") -> str:
    """(doc_id, rank, kind, start, end, found) of a pattern's matches, from the stretches between them."""
    return f"""SELECT doc_id, {rank} AS rank, '{kind}' AS kind, place AS begin, place + length(found) AS stop, found FROM (
  SELECT doc_id, m[i] AS found, (list_sum([length(x) FOR x IN s[1:i]]) + coalesce(list_sum([length(x) FOR x IN m[1:i - 1]]), 0))::BIGINT AS place
  FROM (SELECT doc_id, s, m, unnest(range(1, len(m) + 1)) AS i FROM (SELECT doc_id, string_split_regex(text, $p${pattern}$p$) AS s, regexp_extract_all(text, $p${pattern}$p$) AS m FROM documents WHERE text IS NOT NULL AND {gate}))
) WHERE {check}"""


_ASSIGN = r"""(?:[pP][aA][sS][sS][wW][oO][rR][dD]|[pP][aA][sS][sS][wW][dD]|[sS][eE][cC][rR][eE][tT]|[tT][oO][kK][eE][nN]|[aA][pP][iI]_?[kK][eE][yY])["']?\x20*[:=]\x20*["']?[A-Za-z0-9+/_.=-]+"""
OP6 = f"""
WITH found AS (
{_spans('assign', _ASSIGN, 0, "length(regexp_extract(found, $p$[:=]\\x20*[\"']?([A-Za-z0-9+/_.=-]+)$$p$, 1)) >= 12")}
UNION ALL {_spans('access', 'AKIA[A-Z0-9]+', 1, 'length(found) >= 18')}
UNION ALL {_spans('hex', '[0-9a-f]+', 2, 'length(found) >= 16')}
UNION ALL {_spans('pem', '-----BEGIN [A-Z ]{0,40}PRIVATE KEY-----', 3)}),
lists AS (SELECT doc_id, count(*) FILTER (WHERE rank = 0) AS a, count(*) FILTER (WHERE rank = 1) AS k, count(*) FILTER (WHERE rank = 2) AS h,
  string_agg(kind || ':' || begin || ':' || stop, ',' ORDER BY begin, rank) FILTER (WHERE rank < 3) AS base, string_agg(kind || ':' || begin || ':' || stop, ',' ORDER BY begin, rank) AS every FROM found GROUP BY doc_id)
SELECT d.doc_id, coalesce(a, 0)::BIGINT AS n_assign, coalesce(k, 0)::BIGINT AS n_access, coalesce(h, 0)::BIGINT AS n_hex, sha256(coalesce(base, '')) AS base_sha256, coalesce(every, '') AS spans FROM documents d LEFT JOIN lists USING (doc_id)
"""

OP7 = f"""
WITH RECURSIVE d AS (SELECT doc_id, {_words(_lower('text'))} AS w FROM documents),
shingles AS (SELECT DISTINCT doc_id, x FROM (
  SELECT doc_id, array_to_string(w[p:p + 4], ' ') AS x FROM (SELECT doc_id, w, unnest(range(1, len(w) - 3)) AS p FROM d WHERE len(w) >= 5)
  UNION ALL SELECT doc_id, array_to_string(w, ' ') FROM d WHERE len(w) BETWEEN 1 AND 4)),
sizes AS (SELECT doc_id, count(*) AS n FROM shingles GROUP BY doc_id),
common AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS k FROM shingles a JOIN shingles b ON a.x = b.x AND a.doc_id < b.doc_id GROUP BY ALL),
links AS (SELECT a, b FROM common JOIN sizes x ON x.doc_id = a JOIN sizes y ON y.doc_id = b WHERE 100 * k >= 75 * (x.n + y.n - k)),
twice AS (SELECT a, b FROM links UNION ALL SELECT b, a FROM links),
reach AS (SELECT a, b FROM twice UNION SELECT reach.a, twice.b FROM reach JOIN twice ON reach.b = twice.a),
least AS (SELECT a, min(b) AS c FROM reach GROUP BY a),
many AS (SELECT a, count(*) AS n_links FROM twice GROUP BY a)
SELECT d.doc_id, coalesce(n, 0)::BIGINT AS n_shingles, least(d.doc_id, coalesce(c, d.doc_id)) AS component_id, coalesce(n_links, 0)::BIGINT AS n_links
FROM d LEFT JOIN sizes ON sizes.doc_id = d.doc_id LEFT JOIN least ON least.a = d.doc_id LEFT JOIN many ON many.a = d.doc_id
"""

OP8 = f"""
WITH d AS (SELECT doc_id, source, coalesce(text, '') AS text, {_words('text')} AS w FROM documents),
eights AS (SELECT doc_id, p, count(*) OVER (PARTITION BY doc_id, x) AS k FROM (SELECT doc_id, p, array_to_string(w[p:p + 7], ' ') AS x FROM (SELECT doc_id, w, unnest(range(1, len(w) - 6)) AS p FROM d WHERE len(w) >= 8))),
repeats AS (SELECT doc_id, count(DISTINCT p + i) AS n FROM eights, range(8) AS r(i) WHERE k > 1 GROUP BY doc_id),
lines AS (SELECT doc_id, source, text, t, array_to_string({_words(_lower('t'))}, ' ') AS norm, len({_words('t')}) AS n FROM (SELECT doc_id, source, text, unnest(string_split(text, chr(10))) AS t FROM d) WHERE len({_words('t')}) > 0),
dups AS (SELECT doc_id, count(*) - count(DISTINCT t) AS n FROM lines GROUP BY doc_id),
hosts AS (SELECT source, count(DISTINCT text) AS n FROM documents GROUP BY source),
above AS (SELECT l.source, norm FROM (SELECT source, norm, count(DISTINCT text) AS k FROM lines GROUP BY source, norm HAVING count(DISTINCT text) > 20) l JOIN hosts h ON l.source IS NOT DISTINCT FROM h.source WHERE k > 0.05 * h.n),
cut AS (SELECT doc_id, sum(n) AS n FROM lines l JOIN above a ON l.source IS NOT DISTINCT FROM a.source AND l.norm = a.norm GROUP BY doc_id),
judged AS (SELECT d.doc_id, len(w)::BIGINT AS n_words, coalesce(list_sum([length(x) FOR x IN w]), 0)::BIGINT AS word_chars, length(regexp_replace(text, '[^#*$%&|<>]', '', 'g'))::BIGINT AS n_symbols, coalesce(dups.n, 0)::BIGINT AS n_dup_lines,
  coalesce(repeats.n, 0)::BIGINT AS n_repeat_words, coalesce(cut.n, 0)::BIGINT AS n_removed_words FROM d LEFT JOIN repeats USING (doc_id) LEFT JOIN dups USING (doc_id) LEFT JOIN cut USING (doc_id)),
failed AS (SELECT *, n_words < 20 OR 100 * n_repeat_words > 30 * n_words AS base_failed FROM judged)
SELECT *, NOT base_failed AND NOT (n_removed_words > 0 AND (n_words - n_removed_words < 20 OR n_words - n_removed_words < 0.3 * n_words)) AS kept FROM failed
"""

ORACLES: dict[str, str] = {"op2_substring_dedup": OP2, "op3_decontamination": OP3, "op4_url_filter": OP4, "op5_line_dedup": OP5, "op6_secret_scan": OP6, "op7_ngram_join": OP7, "op8_quality": OP8}
