"""SQL for another engine that computes the results of operators 1, 2, 6, 7 and 8 over whole tables."""

from __future__ import annotations

from . import op1_quality as q1
from . import op2_links as q2
from .common import LOWER, UPPER

_W = r"regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')"
_DOCS = f"d AS (SELECT doc_id, coalesce(lang, '') AS lang, coalesce(text, '') AS text, {_W} AS w FROM documents)"

OP7 = f"""WITH l AS (SELECT doc_id, i, s[i] AS line, translate(trim(s[i], ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)), '{UPPER}', '{LOWER}') AS k
  FROM (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS s FROM documents), unnest(range(1, len(s) + 1)) t(i)),
h AS (SELECT k, max(doc_id) AS owner FROM l WHERE length(k) >= 20 GROUP BY k HAVING count(DISTINCT doc_id) >= 3),
m AS (SELECT l.doc_id, i, line, (owner IS NOT NULL AND owner <> l.doc_id) AS gone FROM l LEFT JOIN h ON l.k = h.k)
SELECT doc_id, count(*) AS n_lines, count(*) FILTER (WHERE gone) AS n_dropped,
  sha256(coalesce(string_agg(line, chr(10) ORDER BY i) FILTER (WHERE NOT gone), '')) AS kept_sha256 FROM m GROUP BY doc_id"""

OP8 = f"""WITH {_DOCS},
p AS (SELECT doc_id, i, w[i] AS word FROM d, unnest(range(1, len(w) + 1)) t(i)),
g AS (SELECT doc_id, i, md5(array_to_string(w[i:i + 19], ' ')) AS k FROM d, unnest(range(1, len(w) - 18)) t(i)),
later AS (SELECT doc_id, i FROM (SELECT doc_id, i, row_number() OVER (PARTITION BY k ORDER BY doc_id, i) AS n FROM g) WHERE n > 1),
gone AS (SELECT DISTINCT doc_id, i + j AS i FROM later, unnest(range(0, 20)) u(j)),
kept AS (SELECT p.doc_id, string_agg(word, ' ' ORDER BY p.i) AS s, count(*) AS n FROM p LEFT JOIN gone ON gone.doc_id = p.doc_id AND gone.i = p.i WHERE gone.i IS NULL GROUP BY p.doc_id)
SELECT d.doc_id, len(w)::BIGINT AS n_words, len(w)::BIGINT - coalesce(n, 0) AS n_removed, sha256(coalesce(s, '')) AS kept_sha256 FROM d LEFT JOIN kept USING (doc_id)"""

OP6 = f"""WITH RECURSIVE d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), '{UPPER}', '{LOWER}'), '[^\\x20\\x09-\\x0D]+') AS w FROM documents),
s AS (SELECT DISTINCT doc_id, md5(array_to_string(w[i:i + 4], ' ')) AS h FROM d, unnest(range(1, greatest(len(w) - 4, 1) + 1)) t(i) WHERE len(w) > 0),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
x AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS k FROM s a JOIN s b ON a.h = b.h AND a.doc_id < b.doc_id GROUP BY 1, 2),
e AS (SELECT a, b FROM x JOIN n p ON p.doc_id = a JOIN n q ON q.doc_id = b WHERE 100 * k >= 75 * (p.n + q.n - k)),
both_ways AS (SELECT a, b FROM e UNION ALL SELECT b, a FROM e),
r(id, low) AS (SELECT doc_id, doc_id FROM documents UNION SELECT r.id, b FROM r JOIN both_ways ON a = low)
SELECT r.id AS doc_id, coalesce(any_value(n.n), 0) AS n_shingles, min(low) AS component_id FROM r LEFT JOIN n ON n.doc_id = r.id GROUP BY r.id"""


def _jsd(name: str, pairs: str) -> str:
    """CTE (doc_id, x) of distances from rows (doc_id, p, q) of counts."""
    part = "CASE WHEN {0} > 0 THEN {0} * log2({0} / ((p + q) / 2)) ELSE 0 END"
    return f"""{name} AS (SELECT doc_id, sqrt(greatest(sum(({part.format('p')} + {part.format('q')}) / 2), 0)) AS x
  FROM (SELECT doc_id, p / sum(p) OVER (PARTITION BY doc_id) AS p, q / sum(q) OVER (PARTITION BY doc_id) AS q FROM ({pairs})) GROUP BY doc_id)"""


_CLASS = [r"[^\x20\x09-\x0D]", r"\P{Lu}", "[^0-9]", r"[^.,;:!?''\"()-]", f"[^{q1.SYMBOLS}]"]
_LEN = [f"length(regexp_replace(text, '{c}', '', 'g'))::DOUBLE" for c in _CLASS]
OP1 = f"""WITH {_DOCS},
g AS (SELECT doc_id, i, array_to_string(w[i:i + 4], ' ') AS k FROM d, unnest(range(1, len(w) - 3)) t(i)),
again AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, k) AS n FROM g) WHERE n > 1),
rep AS (SELECT doc_id, count(DISTINCT i + j) AS n FROM again, unnest(range(0, 5)) u(j) GROUP BY doc_id),
ln AS (SELECT doc_id, count(*) - count(DISTINCT x) AS n FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS x FROM d) WHERE regexp_matches(x, '[^\\x20\\x09-\\x0D]') GROUP BY doc_id),
cl AS (SELECT doc_id, lang, len(w) AS n, length(text) AS chars, {', '.join(f'{x} AS c{k}' for k, x in enumerate(_LEN))} FROM d),
c6 AS (SELECT *, chars - c0 - c1 - c2 - c3 - c4 AS c5 FROM cl),
tot AS (SELECT lang, sum(n)::DOUBLE AS words, {', '.join(f'sum(c{k}) AS t{k}' for k in range(6))} FROM c6 GROUP BY lang HAVING sum(n) >= {q1.MIN_REF_WORDS}),
wc AS (SELECT lang, word, count(*)::DOUBLE AS n FROM (SELECT lang, unnest(w) AS word FROM d) GROUP BY lang, word),
top AS (SELECT lang, word, n FROM (SELECT wc.lang, word, n, row_number() OVER (PARTITION BY wc.lang ORDER BY n DESC, word) AS k FROM wc JOIN tot ON tot.lang = wc.lang WHERE n >= {q1.MIN_WORD_SHARE} * words) WHERE k <= {q1.TOP_WORDS}),
own AS (SELECT doc_id, lang, word, count(*)::DOUBLE AS n FROM (SELECT doc_id, lang, unnest(w) AS word FROM d) GROUP BY ALL),
hit AS (SELECT d.doc_id, top.word, coalesce(own.n, 0) AS p, top.n AS q FROM d JOIN top ON top.lang = d.lang LEFT JOIN own ON own.doc_id = d.doc_id AND own.word = top.word WHERE len(w) >= {q1.MIN_WORDS}),
rest AS (SELECT d.doc_id, len(w) - coalesce(h.p, 0) AS p, words - coalesce(h.q, 0) AS q FROM d JOIN tot ON tot.lang = d.lang LEFT JOIN (SELECT doc_id, sum(p) AS p, sum(q) AS q FROM hit GROUP BY doc_id) h ON h.doc_id = d.doc_id WHERE len(w) >= {q1.MIN_WORDS}),
{_jsd('jw', 'SELECT doc_id, p, q FROM hit UNION ALL SELECT doc_id, p, q FROM rest')},
{_jsd('jc', ' UNION ALL '.join(f'SELECT doc_id, c{k} AS p, t{k} AS q FROM c6 JOIN tot USING (lang) WHERE chars >= {q1.MIN_CHARS}' for k in range(6)))},
topq AS (SELECT lang, word, n AS q FROM top UNION ALL SELECT tot.lang, NULL, words - coalesce((SELECT sum(n) FROM top WHERE top.lang = tot.lang), 0) FROM tot),
{_jsd('none', "SELECT lang AS doc_id, CASE WHEN word IS NULL THEN 1.0 ELSE 0.0 END::DOUBLE AS p, q FROM topq")},
ref AS (SELECT tot.lang, 1 - q / words AS share, none.x AS none FROM tot JOIN topq ON topq.lang = tot.lang AND word IS NULL JOIN none ON none.doc_id = tot.lang),
lw AS (SELECT rest.doc_id, len(w)::DOUBLE AS n, (len(w) - rest.p) / len(w) AS p, jw.x AS far, share, none FROM rest JOIN d USING (doc_id) JOIN jw USING (doc_id) JOIN ref ON ref.lang = d.lang WHERE d.lang <> ''),
lk AS (SELECT doc_id FROM lw WHERE share > 0 AND p < share AND (far > none * ({q1.NONE_PART} + {q1.NONE_SLACK} / sqrt(n * share))
  OR n * (CASE WHEN p > 0 THEN p * (log2(p) - log2(share)) ELSE 0 END + (1 - p) * (log2(1 - p) - log2(CASE WHEN share < 1 THEN 1 - share END))) > {q1.RARE_BITS})),
b AS (SELECT d.doc_id, len(w)::BIGINT AS n_words, length(array_to_string(w, ''))::BIGINT AS word_chars, c4::BIGINT AS n_symbols, coalesce(ln.n, 0)::BIGINT AS n_dup_lines, coalesce(rep.n, 0)::BIGINT AS n_repeat_words,
  coalesce(jc.x, 0) <= {q1.MOST_CHAR_DISTANCE} AND coalesce(jw.x, 0) <= {q1.MOST_WORD_DISTANCE} AND d.doc_id NOT IN (SELECT doc_id FROM lk) AS fine
  FROM d JOIN c6 USING (doc_id) LEFT JOIN ln USING (doc_id) LEFT JOIN rep USING (doc_id) LEFT JOIN jw USING (doc_id) LEFT JOIN jc USING (doc_id))
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, (n_words < 10 OR 100 * n_repeat_words > 20 * n_words) AS base_failed,
  NOT (n_words < 10 OR 100 * n_repeat_words > 20 * n_words) AND fine AS kept FROM b"""


def _op2() -> str:
    fits = lambda h, p: f"((host = '{h}' OR ends_with(host, '.{h}')) AND starts_with(path, '{p}'))"
    order = sorted(q2.RULES, key=lambda r: (-len(r[1] + r[2]), r))
    rule = "CASE " + " ".join(f"WHEN {fits(h, p)} THEN '{h}{p}'" for _, h, p in order) + " END"
    verdict = "CASE " + " ".join(f"WHEN {fits(h, p)} THEN '{v}'" for v, h, p in order) + " END"
    link = q2.LINK.removeprefix("(?i)").replace("'", "''")
    d, rest = q2.DAMPING, 1 - q2.DAMPING
    parts = [
        r"u AS (SELECT page_id, html, CASE WHEN contains(url, '://') THEN substr(url, position('://' IN url) + 3) ELSE '' END AS r FROM pages)",
        rf"h AS (SELECT page_id, html, translate(regexp_extract(r, '^[^/?#]*'), '{UPPER}', '{LOWER}') AS host, regexp_extract(r, '^[^/?#]*([^?#]*)', 1) AS path FROM u)",
        f"j AS (SELECT page_id, html, host, path, {rule} AS rule, {verdict} AS own FROM h)",
        f"s0 AS (SELECT host, CAST(floor(count(*) FILTER (WHERE own = 'allow') * {q2.UNIT} * CAST({rest!r} AS DOUBLE)) AS BIGINT) AS trust, CAST(floor(count(*) FILTER (WHERE own = 'block') * {q2.UNIT} * CAST({rest!r} AS DOUBLE)) AS BIGINT) AS distrust FROM j GROUP BY host HAVING count(own) > 0)",
        f"lk AS (SELECT host AS src, translate(unnest(regexp_extract_all(html, '(?i){link}', 1)), '{UPPER}', '{LOWER}') AS dst FROM j)",
        "ed AS (SELECT src, dst, count(*) AS n FROM lk WHERE src <> dst AND src <> '' GROUP BY src, dst)",
        f"st AS (SELECT src AS a, dst AS b, true AS fw, CAST({d} AS DOUBLE) * (n / sum(n) OVER (PARTITION BY src)) AS share FROM ed UNION ALL SELECT dst, src, false, CAST({d} AS DOUBLE) * (n / sum(n) OVER (PARTITION BY dst)) FROM ed)",
    ]
    for k in range(1, q2.ROUNDS + 1):
        parts.append(f"s{k} AS (SELECT host, CAST(sum(trust) AS BIGINT) AS trust, CAST(sum(distrust) AS BIGINT) AS distrust FROM (SELECT * FROM s0 UNION ALL SELECT b, CASE WHEN fw THEN CAST(floor(trust * share) AS BIGINT) ELSE 0 END, CASE WHEN fw THEN 0 ELSE CAST(floor(distrust * share) AS BIGINT) END FROM st JOIN s{k - 1} ON host = a) GROUP BY host)")
    return "WITH " + ",\n".join(parts) + f" SELECT page_id, j.host, path, rule, coalesce(own, CASE WHEN coalesce(distrust, 0) > 0 AND distrust >= {q2.BLOCK_SHARE} * (trust + distrust) THEN 'block' ELSE 'allow' END) AS verdict FROM j LEFT JOIN s{q2.ROUNDS} s ON s.host = j.host"


OP2 = _op2()
