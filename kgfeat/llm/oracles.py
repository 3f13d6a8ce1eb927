"""DuckDB SQL of the operators that SQL can express, over the whole tables."""

from __future__ import annotations

from kgfeat.llm import chat, mixing, quality, urlfilter

WORDS = r"regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')"


def quality_rules() -> str:
    stat = {r: f"100 * {n} > {{c}} * {d}" for r, (n, d) in quality.RULES.items()}
    steps = [(r, k, i, c, s.format(c=c)) for k, (r, s) in enumerate(stat.items()) for i, c in enumerate(quality.CUTOFFS)]
    cells = " UNION ALL ".join(f"SELECT '{r}' AS rule, {k} AS k, {i} AS i, {c} AS cutoff, count(*) FILTER (good AND tune AND {x}) AS fa FROM tall" for r, k, i, c, x in steps)
    beyond = " OR ".join(f"(p.rule = '{r}' AND {s.format(c='p.cutoff')})" for r, s in stat.items())
    a, d = quality.ALPHA, quality.DELTA
    tail = f"(CASE WHEN {{k}} >= n THEN 1.0 ELSE list_sum(list_transform(range(0, {{k}} + 1), lambda x: exp(lgamma(n + 1) - CASE WHEN x = 0 THEN 0 ELSE lgamma(x + 1) END - lgamma(n - x + 1) + x * ln({a}) + (n - x) * ln(1 - {a})))) END)"
    return f"""
WITH w AS MATERIALIZED (SELECT doc_id, lang, coalesce(text, '') AS text, {WORDS} AS w FROM documents),
win AS MATERIALIZED (SELECT doc_id, i, array_to_string(w[i:i + 7], ' ') AS k FROM (SELECT doc_id, w, unnest(range(1, len(w) - 6)) AS i FROM w WHERE len(w) >= 9)),
rep AS (SELECT doc_id, count(DISTINCT i + j) AS n FROM (SELECT doc_id, i FROM win QUALIFY count(*) OVER (PARTITION BY doc_id, k) > 1), range(0, 8) t(j) GROUP BY doc_id),
ln AS (SELECT doc_id, l, count(*) AS m FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS l FROM w) WHERE regexp_matches(l, '[^\\x20\\x09-\\x0D]') GROUP BY ALL),
dup AS (SELECT doc_id, sum(m) AS n_lines, sum(m - 1) AS n_dup_lines FROM ln GROUP BY doc_id),
c AS MATERIALIZED (SELECT w.doc_id, lang, len(w.w) AS n_words, length(array_to_string(w.w, '')) AS word_chars, length(text) - length(regexp_replace(text, '[#*$%&|<>]', '', 'g')) AS n_symbols,
 coalesce(dup.n_dup_lines, 0)::BIGINT AS n_dup_lines, coalesce(rep.n, 0) AS n_repeat_words, length(text) - length(regexp_replace(text, '\\p{{Lu}}', '', 'g')) AS n_upper, length(text) - length(regexp_replace(text, '[!|]', '', 'g')) AS n_marks, coalesce(dup.n_lines, 0)::BIGINT AS n_lines
 FROM w LEFT JOIN rep USING (doc_id) LEFT JOIN dup USING (doc_id)),
f AS MATERIALIZED (SELECT *, greatest(word_chars - n_symbols - n_marks, 0) AS n_letters, n_words < 20 OR 100 * n_repeat_words > 30 * n_words AS base_failed FROM c),
tall AS MATERIALIZED (SELECT f.*, quality > 0 AS good, ('0x'||substr(md5(doc_id::VARCHAR), 1, 8))::BIGINT % {quality.FOLDS} = 0 AS tune, row_number() OVER () AS rid FROM f JOIN labels USING (doc_id) WHERE NOT base_failed AND quality IS NOT NULL),
path AS MATERIALIZED (SELECT *, row_number() OVER (ORDER BY fa, i, k) AS pos FROM ({cells})),
seen AS MATERIALIZED (SELECT tall.rid, any_value(lang) AS lang, any_value(good) AS good, min(p.pos) AS hit_at FROM tall LEFT JOIN path p ON ({beyond}) WHERE NOT tune GROUP BY tall.rid),
strata AS (SELECT lang, count(*) FILTER (good) AS n FROM seen GROUP BY lang),
level AS (SELECT {d} / count(*) AS l FROM strata),
grp AS MATERIALIZED (SELECT lang, CASE WHEN {tail.format(k='0')} <= l THEN coalesce('x'||lang, 'y') ELSE '' END AS g, n FROM strata, level),
size AS (SELECT g, sum(n)::BIGINT AS n FROM grp GROUP BY g),
got AS MATERIALIZED (SELECT g, pos, size.n, count(*) FILTER (good AND hit_at <= pos) AS fr, count(*) FILTER (NOT good AND hit_at <= pos) AS hit FROM seen JOIN grp ON seen.lang IS NOT DISTINCT FROM grp.lang JOIN size USING (g) CROSS JOIN path GROUP BY ALL),
best AS MATERIALIZED (SELECT g, pos FROM (SELECT got.*, {tail.replace("n + 1", "got.n + 1").replace(">= n", ">= got.n").replace("(n - x", "(got.n - x").format(k='fr')} <= l AS sure FROM got, level) WHERE sure QUALIFY row_number() OVER (PARTITION BY g ORDER BY hit - {quality.PRICE} * fr DESC, pos) = 1 AND hit > {quality.PRICE} * fr),
used AS MATERIALIZED (SELECT grp.lang, p.rule, p.cutoff FROM grp JOIN best USING (g) JOIN path p ON p.pos <= best.pos)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND NOT EXISTS (SELECT 1 FROM used p WHERE p.lang IS NOT DISTINCT FROM f.lang AND ({beyond})) AS kept FROM f
"""


def chat_rotation() -> str:
    end = chat.END.replace("\n", "'||chr(10)||'")
    name = "coalesce(speaker, 'unknown')"
    for mark, entity in chat.ENTITIES:
        name = f"replace({name}, {'chr(10)' if mark == chr(10) else repr(mark)}, '{entity}')"
    return f"""
WITH t AS (SELECT conv_id, turn, role AS speaker, coalesce(text, '') AS text FROM conversations),
p AS (SELECT DISTINCT conv_id, speaker AS perspective FROM t WHERE speaker IS DISTINCT FROM 'system'),
s AS (SELECT t.*, perspective, CASE WHEN speaker = 'system' THEN 'system' WHEN speaker IS NOT DISTINCT FROM perspective THEN 'assistant' ELSE 'user' END AS tag FROM t JOIN p ON t.conv_id IS NOT DISTINCT FROM p.conv_id),
h AS (SELECT *, CASE WHEN tag = 'user' THEN '<|user name="'||{name}||'"|>' ELSE '<|'||tag||'|>' END||chr(10) AS head FROM s),
g AS (SELECT *, head||text||'{end}' AS segment FROM h),
o AS (SELECT *, row_number() OVER w - 1 AS seq, sum(length(segment)) OVER w AS stop FROM g WINDOW w AS (PARTITION BY conv_id, perspective ORDER BY turn NULLS FIRST, speaker NULLS FIRST, text ROWS UNBOUNDED PRECEDING))
SELECT conv_id, perspective, turn, seq, speaker, tag, segment, (stop - length(segment))::BIGINT AS "start", stop::BIGINT AS "end",
 CASE WHEN tag = 'assistant' THEN (stop - length(segment) + length(head))::BIGINT END AS mask_start, CASE WHEN tag = 'assistant' THEN (stop - 1)::BIGINT END AS mask_end FROM o
"""


def warc_records() -> str:
    return """
WITH p AS (SELECT page_id, coalesce(html, '') AS h FROM pages),
d AS (SELECT page_id, strlen(h) AS payload_bytes, sha1(h) AS payload_digest FROM p),
f AS (SELECT payload_digest, max(page_id) AS first FROM d WHERE payload_bytes >= 1000 GROUP BY 1)
SELECT page_id, payload_bytes, payload_digest, CASE WHEN first IS NULL OR first = page_id THEN 'response' ELSE 'revisit' END AS record_type, CASE WHEN first <> page_id THEN first END AS refers_to FROM d LEFT JOIN f USING (payload_digest)
"""


def mixing_sources(seed: int = 7) -> str:
    return f"""
WITH d AS MATERIALIZED (SELECT doc_id, source, len({WORDS}) AS size, ('0x'||substr(md5('{seed}|0'||doc_id), 1, 15))::BIGINT AS r FROM documents),
s AS (SELECT source, sum(size)::BIGINT AS n FROM d GROUP BY source),
w AS (SELECT *, [{", ".join(map(str, mixing.WEIGHTS))}][(row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1] AS weight FROM s),
o AS (SELECT *, {mixing.MOST} * n AS most, {mixing.SHARE} * sum(n) OVER () AS pool, row_number() OVER (ORDER BY n / weight, source) AS i FROM w WHERE n > 0),
q AS (SELECT *, (pool - coalesce(sum(most) OVER (ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)) / sum(weight) OVER (ORDER BY i ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS unit FROM o),
u AS (SELECT min(i) AS i, min_by(unit, i) AS unit FROM q WHERE weight * unit <= most),
t AS (SELECT q.source, q.n, CASE WHEN u.i IS NULL OR q.i < u.i THEN most ELSE weight * u.unit END AS target FROM q, u UNION ALL SELECT source, n, 0 FROM w WHERE n = 0),
b AS (SELECT t.*, CASE WHEN n > 0 THEN round(target)::BIGINT // n ELSE 0 END AS epochs, CASE WHEN n > 0 THEN round(target)::BIGINT % n ELSE 0 END AS rest FROM t),
x AS (SELECT d.*, sum(size) OVER (PARTITION BY source ORDER BY r, doc_id, size ROWS UNBOUNDED PRECEDING) - size AS before FROM d)
SELECT doc_id, size::BIGINT AS size, n AS source_size, target, (epochs * size + least(size, greatest(0, rest - before)))::BIGINT AS taken FROM x JOIN b ON x.source IS NOT DISTINCT FROM b.source
"""


def url_filter(order: int = urlfilter.ORDER) -> str:
    fits = " UNION ALL ".join(f"SELECT '{v}' AS v, '{h}' AS h, '{p}' AS p" for v, h, p in urlfilter.RULES)
    pad, stop = f"repeat(chr({ord(urlfilter.PAD)}), {order})", f"chr({ord(urlfilter.STOP)})"
    cut = f"SELECT url, y, m, substr({pad}||url||{stop}, i, {order + 1}) AS w FROM (SELECT *, unnest(range(1, length(url) + 2)) AS i FROM {{src}})"
    mixed = "CASE WHEN coalesce({t}, 0) + coalesce({d}, 0) = 0 THEN {q} ELSE (coalesce({n}, 0) + coalesce({d}, 0) * {q}) / (coalesce({t}, 0) + coalesce({d}, 0)) END"
    steps = []
    for k in range(order + 1):
        steps.append(f"g{k} AS MATERIALIZED (SELECT right(w, {k + 1}) AS g, sum(good)::DOUBLE AS ng, sum(bad)::DOUBLE AS nb FROM train GROUP BY 1)")
        steps.append(f"x{k} AS MATERIALIZED (SELECT substr(g, 1, {k}) AS c, sum(ng) AS tg, sum(nb) AS tb, count(*) FILTER (ng > 0)::DOUBLE AS dg, count(*) FILTER (nb > 0)::DOUBLE AS db FROM g{k} GROUP BY 1)")
        before = f"p{k - 1}" if k else "(SELECT w, 1.0::DOUBLE / (SELECT 1 + count(DISTINCT right(w, 1)) FROM train) AS pg, 1.0::DOUBLE / (SELECT 1 + count(DISTINCT right(w, 1)) FROM train) AS pb FROM asked)"
        both = ", ".join(f"{mixed.format(q=f'p.p{z}', n=f'n{z}', t=f't{z}', d=f'd{z}')} AS p{z}" for z in "gb")
        steps.append(f"p{k} AS MATERIALIZED (SELECT p.w, {both} FROM {before} p LEFT JOIN g{k} g ON g.g = right(p.w, {k + 1}) LEFT JOIN x{k} x ON x.c = substr(right(p.w, {k + 1}), 1, {k}))")
    return f"""
WITH rules AS ({fits}),
page AS MATERIALIZED (SELECT page_id, coalesce(url, '') AS url, CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages),
part AS MATERIALIZED (SELECT page_id, url, translate(regexp_extract(rest, '^[^/?#]*'), '{urlfilter.UPPER}', '{urlfilter.LOWER}') AS host, regexp_extract(rest, '^[^/?#]*([^?#]*)', 1, 's') AS path FROM page),
ruled AS MATERIALIZED (SELECT part.*, (SELECT max_by({{'rule': h||p, 'v': v}}, length(h||p)) FROM rules WHERE (host = h OR ends_with(host, '.'||h)) AND starts_with(path, p)) AS r FROM part),
texts AS MATERIALIZED (SELECT url, count(*) AS m, any_value(r.v) = 'allow' AS y, ('0x'||substr(md5(url), 1, 8))::BIGINT % 5 = 0 AS held FROM ruled GROUP BY url),
train AS MATERIALIZED (SELECT w, sum(CASE WHEN y THEN m ELSE 0 END) AS good, sum(CASE WHEN y THEN 0 ELSE m END) AS bad FROM ({cut.format(src="(SELECT * FROM texts WHERE y IS NOT NULL AND NOT held)")}) GROUP BY w),
ask AS MATERIALIZED (SELECT url, w, count(*) AS n FROM ({cut.format(src="(SELECT * FROM texts WHERE y IS NULL OR held)")}) GROUP BY ALL),
asked AS (SELECT DISTINCT w FROM ask), {", ".join(steps)},
ratio AS MATERIALIZED (SELECT w, round(1e6 * (ln(pg) - ln(pb)))::BIGINT AS micro FROM p{order}),
scored AS MATERIALIZED (SELECT url, y, floor(sum(n * micro) / (length(url) + 1)::DOUBLE)::BIGINT AS s FROM ask JOIN ratio USING (w) JOIN texts USING (url) GROUP BY url, y),
bins AS (SELECT floor(s / 10000.0)::BIGINT AS b, count(*) FILTER (y) AS g, count(*) FILTER (NOT y) AS x FROM scored WHERE y IS NOT NULL GROUP BY 1),
sums AS (SELECT b, lag(b) OVER o + 1 AS low, sum(g) OVER o - g AS bg, sum(x) OVER o - x AS bb FROM bins WINDOW o AS (ORDER BY b) UNION ALL SELECT NULL, max(b) + 1, sum(g), sum(x) FROM bins),
cuts AS (SELECT 10000 * CASE WHEN low IS NOT NULL AND b IS NOT NULL THEN least(greatest(0, low), b) WHEN b IS NOT NULL THEN least(0, b) ELSE greatest(0, low) END AS cut, round(bg / t.g + (t.x - bb) / t.x, 9) AS err FROM sums, (SELECT sum(g)::DOUBLE AS g, sum(x)::DOUBLE AS x FROM bins) t WHERE t.g > 0 AND t.x > 0 UNION ALL SELECT 0, 2.0),
best AS (SELECT cut FROM cuts ORDER BY err, abs(cut), cut LIMIT 1)
SELECT page_id, host, path, r.rule AS rule, coalesce(r.v, CASE WHEN scored.s >= best.cut THEN 'allow' ELSE 'block' END) AS verdict FROM ruled LEFT JOIN scored ON scored.url = ruled.url AND scored.y IS NULL, best
"""


def shards(n: int = 16, slack: float = 0.02) -> str:
    crc = "list_reduce(list_prepend(4294967295::BIGINT, list_transform(range(0, strlen(t)), lambda k: ('0x'||substr(hex(encode(t)), 2 * k + 1, 2))::BIGINT)), lambda c, b: xor(c >> 8, tab[(xor(c, b) & 255) + 1]))"
    half = "CASE WHEN aim - {s} <= {e} - aim THEN {s} ELSE {e} END"
    return f"""
WITH tab AS MATERIALIZED (SELECT list(v ORDER BY i) AS tab FROM (SELECT i, list_reduce(list_prepend(i, [0::BIGINT, 0, 0, 0, 0, 0, 0, 0]), lambda c, z: CASE WHEN c & 1 = 1 THEN xor(c >> 1, 3988292384::BIGINT) ELSE c >> 1 END) AS v FROM (SELECT unnest(range(0, 256))::BIGINT AS i))),
txt AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
one AS MATERIALIZED (SELECT t, xor(CASE WHEN t = '' THEN 4294967295::BIGINT ELSE {crc} END, 4294967295::BIGINT) AS text_crc32 FROM (SELECT DISTINCT t FROM txt), tab),
d AS MATERIALIZED (SELECT doc_id, strlen(t) + 1 AS size, text_crc32, md5(t) AS h FROM txt JOIN one USING (t)),
o AS MATERIALIZED (SELECT *, row_number() OVER w - 1 AS num, (sum(size) OVER w)::BIGINT AS stop FROM d WINDOW w AS (ORDER BY text_crc32, h, doc_id NULLS FIRST ROWS UNBOUNDED PRECEDING)),
total AS (SELECT coalesce(sum(size), 0)::BIGINT AS total FROM d),
aims AS (SELECT j, total * j / {n}::DOUBLE AS aim, total FROM total, (SELECT unnest(range(1, {n})) AS j)),
span AS (SELECT text_crc32, h, min(stop - size) AS s, max(stop) AS e FROM o GROUP BY ALL),
edge AS (SELECT j, aim, total, o.stop - o.size AS ds, o.stop AS de, span.s, span.e FROM aims JOIN o ON o.stop - o.size <= aim AND aim < o.stop JOIN span USING (text_crc32, h)),
near AS (SELECT *, {half.format(s='s', e='e')} AS g, {half.format(s='ds', e='de')} AS one FROM edge),
cuts AS (SELECT j, CASE WHEN abs(g - aim) <= {slack} * total / {n} THEN g ELSE one END AS cut FROM near),
firsts AS MATERIALIZED (SELECT j, (SELECT count(*) FROM o WHERE stop - size < cut) AS first FROM cuts UNION ALL SELECT 0, 0)
SELECT doc_id, size, text_crc32, 'bytes' AS law, (max(j))::INTEGER AS shard, (num - max_by(first, j))::BIGINT AS slot, NULL::INTEGER AS grown_shard FROM o JOIN firsts ON num >= first GROUP BY doc_id, size, text_crc32, num
"""
