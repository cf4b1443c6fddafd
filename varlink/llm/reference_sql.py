"""DuckDB SQL for the rows of the operators' queries, where SQL can express them."""

from __future__ import annotations

import math

from . import decontamination, mixing, quality, url_filter

_UP, _LOW = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_WS = r"[^\x20\x09-\x0D]+"


def _quality() -> str:
    r = quality.RULES
    g = r.gamma
    value = lambda a, b: f"CASE WHEN {b} > 0 THEN {a}::DOUBLE / {b} ELSE 0.0 END"
    error = lambda a, b, unit: f"{r.errors} * CASE WHEN {b} > 0 THEN sqrt({unit} * {a}::DOUBLE) / {b} ELSE 0.0 END"
    measures = " UNION ALL ".join(f"SELECT doc_id, lang, source, '{k}' AS measure, {value(a, b)} AS v FROM counted WHERE NOT base_failed" for k, a, b, _, _ in quality.MEASURES)
    fence = lambda k, side: f"max(CASE WHEN measure = '{k}' THEN {side} END)"
    tests = " AND ".join(
        f"NOT coalesce({value(a, b)} - {error(a, b, unit)} > {fence(k, 'high')}, false)" + (f" AND NOT coalesce({value(a, b)} + {error(a, b, unit)} < {fence(k, 'low')}, false)" if below else "") for k, a, b, unit, below in quality.MEASURES
    )
    at = lambda percent: f"min(CASE WHEN upto * 100 >= {percent} * total THEN v END)"
    toward = lambda n, own, above: f"(({n} * {own} + {r.prior} * {above}) / ({n} + {r.prior}))"
    mid, up, down = (toward("a.n", f"a.{c}", toward("b.n", f"b.{c}", f"c.{c}")) for c in ("mid", "up", "down"))
    return rf"""
WITH docs AS (SELECT doc_id, coalesce(text, '') AS text, coalesce(lang, '') AS lang, coalesce(source, '') AS source FROM documents),
w AS (SELECT doc_id, lang, source, text, regexp_extract_all(text, '{_WS}') AS words FROM docs),
placed AS (SELECT doc_id, unnest(words) AS word, unnest(range(1, len(words) + 1)) AS i FROM w),
grams AS (SELECT doc_id, i, concat_ws(' ', word, lead(word) OVER o, lead(word, 2) OVER o) AS gram, lead(word, 2) OVER o AS third FROM placed WINDOW o AS (PARTITION BY doc_id ORDER BY i)),
twice AS (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, gram) AS n FROM grams WHERE third IS NOT NULL),
hit AS (SELECT doc_id, count(DISTINCT i + k) AS n_repeat_words FROM twice, (SELECT unnest([0, 1, 2]) AS k) WHERE n > 1 GROUP BY doc_id),
lines AS (SELECT doc_id, count(*) AS n_lines, count(*) - count(DISTINCT line) AS n_dup_lines FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM docs) WHERE regexp_matches(line, '{_WS}') GROUP BY doc_id),
counted AS (
  SELECT w.doc_id, lang, source, len(words)::BIGINT AS n_words, coalesce(list_sum(list_transform(words, lambda x: length(x))), 0)::BIGINT AS word_chars,
    len(regexp_extract_all(text, '[#*$%&|<>]'))::BIGINT AS n_symbols, coalesce(n_dup_lines, 0)::BIGINT AS n_dup_lines, coalesce(n_repeat_words, 0)::BIGINT AS n_repeat_words, coalesce(n_lines, 0)::BIGINT AS n_lines,
    len(words) < {r.min_words} OR 100 * coalesce(n_repeat_words, 0) > {r.max_repeat_percent} * len(words) AS base_failed
  FROM w LEFT JOIN hit USING (doc_id) LEFT JOIN lines USING (doc_id)),
m AS ({measures}),
buckets AS (SELECT lang, source, measure, CASE WHEN v > 0 THEN ceil(ln(v) / {math.log(g)!r})::INTEGER END AS bucket FROM m),
levels AS (SELECT 0 AS level, lang, source, measure, bucket, count(*) AS n FROM buckets GROUP BY ALL
  UNION ALL SELECT 1, lang, NULL, measure, bucket, count(*) FROM buckets GROUP BY ALL
  UNION ALL SELECT 3, NULL, NULL, measure, bucket, count(*) FROM buckets GROUP BY ALL),
ranked AS (SELECT *, coalesce(2.0 * pow({g!r}, bucket) / ({g!r} + 1), 0.0) AS v, sum(n) OVER (PARTITION BY level, lang, source, measure ORDER BY bucket NULLS FIRST) AS upto, sum(n) OVER (PARTITION BY level, lang, source, measure) AS total FROM levels),
q AS (SELECT level, lang, source, measure, max(total) AS n, {at(50)} AS mid, {at(90)} - {at(50)} AS up, {at(50)} - {at(10)} AS down FROM ranked GROUP BY ALL),
fences AS (
  SELECT a.lang, a.source, a.measure, {mid} - {r.reach} * {down} AS low, {mid} + {r.reach} * {up} AS high
  FROM q a JOIN q b ON b.level = 1 AND b.lang = a.lang AND b.measure = a.measure JOIN q c ON c.level = 3 AND c.measure = a.measure WHERE a.level = 0)
SELECT c.doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND {tests} AS kept
FROM counted c LEFT JOIN fences f ON f.lang = c.lang AND f.source = c.source
GROUP BY c.doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_lines, base_failed
"""


def _urls() -> str:
    p = url_filter.Reputation()
    rules = sorted(url_filter.RULES, key=lambda r: -len(r[1] + r[2]))
    fits = lambda h, s: f"(host = '{h}' OR ends_with(host, '.{h}')) AND starts_with(path, '{s}')"
    rule = "CASE " + " ".join(f"WHEN {fits(h, s)} THEN '{h}{s}'" for _, h, s in rules) + " END"
    said = "CASE " + " ".join(f"WHEN {fits(h, s)} THEN '{v}'" for v, h, s in rules) + " END"

    def kappa(src: str, key: str) -> str:
        m = "(sum(bad)::DOUBLE / sum(n))"
        spread = f"((sum(bad::DOUBLE * bad / n) - sum(n)::DOUBLE * {m} * {m} - (count(*) - 1) * {m} * (1 - {m})) / sum(n))"
        return f"SELECT {key} least(greatest(coalesce(CASE WHEN count(*) < 2 THEN {p.least} WHEN {spread} > 0 THEN {m} * (1 - {m}) / {spread} - 1 ELSE {p.most} END, {p.most}), {p.least}), {p.most}) AS kappa, sum(bad)::DOUBLE AS bad_up, sum(n)::DOUBLE AS n_up FROM {src} {f'GROUP BY {key[:-1]}' if key else ''}"

    low = f"coalesce(rate - {p.z} * sqrt(rate * (1 - rate) / (weight + 1)) > {p.block_over} * (SELECT rate FROM top), false)"
    two, last = "array_to_string(labels[-2:], '.')", ", ".join(f"'{x}'" for x in url_filter.SUFFIXES)
    address = f"regexp_matches(bare, '{url_filter.ADDRESS}')"
    return rf"""
WITH located AS (SELECT page_id, translate(coalesce(regexp_extract(url, '^.*?://([^/?#]*)', 1, 's'), ''), '{_UP}', '{_LOW}') AS host, coalesce(regexp_extract(url, '^.*?://[^/?#]*([^?#]*)', 1, 's'), '') AS path FROM pages),
ruled AS (SELECT *, {rule} AS rule, {said} AS said FROM located),
bared AS (SELECT DISTINCT host, regexp_replace(host, '{url_filter.TRIMMED}', '', 'g') AS bare FROM ruled),
split AS (SELECT host, bare, string_split(bare, '.') AS labels FROM bared),
names AS (SELECT host, bare, CASE WHEN {address} THEN bare WHEN {two} IN ({last}) THEN array_to_string(labels[-3:], '.') ELSE {two} END AS domain,
  CASE WHEN {address} THEN '#address' WHEN {two} IN ({last}) THEN {two} ELSE labels[-1] END AS suffix FROM split),
known AS (SELECT doc_id, max(quality = 0 OR toxic = 1) AS bad FROM labels WHERE quality IS NOT NULL OR toxic IS NOT NULL GROUP BY doc_id),
hosts AS (SELECT bare AS host, domain, suffix, count(*) AS n, count(*) FILTER (bad) AS bad FROM ruled JOIN names USING (host) JOIN known ON doc_id = TRY_CAST(regexp_extract(path, '^/[^/]*/([0-9]+)', 1) AS BIGINT) WHERE said IS NULL AND bad IS NOT NULL GROUP BY ALL),
domains AS (SELECT domain, suffix, sum(n) AS n, sum(bad) AS bad FROM hosts GROUP BY ALL),
suffixes AS (SELECT suffix, sum(n) AS n, sum(bad) AS bad FROM domains GROUP BY ALL),
top AS (SELECT (bad_up + 1) / (n_up + 2) AS rate, kappa AS weight FROM ({kappa("suffixes", "")})),
s AS (SELECT suffix, (bad + t.weight * t.rate) / (n + t.weight) AS rate, n + t.weight AS weight FROM suffixes, top t),
d AS (SELECT domain, (bad + kappa * s.rate) / (domains.n + kappa) AS rate, domains.n + kappa AS weight FROM domains JOIN s USING (suffix) JOIN ({kappa("domains", "suffix,")}) USING (suffix)),
h AS (SELECT host, (bad + kappa * d.rate) / (hosts.n + kappa) AS rate, hosts.n + kappa AS weight FROM hosts JOIN d USING (domain) JOIN ({kappa("hosts", "domain,")}) USING (domain)),
judged AS (SELECT host, coalesce((SELECT {low} FROM h WHERE h.host = names.bare), (SELECT {low} FROM d WHERE d.domain = names.domain), (SELECT {low} FROM s WHERE s.suffix = names.suffix), (SELECT {low} FROM top), false) AS blocked FROM names)
SELECT page_id, host, path, rule, coalesce(said, CASE WHEN blocked THEN 'block' ELSE 'allow' END) AS verdict FROM ruled JOIN judged USING (host)
"""


def _mix() -> str:
    t = mixing.TARGETS
    if t.weights or t.budget is not None or t.budget_share != 1.0:
        raise ValueError("the reference covers equal weights and the whole budget")
    e, w = t.max_epochs, t.default_weight

    def share(src: str, parent: str, child: str) -> str:
        part = f"PARTITION BY {parent}" if parent else ""
        rows = ", ".join(x for x in (parent, child) if x)
        return f"""(SELECT {rows}, CASE WHEN filled THEN capacity ELSE rest * {w} / open END AS budget FROM (
  SELECT *, given - coalesce(sum(CASE WHEN filled THEN capacity END) OVER ({part}), 0) AS rest, sum(CASE WHEN NOT filled THEN {w} END) OVER ({part}) AS open FROM (
    SELECT *, capacity / {w} <= (given - coalesce(sum(capacity) OVER (o ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)) / sum({w}) OVER (o ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS filled
    FROM {src} WINDOW o AS ({part} ORDER BY capacity / {w}, {child}))))"""

    digest = "md5(coalesce(text, ''))"
    key = f"('0x' || substr(md5(concat_ws('|', '{t.seed}', epochs::VARCHAR, coalesce(doc_id::VARCHAR, ''), digest)), 1, 15))::BIGINT"
    return rf"""
WITH rows AS (SELECT doc_id, lang AS own_lang, source AS own_source, coalesce(lang, '') AS lang, coalesce(source, '') AS source, 'd' || (('0x' || substr(md5(coalesce(source, '')), 1, 6))::BIGINT % {t.domains})::VARCHAR AS domain, {digest} AS digest, len(regexp_extract_all(coalesce(text, ''), '{_WS}'))::BIGINT AS n_tokens FROM documents),
leaves AS (SELECT domain, lang, source, sum(n_tokens)::DOUBLE AS tokens, sum(n_tokens)::DOUBLE * {e} AS capacity FROM rows GROUP BY ALL),
langs AS (SELECT domain, lang, sum(capacity) AS capacity FROM leaves GROUP BY ALL),
doms AS (SELECT domain, sum(capacity) AS capacity, (SELECT sum(tokens) FROM leaves) AS given FROM langs GROUP BY domain),
b1 AS {share("doms", "", "domain")},
b2 AS {share("(SELECT l.*, b.budget AS given FROM langs l JOIN b1 b USING (domain))", "domain", "lang")},
b3 AS {share("(SELECT l.*, b.budget AS given FROM leaves l JOIN b2 b USING (domain, lang))", "domain, lang", "source")},
budgets AS (SELECT domain, lang, source, tokens::BIGINT AS tokens, floor(round(budget, 3))::BIGINT AS budget FROM b3 JOIN leaves USING (domain, lang, source)),
dealt AS (SELECT *, CASE WHEN tokens > 0 THEN budget // tokens ELSE 0 END AS epochs FROM budgets),
keyed AS (SELECT r.*, d.epochs, d.budget - d.epochs * d.tokens AS rest, {key} AS k FROM rows r JOIN dealt d USING (domain, lang, source)),
run AS (SELECT *, sum(n_tokens) OVER (PARTITION BY domain, lang, source ORDER BY k RANGE UNBOUNDED PRECEDING) AS through FROM keyed)
SELECT doc_id, domain, own_lang AS lang, own_source AS source, n_tokens, (epochs + CASE WHEN through <= rest THEN 1 ELSE 0 END)::BIGINT AS copies
FROM run WHERE n_tokens > 0 AND epochs + CASE WHEN through <= rest THEN 1 ELSE 0 END > 0
"""


_WARC = """
WITH p AS (SELECT page_id, strlen(coalesce(html, ''))::BIGINT AS payload_bytes, sha1(coalesce(html, '')) AS payload_digest FROM pages),
best AS (SELECT payload_digest, payload_bytes, max(page_id) AS keeper FROM p WHERE payload_bytes >= 1000 GROUP BY ALL HAVING count(*) > 1)
SELECT page_id, payload_bytes, payload_digest, CASE WHEN keeper IS NOT NULL AND page_id IS DISTINCT FROM keeper THEN 'revisit' ELSE 'response' END AS record_type,
  CASE WHEN page_id IS DISTINCT FROM keeper THEN keeper END AS refers_to
FROM p LEFT JOIN best USING (payload_digest, payload_bytes)
"""

_GRAM = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
_LEAKS = rf"""
WITH d AS (SELECT row_number() OVER () AS rid, doc_id, regexp_extract_all(translate(coalesce(text, ''), '{_UP}', '{_LOW}'), '{_GRAM}') AS w FROM documents),
b AS (SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), '{_UP}', '{_LOW}'), '{_GRAM}') AS w FROM benchmark WHERE item_id IS NOT NULL),
bw AS (SELECT DISTINCT item_id, least(len(w), 10) AS n, array_to_string(w[k : k + least(len(w), 10) - 1], ' ') AS gram FROM (SELECT *, unnest(range(1, len(w) - least(len(w), 10) + 2)) AS k FROM b WHERE len(w) > 0)),
sizes AS (SELECT DISTINCT n FROM bw),
dw AS (SELECT rid, n, k, array_to_string(w[k : k + n - 1], ' ') AS gram FROM (SELECT rid, w, n, unnest(range(1, len(w) - n + 2)) AS k FROM d, sizes WHERE len(w) >= n)),
met AS (SELECT rid, k, dw.n, item_id FROM dw JOIN bw ON dw.n = bw.n AND dw.gram = bw.gram),
hit AS (SELECT rid, count(DISTINCT pos) AS n_hit FROM (SELECT rid, unnest(range(k, k + n)) AS pos FROM met) GROUP BY rid),
items AS (SELECT rid, count(DISTINCT item_id) AS n_items, string_agg(DISTINCT item_id::VARCHAR, ',' ORDER BY item_id::VARCHAR) AS ids FROM met GROUP BY rid),
placed AS (SELECT rid, unnest(w) AS term, unnest(range(0, len(w))) AS pos FROM d),
totals AS (SELECT term, count(*) AS total FROM placed GROUP BY term),
own AS (SELECT row_number() OVER () AS item, item_id, w, least(len(w), 10) AS n FROM (SELECT DISTINCT item_id, w FROM b WHERE len(w) > 0)),
spots AS (SELECT item, k, n, w[k + i + 1] AS term, k + i AS place FROM (SELECT *, unnest(range(0, n)) AS i FROM (SELECT *, unnest(range(0, len(w) - n + 1)) AS k FROM own))),
rare AS (SELECT item, k, count(total) AS present, n, list({{'total': total, 'term': term, 'place': place}} ORDER BY total, term, place) FILTER (total IS NOT NULL) AS r FROM spots LEFT JOIN totals USING (term) GROUP BY item, k, n),
pairs AS (SELECT DISTINCT item, r[1].term AS lead, r[1].place AS a, r[2].term AS other, r[2].place AS z FROM rare WHERE present > 1),
close AS (SELECT DISTINCT x.rid, p.item, p.a, p.z FROM pairs p JOIN placed x ON x.term = p.lead JOIN placed y ON y.rid = x.rid AND y.term = p.other AND abs((y.pos - x.pos) - (p.z - p.a)) <= {decontamination.SLACK}),
near AS (SELECT rid, count(DISTINCT item_id) AS n_near FROM (SELECT rid, item, count(*) AS met_pairs FROM close GROUP BY rid, item) JOIN (SELECT item, count(*) AS all_pairs FROM pairs GROUP BY item) USING (item) JOIN own USING (item) WHERE met_pairs >= {decontamination.NEAR_SHARE} * all_pairs GROUP BY rid)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items, sha256(coalesce(ids, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated, coalesce(n_near, 0)::BIGINT AS n_near
FROM d LEFT JOIN hit USING (rid) LEFT JOIN items USING (rid) LEFT JOIN near USING (rid)
"""

_TRIM = "chr(32) || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)"
_LINES = rf"""
WITH l AS (SELECT doc_id, i, line, translate(trim(line, {_TRIM}), '{_UP}', '{_LOW}') AS k FROM (
  SELECT doc_id, unnest(lines) AS line, unnest(range(1, len(lines) + 1)) AS i FROM (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS lines FROM documents))),
over AS (SELECT k, max(doc_id) AS keeper FROM l WHERE length(k) >= 20 GROUP BY k HAVING count(DISTINCT doc_id) >= 3),
marked AS (SELECT doc_id, i, line, keeper IS NOT NULL AND doc_id <> keeper AS gone FROM l LEFT JOIN over USING (k))
SELECT doc_id, count(*) AS n_lines, count(*) FILTER (gone) AS n_dropped, sha256(coalesce(string_agg(line, chr(10) ORDER BY i) FILTER (NOT gone), '')) AS kept_sha256 FROM marked GROUP BY doc_id
"""

SQL: dict[str, str] = {
    "op1_quality_rules": _quality(),
    "op4_url_filter": _urls(),
    "op6_source_mix": _mix(),
    "op8_warc": _WARC,
    "op9_decontamination": _LEAKS,
    "op10_line_dedup": _LINES,
}
