"""SQL for DuckDB that gives the rows of the workload queries on the same tables."""

from __future__ import annotations

from ..functions.text import LANGUAGE_WORDS, MEDIA
from ..operators.analysis import POISSON
from ..tables import MODELS, RISING
from .queries import FEATURES, KINDS

ORACLES: dict[str, str] = {}

STAR = f"""
m AS (SELECT CAST(range AS INTEGER) AS model_id, CASE WHEN range % 2 = 0 THEN 'proprietary' ELSE 'open' END AS access, CASE WHEN range % 5 = 0 THEN 'medical' ELSE 'general' END AS domain,
  CAST(4 + (range * 13) % 120 AS INTEGER) AS params_b, CAST(DATE '1996-01-01' + CAST(range * 40 + CASE WHEN range % 7 = 3 THEN 120 ELSE 0 END AS INTEGER) AS DATE) AS eff FROM range({MODELS})),
cs AS (SELECT o_orderkey AS case_id, o_orderpriority AS theme, n_name AS specialty, CAST(o_custkey % 4 AS INTEGER) AS source, CAST(n_regionkey % 2 AS INTEGER) AS lang, CAST(o_orderdate AS DATE) AS published
  FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey),
cr AS (SELECT l_orderkey AS case_id, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_orderkey, l_partkey, l_suppkey, l_linenumber, l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate) AS criterion_no,
  CASE WHEN l_returnflag = 'R' THEN -1 ELSE 1 END * CAST(1 + CAST(l_quantity AS INTEGER) % 10 AS INTEGER) AS weight, CAST(substr(p_brand, 7) AS INTEGER) % 5 AS axis
  FROM lineitem JOIN part ON l_partkey = p_partkey),
j0 AS (SELECT model_id, cr.case_id, criterion_no, weight, axis, published, eff, (cr.case_id * 7919 + criterion_no * 104729 + CAST(model_id AS BIGINT) * 1299709) % 1000003 % 100 AS luck
  FROM cr JOIN (SELECT o_orderkey AS case_id, CAST(o_orderdate AS DATE) AS published FROM orders) o ON o.case_id = cr.case_id CROSS JOIN m),
j AS (SELECT *, luck < 20 + model_id + CASE WHEN published <= eff THEN 0 WHEN model_id % 6 = {RISING} THEN 2 ELSE -5 END AS met FROM j0),
s0 AS (SELECT model_id, case_id, any_value(published) AS published, any_value(eff) AS eff, CAST(sum(CASE WHEN met THEN weight ELSE 0 END) AS BIGINT) AS got, CAST(sum(CASE WHEN weight > 0 THEN weight ELSE 0 END) AS BIGINT) AS possible FROM j GROUP BY model_id, case_id),
s1 AS (SELECT *, CASE WHEN possible > 0 THEN got / possible::DOUBLE END AS raw FROM s0),
s AS (SELECT *, CASE WHEN raw IS NOT NULL THEN least(greatest(raw, 0.0), 1.0) END AS score FROM s1),
board AS (SELECT model_id, round(avg(score), 6) AS score, count(score) AS n_cases, CAST(sum(CASE WHEN score IS NULL THEN 1 ELSE 0 END) AS BIGINT) AS n_excluded FROM s GROUP BY model_id)
"""

votes = {k: f"len(list_filter(t, lambda x: list_contains([{', '.join(repr(w) for w in ws)}], x)))" for k, ws in sorted(LANGUAGE_WORDS.items())}
TOK = "regexp_extract_all(lower({0}), '[\\p{{L}}\\p{{N}}]+')"
CONTENT = "list_distinct(list_filter(" + TOK + ", lambda x: length(x) >= 4))"
SENT = "list_filter(list_transform(regexp_split_to_array({0}, '[.!?\\n]+'), lambda s: trim(s)), lambda s: length(s) >= 3)"
SHARE = "CASE WHEN length(text) > 0 THEN length(regexp_replace(text, '[\\p{L}\\p{N}]', '', 'g')) / length(text)::DOUBLE ELSE 1.0 END"
NORM = "lower(trim(regexp_replace(coalesce(text, ''), '[ \\t\\r\\n]+', ' ', 'g')))"


def first_seen(arr: str) -> str:
    """Distinct elements in the order of their first appearance."""
    return f"list_transform(list_filter(list_zip({arr}, range(1, len({arr}) + 1)), lambda p: list_position({arr}, p[1]) = p[2]), lambda p: p[1])"


def language(text: str) -> str:
    t = TOK.format(text)
    v = [x.replace("(t,", f"({t},") for x in votes.values()]
    return "CASE " + " ".join(f"WHEN {x} = greatest({', '.join(v)}) AND {x} > 0 THEN '{k}'" for k, x in zip(votes, v, strict=True)) + " END"


def coverage(a: str, b: str) -> str:
    return f"CASE WHEN len({a}) > 0 THEN len(list_intersect({a}, {b})) / len({a})::DOUBLE ELSE 0.0 END"


THREADS = f"""
msg AS (SELECT conv_id AS thread_id, turn, role, text FROM conversations WHERE role <> 'system'),
lastr AS (SELECT thread_id, max(turn) FILTER (role = 'assistant') AS lr FROM msg GROUP BY thread_id),
qt AS (SELECT msg.thread_id, arg_max(text, turn) AS qtext FROM msg JOIN lastr USING (thread_id) WHERE role = 'user' AND turn < lr GROUP BY msg.thread_id),
fl AS (SELECT thread_id, coalesce(flatten(list({SENT.format('text')} ORDER BY turn) FILTER (role = 'user')), []) AS f0, coalesce(flatten(list({SENT.format('text')} ORDER BY turn) FILTER (role = 'assistant')), []) AS a0,
  string_agg(text, chr(10) ORDER BY turn) AS thread_text FROM msg GROUP BY thread_id),
sc0 AS (SELECT fl.thread_id, {first_seen('f0')} AS f1, {first_seen('a0')} AS advice, thread_text, ({SENT.format('qtext')})[1] AS query FROM fl LEFT JOIN qt USING (thread_id)),
sc AS (SELECT thread_id, query, list_filter(f1, lambda x: x IS DISTINCT FROM query) AS facts, advice, thread_text FROM sc0),
fw AS (SELECT *, len(facts) > 0 AND length(trim(coalesce(query, ''))) > 0 AND len(advice) > 0 AS forwarded FROM sc)
"""
SUFF = f"""
su AS (SELECT thread_id, CAST(len({TOK.format('query')}) >= 3 AND len({CONTENT.format('query')}) >= 1 AND ({language('query')}) IS NOT NULL AS INTEGER) AS s_cc,
  CASE WHEN len({CONTENT.format('query')}) > 0 THEN len(list_filter({CONTENT.format('query')}, lambda t: list_contains(list_transform({CONTENT.format("array_to_string(facts, ' ')")}, lambda y: substr(y, 1, 3)), substr(t, 1, 3)))) / len({CONTENT.format('query')})::DOUBLE ELSE 0.0 END AS s_inf
  FROM fw WHERE forwarded)
"""
EVIDENCE = f"""
pa AS (SELECT doc_id, text, toxic FROM documents JOIN labels USING (doc_id) WHERE quality = 1),
ad AS (SELECT thread_id, CAST(generate_subscripts(advice, 1) - 1 AS INTEGER) AS advice_no, unnest(advice) AS advice_text FROM fw WHERE forwarded),
pt AS (SELECT doc_id, {TOK.format('text')} AS t FROM pa),
pst AS (SELECT count(*) AS n, avg(len(t)) AS mean FROM pt),
ptf AS (SELECT doc_id, len, term, count(*) AS c FROM (SELECT doc_id, len(t) AS len, unnest(t) AS term FROM pt) GROUP BY ALL),
pdf AS (SELECT term, count(*) AS d FROM ptf GROUP BY term),
pp AS (SELECT term, doc_id, CAST(floor(ln(1 + (n - d + 0.5::DOUBLE) / (d + 0.5::DOUBLE)) * (c * 2.2::DOUBLE / (c + 1.2::DOUBLE * (0.25::DOUBLE + 0.75::DOUBLE * len / mean))) * 1000 + 0.5::DOUBLE) AS BIGINT) AS v FROM ptf JOIN pdf USING (term) CROSS JOIN pst),
aq AS (SELECT thread_id, advice_no, unnest(list_distinct({TOK.format('advice_text')})) AS term FROM ad),
hs AS (SELECT thread_id, advice_no, doc_id, CAST(sum(v) AS BIGINT) AS score FROM aq JOIN pp USING (term) GROUP BY ALL),
hits AS (SELECT *, row_number() OVER (PARTITION BY thread_id, advice_no ORDER BY score DESC, doc_id) AS rank FROM hs QUALIFY rank <= 5),
ve AS (SELECT ad.thread_id, ad.advice_no,
    CASE WHEN coalesce(bool_or(toxic = 1 AND cov >= 0.6), false) THEN 0.0 WHEN coalesce(bool_or(toxic = 0 AND cov >= 0.4), false) THEN 1.0 ELSE 0.5 END::DOUBLE AS verdict
  FROM ad LEFT JOIN (SELECT h.thread_id, h.advice_no, toxic, {coverage(CONTENT.format('advice_text'), CONTENT.format('text'))} AS cov FROM hits h JOIN ad USING (thread_id, advice_no) JOIN pa USING (doc_id)) x ON x.thread_id = ad.thread_id AND x.advice_no = ad.advice_no GROUP BY ALL),
al AS (SELECT thread_id, avg(verdict) AS s_align, bool_or(verdict = 0) AS vetoed FROM ve GROUP BY thread_id),
va AS (SELECT su.*, s_align, vetoed, s_cc = 1 AND s_inf > 0.5 AND coalesce(s_align, 0) > 0.5 AND NOT coalesce(vetoed, true) AS keep FROM su LEFT JOIN al USING (thread_id))
"""
AUDIT = f"""
au AS (SELECT thread_id, list_concat(facts, list_filter(advice, lambda x: NOT list_contains(facts, x))) AS el, {CONTENT.format('thread_text')} AS own FROM fw WHERE forwarded),
au1 AS (SELECT thread_id, len(el) AS n_elements, len(list_filter(el, lambda x: len({CONTENT.format('x')}) > 0 AND len(list_intersect({CONTENT.format('x')}, own)) < len({CONTENT.format('x')}))) AS bad FROM au)
"""
HASH = "CAST('0x' || substr(md5({0}), 1, 6) AS INTEGER)"
theme = "CASE " + " ".join(f"WHEN v[{i + 1}] = list_max(v) THEN {i}" for i in range(5)) + " END"
RUBRIC = f"""
r0 AS (SELECT f.thread_id AS case_id, f.advice, f.facts, {CONTENT.format("array_to_string(f.advice, ' ')")} AS own, o.facts AS foreign_ FROM fw f LEFT JOIN fw o ON o.thread_id = f.thread_id + 1 AND o.forwarded WHERE f.forwarded),
r1 AS (SELECT *, [{', '.join(f"len(list_filter(own, lambda t: length(t) % 5 = {i}))" for i in range(5))}] AS v FROM r0),
r2 AS (SELECT *, {theme} AS theme FROM r1),
r3 AS (SELECT *, list_filter(advice, lambda s: len(list_filter({CONTENT.format('s')}, lambda t: length(t) % 5 = theme)) > 0) AS fit FROM r2),
r4 AS (SELECT case_id, CASE WHEN len(fit) > 0 THEN fit ELSE advice END AS good, list_filter(coalesce(foreign_, []), lambda s: ({coverage(CONTENT.format('s'), 'own')}) < 0.5)[1:2] AS bad FROM r3),
r5 AS (SELECT case_id, CAST(generate_subscripts(list_concat(good, bad), 1) AS INTEGER) AS criterion_no, unnest(list_concat(good, bad)) AS criterion, len(good) AS ng FROM r4),
ru AS (SELECT case_id, criterion_no, criterion, CASE WHEN criterion_no <= ng THEN 1 ELSE -1 END AS polarity, CAST({HASH.format('criterion')} % 5 AS INTEGER) AS axis,
  CAST(CASE WHEN criterion_no <= ng THEN 1 ELSE -1 END * (1 + CAST(floor({HASH.format('criterion')} / 5) AS INTEGER) % 10) AS INTEGER) AS weight FROM r5)
"""
ANSWERS = """
a0 AS (SELECT f.thread_id AS case_id, f.advice, f.facts, o.advice AS oa, o.facts AS ofa FROM fw f LEFT JOIN fw o ON o.thread_id = f.thread_id + 1 AND o.forwarded WHERE f.forwarded),
an AS (SELECT case_id, 'reference' AS model, array_to_string(advice, '. ') AS text FROM a0
  UNION ALL SELECT case_id, 'half', array_to_string(advice[1:CAST(ceil(len(advice) / 2.0) AS INTEGER)], '. ') FROM a0
  UNION ALL SELECT case_id, 'echo', array_to_string(facts, '. ') FROM a0
  UNION ALL SELECT case_id, 'foreign', array_to_string(coalesce(oa, []), '. ') FROM a0
  UNION ALL SELECT case_id, 'tainted', array_to_string(list_concat(advice, coalesce(ofa, [])[1:1]), '. ') FROM a0)
"""
TEXT_SCORES = f"""
tj AS (SELECT model, ru.case_id, weight, ({coverage(CONTENT.format('criterion'), CONTENT.format('text'))}) >= 0.8 AS met FROM ru JOIN an USING (case_id)),
ts0 AS (SELECT model, case_id, sum(CASE WHEN met THEN weight ELSE 0 END)::DOUBLE AS got, sum(CASE WHEN weight > 0 THEN weight ELSE 0 END) AS possible FROM tj GROUP BY ALL),
ts AS (SELECT model, case_id, CASE WHEN possible > 0 THEN got / possible END AS raw, CASE WHEN possible > 0 THEN least(greatest(got / possible, 0), 1) END AS score FROM ts0)
"""
PAIRS = """pr AS (SELECT a.model || ':' || a.case_id AS id, a.text AS candidate, r.text AS reference, regexp_extract_all(lower(a.text), '[\\p{L}\\p{N}]+') AS ct, regexp_extract_all(lower(r.text), '[\\p{L}\\p{N}]+') AS rt FROM an a JOIN an r ON r.case_id = a.case_id AND r.model = 'reference')"""


def grams(side: str, n: int) -> str:
    t = {"candidate": "ct", "reference": "rt", "text": "t"}[side]
    return f"CASE WHEN len({t}) >= {n} THEN list_transform(range(1, len({t}) - {n} + 2), lambda i: array_to_string({t}[i:i + {n - 1}], ' ')) ELSE CAST([] AS VARCHAR[]) END"


def ngram_counts(n: int) -> str:
    side = lambda c: f"(SELECT id, g, count(*) AS c FROM (SELECT id, unnest({grams(c, n)}) AS g FROM pr) GROUP BY ALL)"
    return f"g{n} AS (SELECT pr.id, coalesce(h, 0) AS hits, greatest(len(ct) - {n - 1}, 0) AS ic, greatest(len(rt) - {n - 1}, 0) AS ir FROM pr LEFT JOIN (SELECT a.id, CAST(sum(least(a.c, b.c)) AS BIGINT) AS h FROM {side('candidate')} a JOIN {side('reference')} b ON a.id = b.id AND a.g = b.g GROUP BY a.id) x ON x.id = pr.id)"


def rouge(n: int) -> str:
    p, r = "CASE WHEN ic > 0 THEN hits / ic::DOUBLE ELSE 0 END", "CASE WHEN ir > 0 THEN hits / ir::DOUBLE ELSE 0 END"
    return f"SELECT id, round({p}, 6) AS precision, round({r}, 6) AS recall, round(CASE WHEN ({p}) + ({r}) > 0 THEN 2 * ({p}) * ({r}) / (({p}) + ({r})) ELSE 0 END, 6) AS f, {n} AS n FROM g{n}"


GRAM = "CASE WHEN len({0}) >= {1} THEN list_transform(range(1, len({0}) - {1} + 2), lambda i: array_to_string({0}[i:i + {1} - 1], ' ')) ELSE CAST([] AS VARCHAR[]) END"
SCHEME = "['disease', 'function', 'intervention'][CAST('0x' || substr(md5(term), 1, 6) AS INTEGER) % 3 + 1]"
FIRST = "length(split_part({0}, ' ', 1)) >= 9"


def book(source: str, key: str) -> str:
    """Code terms of one and two words, the runs of up to three words of the source, and the terms that each of its rows has."""
    runs = " || ".join(f"({GRAM.format('t', n)})" for n in (1, 2, 3))
    return f"""bt AS (SELECT {TOK.format('text')} AS t FROM benchmark),
bk AS (SELECT term, {SCHEME} AS scheme FROM (SELECT DISTINCT unnest(({GRAM.format('t', 1)}) || ({GRAM.format('t', 2)})) AS term FROM bt) WHERE {FIRST.format('term')}),
sr AS (SELECT {key}, unnest(list_distinct({runs})) AS term FROM (SELECT {key}, {TOK.format('text')} AS t FROM {source})),
cm AS (SELECT {key}, term, scheme FROM sr JOIN bk USING (term)),
ch AS (SELECT {key}, list_sort(list(DISTINCT term)) AS matched FROM cm GROUP BY {key})"""


def dups(source: str, key: str) -> str:
    return f"h AS (SELECT {key}, md5({NORM}) AS h FROM {source}), hf AS (SELECT h, min({key}) AS first FROM h GROUP BY h HAVING count(*) > 1), du AS (SELECT {key}, CASE WHEN {key} > first THEN first END AS dup_of FROM h LEFT JOIN hf USING (h))"


BOOK, DUP = book("documents", "doc_id"), dups("documents", "doc_id")
RULES = ("date", "tags", "text only", "symbols", "language", "code term", "duplicate", "verified reply")
TO_FILTER = """tf0 AS (SELECT thread_id, string_agg(text, chr(10) ORDER BY turn) AS t0, min(posted_at) AS posted_at, bool_or(role = 'assistant') AS replied FROM po WHERE role <> 'system' GROUP BY thread_id),
tf AS (SELECT thread_id, CASE WHEN thread_id % 11 = 0 THEN t0 || chr(10) || '[image]' ELSE t0 END AS text, posted_at, replied, thread_id % 7 AS tag FROM tf0)"""
HAN = "length(text) - length(regexp_replace(text, '[\\x{4E00}-\\x{9FFF}]', '', 'g'))"
RULED = f"""rl AS (SELECT thread_id, posted_at >= DATE '2024-01-04' AS t1, tag NOT IN (2, 3) AS t2, NOT regexp_matches(text, '{MEDIA}') AS t3, ({SHARE}) < 0.5 AS t4,
  coalesce({HAN} >= 0.2 * greatest(length(text), 1) OR ({language('text')}) = 'en', false) AS t5, coalesce(len(matched), 0) > 0 AS t6, dup_of IS NULL AS t7, replied AS t8
  FROM tf LEFT JOIN ch USING (thread_id) LEFT JOIN du USING (thread_id))"""
POSTS = "po AS (SELECT conv_id AS thread_id, turn, role, text, ts AS posted_at, 'p' || (conv_id % 4) AS platform FROM conversations JOIN events ON event_id = (conv_id * 97) % (SELECT count(*) FROM events))"
RATED = f"ra AS (SELECT doc_id, quality AS a, CAST(({SHARE}) < 0.25 AND length(text) >= 100 AS INTEGER) AS b FROM labels JOIN documents USING (doc_id))"


def put(name: str, sql: str, *ctes: str) -> None:
    ORACLES[name] = ("WITH " + ",\n".join(x.strip() for x in ctes) + "\n" if ctes else "") + sql


put("platform_activity", "SELECT event_type, count(DISTINCT date_trunc('week', ts)) AS active_weeks, count(DISTINCT date_trunc('week', ts)) >= 5 AND count(DISTINCT date_trunc('week', ts)) = date_diff('week', min(ts), max(ts)) + 1 AS ok FROM events GROUP BY event_type")
put("platform_verified", "SELECT event_type, count(DISTINCT user_id) AS n_verified, count(DISTINCT user_id) >= 100 AS ok FROM events GROUP BY event_type")
put("platform_selection", "SELECT *, active AND endorsed AND verified AS selected FROM (SELECT event_type, count(DISTINCT date_trunc('week', ts)) >= 5 AND count(DISTINCT date_trunc('week', ts)) = date_diff('week', min(ts), max(ts)) + 1 AS active, event_type IN ('click', 'view', 'purchase') AS endorsed, count(DISTINCT user_id) >= 100 AS verified FROM events GROUP BY event_type)")
steps = " UNION ALL ".join(f"SELECT {k} AS step, '{('all', *RULES)[k]}' AS rule, " + ("count(*) AS remaining, CAST(0 AS BIGINT) AS removed, count(*) AS without" if not k else f"count(*) FILTER ({' AND '.join(f't{i}' for i in range(1, k + 1))}) AS remaining, count(*) FILTER ({' AND '.join([f't{i}' for i in range(1, k)] + [f'NOT t{k}'])}) AS removed, count(*) FILTER ({' AND '.join(f't{i}' for i in range(1, len(RULES) + 1) if i != k)}) AS without") + " FROM rl" for k in range(len(RULES) + 1))
FILTERED = (POSTS, TO_FILTER, book("tf", "thread_id"), dups("tf", "thread_id"), RULED)
put("post_filter_funnel", steps, *FILTERED)
put("post_filter_reasons", "SELECT thread_id, array_to_string(list_filter([" + ", ".join(f"CASE WHEN NOT t{k + 1} THEN '{n}' END" for k, n in enumerate(RULES)) + "], lambda x: x IS NOT NULL), ',') AS reasons, " + " AND ".join(f"t{k + 1}" for k in range(len(RULES))) + " AS kept FROM rl", *FILTERED)
put("code_scheme_hits", "SELECT scheme, count(DISTINCT doc_id) AS docs, count(*) AS terms FROM cm GROUP BY scheme", BOOK)
BODY = "regexp_replace(regexp_replace(regexp_replace(coalesce(html, ''), '(?is)<(script|style)[^>]*>.*?</(script|style)>', ' ', 'g'), '(?s)<[^>]*>', ' ', 'g'), '\\s+', ' ', 'g')"
for sign, plain in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "''"), ("&nbsp;", " "), ("&amp;", "&")):
    BODY = f"replace({BODY}, '{sign}', '{plain}')"
put("page_bodies", f"SELECT page_id, length(trim({BODY})) AS chars, md5(trim({BODY})) AS body_md5 FROM pages")
put("code_term_hits", "SELECT doc_id, array_to_string(matched, ',') AS matched FROM ch", BOOK)
put("symbol_share", f"SELECT doc_id, round({SHARE}, 6) AS share, ({SHARE}) < 0.5 AS ok FROM documents")
put("language_vote", f"SELECT doc_id, {language('text')} AS voted, lang FROM documents")
put("media_pages", f"SELECT page_id, trim(regexp_extract(html, '(?is)<title[^>]*>(.*?)</title>', 1)) AS title, regexp_extract(html, '(?i)<html[^>]*\\blang=\"?([A-Za-z-]+)', 1) AS lang, len(regexp_extract_all(html, '(?i)<(img|video|audio)\\b')) AS n_media, NOT regexp_matches(html, '{MEDIA}') AS text_only FROM pages")
put("verified_reply", "SELECT thread_id, bool_or(role = 'assistant') AS ok FROM msg GROUP BY thread_id", THREADS)
put("dedup_exact", "SELECT * FROM du", DUP)
put("dedup_index_anti", f"SELECT min(doc_id) AS doc_id FROM documents WHERE source >= 'src5' AND {NORM} NOT IN (SELECT {NORM} FROM documents WHERE source < 'src5') GROUP BY {NORM}")
put("screen_forward", "SELECT thread_id, query, len(facts) AS n_facts, len(advice) AS n_advice, forwarded FROM fw", THREADS)
put("narrative_sufficiency", "SELECT thread_id, s_cc, round(s_inf, 6) AS s_inf FROM su", THREADS, SUFF)
put("evidence_topk_bm25", "SELECT thread_id, advice_no, CAST(rank AS BIGINT) AS rank, doc_id, score FROM hits", THREADS, SUFF, EVIDENCE)
put("advice_verdicts", "SELECT thread_id, advice_no, verdict FROM ve", THREADS, SUFF, EVIDENCE)
put("validator_keep", "SELECT thread_id, s_cc, round(s_inf, 6) AS s_inf, round(s_align, 6) AS s_align, vetoed, keep FROM va", THREADS, SUFF, EVIDENCE)
put("threshold_sweep", "SELECT a AS tau_inf, b AS tau_align, count(*) FILTER (s_cc = 1 AND s_inf > a AND s_align > b AND NOT vetoed) AS kept FROM va CROSS JOIN (VALUES (0.25::DOUBLE), (0.5::DOUBLE), (0.75::DOUBLE)) x(a) CROSS JOIN (VALUES (0.25::DOUBLE), (0.5::DOUBLE), (0.75::DOUBLE)) y(b) GROUP BY a, b", THREADS, SUFF, EVIDENCE)
put("audit_support", f"SELECT thread_id, len(el) AS n_elements, len(list_filter(el, lambda x: {(bad := f'len({CONTENT.format("x")}) > 0 AND len(list_intersect({CONTENT.format("x")}, own)) < len({CONTENT.format("x")})')})) AS n_fabricated, len(list_filter(el, lambda x: {bad})) = 0 AS supported FROM (SELECT f.thread_id, list_concat(f.facts, list_filter({first_seen('ax')}, lambda x: NOT list_contains(f.facts, x))) AS el, {CONTENT.format('f.thread_text')} AS own FROM (SELECT fw.*, CASE WHEN fw.thread_id % 2 = 0 AND o.advice[1] IS NOT NULL THEN list_append(fw.advice, o.advice[1]) ELSE fw.advice END AS ax FROM fw LEFT JOIN fw o ON o.thread_id = fw.thread_id + 1) f WHERE forwarded)", THREADS)
put("curation_funnel", """, pl AS (SELECT fw.thread_id, CASE WHEN NOT forwarded THEN 1 WHEN s_cc <> 1 THEN 2 WHEN s_inf <= 0.5 THEN 3 WHEN vetoed THEN 4 WHEN NOT keep THEN 5 WHEN bad > 0 THEN 6 ELSE 7 END AS place FROM fw LEFT JOIN va USING (thread_id) LEFT JOIN au1 USING (thread_id))
SELECT k AS step, ['threads', 'screen', 'complaint', 'sufficiency', 'veto', 'alignment', 'audit'][k + 1] AS stage, count(*) FILTER (place > k) AS remaining FROM pl CROSS JOIN (SELECT CAST(range AS INTEGER) AS k FROM range(7)) GROUP BY k""".lstrip(), THREADS, SUFF, EVIDENCE, AUDIT)
PLACE = ", pl AS (SELECT fw.thread_id, CASE WHEN NOT forwarded THEN 1 WHEN s_cc <> 1 THEN 2 WHEN s_inf <= 0.5 THEN 3 WHEN vetoed THEN 4 WHEN NOT keep THEN 5 WHEN bad > 0 THEN 6 ELSE 7 END AS place FROM fw LEFT JOIN va USING (thread_id) LEFT JOIN au1 USING (thread_id))"
put("curation_rejects", "SELECT thread_id, ['screen', 'complaint', 'sufficiency', 'veto', 'alignment', 'audit'][place] AS reason FROM pl WHERE place < 7", THREADS, SUFF, EVIDENCE, AUDIT, PLACE[2:])
put("note_sections", "SELECT thread_id, len(facts) AS n_s, len(list_filter(facts, lambda x: regexp_matches(x, '[0-9]'))) AS n_o, len(advice) - 1 AS n_p, advice[1] AS assessment FROM fw WHERE forwarded", THREADS)
put("fold_strictest", "SELECT thread_id, min(verdict) AS s_align, bool_or(verdict = 0) AS vetoed FROM ve GROUP BY thread_id", THREADS, SUFF, EVIDENCE)
put("curated_cases", "SELECT fw.thread_id AS case_id, array_to_string(facts, '. ') AS narrative, query, array_to_string(advice, '. ') AS advice FROM fw JOIN va USING (thread_id) JOIN au1 USING (thread_id) WHERE keep AND bad = 0", THREADS, SUFF, EVIDENCE, AUDIT)
DENSE = "dn AS (SELECT q.vec_id AS q_id, v.vec_id AS doc_id, q.label AS ql, v.label AS dl, round(list_dot_product(CAST(q.embedding AS DOUBLE[]), CAST(v.embedding AS DOUBLE[])), 6) AS score FROM embeddings q JOIN embeddings v ON q.vec_id <> v.vec_id WHERE q.vec_id % 10 = 0), dk AS (SELECT *, row_number() OVER (PARTITION BY q_id ORDER BY score DESC, doc_id) AS rank FROM dn QUALIFY rank <= 5)"
put("evidence_topk_dense", "SELECT q_id, doc_id, CAST(rank AS BIGINT) AS rank, score FROM dk", DENSE)
put("retrieval_precision", "SELECT count(*) AS n, round(avg(CAST(ql = dl AS INTEGER)), 6) AS precision FROM dk", DENSE)
put("rubric_text", "SELECT * FROM ru", THREADS, RUBRIC)
put("rubric_star", "SELECT axis, count(*) AS n, CAST(sum(weight) AS BIGINT) AS weights, count(*) FILTER (weight < 0) AS negative FROM cr GROUP BY axis", STAR)
put("rubric_violations", "SELECT 'no positive' AS violation, count(*) AS n FROM (SELECT case_id FROM cr GROUP BY case_id HAVING max(weight) <= 0) HAVING count(*) > 0", STAR)
put("rubric_text_violations", """SELECT violation, count(*) AS n FROM (
  SELECT unnest(list_filter([CASE WHEN weight IS NULL OR abs(weight) > 10 THEN 'range' END, CASE WHEN weight = 0 THEN 'zero' END, CASE WHEN sign(weight) <> polarity THEN 'sign' END], lambda x: x IS NOT NULL)) AS violation FROM ru
  UNION ALL SELECT 'no positive' FROM ru GROUP BY case_id HAVING coalesce(max(weight), 0) <= 0
  UNION ALL SELECT 'duplicate' FROM ru GROUP BY case_id, criterion HAVING count(*) > 1) GROUP BY violation""", THREADS, RUBRIC)
put("unique_criteria", "SELECT md5(lower(trim(criterion))) AS criterion_hash, count(*) AS uses, min(case_id) AS first_case FROM ru GROUP BY 1", THREADS, RUBRIC)
put("case_scores", "SELECT model_id, CAST(sum(got) AS BIGINT) AS got, CAST(sum(possible) AS BIGINT) AS possible, count(score) AS n_scored, count(*) FILTER (raw < 0) AS clipped, round(avg(raw), 6) AS raw, round(avg(score), 6) AS score FROM s GROUP BY model_id", STAR)
put("leaderboard", "SELECT *, rank() OVER (ORDER BY score DESC) AS rank FROM board", STAR)
put("leaderboard_modes", "SELECT model_id, round(sum(CASE WHEN met THEN weight ELSE 0 END) / sum(CASE WHEN weight > 0 THEN weight ELSE 0 END)::DOUBLE, 6) AS micro, round(avg(CAST(met AS INTEGER)), 6) AS unweighted, round(count(*) FILTER (met AND weight > 0) / (count(*) FILTER (weight > 0))::DOUBLE, 6) AS positive, round(count(*) FILTER (met AND abs(weight) = 10) / (count(*) FILTER (abs(weight) = 10))::DOUBLE, 6) AS critical FROM j GROUP BY model_id", STAR)
put("axis_scores", "SELECT model_id, axis, round(sum(CASE WHEN met THEN weight ELSE 0 END) / sum(CASE WHEN weight > 0 THEN weight ELSE 0 END)::DOUBLE, 6) AS score FROM j GROUP BY ALL", STAR)
put("snapshot_leaderboard", "SELECT *, rank() OVER (ORDER BY score DESC) AS rank FROM (SELECT model_id, round(avg(score), 6) AS score, count(score) AS n_cases, count(*) FILTER (score IS NULL) AS n_excluded FROM s WHERE published <= DATE '1996-12-31' GROUP BY model_id)", STAR)
put("pairwise_wins", "SELECT a.model_id AS a, b.model_id AS b, count(*) FILTER (a.score > b.score) AS wins, count(*) FILTER (a.score < b.score) AS losses, count(*) FILTER (a.score = b.score) AS ties FROM s a JOIN s b ON a.case_id = b.case_id AND a.model_id < b.model_id WHERE a.score IS NOT NULL AND b.score IS NOT NULL GROUP BY ALL", STAR)
put("text_leaderboard", "SELECT model, count(score) AS n, round(avg(raw), 6) AS raw, round(avg(score), 6) AS score FROM ts GROUP BY model", THREADS, RUBRIC, ANSWERS, TEXT_SCORES)
DELTA = "de AS (SELECT model_id, avg(score) AS f, avg(score) FILTER (published > eff) AS p, count(score) FILTER (published > eff) AS n_post FROM s GROUP BY model_id), dl AS (SELECT model_id, round(f, 6) AS full, round(p, 6) AS post, round(p - f, 6) AS diff, n_post FROM de)"
put("cutoff_delta", "SELECT * FROM dl", STAR, DELTA.replace(" AS full,", ' AS "full",'))
put("degraded_share", "SELECT count(diff) AS n, count(*) FILTER (diff < 0) AS n_down, round(avg(CAST(diff < 0 AS INTEGER)), 6) AS share, min(diff) AS worst, max(diff) AS best FROM dl", STAR, DELTA.replace(" AS full,", ' AS "full",'))
put("degraded_by_family", "SELECT access, count(diff) AS n, count(*) FILTER (diff < 0) AS n_down, round(avg(CAST(diff < 0 AS INTEGER)), 6) AS share, round(avg(diff), 6) AS mean_diff, min(diff) AS worst FROM dl JOIN m USING (model_id) GROUP BY ROLLUP (access)", STAR, DELTA.replace(" AS full,", ' AS "full",'))
put("score_by_month", "SELECT CAST(CAST(date_trunc('month', published) AS DATE) AS VARCHAR) AS start, count(*) AS n, round(avg(score), 6) AS mean FROM s WHERE score IS NOT NULL GROUP BY 1", STAR)
put("score_sliding", "SELECT CAST(CAST(w AS DATE) AS VARCHAR) AS start, count(*) AS n, round(avg(score), 6) AS mean FROM s JOIN (SELECT unnest(generate_series(TIMESTAMP '1990-01-01', TIMESTAMP '2010-01-01', INTERVAL 3 MONTH)) AS w) ON published >= w AND published < w + INTERVAL 12 MONTH WHERE score IS NOT NULL GROUP BY 1", STAR)
put("score_skew", "SELECT model_id, count(*) AS n, round(avg(pow(score - mean, 3)) / pow(avg(pow(score - mean, 2)), 1.5), 5) AS skew FROM (SELECT *, avg(score) OVER (PARTITION BY model_id) AS mean FROM s WHERE score IS NOT NULL) GROUP BY model_id", STAR)
put("criteria_profile", "SELECT 'axis' AS facet, axis::DOUBLE AS value, count(*) AS n, round(count(*) / sum(count(*)) OVER (), 6) AS share FROM cr GROUP BY axis UNION ALL SELECT * FROM (SELECT unnest(['mean per case', 'least per case', 'most per case']) AS facet, unnest([round(avg(c), 6), min(c)::DOUBLE, max(c)::DOUBLE]) AS value, count(*) AS n, NULL::DOUBLE AS share FROM (SELECT count(*) AS c FROM cr GROUP BY case_id))", STAR)
put("drop_significance", "SELECT model_id, n0 AS n_pre, n1 AS n_post, round((m1 - m0) / sqrt(v0 / n0 + v1 / n1), 4) AS t, round(pow(v0 / n0 + v1 / n1, 2) / (pow(v0 / n0, 2) / (n0 - 1) + pow(v1 / n1, 2) / (n1 - 1)), 2) AS df FROM (SELECT model_id, count(score) FILTER (published <= eff) AS n0, count(score) FILTER (published > eff) AS n1, avg(score) FILTER (published <= eff) AS m0, avg(score) FILTER (published > eff) AS m1, var_samp(score) FILTER (published <= eff) AS v0, var_samp(score) FILTER (published > eff) AS v1 FROM s GROUP BY model_id)", STAR)
put("score_by_quarter", "SELECT CAST(quarter AS VARCHAR) AS quarter, n, round(t / n, 6) AS mean, round(sum(t) OVER w / sum(n) OVER w, 6) AS moving FROM (SELECT CAST(date_trunc('quarter', published) AS DATE) AS quarter, count(*) AS n, sum(score) AS t FROM s WHERE score IS NOT NULL GROUP BY 1) WINDOW w AS (ORDER BY quarter ROWS BETWEEN 1 PRECEDING AND CURRENT ROW)", STAR)
put("score_trend", "SELECT round(regr_slope(score, date_diff('day', DATE '1970-01-01', published) / 30.0::DOUBLE), 8) AS slope FROM s WHERE score IS NOT NULL", STAR)
put("aligned_windows", "SELECT CAST(floor((date_diff('day', eff, published) - 1) / 365.0) AS BIGINT) AS rel_window, count(*) AS n, round(avg(score), 6) AS mean FROM s WHERE score IS NOT NULL GROUP BY 1", STAR)
put("separation_violations", "SELECT model_id, count(*) AS n FROM m JOIN orders ON CAST(o_orderdate AS DATE) <= eff GROUP BY model_id", STAR)
LEAK = f"ig AS (SELECT item_id, unnest(list_distinct({grams('text', 8)})) AS g FROM (SELECT item_id, {TOK.format('text')} AS t FROM benchmark)), dg AS (SELECT doc_id, unnest(list_distinct({grams('text', 8)})) AS g FROM (SELECT doc_id, {TOK.format('text')} AS t FROM documents)), lk AS (SELECT item_id, doc_id, count(*) AS shared FROM ig JOIN dg USING (g) GROUP BY ALL)"
put("leak_exact", "SELECT item_id, doc_id FROM benchmark b JOIN documents d ON contains(d.text, b.text)")
put("leak_ngram", "SELECT item_id, doc_id, shared, round(shared / n::DOUBLE, 6) AS share FROM lk JOIN (SELECT item_id, count(*) AS n FROM ig GROUP BY item_id) USING (item_id)", LEAK)
put("leak_gap", "SELECT model_id, round(avg(score) FILTER (case_id IN (SELECT item_id FROM lk)), 6) AS leaked, round(avg(score) FILTER (case_id NOT IN (SELECT item_id FROM lk)), 6) AS clean FROM s WHERE case_id IN (SELECT item_id FROM benchmark) GROUP BY model_id", STAR, LEAK)
put("approval", "SELECT 'quality' AS dim, k AS rater_id, count(r) AS n, round(avg(CAST(r >= 1 AS INTEGER)), 6) AS rate FROM (SELECT 1 AS k, a AS r FROM ra UNION ALL SELECT 2, b FROM ra) GROUP BY k", RATED)
AC = "x AS (SELECT count(*) AS n, avg(CAST(a = b AS INTEGER)) AS pa, avg(a) AS ma, avg(b) AS mb FROM ra), y AS (SELECT *, 2 * ((ma + mb) / 2) * (1 - (ma + mb) / 2) AS pe, ma * mb + (1 - ma) * (1 - mb) AS ke FROM x), z AS (SELECT n, round(pa, 6) AS pa, round(pe, 6) AS pe, round((pa - pe) / (1 - pe), 6) AS ac1, round((pa - ke) / (1 - ke), 6) AS kappa FROM y)"
put("gwet_ac1", "SELECT *, CASE WHEN ac1 > 0.8 THEN 'almost perfect' WHEN ac1 > 0.6 THEN 'substantial' WHEN ac1 > 0.4 THEN 'moderate' WHEN ac1 > 0.2 THEN 'fair' ELSE 'slight' END AS band FROM z", RATED, AC)


LEVELS = "l3 AS (SELECT a + CAST(length(text) >= 900 AS INTEGER) AS a, b + CAST(length(text) >= 800 AS INTEGER) AS b FROM ra JOIN documents USING (doc_id))"
mean = lambda c, k: f"avg(CAST({c} = {k} AS INTEGER))"
chance = " + ".join(f"(a{k} + b{k}) / 2 * (1 - (a{k} + b{k}) / 2)" for k in range(3))
both = " + ".join(f"a{k} * b{k}" for k in range(3))
put("gwet_ac1_levels", "SELECT n, round(pa, 6) AS pa, round(pe, 6) AS pe, round((pa - pe) / (1 - pe), 6) AS ac1, round((pa - ke) / (1 - ke), 6) AS kappa FROM l5", RATED, LEVELS, "l4 AS (SELECT count(*) AS n, avg(CAST(a = b AS INTEGER)) AS pa, " + ", ".join(f"{mean(c, k)} AS {c}{k}" for c in "ab" for k in range(3)) + " FROM l3)", f"l5 AS (SELECT n, pa, ({chance}) / 2 AS pe, {both} AS ke FROM l4)")


def f1(pred: str, truth: str, source: str) -> str:
    c = lambda p, t: f"count(*) FILTER ({pred} = {p} AND {truth} = {t})"
    wrong = f"({c(1, 0)} + {c(0, 1)})"
    part = lambda k: f"(2 * {c(k, k)} / (2 * {c(k, k)} + {wrong})::DOUBLE)"
    return f"round({part(1)}, 6) AS f1_yes, round({part(0)}, 6) AS f1_no, round(({part(1)} + {part(0)}) / 2, 6) AS macro_f1 FROM {source}"


put("macro_f1", "SELECT " + f1("b", "a", "ra"), RATED)
flip = lambda k: f"CAST(met <> ((case_id * 31 + criterion_no * 17 + {k}) % 11 = 0) AS INTEGER) AS p{k}"
put("grader_alignment", " UNION ALL ".join(f"SELECT '{n}' AS pair, macro_f1 FROM (SELECT {f1(a, b, 'ga')})" for n, a, b in (("grader 1", "k", "p1"), ("grader 2", "k", "p2"), ("raters", "p1", "p2"))), STAR, f"ga AS (SELECT CAST(met AS INTEGER) AS k, {flip(1)}, {flip(2)} FROM j)")
put("grader_mean", "SELECT CASE WHEN pair = 'raters' THEN 'raters' ELSE 'grader' END AS who, round(avg(macro_f1), 6) AS macro_f1 FROM (" + ORACLES["grader_alignment"] + ") GROUP BY 1")
put("pearson_case", "SELECT count(*) AS n, round(corr(x, y), 6) AS r FROM (SELECT max(score) FILTER (model_id = 36) AS x, max(score) FILTER (model_id = 37) AS y FROM s WHERE model_id IN (36, 37) GROUP BY case_id) WHERE x IS NOT NULL AND y IS NOT NULL", STAR)
put("sampled_cases", "SELECT case_id, theme FROM cs ORDER BY md5('42:' || case_id), case_id LIMIT 50", STAR)
put("score_histogram", "SELECT CAST(least(floor(score * 10), 9) AS BIGINT) AS bin, count(*) AS n FROM s WHERE score IS NOT NULL GROUP BY 1", STAR)
HOL = "ho AS (SELECT model, case_id, length(text) AS len, least(1.0::DOUBLE, 0.55::DOUBLE + ln(1.0::DOUBLE + length(text)) / 20) AS holistic FROM an)"
put("length_bias", "SELECT count(score) AS n, round(corr(score, ln(1 + len)), 5) AS rubric_r, round(corr(holistic, ln(1 + len)), 5) AS holistic_r FROM ho JOIN ts USING (model, case_id)", THREADS, RUBRIC, ANSWERS, TEXT_SCORES, HOL)
put("missed_hazards", "SELECT model, count(*) AS n FROM ho JOIN ts USING (model, case_id) WHERE score = 0 AND holistic >= 0.7 GROUP BY model", THREADS, RUBRIC, ANSWERS, TEXT_SCORES, HOL)
put("holistic_scores", "SELECT model, count(*) AS n, round(avg(holistic), 6) AS score FROM ho GROUP BY model", THREADS, ANSWERS, HOL)
put("rouge_scores", rouge(1) + " UNION ALL " + rouge(2), THREADS, ANSWERS, PAIRS, ngram_counts(1), ngram_counts(2))
logs = " + ".join(f"CASE WHEN g{n}.hits + {a} > 0 AND g{n}.ic + {a} > 0 THEN ln((g{n}.hits + {a}) / (g{n}.ic + {a})::DOUBLE) END" for n, a in ((1, 0), (2, 1), (3, 1), (4, 1)))
put("bleu_scores", f"SELECT g1.id, round(coalesce(CASE WHEN g1.ic >= g1.ir THEN 1.0 WHEN g1.ic = 0 THEN 0.0 ELSE exp(1 - g1.ir / g1.ic::DOUBLE) END * exp(({logs}) / 4), 0.0), 6) AS bleu FROM g1 JOIN g2 USING (id) JOIN g3 USING (id) JOIN g4 USING (id)", THREADS, ANSWERS, PAIRS, *map(ngram_counts, (1, 2, 3, 4)))
put("choice_accuracy", "SELECT CAST(l_suppkey % 38 AS INTEGER) AS model_id, count(*) AS n, round(avg(CAST(CAST(l_quantity AS INTEGER) % 4 = p_size % 4 AS INTEGER)), 6) AS accuracy FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1")
SG = "sg AS (SELECT model_id, {0}, round(avg(score), 6) AS score, count(*) AS n FROM s JOIN cs USING (case_id) WHERE score IS NOT NULL GROUP BY ALL)"
put("specialty_matrix", "SELECT * FROM sg", STAR, SG.format("specialty"))
put("theme_profile", "SELECT * FROM sg", STAR, SG.format("theme"))
put("specialty_extremes", "SELECT * FROM (SELECT specialty, mean, 'weak' AS side, row_number() OVER (ORDER BY mean, specialty) AS place FROM gm) WHERE place <= 3 UNION ALL SELECT * FROM (SELECT specialty, mean, 'strong', row_number() OVER (ORDER BY mean DESC, specialty) AS place FROM gm) WHERE place <= 3", STAR, SG.format("specialty"), "gm AS (SELECT specialty, round(avg(score), 6) AS mean FROM sg GROUP BY specialty)")
put("specialty_correlation", "SELECT a.specialty AS g1, b.specialty AS g2, round(corr(a.score, b.score), 5) AS r FROM sg a JOIN sg b ON a.model_id = b.model_id AND a.specialty < b.specialty GROUP BY ALL", STAR, SG.format("specialty"))
put("prevalence_effect", "SELECT count(*) AS groups, round(corr(n, x), 5) AS r FROM (SELECT specialty, sum(n)::DOUBLE AS n, avg(score) AS x FROM sg GROUP BY specialty)", STAR, SG.format("specialty"))
put("class_contrast", "SELECT access, domain, round(avg(score), 6) AS mean, count(*) AS n FROM board JOIN m USING (model_id) GROUP BY GROUPING SETS ((access), (domain), (access, domain))", STAR)
put("efficiency", "SELECT model_id, params_b, score, round(score / params_b, 6) AS ratio, score >= max(score) OVER (ORDER BY params_b RANGE BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS on_front FROM board JOIN m USING (model_id)", STAR)
ER = "er AS (SELECT model_id, axis, round(avg(CAST(bad AS INTEGER)), 6) AS rate, round(count(*) FILTER (bad AND weight > 0) / (count(*) FILTER (weight > 0))::DOUBLE, 6) AS positive_only, round(sum(CASE WHEN bad THEN abs(weight) ELSE 0 END) / sum(abs(weight))::DOUBLE, 6) AS weighted, count(*) AS n FROM (SELECT *, CASE WHEN weight > 0 THEN NOT met ELSE met END AS bad FROM j) GROUP BY ALL)"
put("axis_error_rate", "SELECT * FROM er", STAR, ER)
put("worst_per_axis", "SELECT axis, max(model_id) FILTER (a = 1) AS worst, max(model_id) FILTER (b = 1) AS best FROM (SELECT *, row_number() OVER (PARTITION BY axis ORDER BY rate DESC, model_id) AS a, row_number() OVER (PARTITION BY axis ORDER BY rate, model_id) AS b FROM er) GROUP BY axis", STAR, ER)
BOT = "bo AS (SELECT model_id, case_id, row_number() OVER (PARTITION BY model_id ORDER BY raw, case_id) AS place FROM s WHERE raw IS NOT NULL QUALIFY place <= 100)"
put("bottom_k", "SELECT * FROM bo", STAR, BOT)
put("bottom_overlap", "SELECT a.model_id AS m1, b.model_id AS m2, coalesce(c, 0) AS shared, round(coalesce(c, 0) / (a.n + b.n - coalesce(c, 0))::DOUBLE, 6) AS jaccard FROM sz a JOIN sz b ON a.model_id < b.model_id LEFT JOIN (SELECT x.model_id AS m1, y.model_id AS m2, count(*) AS c FROM bo x JOIN bo y ON x.case_id = y.case_id AND x.model_id < y.model_id GROUP BY ALL) k ON k.m1 = a.model_id AND k.m2 = b.model_id", STAR, BOT, "sz AS (SELECT model_id, count(*) AS n FROM bo GROUP BY model_id)")
put("mean_overlap", "SELECT count(*) AS pairs, round(avg(jaccard), 6) AS mean, min(jaccard) AS least, max(jaccard) AS most FROM (" + ORACLES["bottom_overlap"] + ")")
put("cause_share", "SELECT cause, CAST(sum(c) AS BIGINT) AS n, round(min(c / t), 6) AS lowest, round(max(c / t), 6) AS highest, round(sum(c) / sum(sum(c)) OVER (), 6) AS share FROM (SELECT model_id, cause, count(*) AS c, sum(count(*)) OVER (PARTITION BY model_id) AS t FROM ca GROUP BY model_id, cause) GROUP BY cause", STAR, BOT, """ca AS (SELECT model_id, CASE WHEN weight <= -8 THEN 'hallucination' WHEN weight < 0 THEN 'guideline overgeneralisation' WHEN axis = 3 THEN 'context neglect' WHEN axis = 0 THEN 'knowledge gap' WHEN axis = 1 THEN 'other_1' WHEN axis = 2 THEN 'other_2' ELSE 'other_3' END AS cause
  FROM (SELECT j.*, row_number() OVER (PARTITION BY j.model_id, j.case_id ORDER BY abs(weight) DESC, criterion_no) AS k FROM j JOIN bo USING (model_id, case_id) WHERE CASE WHEN weight > 0 THEN NOT met ELSE met END) WHERE k = 1)""")
MODES = """mo0 AS (SELECT model_id, case_id, weight, met, met OR (weight > 0 AND luck < 24 + model_id) AS helped FROM j WHERE published >= DATE '2001-07-01'),
mo1 AS (SELECT model_id, case_id, sum(CASE WHEN met THEN weight ELSE 0 END)::DOUBLE AS g, sum(CASE WHEN helped THEN weight ELSE 0 END)::DOUBLE AS h, sum(CASE WHEN weight > 0 THEN weight ELSE 0 END) AS p FROM mo0 GROUP BY ALL),
mo AS (SELECT b.model_id, b.baseline, x.closed, x.open FROM (SELECT model_id, avg(score) AS baseline FROM s GROUP BY model_id) b JOIN (SELECT model_id, avg(least(greatest(g / p, 0), 1)) AS closed, avg(least(greatest(h / p, 0), 1)) AS open FROM mo1 WHERE p > 0 GROUP BY model_id) x USING (model_id))"""
put("injection_modes", "SELECT model_id, round(baseline, 6) AS baseline, round(closed, 6) AS closed, round(open, 6) AS open FROM mo", STAR, MODES)
put("recovery", 'SELECT model_id, round(open - closed, 6) AS gain, round(baseline - closed, 6) AS "drop", round(CASE WHEN baseline - closed > 0 THEN (open - closed) / (baseline - closed) END, 6) AS recovery FROM mo', STAR, MODES)
put("all_improve", "SELECT bool_and(open > closed) AS all_improve FROM mo", STAR, MODES)
rows = ", ".join(f"('{n}', {', '.join('true' if c == '1' else 'false' for c in b)})" for n, b in (x.split(":") for x in FEATURES.split()))
put("feature_matrix", f"SELECT *, free_response AND multilingual AND case_rubric AND updated AS all_true FROM (SELECT * FROM (VALUES {rows}) t(benchmark, free_response, multilingual, case_rubric, updated) UNION ALL SELECT 'ours', true, (SELECT count(DISTINCT lang) >= 2 FROM cs), true, (SELECT count(DISTINCT date_trunc('week', posted_at)) >= 2 FROM po))", STAR, POSTS)
put("difficulty_table", "SELECT model_id, round(avg(score), 6) AS standard, round(avg(score) FILTER (mean <= bound), 6) AS hard FROM s JOIN mean_ USING (case_id) CROSS JOIN (SELECT round(quantile_cont(mean, 0.2), 6) AS bound FROM mean_) WHERE model_id IN (34, 35, 36, 37) GROUP BY model_id", STAR, "mean_ AS (SELECT case_id, round(avg(score), 6) AS mean FROM s WHERE score IS NOT NULL GROUP BY case_id)")
facets = " UNION ALL ".join(f"SELECT '{f}' AS facet, CAST({f} AS VARCHAR) AS value FROM cs" for f in ("theme", "specialty", "source", "lang"))
put("dataset_profile", f"SELECT facet, value, count(*) AS n, round(count(*) / sum(count(*)) OVER (PARTITION BY facet), 6) AS share FROM ({facets}) GROUP BY facet, value", STAR)
put("criteria_histogram", "SELECT criteria, count(*) AS cases FROM (SELECT case_id, count(*) AS criteria FROM cr GROUP BY case_id) GROUP BY criteria", STAR)
TAIL = "lt0 AS (SELECT specialty, count(*) AS n FROM cs GROUP BY specialty), lt AS (SELECT specialty, n, row_number() OVER w AS place, round(n / sum(n) OVER (), 6) AS share, round(sum(n) OVER w / sum(n) OVER (), 6) AS cumulative FROM lt0 WINDOW w AS (ORDER BY n DESC, specialty ROWS UNBOUNDED PRECEDING))"
put("long_tail", "SELECT * FROM lt", STAR, TAIL)
put("tail_gini", "SELECT round((count(*) + 1 - 2 * sum(place * n) / sum(n)::DOUBLE) / count(*), 6) AS gini FROM lt", STAR, TAIL)
put("weekly_growth", "SELECT CAST(CAST(date_trunc('week', posted_at) AS DATE) AS VARCHAR) AS week, platform, count(*) AS posts, count(DISTINCT thread_id) AS threads FROM po GROUP BY ALL", POSTS)
ORACLES["curation_funnel"] = ORACLES["curation_funnel"].replace("\n, pl AS", ",\npl AS")
agents = {"screen": ("screener", 4), "audit": ("controller", 4)}
tier = lambda i: " ".join(f"WHEN '{k}' THEN {v[i]!r}" for k, v in agents.items())
put("cascade_cost", f"SELECT stage, CASE stage {tier(0)} ELSE 'validator' END AS agent, CAST(CASE stage {tier(1)} ELSE 120 END AS INTEGER) AS params_b, calls, flat_calls FROM (SELECT *, lag(remaining) OVER (ORDER BY step) AS calls, max(remaining) OVER () AS flat_calls FROM ({ORACLES['curation_funnel']})) WHERE step > 0")
SOURCES = f"""
ep0 AS (SELECT doc_id, {TOK.format('text')} AS t FROM documents JOIN labels USING (doc_id) WHERE quality = 1),
ep AS (SELECT doc_id, t, CAST(doc_id % {len(KINDS)} AS INTEGER) AS kind FROM ep0 UNION ALL SELECT doc_id, t, {len(KINDS)} FROM ep0),
est AS (SELECT kind, count(*) AS n, avg(len(t)) AS mean FROM ep GROUP BY kind),
etf AS (SELECT kind, doc_id, len, term, count(*) AS c FROM (SELECT kind, doc_id, len(t) AS len, unnest(t) AS term FROM ep) GROUP BY ALL),
edf AS (SELECT kind, term, count(*) AS d FROM etf GROUP BY kind, term),
ev AS (SELECT kind, term, doc_id, CAST(floor(ln(1 + (n - d + 0.5::DOUBLE) / (d + 0.5::DOUBLE)) * (c * 2.2::DOUBLE / (c + 1.2::DOUBLE * (0.25::DOUBLE + 0.75::DOUBLE * len / mean))) * 1000 + 0.5::DOUBLE) AS BIGINT) AS v FROM etf JOIN edf USING (kind, term) JOIN est USING (kind)),
eq AS (SELECT thread_id, unnest(list_distinct({TOK.format('query')})) AS term FROM fw WHERE forwarded),
eh AS (SELECT kind, thread_id, doc_id, CAST(sum(v) AS BIGINT) AS score FROM eq JOIN ev USING (term) GROUP BY ALL),
ek AS (SELECT *, row_number() OVER (PARTITION BY kind, thread_id ORDER BY score DESC, doc_id) AS rank FROM eh QUALIFY rank <= 5)
"""
put("evidence_by_source", f"SELECT {list(KINDS)}[kind + 1] AS source, thread_id, rank, doc_id, score FROM ek WHERE kind < {len(KINDS)}", THREADS, SOURCES)
put("evidence_fused", "SELECT thread_id, row_number() OVER (PARTITION BY thread_id ORDER BY f DESC, doc_id) AS rank, doc_id, round(f, 6) AS score FROM (SELECT thread_id, doc_id, round(sum(1.0::DOUBLE / (60 + rank)), 9) AS f FROM ek GROUP BY ALL) QUALIFY rank <= 5", THREADS, SOURCES)
put("weekly_harvest", "SELECT thread_id, turn, platform, '2024-01-08' AS harvest_week FROM po WHERE posted_at >= TIMESTAMP '2024-01-08' AND posted_at < TIMESTAMP '2024-01-15'", POSTS)
put("repeated_runs", "SELECT CAST(l_suppkey % 38 AS INTEGER) AS model_id, l_partkey AS item_id, count(*) AS n FROM lineitem GROUP BY ALL HAVING count(*) > 1")
put("perturbed_cases", f"SELECT thread_id, length(x) AS chars, array_to_string(list_filter(string_split(x, ' '), lambda t: {HASH.format("'7:' || t")} % 8 <> 0), ' ') AS rewritten FROM (SELECT thread_id, array_to_string(facts, '. ') AS x FROM fw WHERE forwarded)", THREADS)
put("pearson_pairs", "SELECT *, round(r * sqrt((n - 2) / nullif(1 - r * r, 0)), 3) AS t FROM (SELECT a.model_id AS a, b.model_id AS b, count(*) AS n, round(corr(a.score, b.score), 5) AS r FROM s a JOIN s b ON a.case_id = b.case_id AND a.model_id < b.model_id WHERE a.score IS NOT NULL AND b.score IS NOT NULL GROUP BY ALL)", STAR)
weight = " + ".join(f"CAST(h >= {int(c * (1 << 24))} AS INTEGER)" for c in POISSON)
BOOT = f"""
bb AS (SELECT model_id, {HASH.format('CAST(case_id AS VARCHAR)')} % 256 AS block, count(*) AS n, sum(score) AS t, count(*) FILTER (published > eff) AS n1, coalesce(sum(score) FILTER (published > eff), 0) AS t1 FROM s WHERE score IS NOT NULL GROUP BY ALL),
bw AS (SELECT block, rep, {weight} AS k FROM (SELECT x.range AS block, y.range AS rep, {HASH.format("'0:' || x.range || ':' || y.range")} AS h FROM range(256) x CROSS JOIN range(100) y)),
bd AS (SELECT model_id, rep, sum(k * t1) / nullif(sum(k * n1), 0)::DOUBLE - sum(k * t) / nullif(sum(k * n), 0)::DOUBLE AS d FROM bb JOIN bw USING (block) WHERE k > 0 GROUP BY ALL)
"""
put("drop_bootstrap", "SELECT model_id, round(quantile_cont(d, 0.025), 6) AS low, round(quantile_cont(d, 0.5), 6) AS mid, round(quantile_cont(d, 0.975), 6) AS high, round(avg(CAST(d >= 0 AS INTEGER)), 6) AS p FROM bd GROUP BY model_id", STAR, BOOT)
put("cascade_tokens", f"SELECT ['screen', 'complaint', 'sufficiency', 'veto', 'alignment', 'audit'][k] AS stage, count(*) FILTER (place >= k) AS calls, CAST(coalesce(sum(n) FILTER (place >= k), 0) AS BIGINT) AS tokens, CAST(coalesce(sum(n), 0) AS BIGINT) AS flat_tokens FROM (SELECT place, len({TOK.format('thread_text')}) AS n FROM pl JOIN fw USING (thread_id)) CROSS JOIN (SELECT range AS k FROM range(1, 7)) GROUP BY k", THREADS, SUFF, EVIDENCE, AUDIT, PLACE[2:])
put("requirement_checklist", f"SELECT thread_id, requirement, list_contains(list_transform({CONTENT.format("array_to_string(facts, ' ')")}, lambda y: substr(y, 1, 3)), substr(requirement, 1, 3)) AS met FROM (SELECT thread_id, facts, unnest({CONTENT.format('query')}) AS requirement FROM fw WHERE forwarded)", THREADS)
put("theme_cube", "SELECT theme, source, count(*) AS n, round(avg(score), 6) AS score, round(min(score), 6) AS lowest, round(max(score), 6) AS highest FROM s JOIN cs USING (case_id) WHERE score IS NOT NULL GROUP BY CUBE (theme, source)", STAR)
