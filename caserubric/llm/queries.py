"""The ten operators over their whole tables with production parameters, and SQL for those that SQL can express."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .chat import ChatTemplate, chat_digest, format_chats
from .common import table
from .licenses import KNOWN, RULES, license_scan
from .mixing import mix
from .neardup import Overlap, near_duplicates
from .packing import pack
from .quality import classify
from .repeats import remove_repeats
from .search import bm25_top_k
from .tiff import store_texts
from .warc import warc_round_trip

PROBE = "\\### Assistant: </turn> ok"


def op1_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan(table(spark, sf_dir, "documents"))


def op2_tiff(spark: SparkSession, sf_dir: str) -> DataFrame:
    return store_texts(table(spark, sf_dir, "documents"))


def op3_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents"))


def op4_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix(table(spark, sf_dir, "documents")).select("doc_id", "source", "size", "source_size", "target", "copies", "taken")


def op5_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc_round_trip(table(spark, sf_dir, "pages")).drop("digest_holds")


def op6_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    rated = classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
    return rated.select("row.doc_id", F.round("quality", 6).alias("quality"), "toxic", "votes", "keep")


def op7_bm25(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    queries = docs.where("doc_id % 50 = 0").select(F.col("doc_id").alias("query_id"), F.col("text").alias("query"))
    return bm25_top_k(docs, queries, k=10)


def op8_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    probe = spark.range(1).select(F.explode(F.array(*[F.struct(F.lit(-7).cast("long").alias("conv_id"), F.lit(k).cast("long").alias("turn"), F.lit(r).alias("role"), F.lit(PROBE).alias("text")) for k, r in enumerate(("user", "assistant"))])).alias("m")).select("m.*")
    return chat_digest(format_chats(rows.unionByName(probe)))


def op9_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    cut = remove_repeats(table(spark, sf_dir, "documents").select("doc_id", "text"), width=35)
    return cut.select("row.doc_id", "n_words", "n_removed", "kept_sha256")


def op10_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"), Overlap(width=4, num=85, den=100)).select("doc_id", "n_shingles", "component_id")


QUERIES = {f.__name__: f for f in (op1_license_scan, op2_tiff, op3_best_fit_packing, op4_source_mix, op5_warc, op6_quality, op7_bm25, op8_chat, op9_substring_dedup, op10_jaccard_join)}


def quoted(x: str) -> str:
    return "'" + x.replace("'", "''") + "'"


def license_sql() -> str:
    table_ = "MAP {" + ", ".join(f"{quoted(k)}: {quoted(v)}" for k, v in KNOWN.items()) + "}"
    steps = [
        "sentences AS (SELECT doc_id, list_filter(list_transform(regexp_split_to_array(regexp_replace(regexp_replace(lower(coalesce(text, '')), '([.!?])[ \\t]+', '\\1' || chr(10), 'g'), '[^\\p{L}\\p{N}\\n\\r]+', ' ', 'g'), '[\\r\\n]+'), lambda s: trim(s)), lambda s: map_contains(" + table_ + ", s)) AS known FROM documents)",
        "r0 AS (SELECT doc_id, list_transform(known, lambda s: " + table_ + "[s]) AS ids, CAST([] AS VARCHAR[]) AS names, CAST([] AS VARCHAR[]) AS kinds, array_to_string(list_transform(known, lambda s: '<' || " + table_ + "[s] || '>'), '') AS rest FROM sentences)",
    ]
    for k, (name, family, ids) in enumerate(RULES):
        mark = quoted("".join(f"<{i}>" for i in ids))
        steps.append(f"r{k + 1} AS (SELECT doc_id, ids, CASE WHEN contains(rest, {mark}) THEN list_append(names, {quoted(name)}) ELSE names END AS names, CASE WHEN contains(rest, {mark}) THEN list_append(kinds, {quoted(family)}) ELSE kinds END AS kinds, replace(rest, {mark}, '<>') AS rest FROM r{k})")
    return "WITH " + ",\n".join(steps) + f"\nSELECT doc_id, CAST(len(ids) AS BIGINT) AS n_known, array_to_string(ids, ',') AS sentence_ids, array_to_string(names, ',') AS licenses, array_to_string(list_sort(list_distinct(kinds)), ',') AS families FROM r{len(RULES)}"


WARC_SQL = """
WITH p AS (SELECT page_id, coalesce(html, '') AS body, sha256(coalesce(html, '')) AS d, CAST(octet_length(encode(coalesce(html, ''))) AS BIGINT) AS n FROM pages),
f AS (SELECT d, min(page_id) AS first FROM p WHERE n >= 100 GROUP BY d)
SELECT page_id, n AS payload_bytes, p.d AS payload_digest,
       CASE WHEN first IS NULL OR page_id = first THEN 'response' ELSE 'revisit' END AS record_type,
       CASE WHEN first IS NULL OR page_id = first THEN NULL ELSE first END AS refers_to
FROM p LEFT JOIN f ON p.d = f.d
"""


def chat_sql(t: ChatTemplate = ChatTemplate()) -> str:
    def guard(x: str, role: bool = False) -> str:
        x = f"replace({x}, {quoted(t.escape)}, {quoted(t.escape + 'b')})"
        for plain, letter in t.controls + (t.role_controls if role else ()):
            x = f"replace({x}, {quoted(plain)}, {quoted(t.escape + letter)})"
        return x

    moves = " ".join(f"WHEN prev = {quoted(s)} AND role = {quoted(r)} THEN {quoted(to)}" for s, r, to in t.moves)
    fixed = len(t.head) + len(t.head_end) + len(t.tail)
    loss = ", ".join(map(quoted, t.loss_roles))
    return f"""
WITH RECURSIVE rows_ AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', {quoted(PROBE)} UNION ALL SELECT -7, 1, 'assistant', {quoted(PROBE)}),
n AS (SELECT *, row_number() OVER (PARTITION BY conv_id ORDER BY turn NULLS FIRST, role, text) AS k FROM rows_),
walk AS (
  SELECT conv_id, 0::BIGINT AS k, {quoted(t.start)} AS prev FROM n GROUP BY conv_id
  UNION ALL
  SELECT n.conv_id, n.k, CASE {moves} ELSE 'invalid' END FROM walk JOIN n ON n.conv_id IS NOT DISTINCT FROM walk.conv_id AND n.k = walk.k + 1),
ends AS (SELECT conv_id, arg_max(prev, k) AS state FROM walk GROUP BY conv_id),
g AS (SELECT conv_id, CAST(count(*) AS BIGINT) AS n_turns,
    sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY k)) AS turns_sha256,
    CAST(coalesce(sum(length(text)) FILTER (role IN ({loss})), 0) AS BIGINT) AS loss_chars,
    sha256(coalesce(string_agg(text, '' ORDER BY k) FILTER (role IN ({loss})), '')) AS loss_sha256,
    CAST(sum({fixed} + length({guard('role', True)}) + length({guard('text')})) AS BIGINT) AS formatted_chars
  FROM n GROUP BY conv_id)
SELECT g.*, state, state IN ({', '.join(map(quoted, t.accept))}) AS valid FROM g JOIN ends ON g.conv_id IS NOT DISTINCT FROM ends.conv_id
"""


SUBSTRING_SQL = """
WITH w AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+') AS ws FROM documents),
x AS (SELECT doc_id, generate_subscripts(ws, 1) AS i, unnest(ws) AS word, len(ws) AS n FROM w),
s AS (SELECT x.doc_id, i, word, CASE WHEN i + 34 <= n THEN array_to_string(ws[i:i + 34], ' ') END AS win FROM x JOIN w USING (doc_id)),
c AS (SELECT *, CASE WHEN win IS NOT NULL AND count(*) OVER (PARTITION BY win) > 1 THEN 1 ELSE 0 END AS rep FROM s),
m AS (SELECT *, max(rep) OVER (PARTITION BY doc_id ORDER BY i ROWS BETWEEN 34 PRECEDING AND CURRENT ROW) AS gone FROM c),
k AS (SELECT doc_id, sum(gone) AS n_removed, string_agg(word, ' ' ORDER BY i) FILTER (gone = 0) AS kept FROM m GROUP BY doc_id)
SELECT w.doc_id, CAST(len(ws) AS BIGINT) AS n_words, CAST(coalesce(n_removed, 0) AS BIGINT) AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256
FROM w LEFT JOIN k USING (doc_id)
"""

JACCARD_SQL = """
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x20\\x09-\\x0D]+') AS ws FROM documents),
s AS (SELECT doc_id, list_distinct(CASE WHEN len(ws) = 0 THEN CAST([] AS VARCHAR[]) WHEN len(ws) < 4 THEN [array_to_string(ws, ' ')] ELSE list_transform(range(1, len(ws) - 2), lambda i: array_to_string(ws[i:i + 3], ' ')) END) AS sh FROM w),
n AS (SELECT doc_id, CAST(len(sh) AS BIGINT) AS n FROM s),
e AS MATERIALIZED (SELECT doc_id, unnest(sh) AS g FROM s),
p AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS both_ FROM e a JOIN e b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY ALL),
l AS MATERIALIZED (SELECT x, y FROM p JOIN n a ON a.doc_id = x JOIN n b ON b.doc_id = y WHERE 100 * both_ >= 85 * (a.n + b.n - both_)),
u AS (SELECT x AS a, y AS b FROM l UNION ALL SELECT y, x FROM l),
r AS (SELECT doc_id AS a, doc_id AS b FROM n UNION SELECT r.a, u.b FROM r JOIN u ON r.b = u.a)
SELECT n.doc_id, n.n AS n_shingles, min(r.b) AS component_id FROM n JOIN r ON r.a = n.doc_id GROUP BY n.doc_id, n.n
"""

BM25_SQL = """
WITH t AS (SELECT doc_id, regexp_extract_all(lower(coalesce(text, '')), '[\\p{L}\\p{N}]+') AS ws FROM documents),
st AS (SELECT count(*) AS n, sum(len(ws)) / count(*) AS mean FROM t),
tf AS (SELECT doc_id, term, count(*) AS c FROM (SELECT doc_id, unnest(ws) AS term FROM t) GROUP BY ALL),
df AS (SELECT term, count(*) AS d FROM tf GROUP BY term),
i AS (SELECT tf.doc_id, term, ln(1 + (n - d + 0.5) / CAST(d + 0.5 AS DOUBLE)) AS w, c * 2.2::DOUBLE / (c + 1.2::DOUBLE * (0.25::DOUBLE + 0.75::DOUBLE * len(ws) / mean)) AS part FROM tf JOIN df USING (term) JOIN t ON t.doc_id = tf.doc_id CROSS JOIN st),
q AS (SELECT DISTINCT doc_id AS query_id, term FROM tf WHERE doc_id % 50 = 0),
s AS (SELECT query_id, doc_id, CAST(sum(floor(w * part * 1000 + 0.5)) AS BIGINT) AS score FROM q JOIN i USING (term) GROUP BY ALL),
k AS (SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, doc_id) AS BIGINT) AS rank, doc_id, score FROM s WHERE score > 0)
SELECT * FROM k WHERE rank <= 10
"""

ORACLES = {"op1_license_scan": license_sql(), "op5_warc": WARC_SQL, "op7_bm25": BM25_SQL, "op8_chat": chat_sql(), "op9_substring_dedup": SUBSTRING_SQL, "op10_jaccard_join": JACCARD_SQL}
