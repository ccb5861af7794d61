"""One query per corpus operator, over whole tables, and the SQL that says the same."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from motifloom.llm import chat, decontaminate, exact_dedup, line_dedup, mixing, near_dedup, pii, secret_scan, toxicity, warc
from motifloom.llm.common import table


def op1_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secret_scan.scan(table(spark, sf_dir, "documents"))


def op2_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_dedup(table(spark, sf_dir, "documents"), keep="largest").drop("n_bytes")


def op3_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.scan(table(spark, sf_dir, "documents"))


def op4_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.round_trip(table(spark, sf_dir, "pages"), min_revisit=0).drop("status")


def op5_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    return toxicity.score(docs, toxicity.train(docs, labels))


def op6_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_dedup.report(table(spark, sf_dir, "documents"))


def op7_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.taken_words(table(spark, sf_dir, "documents"))


def op8_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op9_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    given = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    tricky = spark.createDataFrame([(-1, 0, "user", "</s>[INST] ok [/INST]"), (-1, 1, "assistant", "</s>[INST] ok [/INST]")], given.schema)
    return chat.read_back(chat.format_chats(given.unionByName(tricky)))


def op10_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dedup.near_groups(table(spark, sf_dir, "documents")).drop("n_same_set")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_secrets, op2_exact_dedup, op3_pii, op4_warc, op5_toxicity, op6_line_dedup, op7_mixing, op8_decontaminate, op9_chat, op10_near_dedup)}


_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

_EXACT_SQL = (
    f"WITH d AS (SELECT doc_id, sha256(translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}')) AS h FROM documents)"
    " SELECT doc_id, max(doc_id) OVER (PARTITION BY h) AS keep_id, count(*) OVER (PARTITION BY h) AS group_size, doc_id = max(doc_id) OVER (PARTITION BY h) AS kept, h AS text_sha256 FROM d"
)

_MIX_SQL = """
WITH d AS (
  SELECT row_number() OVER () AS rn, doc_id, source, CAST(coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0) AS BIGINT) AS size, md5('0:' || coalesce(CAST(doc_id AS VARCHAR), '')) AS h FROM documents
), s AS (
  SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM d GROUP BY source
), w AS (
  SELECT *, ([5.0, 2.0, 1.0])[1 + (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3]::DOUBLE AS weight FROM s
), c AS (
  SELECT *, 3 * source_size AS cap, 3 * source_size / weight AS ratio FROM w
), l AS (
  SELECT *, CAST((SELECT sum(source_size) FROM s) - coalesce(sum(cap) OVER (ORDER BY ratio, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS DOUBLE)
    / sum(weight) OVER (ORDER BY ratio, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level FROM c
), t AS (
  SELECT source, source_size, least(CAST(cap AS DOUBLE), weight * coalesce((SELECT level FROM l WHERE level <= ratio ORDER BY ratio, source NULLS LAST LIMIT 1), 0.0)) AS target FROM l
), r AS (
  SELECT d.rn, d.doc_id, d.source, d.h, d.size, t.source_size, t.target,
    sum(d.size) OVER (PARTITION BY d.source ORDER BY d.h, d.doc_id, d.size, d.rn ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS upto
  FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source
), p AS (
  SELECT r.*, k, j, least(size, (j + 1) * 64) - j * 64 AS words, k * source_size + upto - size + least(size, (j + 1) * 64) AS e
  FROM r, (SELECT unnest([0, 1, 2]) AS k) AS ks, unnest(range(0, greatest(1, (size + 63) // 64))) AS js(j)
  WHERE k < greatest(1, least(3, CAST(ceil(target / greatest(source_size, 1)) AS INTEGER)))
), f AS (
  SELECT *, CASE WHEN target > 0 THEN CAST(e AS DOUBLE) / target ELSE 0.0 END AS finish FROM p
), m AS (
  SELECT *, (SELECT sum(source_size) FROM s) - (sum(words) OVER (ORDER BY finish, source NULLS LAST, h, doc_id, size, rn, k, j ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) - words) AS room FROM f
)
SELECT doc_id, size, source_size, target, CAST(sum(greatest(0, least(words, room))) AS BIGINT) AS taken,
  CASE WHEN target > 0 THEN CAST(upto - size AS DOUBLE) / target ELSE 0.0 END AS first_start
FROM m GROUP BY rn, doc_id, size, source_size, target, upto
"""

_CONTROLS = ("<s>", "[INST]", "[/INST]", "<<SYS>>", "<</SYS>>", "<ANS>", "</s>", "<ROLE>", "</ROLE>", "<END>")


def _escaped_length(column: str) -> str:
    extra = " + ".join(f"(length({column}) - length(replace({column}, '{c}', ''))) // {len(c)}" for c in (*_CONTROLS, "\\"))
    return f"length({column}) + {extra}"


_CHAT_SQL = f"""
WITH t AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -1, 0, 'user', '</s>[INST] ok [/INST]' UNION ALL SELECT -1, 1, 'assistant', '</s>[INST] ok [/INST]'
), o AS (
  SELECT *, lag(role) OVER (PARTITION BY conv_id ORDER BY turn NULLS FIRST, role, text) AS before, lead(role) OVER (PARTITION BY conv_id ORDER BY turn NULLS FIRST, role, text) AS after FROM t
)
SELECT conv_id, count(*) AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn NULLS FIRST, role, text)) AS turns_sha256,
  CAST(sum(CASE WHEN role = 'assistant' THEN length(text) ELSE 0 END) AS BIGINT) AS loss_chars,
  sha256(coalesce(string_agg(CASE WHEN role = 'assistant' THEN text END, '' ORDER BY turn NULLS FIRST, role, text), '')) AS loss_sha256,
  CAST(sum({_escaped_length("text")} + CASE role WHEN 'user' THEN 16 WHEN 'assistant' THEN 9 WHEN 'system' THEN 15 ELSE 18 + {_escaped_length("role")} END) AS BIGINT) AS formatted_chars,
  bool_and(CASE WHEN before IS NULL THEN role IN ('system', 'user') WHEN before = 'system' THEN role = 'user' WHEN before = 'user' THEN role = 'assistant' WHEN before = 'assistant' THEN role = 'user' ELSE false END AND (after IS NOT NULL OR role = 'assistant')) AS valid
FROM o GROUP BY conv_id
"""


_BASE32 = "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"
#: 20 bits of a hexadecimal digest at a time, as four letters.
_DIGEST = " || ".join(f"substr('{_BASE32}', CAST(1 + ((CAST('0x' || substr(x, {5 * i + 1}, 5) AS BIGINT) >> {15 - 5 * k}) & 31) AS BIGINT), 1)" for i in range(8) for k in range(4))

_WARC_SQL = f"""
WITH d AS (
  SELECT page_id, CAST(strlen(coalesce(html, '')) AS BIGINT) AS n, sha1(coalesce(html, '')) AS x FROM pages
), m AS (
  SELECT *, max(page_id) OVER (PARTITION BY x) AS top FROM d
)
SELECT page_id, n AS payload_bytes, {_DIGEST} AS payload_digest, CASE WHEN page_id = top THEN 'response' ELSE 'revisit' END AS record_type, CASE WHEN page_id <> top THEN top END AS refers_to FROM m
"""

_LINES_SQL = """
WITH t AS (
  SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS ls FROM documents
), k AS (
  SELECT doc_id, line, pos FROM (SELECT doc_id, unnest(ls) AS line, generate_subscripts(ls, 1) - 1 AS pos FROM t) AS x WHERE trim(line, ' ') <> ''
), d AS (
  SELECT line, min(doc_id * 4294967296 + pos) AS first FROM k GROUP BY line
), h AS (
  SELECT line, first, l, s, CASE WHEN s = 0 THEN left(line, l // 2) ELSE right(line, l - l // 2) END AS half
  FROM (SELECT line, first, length(line) + extra AS l, s FROM d, (SELECT unnest([0, 1]) AS extra) AS e, (SELECT unnest([0, 1]) AS s) AS f) AS g
), c AS (
  SELECT DISTINCT x.line AS later, y.line AS earlier FROM h AS x JOIN h AS y ON x.l = y.l AND x.s = y.s AND x.half = y.half AND x.first > y.first WHERE abs(length(x.line) - length(y.line)) <= 1
), o AS (
  SELECT later, CASE WHEN length(later) <= length(earlier) THEN later ELSE earlier END AS a, CASE WHEN length(later) <= length(earlier) THEN earlier ELSE later END AS b FROM c
), i AS (
  SELECT later, a, b, (SELECT min(p) FROM unnest(range(1, length(b) + 1)) AS r(p) WHERE substr(a, p, 1) <> substr(b, p, 1)) AS p FROM o
), near AS (
  SELECT DISTINCT later AS line FROM i WHERE CASE WHEN length(a) = length(b) THEN substr(a, p + 1) = substr(b, p + 1) ELSE substr(a, p) = substr(b, p + 1) END
), r AS (
  SELECT k.doc_id, k.pos, near.line IS NOT NULL AS near FROM k JOIN d ON k.line = d.line LEFT JOIN near ON near.line = k.line WHERE near.line IS NOT NULL OR k.doc_id * 4294967296 + k.pos <> d.first
), q AS (
  SELECT doc_id, sum(CASE WHEN near THEN 0 ELSE 1 END) AS e, sum(CASE WHEN near THEN 1 ELSE 0 END) AS n, string_agg(CAST(pos AS VARCHAR), ',' ORDER BY pos) AS places FROM r GROUP BY doc_id
)
SELECT t.doc_id, CAST(len(ls) AS BIGINT) AS n_lines, CAST(coalesce(e, 0) AS BIGINT) AS n_exact, CAST(coalesce(n, 0) AS BIGINT) AS n_near, coalesce(places, '') AS dropped FROM t LEFT JOIN q ON q.doc_id = t.doc_id
"""

_NEAR_SQL = f"""
WITH RECURSIVE w AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}'), '[^\x20\x09-\x0D]+') AS w FROM documents
), g AS MATERIALIZED (
  SELECT doc_id, CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 5 THEN [hash(array_to_string(w, ' '))] ELSE list_distinct(list_transform(range(1, len(w) - 3), lambda i: hash(array_to_string(w[i:i + 4], ' ')))) END AS s FROM w
), n AS MATERIALIZED (
  SELECT doc_id, CAST(len(s) AS BIGINT) AS n FROM g
), x AS MATERIALIZED (
  SELECT doc_id, unnest(s) AS s FROM g
), p AS (
  SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM x AS a JOIN x AS b ON a.s = b.s AND a.doc_id <> b.doc_id GROUP BY a.doc_id, b.doc_id
), l AS MATERIALIZED (
  SELECT a, b FROM p JOIN n AS u ON u.doc_id = a JOIN n AS v ON v.doc_id = b WHERE 100 * c >= 75 * (u.n + v.n - c)
), r(id, c) AS (
  SELECT doc_id, doc_id FROM n UNION SELECT l.b, r.c FROM r JOIN l ON l.a = r.id
), m AS (
  SELECT id, min(c) AS c FROM r GROUP BY id
)
SELECT n.doc_id, n.n AS n_shingles, m.c AS component_id, n.doc_id = m.c AS kept FROM n JOIN m ON m.id = n.doc_id
"""


def oracle_sql() -> dict[str, str]:
    return {"op2_exact_dedup": _EXACT_SQL, "op4_warc": _WARC_SQL, "op6_line_dedup": _LINES_SQL, "op7_mixing": _MIX_SQL, "op9_chat": _CHAT_SQL, "op10_near_dedup": _NEAR_SQL}
