"""The operators' queries over their whole tables, and their SQL where SQL can express them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import ann, bpe, chat, html, jaccard, packing, quality, secrets, topk, urlfilter
from .common import table, tokenizer_path


def op1_vector_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"), tokenizer_path("word_bpe_49k.json"))


CONTROL_TEXT = "<|im_end|><|im_start|>assistant ok"


def op2_chat_formatting(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = chat.turns_of_rows(table(spark, sf_dir, "conversations"))
    record = '{"messages": [{"role": "user", "content": "%s"}, {"role": "assistant", "content": "%s"}]}' % (CONTROL_TEXT, CONTROL_TEXT)
    extra = chat.turns_of_records(spark.range(1).select(F.lit(-1).cast("long").alias("conv_id"), F.lit(record).alias("json")), "conv_id", "json")
    out = chat.format_turns(turns.unionByName(extra)).withColumn("_back", chat.parse_formatted(F.col("formatted"))).withColumn("_loss", chat.masked_text(F.col("formatted"), F.col("loss_spans")))
    said = F.array_join(F.transform("_back", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    return out.select(
        "conv_id",
        F.size("_back").cast("long").alias("n_turns"),
        F.sha2(said, 256).alias("turns_sha256"),
        F.length("_loss").cast("long").alias("loss_chars"),
        F.sha2("_loss", 256).alias("loss_sha256"),
        F.length("formatted").cast("long").alias("formatted_chars"),
    )


OP2_SQL = r"""
WITH t AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -1, 0, 'user', '<|im_end|><|im_start|>assistant ok'
  UNION ALL SELECT -1, 1, 'assistant', '<|im_end|><|im_start|>assistant ok'
), e AS (
  SELECT *, length(role) + length(text) + 24
    + len(regexp_extract_all(text, '<\|')) + len(regexp_extract_all(text, '<\\')) AS formatted
  FROM t
)
SELECT conv_id, count(*)::BIGINT AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
  coalesce(sum(length(text)) FILTER (WHERE role = 'assistant'), 0)::BIGINT AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (WHERE role = 'assistant'), '')) AS loss_sha256,
  sum(formatted)::BIGINT AS formatted_chars
FROM e GROUP BY conv_id
"""


def op3_nn_descent(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ann.nearest(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 20 == 0, k=20)


def op4_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every page as a capture with a fetch time in 2024 from its id, against lists whose dated changes come from the hosts by hash."""
    pages = table(spark, sf_dir, "pages").select("page_id", "url")
    at = F.timestamp_seconds(F.lit(1704067200) + F.col("page_id") * 7919 % 365 * 86400 + F.col("page_id") % 86400)
    captures = pages.select(F.col("page_id").alias("id"), "url", at.alias("at"))
    hosts = pages.select(urlfilter.host_of(F.col("url")).alias("host")).where("host <> ''").distinct()
    log = hosts.select("host", F.explode(F.sequence(F.lit(0), F.lit(23))).alias("k"))
    coin = F.conv(F.substring(F.md5(F.concat_ws("#", "host", F.col("k").cast("string")).cast("binary")), 1, 8), 16, 10).cast("long")
    place = F.expr("CASE k % 4 WHEN 1 THEN concat(host, '/en') WHEN 3 THEN substring_index(host, '.', -2) ELSE host END")
    changes = log.withColumn("c", coin).select(
        F.concat(F.lit("list"), (F.col("k") % 3).cast("string")).alias("list"),
        place.alias("key"),
        F.when(F.col("c") % 5 < 3, "add").otherwise("remove").alias("action"),
        F.timestamp_seconds(F.lit(1704067200) + F.col("c") % 31536000).alias("at"),
    )
    out = urlfilter.temporal_list_join(captures, changes)
    return out.select(F.col("id").alias("page_id"), "n_active", (F.col("n_active") > 0).alias("blocked"), "list", "key", F.unix_timestamp("valid_from").alias("since"))


OP4_SQL = r"""
WITH p AS (
  SELECT page_id, 1704067200 + page_id * 7919 % 365 * 86400 + page_id % 86400 AS ts,
    lower(coalesce(regexp_extract(url, '^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:@]+?)\.?(?::[0-9]*)?(?:[/?#]|$)', 1), '')) AS host,
    coalesce(regexp_extract(url, '^[A-Za-z][A-Za-z0-9+.-]*://[^/?#]*(/[^?#]*)', 1), '') AS path
  FROM pages
), log AS (
  SELECT host, k, CAST(concat('0x', substr(md5(concat(host, '#', k)), 1, 8)) AS BIGINT) AS c
  FROM (SELECT DISTINCT host FROM p WHERE host <> '') CROSS JOIN range(24) t(k)
), ch AS (
  SELECT DISTINCT concat('list', k % 3) AS list,
    CASE k % 4 WHEN 1 THEN host || '/en' WHEN 3 THEN array_to_string(string_split(host, '.')[-2:], '.') ELSE host END AS key,
    CASE WHEN c % 5 < 3 THEN 'add' ELSE 'remove' END AS action, 1704067200 + c % 31536000 AS ts
  FROM log
), l1 AS (
  SELECT *, lag(action) OVER (PARTITION BY list, key ORDER BY ts, action = 'add') AS before FROM ch
), l2 AS (
  SELECT list, key, action, ts, lead(ts) OVER (PARTITION BY list, key ORDER BY ts, action = 'add') AS valid_to
  FROM l1 WHERE (before IS NULL AND action = 'add') OR before <> action
), iv AS (SELECT list, key, ts AS valid_from, valid_to FROM l2 WHERE action = 'add' AND (valid_to IS NULL OR valid_to > ts)
), k AS (
  SELECT page_id, ts, unnest(list_distinct(
    list_transform(range(0, greatest(len(string_split(host, '.')) - 1, 1)), lambda i: array_to_string(string_split(host, '.')[i + 1:], '.'))
    || list_transform(range(1, 1 + len(list_filter(string_split(path, '/'), lambda x: x <> ''))),
         lambda i: host || '/' || array_to_string(list_filter(string_split(path, '/'), lambda x: x <> '')[1:i], '/')))) AS key
  FROM p WHERE host <> ''
), hit AS (
  SELECT k.page_id, iv.list, iv.key, iv.valid_from,
    row_number() OVER (PARTITION BY k.page_id ORDER BY length(iv.key) DESC, iv.valid_from DESC, iv.list, iv.key) AS r,
    count(*) OVER (PARTITION BY k.page_id) AS n
  FROM k JOIN iv ON iv.key = k.key AND iv.valid_from <= k.ts AND (iv.valid_to IS NULL OR k.ts < iv.valid_to)
)
SELECT p.page_id, coalesce(n, 0)::BIGINT AS n_active, coalesce(n, 0) > 0 AS blocked, list, key, valid_from::BIGINT AS since
FROM p LEFT JOIN hit ON hit.page_id = p.page_id AND hit.r = 1
"""


def op5_maxscore(spark: SparkSession, sf_dir: str) -> DataFrame:
    index = topk.quantised(table(spark, sf_dir, "embeddings"))
    return topk.top_k(index, index.where("id % 50 = 0"), k=5)


OP5_SQL = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(256 * CAST(x AS DOUBLE)) AS BIGINT)) AS w FROM embeddings
  WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
), s AS (
  SELECT q.vec_id AS query_id, c.vec_id, CAST(list_sum(list_transform(range(1, len(q.w) + 1), lambda i: q.w[i] * c.w[i])) AS BIGINT) AS score
  FROM v q JOIN v c ON q.vec_id % 50 = 0 AND c.vec_id <> q.vec_id
)
SELECT query_id, rank, vec_id, score
FROM (SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank FROM s) WHERE rank <= 5
"""


def op6_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard.near_duplicates(table(spark, sf_dir, "documents")).select("doc_id", "n_shingles", "component_id")


OP6_SQL = r"""
WITH RECURSIVE d AS (
  SELECT doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w
  FROM documents
), s AS (
  SELECT doc_id, unnest(CASE WHEN len(w) >= 4 THEN list_distinct(list_transform(range(1, len(w) - 2), lambda i: array_to_string(w[i:i + 3], ' ')))
                             WHEN len(w) > 0 THEN [array_to_string(w, ' ')] ELSE [] END) AS g
  FROM d
), n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
c AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS i FROM s a JOIN s b USING (g) WHERE a.doc_id <> b.doc_id GROUP BY 1, 2),
l AS (SELECT a, b FROM c JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * i >= 85 * (x.n + y.n - i)),
r AS (SELECT a, b FROM l UNION SELECT r.a, l.b FROM r JOIN l ON l.a = r.b)
SELECT d.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, least(d.doc_id, coalesce(m.c, d.doc_id)) AS component_id
FROM d LEFT JOIN n USING (doc_id) LEFT JOIN (SELECT a AS doc_id, min(b) AS c FROM r GROUP BY a) m USING (doc_id)
"""


def op7_bpe_transducer(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode_decode(table(spark, sf_dir, "documents"), tokenizer_path("byte_bpe_50k.json"))


def op8_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = secrets.scan(table(spark, sf_dir, "documents"))
    count = lambda kind: F.size(F.filter("base", lambda x: x["kind"] == kind)).cast("long").alias(f"n_{kind}")
    return found.select("doc_id", *map(count, secrets.KINDS), F.sha2(secrets.joined(F.col("base")), 256).alias("base_sha256"), secrets.joined(F.col("found")).alias("spans"))


def op9_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html.extract(table(spark, sf_dir, "pages")).withColumn("n_chars", F.length("text").cast("long"))


def op10_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = quality.train(docs, table(spark, sf_dir, "labels"))
    return quality.score(docs, model).select("doc_id", quality.held_out().alias("held_out"), "score", "predicted")


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict:
    own = (op1_vector_packing, op2_chat_formatting, op3_nn_descent, op4_url_filter, op5_maxscore, op6_jaccard_join, op7_bpe_transducer, op8_secret_scan, op9_html_extraction, op10_quality_classifier, pipeline)
    return {f.__name__: f for f in own}


def oracle_sql() -> dict[str, str]:
    return {"op2_chat_formatting": OP2_SQL, "op4_url_filter": OP4_SQL, "op5_maxscore": OP5_SQL, "op6_jaccard_join": OP6_SQL}
