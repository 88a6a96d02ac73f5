"""Queries opN_<name> of the training-data operators, in production parameters, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from modelsort.llm import balltree, chat, decontaminate, langid, licences, mixing, quality, simhash, toxicity, warc
from modelsort.llm.samples import fold_of
from modelsort.plans.durable import materialize


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.near_duplicates(table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lower(F.lpad(F.hex("print"), 16, "0")).alias("fingerprint"), "component_id")


def op2_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    match = F.col("match")
    return decontaminate.with_matches(docs, table(spark, sf_dir, "benchmark")).select(
        "doc_id",
        match["n_words"].alias("n_words"),
        match["n_hit"].alias("n_hit"),
        F.size(match["items"]).cast("long").alias("n_items"),
        decontaminate.items_digest(match["items"]).alias("items_sha256"),
        decontaminate.is_contaminated(match).alias("contaminated"),
    )


OP2_SQL = r"""
WITH item_rows AS (
  SELECT CAST(item_id AS VARCHAR) AS item_id, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS words
  FROM benchmark WHERE item_id IS NOT NULL AND text IS NOT NULL
), windows AS (
  SELECT DISTINCT item_id, size, array_to_string(words[p : p + size - 1], ' ') AS gram
  FROM (SELECT *, unnest(range(1, len(words) - size + 2)) AS p FROM (SELECT *, least(13, len(words)) AS size FROM item_rows WHERE len(words) > 0))
), doc_words AS (
  SELECT row_number() OVER () AS r, doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS words FROM documents
), grams AS (
  SELECT r, p, size, array_to_string(words[p : p + size - 1], ' ') AS gram
  FROM (SELECT r, words, size, unnest(range(1, len(words) - size + 2)) AS p FROM doc_words, (SELECT DISTINCT size FROM windows))
), found AS (SELECT r, p, size, item_id FROM grams JOIN windows USING (size, gram)),
hits AS (SELECT r, count(DISTINCT w) AS n_hit FROM (SELECT r, unnest(range(p, p + size)) AS w FROM (SELECT DISTINCT r, p, size FROM found)) GROUP BY r),
items AS (SELECT r, count(*) AS n_items, string_agg(item_id, ',' ORDER BY item_id) AS ids FROM (SELECT DISTINCT r, item_id FROM found) GROUP BY r)
SELECT doc_id, CAST(len(words) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items,
  sha256(coalesce(ids, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(words) AS contaminated
FROM doc_words LEFT JOIN hits USING (r) LEFT JOIN items USING (r)
"""


def op3_chat_formatting(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chat.read_back(chat.format_conversations(with_probe(table(spark, sf_dir, "conversations"))))


def with_probe(turns: DataFrame) -> DataFrame:
    """All conversations, and one whose texts hold control strings."""
    said = "\\### Assistant: </turn> ok"
    probe = turns.sparkSession.createDataFrame([(-7, 0, "user", said), (-7, 1, "assistant", said)], "conv_id long, turn long, role string, text string")
    return turns.select("conv_id", "turn", "role", "text").unionByName(probe)


OP3_SQL = """
WITH probe(conv_id, turn, role, text) AS (VALUES (-7, 0, 'user', '\\### Assistant: </turn> ok'), (-7, 1, 'assistant', '\\### Assistant: </turn> ok')),
turns AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM (SELECT conv_id, turn, role, text FROM conversations UNION ALL SELECT * FROM probe)
), marked AS (
  SELECT *, length(role) + length(text) + 8 + 8 + 8 + (length(role || chr(10) || text) - length(replace(role || chr(10) || text, '<|', ''))) // 2 + (length(role || chr(10) || text) - length(replace(role || chr(10) || text, '<\\', ''))) // 2 AS chars FROM turns
)
SELECT conv_id, count(*) AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn NULLS FIRST, role, text)) AS turns_sha256,
  CAST(coalesce(sum(length(text)) FILTER (WHERE role = 'assistant'), 0) AS BIGINT) AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn NULLS FIRST, role, text) FILTER (WHERE role = 'assistant'), '')) AS loss_sha256,
  CAST(sum(chars) AS BIGINT) AS formatted_chars
FROM marked GROUP BY conv_id
"""


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = toxicity.train(docs, table(spark, sf_dir, "labels"))
    scored = docs.select("doc_id", toxicity.toxicity(F.col("text"), model, spark).alias("found"))
    score = F.col("found")["score"]
    return scored.select("doc_id", held_out(5, 0), score.alias("score"), (score >= 0.5).cast("int").alias("predicted"), F.col("found")["segments"].alias("segments"))


def held_out(parts: int, which: int) -> Column:
    """Whether the id's fold is ``which``; a null id is in no fold and teaches nothing."""
    return F.coalesce(fold_of("doc_id", parts) == which, F.lit(False)).alias("held_out")


def op5_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    trees = langid.train(docs.where(fold_of("doc_id", 3) != 1))
    scored = docs.select("doc_id", langid.predict(F.col("text"), trees, spark).alias("found"))
    return scored.select("doc_id", held_out(3, 1), F.col("found")["lang"].alias("lang_pred"), F.col("found")["score"].alias("score"))


def op6_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    records = warc.read_archives(warc.write_archives(table(spark, sf_dir, "pages")))
    return warc.check_revisits(materialize(records.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"), "warc-records"))


OP6_SQL = """
WITH pages_ AS (SELECT page_id, coalesce(html, '') AS html, sha1(coalesce(html, '')) AS hex FROM pages),
winner AS (SELECT hex, max(page_id) AS first FROM pages_ GROUP BY hex)
SELECT page_id, CAST(octet_length(encode(html)) AS BIGINT) AS payload_bytes,
  list_aggregate(list_transform(range(32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', 1 +
    (((((strpos('0123456789abcdef', substr(hex, CAST(1 + (5 * i) // 4 AS INTEGER), 1)) - 1) * 16 + strpos('0123456789abcdef', substr(hex, CAST(2 + (5 * i) // 4 AS INTEGER), 1)) - 1)) >> CAST(3 - (5 * i) % 4 AS INTEGER)) & 31)::INTEGER, 1)), 'string_agg', '') AS payload_digest,
  CASE WHEN page_id IS DISTINCT FROM first AND first IS NOT NULL THEN 'revisit' ELSE 'response' END AS record_type,
  CASE WHEN page_id IS DISTINCT FROM first THEN first END AS refers_to
FROM pages_ JOIN winner USING (hex)
"""


def op7_mixing_to_targets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Languages as domains, learned from the labelled documents, mixed to equal token shares."""
    docs = table(spark, sf_dir, "documents")
    rates, _, _ = mixing.mix(docs, labelled_languages(docs, table(spark, sf_dir, "labels")))
    return rates


def labelled_languages(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """Columns ``doc_id, domain`` of the labelled documents."""
    return docs.select("doc_id", F.col("lang").alias("domain")).join(labels.select("doc_id"), "doc_id", "left_semi")


def op8_exact_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    is_query = F.col("vec_id") % balltree.QUERY_EVERY == 0
    return balltree.top_inner_products(table(spark, sf_dir, "embeddings"), is_query)


OP8_SQL = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(256 * CAST(x AS DOUBLE)) AS DOUBLE)) AS q FROM embeddings
  WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
), scored AS (
  SELECT a.vec_id AS query_id, b.vec_id, CAST(list_inner_product(a.q, b.q) AS BIGINT) AS score
  FROM v a JOIN v b ON a.vec_id % 50 = 0 AND a.vec_id <> b.vec_id
), ranked AS (SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank FROM scored)
SELECT query_id, rank, vec_id, score FROM ranked WHERE rank <= 5
"""


def op9_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    net = quality.train(docs, table(spark, sf_dir, "labels"))
    scored = docs.select("doc_id", quality.quality(F.col("text"), net, spark).alias("found"))
    score = F.col("found")["score"]
    return scored.select("doc_id", held_out(5, 0), score.alias("score"), (score >= quality.THRESHOLD).cast("int").alias("predicted"), F.col("found")["n_passages"].alias("n_passages"))


def op10_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents, and a variant of every known text: capitals, other spelling and spacing, a copyright line."""
    known = licences.known_table(spark)
    return licences.scan(table(spark, sf_dir, "documents").select("doc_id", "text").unionByName(with_variants(known)), known.drop("n"))


def with_variants(known: DataFrame) -> DataFrame:
    text = F.replace(F.replace(F.upper("text"), F.lit("LICENSE"), F.lit("LICENCE")), F.lit(" "), F.lit(" \t "))
    return known.select((-F.col("n")).alias("doc_id"), F.concat(F.lit("Copyright (c) 2020 Some Owner\n\n"), text).alias("text"))


def op10_sql() -> str:
    known = ", ".join(f"({n}, '{name}', '" + text.replace("'", "''") + "')" for n, name, text in licences.known_texts())
    return f"""
WITH known(n, license_id, text) AS (VALUES {known}),
variants AS (SELECT -n AS doc_id, 'Copyright (c) 2020 Some Owner' || chr(10) || chr(10) || replace(replace(upper(text), 'LICENSE', 'LICENCE'), ' ', ' ' || chr(9) || ' ') AS text FROM known),
digests AS (SELECT sha256(form) AS digest, min(license_id) AS license_id FROM (SELECT license_id, {licences.canonical_sql("text")} AS form FROM known) WHERE form <> '' GROUP BY 1),
forms AS (SELECT doc_id, {licences.canonical_sql("text")} AS form FROM (SELECT doc_id, text FROM documents UNION ALL SELECT * FROM variants))
SELECT CAST(doc_id AS BIGINT) AS doc_id, CAST(length(form) AS BIGINT) AS canonical_chars, sha256(form) AS digest, license_id
FROM forms LEFT JOIN digests ON sha256(form) = digests.digest
"""


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_simhash_near_dedup, op2_benchmark_decontamination, op3_chat_formatting, op4_toxicity, op5_language_id, op6_warc, op7_mixing_to_targets, op8_exact_top_k, op9_quality_classifier, op10_license_scan)}


def oracle_sql() -> dict[str, str]:
    return {"op2_benchmark_decontamination": OP2_SQL, "op3_chat_formatting": OP3_SQL, "op6_warc": OP6_SQL, "op8_exact_top_k": OP8_SQL, "op10_license_scan": op10_sql()}
