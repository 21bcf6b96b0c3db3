"""The queries of this subpackage's operators, with production parameters, and their SQL where it can say the same."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..shipping import ship
from . import chat, common, decontam, neardup, packing, pii, repetition, secrets, tokenfile, urls, warc

#: The key of the pseudonyms; a user brings a secret one.
PSEUDONYM_KEY = "example-key"
BYTE_VOCABULARY, WORD_VOCABULARY = 50_257, 49_408


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def byte_tokenizer() -> str:
    return public_tokenizers.path("byte_bpe_50k.json")


def word_tokenizer() -> str:
    return public_tokenizers.path("word_bpe_49k.json")


def op1_chat_formatting(spark: SparkSession, sf_dir: str) -> DataFrame:
    probe = "</s>[INST] ok [/INST]"
    schema = T.StructType([T.StructField("conv_id", T.LongType()), T.StructField("turn", T.LongType()), T.StructField("role", T.StringType()), T.StructField("text", T.StringType())])
    more = spark.createDataFrame([(-1, 0, "user", probe), (-1, 1, "assistant", probe)], schema)
    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text").unionByName(more)
    return chat.digests(chat.formatted(rows, byte_tokenizer(), BYTE_VOCABULARY), byte_tokenizer(), BYTE_VOCABULARY)


def op2_repetition_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repetition.measure(table(spark, sf_dir, "documents")).drop("covered_words", "longest_repeat")


def packed_digests(docs: DataFrame, with_ids: bool = False) -> DataFrame:
    cut = common.written(packing.pieces(docs, byte_tokenizer()), "pieces")
    placed = packing.pack(cut).withColumn("ids_crc32", F.crc32("ids"))
    return placed if with_ids else placed.drop("ids")


def op3_sequence_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packed_digests(table(spark, sf_dir, "documents"))


def op4_pseudonyms(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.report(table(spark, sf_dir, "documents"), PSEUDONYM_KEY)


def op5_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    spans = F.col("spans")
    base = [r.kind for r in secrets.BASE]
    count = lambda kind: F.size(F.filter(spans, lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")
    return secrets.scan(table(spark, sf_dir, "documents")).select(
        "doc_id", *map(count, base), F.sha2(secrets.written_spans(spans, base), 256).alias("base_sha256"), secrets.written_spans(spans).alias("spans")
    )


def op6_url_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    return urls.judged(table(spark, sf_dir, "pages")).select("page_id", "host", "path", "rule", "verdict")


def op7_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = neardup.linked(table(spark, sf_dir, "documents"))
    return found.select("doc_id", "n_shingles", "component_id", F.coalesce(F.col("doc_id") == F.col("component_id"), F.col("component_id").isNull()).alias("kept"))


def op8_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    shards = tokenfile.write(table(spark, sf_dir, "documents"), word_tokenizer(), True, 1, WORD_VOCABULARY, common.new_folder(spark, "token-files"))
    return tokenfile.digests(shards)


def op9_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    archives = warc.write(table(spark, sf_dir, "pages"), common.new_folder(spark, "warc"))
    return warc.summary(warc.read(archives, payloads=False))


def op10_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontam.matches(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (op1_chat_formatting, op2_repetition_rules, op3_sequence_packing, op4_pseudonyms, op5_secret_scan, op6_url_filters, op7_near_duplicates, op8_token_files, op9_warc, op10_decontamination, pipeline)
}


ORACLES = {
    "op1_chat_formatting": r"""
WITH turns AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -1, 0, 'user', '</s>[INST] ok [/INST]' UNION ALL SELECT -1, 1, 'assistant', '</s>[INST] ok [/INST]'
), sized AS (
  SELECT *, length(regexp_replace(text, '(<)(\\*)(s>|/s>)', '\1\\\2\3', 'g'))
    + len(regexp_extract_all(text, '\[\\*(INST\]|/INST\]|SYS\]|/SYS\]|ROLE\]|/ROLE\])'))
    + CASE role WHEN 'system' THEN 11 WHEN 'user' THEN 13 WHEN 'assistant' THEN 7
      ELSE 17 + length(regexp_replace(role, '(<)(\\*)(s>|/s>)', '\1\\\2\3', 'g')) + len(regexp_extract_all(role, '\[\\*(INST\]|/INST\]|SYS\]|/SYS\]|ROLE\]|/ROLE\])')) END AS chars
  FROM turns
)
SELECT conv_id, count(*) AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
  CAST(coalesce(sum(length(text)) FILTER (role = 'assistant'), 0) AS BIGINT) AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (role = 'assistant'), '')) AS loss_sha256,
  CAST(sum(chars) AS BIGINT) AS formatted_chars
FROM sized GROUP BY conv_id
""",
    "op2_repetition_rules": r"""
WITH base AS (
  SELECT doc_id, coalesce(text, '') AS text, list_filter(string_split_regex(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS words FROM documents
), places AS (
  SELECT doc_id, unnest(words) AS w, unnest(range(1, len(words) + 1)) AS i FROM base
), five AS (
  SELECT *, w || ' ' || lead(w, 1) OVER d || ' ' || lead(w, 2) OVER d || ' ' || lead(w, 3) OVER d || ' ' || lead(w, 4) OVER d AS k5 FROM places WINDOW d AS (PARTITION BY doc_id ORDER BY i)
), twenty AS (
  SELECT *, md5(k5 || ' ' || lead(k5, 5) OVER d || ' ' || lead(k5, 10) OVER d || ' ' || lead(k5, 15) OVER d) AS k20 FROM five WINDOW d AS (PARTITION BY doc_id ORDER BY i)
), hundred AS (
  SELECT *, k20 || lead(k20, 20) OVER d || lead(k20, 40) OVER d || lead(k20, 60) OVER d || lead(k20, 80) OVER d || lead(w, 100) OVER d AS k101 FROM twenty WINDOW d AS (PARTITION BY doc_id ORDER BY i)
), twice AS (
  SELECT doc_id, i, k5 IS NOT NULL AND count(*) OVER (PARTITION BY doc_id, k5) > 1 AS r5, k20 IS NOT NULL AND count(*) OVER (PARTITION BY doc_id, k20) > 1 AS r20,
    k101 IS NOT NULL AND count(*) OVER (PARTITION BY doc_id, k101) > 1 AS r101 FROM hundred
), spread AS (
  SELECT doc_id, max(r5::INT) OVER (PARTITION BY doc_id ORDER BY i ROWS 4 PRECEDING) AS c5, max(r20::INT) OVER (PARTITION BY doc_id ORDER BY i ROWS 19 PRECEDING) AS c20, r101::INT AS r101 FROM twice
), summed AS (
  SELECT doc_id, sum(c5) AS n_repeat, sum(c20) AS covered, max(r101) AS long FROM spread GROUP BY doc_id
), lines AS (
  SELECT doc_id, count(*) - count(DISTINCT line) AS n_dup_lines FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM base) WHERE regexp_matches(line, '[^\x20\x09-\x0D]') GROUP BY doc_id
), all_of AS (
  SELECT b.doc_id, CAST(len(words) AS BIGINT) AS n_words, CAST(length(array_to_string(words, '')) AS BIGINT) AS word_chars, CAST(len(regexp_extract_all(text, '[#*$%&|<>]')) AS BIGINT) AS n_symbols,
    CAST(coalesce(n_dup_lines, 0) AS BIGINT) AS n_dup_lines, CAST(coalesce(n_repeat, 0) AS BIGINT) AS n_repeat_words, coalesce(covered, 0) AS covered, coalesce(long, 0) AS long
  FROM base b LEFT JOIN summed s USING (doc_id) LEFT JOIN lines l USING (doc_id)
)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_words < 10 OR 100 * n_repeat_words > 20 * n_words AS base_failed,
  NOT (n_words < 10 OR 100 * n_repeat_words > 20 * n_words OR 100 * covered > 15 * n_words OR long = 1) AS kept FROM all_of
""",
    "op7_near_duplicates": r"""
WITH RECURSIVE words AS (
  SELECT doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents
), shingled AS (
  SELECT DISTINCT doc_id, md5(array_to_string(w[i:i + 4], ' ')) AS s FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 3, 2))) AS i FROM words WHERE len(w) > 0)
), sizes AS (SELECT doc_id, count(*) AS n FROM shingled GROUP BY doc_id
), shared AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS k FROM shingled a JOIN shingled b ON a.s = b.s AND a.doc_id > b.doc_id GROUP BY 1, 2
), links AS (
  SELECT a, b FROM shared JOIN sizes x ON x.doc_id = a JOIN sizes y ON y.doc_id = b WHERE 100 * k >= 75 * (x.n + y.n - k)
), both_ways AS (SELECT a, b FROM links UNION SELECT b, a FROM links
), reach(node, least) AS (
  SELECT doc_id, doc_id FROM documents UNION SELECT both_ways.b, reach.least FROM reach JOIN both_ways ON reach.node = both_ways.a AND reach.least < both_ways.b
)
SELECT d.doc_id, coalesce(n, 0) AS n_shingles, c AS component_id, d.doc_id = c AS kept FROM documents d LEFT JOIN sizes USING (doc_id) JOIN (SELECT node, min(least) AS c FROM reach GROUP BY node) ON node = d.doc_id
""",
    "op9_warc": r"""
WITH payloads AS (
  SELECT page_id, encode(coalesce(html, '')) AS body FROM pages
), hexes AS (SELECT page_id, octet_length(body) AS payload_bytes, sha1(body) AS h FROM payloads
), digests AS (
  SELECT page_id, payload_bytes, array_to_string(list_transform(range(0, 32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', CAST((CAST('0x' || substr(h, CAST(i // 4 * 5 + 1 AS INT), 5) AS BIGINT) >> CAST(15 - 5 * (i % 4) AS INT)) & 31 AS INT) + 1, 1)), '') AS payload_digest FROM hexes
), firsts AS (SELECT *, min(page_id) OVER (PARTITION BY payload_digest) AS first FROM digests)
SELECT page_id, payload_bytes, payload_digest, CASE WHEN page_id = first THEN 'response' ELSE 'revisit' END AS record_type, CASE WHEN page_id <> first THEN first END AS refers_to FROM firsts
""",
}


def _spans_sql(kind: str, pattern: str, least: int, group: int, k: int) -> str:
    own = f"regexp_extract_all(text, '{pattern}', {group})"
    return f"""
SELECT * FROM (SELECT doc_id, '{kind}' AS kind, {k} AS k, unnest(starts) AS s, unnest(ends) AS e, unnest(owns) AS own FROM (
  SELECT doc_id, list_transform(range(1, len(found) + 1), lambda i: list_sum(list_transform(gaps[1:i], lambda x: length(x))) + coalesce(list_sum(list_transform(found[1:i - 1], lambda x: length(x))), 0)) AS starts,
    list_transform(range(1, len(found) + 1), lambda i: list_sum(list_transform(gaps[1:i], lambda x: length(x))) + list_sum(list_transform(found[1:i], lambda x: length(x)))) AS ends,
    list_transform({'owns' if group else 'found'}, lambda x: length(x)) AS owns
  FROM (SELECT doc_id, regexp_extract_all(text, '{pattern}') AS found, string_split_regex(text, '{pattern}') AS gaps{f", {own} AS owns" if group else ""} FROM texts WHERE regexp_matches(text, '{pattern}'))) AS listed) AS found_spans
WHERE own >= {least}"""


def _secret_sql() -> str:
    parts = [_spans_sql(r.kind, secrets.once(r).replace("\\\"", '"').replace("'", "''"), r.least, r.group, k) for k, r in enumerate(secrets.BASE + secrets.MORE)]
    base = ", ".join(f"'{r.kind}'" for r in secrets.BASE)
    counts = ", ".join(f"count(*) FILTER (kind = '{r.kind}') AS n_{r.kind}" for r in secrets.BASE)
    line = "kind || ':' || CAST(CAST(s AS BIGINT) AS VARCHAR) || ':' || CAST(CAST(e AS BIGINT) AS VARCHAR)"
    return f"""
WITH texts AS (SELECT doc_id, coalesce(text, '') AS text FROM documents), spans AS ({" UNION ALL ".join(parts)}),
summed AS (SELECT doc_id, {counts}, sha256(coalesce(string_agg({line}, ',' ORDER BY s, k) FILTER (kind IN ({base})), '')) AS base_sha256, string_agg({line}, ',' ORDER BY s, k) AS spans FROM spans GROUP BY doc_id)
SELECT t.doc_id, {", ".join(f"coalesce(n_{r.kind}, 0) AS n_{r.kind}" for r in secrets.BASE)}, coalesce(base_sha256, sha256('')) AS base_sha256, coalesce(spans, '') AS spans FROM texts t LEFT JOIN summed USING (doc_id)"""


ORACLES["op5_secret_scan"] = _secret_sql()
