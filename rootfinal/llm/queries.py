"""The thin queries over the given tables, and their SQL where SQL can express them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from . import boundaries, bpe_codec, html_text, mixing, near_copies, personal_data, quality, sharding, token_count, vector_links
from .shared import table

SHARD_BYTES = 1 << 20
END_ID = 2


def tokenizer_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_token_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    return boundaries.read_blocks(boundaries.write_blocks(spark, table(spark, sf_dir, "documents"), tokenizer_path("word_bpe_49k.json"), END_ID))


def op2_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    return personal_data.span_table(table(spark, sf_dir, "documents"), ["doc_id"])


def op3_bpe_codec(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe_codec.encode_column(table(spark, sf_dir, "documents"), tokenizer_path("word_bpe_49k.json"), ["doc_id"])


def op4_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = quality.apply_policy(quality.ledger(table(spark, sf_dir, "documents"), ["doc_id"]))
    return rows.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "failed_bits")


def op5_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_count.count_tokens(table(spark, sf_dir, "documents"), tokenizer_path("byte_bpe_50k.json"), ["doc_id"])


def op6_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard(spark, table(spark, sf_dir, "documents"), SHARD_BYTES)


def op7_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_text.extract(table(spark, sf_dir, "pages"), ["page_id", "url"])


def op8_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row for each document, read off the ranged schedule; op8_schedule has its positions."""
    return mixing.schedule(table(spark, sf_dir, "documents")).where("copy <= 1").select("doc_id", "size", "source_size", "target", "taken")


def op8_schedule(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row for each copy taken, in training order."""
    return mixing.schedule(table(spark, sf_dir, "documents")).where("copy > 0").select("doc_id", "source", "size", "copy", "position")


def op9_vector_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vector_links.link(spark, table(spark, sf_dir, "embeddings"))


def op10_near_copies(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_copies.classes(spark, table(spark, sf_dir, "documents"))


QUERIES = {f.__name__: f for f in (op1_token_ids, op2_personal_data, op3_bpe_codec, op4_quality_rules, op5_token_counts, op6_sharding, op7_html_text, op8_mixing, op8_schedule, op9_vector_links, op10_near_copies)}

ORACLE_SQL = {
    "op8_mixing": r"""
WITH d AS (SELECT doc_id, source, md5(coalesce(CAST(doc_id AS varchar), '')) AS h,
    CAST(coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0) AS bigint) AS size FROM documents),
s AS (SELECT source, CAST(sum(size) AS bigint) AS source_size FROM d GROUP BY source),
w AS (SELECT *, (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1 AS weight FROM s),
o AS (SELECT *, CAST(sum(source_size) OVER () AS bigint) AS total,
    CAST(coalesce(sum(source_size) OVER (ORDER BY source_size / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS bigint) AS size_before,
    CAST(sum(weight) OVER (ORDER BY source_size / weight, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS bigint) AS weight_after FROM w),
c AS (SELECT *, 3 * source_size * weight_after <= weight * (total - 3 * size_before) AS capped FROM o),
t AS (SELECT source, source_size, CASE WHEN capped THEN CAST(3 * source_size AS double)
    ELSE CAST(weight * (total - 3 * coalesce(sum(CASE WHEN capped THEN source_size END) OVER (), 0)) AS double) / CAST(sum(CASE WHEN NOT capped THEN weight END) OVER () AS double) END AS target FROM c),
p AS (SELECT doc_id, source, size, coalesce(sum(size) OVER (PARTITION BY source ORDER BY h, doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) + size / 2.0 AS mid FROM d)
SELECT p.doc_id, p.size, t.source_size, t.target,
    p.size * CAST(CASE WHEN p.size = 0 OR p.mid > t.target THEN 0 ELSE least(3, floor((t.target - p.mid) / t.source_size) + 1) END AS bigint) AS taken
FROM p JOIN t ON p.source IS NOT DISTINCT FROM t.source
""",
}
# the shares of op8_mixing, carried on to each copy's position
ORACLE_SQL["op8_schedule"] = ORACLE_SQL["op8_mixing"].rsplit("SELECT p.doc_id", 1)[0].rstrip() + r""",
e AS (SELECT p.doc_id, p.source, p.size, p.mid, t.source_size, t.target, CAST(CASE WHEN w.weight % 2 = 1 THEN 0.5 ELSE -0.5 END AS double) AS a,
    CAST(CASE WHEN p.size = 0 OR p.mid > t.target THEN 0 ELSE least(3, floor((t.target - p.mid) / t.source_size) + 1) END AS bigint) AS copies
    FROM p JOIN t ON p.source IS NOT DISTINCT FROM t.source JOIN w ON p.source IS NOT DISTINCT FROM w.source),
k AS (SELECT *, unnest(generate_series(1, copies)) AS copy FROM e),
m AS (SELECT *, (mid + (copy - 1) * source_size) / target AS d FROM k)
SELECT doc_id, source, size, copy, 2 * d / (1 - a + sqrt((1 - a) * (1 - a) + 4 * a * d)) AS position FROM m
"""
ORACLE_SQL["op9_vector_links"] = """
WITH RECURSIVE v AS (SELECT vec_id, CAST(embedding AS double[]) AS e FROM embeddings),
l AS (SELECT a.vec_id AS a, b.vec_id AS b FROM v a JOIN v b ON a.vec_id <> b.vec_id AND len(a.e) = len(b.e) AND list_cosine_similarity(a.e, b.e) >= 0.9),
r AS (SELECT vec_id AS n, vec_id AS c FROM v UNION SELECT l.a, r.c FROM r JOIN l ON l.b = r.n)
SELECT v.vec_id, (SELECT count(*) FROM l WHERE l.a = v.vec_id) AS n_links, min(r.c) AS component_id, v.vec_id = min(r.c) AS kept FROM v JOIN r ON r.n = v.vec_id GROUP BY v.vec_id
"""
