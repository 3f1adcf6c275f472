"""Queries of the training-data operators: one opN_<name> each, and the pipeline."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from runloom.llm import ann, compaction, decontam, licences, mixing, ngram_join, quality, sanitise, secret_scan, token_shards
from runloom.llm.common import table, work_dir


def op1_token_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return token_shards.encode_table(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))


def op2_licences(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licences.scan(table(spark, sf_dir, "documents"))


def op3_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secret_scan.scan(table(spark, sf_dir, "documents"))


def op4_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    store = compaction.shard(table(spark, sf_dir, "documents"), work_dir(spark, "shards"))
    return compaction.shard_report(store)


def op5_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = decontam.scan(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return found.select("doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated")


def op6_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(table(spark, sf_dir, "documents"))


def op7_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_join.join(table(spark, sf_dir, "documents"))


def op8_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op9_ann(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "embeddings")
    return ann.search(rows, rows.filter("vec_id % 20 = 0"))


def op10_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sanitise.scan(table(spark, sf_dir, "documents"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


_ALL = (op1_token_shards, op2_licences, op3_secret_scan, op4_sharding, op5_decontamination, op6_source_mixing, op7_ngram_join, op8_quality, op9_ann, op10_pii, pipeline)
QUERIES = {f.__name__: f for f in _ALL}

_LOWER = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
_ALNUM = rf"regexp_extract_all({_LOWER}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"
_SPACED = rf"regexp_extract_all({_LOWER}, '[^\x20\x09-\x0D]+')"

ORACLE_SQL: dict[str, str] = {
    "op5_decontamination": f"""WITH docs AS (SELECT row_number() OVER () AS r, doc_id, {_ALNUM} AS w FROM documents),
items AS (SELECT coalesce(CAST(item_id AS VARCHAR), '') AS item, w, least(10, len(w)) AS n FROM (SELECT item_id, {_ALNUM} AS w FROM benchmark) WHERE len(w) > 0),
windows AS (SELECT DISTINCT item, n, array_to_string(w[k : k + n - 1], ' ') AS s FROM (SELECT *, unnest(generate_series(1, len(w) - n + 1)) AS k FROM items)),
places AS (SELECT r, n, k, array_to_string(w[k : k + n - 1], ' ') AS s FROM (SELECT r, w, n, unnest(generate_series(1, len(w) - n + 1)) AS k FROM docs, (SELECT DISTINCT n FROM windows) WHERE len(w) >= n)),
hits AS (SELECT r, k, n, item FROM places JOIN windows USING (n, s)),
words AS (SELECT r, count(*) AS n_hit FROM (SELECT DISTINCT r, unnest(generate_series(k, k + n - 1)) AS at FROM hits) GROUP BY r),
found AS (SELECT r, list_sort(list(DISTINCT item)) AS ids FROM hits GROUP BY r)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(len(ids), 0) AS BIGINT) AS n_items, sha256(coalesce(array_to_string(ids, ','), '')) AS items_sha256,
  coalesce(n_hit, 0) > 0 AS contaminated FROM docs LEFT JOIN words USING (r) LEFT JOIN found USING (r)""",
    "op6_source_mixing": r"""WITH docs AS (SELECT doc_id, source, CAST(coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0) AS BIGINT) AS size,
  CAST('0x' || substr(md5(concat_ws('|', '17', coalesce(CAST(doc_id AS VARCHAR), ''), coalesce(text, ''))), 1, 15) AS BIGINT) AS draw FROM documents),
sources AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM docs GROUP BY 1),
ranked AS (SELECT *, (row_number() OVER (ORDER BY source IS NULL, source) - 1) % 3 + 1 AS weight, 3 * source_size AS cap FROM sources),
needs AS (SELECT *, sum(source_size) OVER () - coalesce(sum(cap) OVER (ORDER BY cap / weight, source IS NULL, source ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS rest,
  sum(weight) OVER (ORDER BY cap / weight, source IS NULL, source ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS weights, row_number() OVER (ORDER BY cap / weight, source IS NULL, source) AS place FROM ranked),
ends AS (SELECT place AS last, rest AS unit_rest, weights AS unit_weights FROM needs WHERE rest * weight <= cap * weights ORDER BY place LIMIT 1),
targets AS (SELECT source, source_size, CASE WHEN last IS NULL OR place < last THEN CAST(cap AS DOUBLE) ELSE CAST(unit_rest * weight AS DOUBLE) / CAST(unit_weights AS DOUBLE) END AS target,
  CAST(CASE WHEN last IS NULL OR place < last THEN cap ELSE (unit_rest * weight) // unit_weights END AS BIGINT) AS budget FROM needs LEFT JOIN ends ON true),
plan AS (SELECT *, CASE WHEN source_size > 0 THEN budget // source_size ELSE 0 END AS epochs FROM targets),
ties AS (SELECT source, draw, sum(size) AS words FROM docs GROUP BY 1, 2),
places AS (SELECT t.source, draw, words, budget - epochs * source_size - coalesce(sum(words) OVER (PARTITION BY t.source ORDER BY draw ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS rest
  FROM ties t JOIN plan p ON t.source IS NOT DISTINCT FROM p.source),
cuts AS (SELECT source, draw AS cut_draw, rest AS cut_words FROM places WHERE rest >= 0 AND rest < words)
SELECT d.doc_id, size, source_size, target, CAST(epochs * size + CASE WHEN cut_draw IS NULL THEN 0 WHEN draw < cut_draw THEN size WHEN draw = cut_draw THEN least(greatest(cut_words - (row_number() OVER (PARTITION BY d.source, draw) - 1) * size, 0), size) ELSE 0 END AS BIGINT) AS taken
FROM docs d JOIN plan p ON d.source IS NOT DISTINCT FROM p.source LEFT JOIN cuts c ON d.source IS NOT DISTINCT FROM c.source""",
    "op7_ngram_join": f"""WITH RECURSIVE docs AS MATERIALIZED (SELECT row_number() OVER () AS r, doc_id, {_SPACED} AS w FROM documents),
shingles AS MATERIALIZED (SELECT DISTINCT r, array_to_string(w[k : k + 4], ' ') AS g FROM (SELECT r, w, unnest(generate_series(1, greatest(len(w) - 4, least(len(w), 1)))) AS k FROM docs)),
sizes AS MATERIALIZED (SELECT r, count(*) AS n FROM shingles GROUP BY r),
pairs AS (SELECT a.r AS a, b.r AS b, count(*) AS c FROM shingles a JOIN shingles b ON a.g = b.g AND a.r <> b.r GROUP BY 1, 2),
links AS MATERIALIZED (SELECT a, b FROM pairs JOIN sizes x ON x.r = a JOIN sizes y ON y.r = b WHERE 100 * c >= 75 * (x.n + y.n - c)),
reach(a, b) AS (SELECT r, r FROM docs UNION SELECT reach.a, links.b FROM reach JOIN links ON reach.b = links.a)
SELECT d.doc_id, CAST(coalesce(n, 0) AS BIGINT) AS n_shingles, component_id FROM docs d LEFT JOIN sizes USING (r) JOIN (SELECT reach.a AS r, min(x.doc_id) AS component_id FROM reach JOIN docs x ON x.r = reach.b GROUP BY 1) USING (r)""",
}
