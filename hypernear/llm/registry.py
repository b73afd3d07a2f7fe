"""Queries of the corpus operators, and their SQL where SQL can express them."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import contamination, html_text, licenses, mixing, order_minhash, packing, rotated_codes, shards, toxicity, url_filter
from .common import read, shared_dir, small_batches

QUERIES: dict = {}
ORACLES: dict = {}


def query(function):
    """Register function, to run with small Arrow batches."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        small_batches(spark)
        return function(spark, sf_dir)

    QUERIES[function.__name__] = run
    return run


@query
def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = read(spark, sf_dir, "documents"), read(spark, sf_dir, "labels")
    scorer = toxicity.fit(docs, labels.filter(~toxicity.held_out()))
    scored = toxicity.score(docs.select("doc_id", "text"), scorer)
    return scored.select("doc_id", toxicity.held_out().alias("held_out"), "score", (F.col("score") >= 0.7).cast("int").alias("predicted"))


@query
def op6_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    mixed = mixing.copies(read(spark, sf_dir, "documents").select("doc_id", "text", "source"))
    return mixed.select("doc_id", "size", "source_size", "target", (F.col("size") * F.col("copies")).alias("taken"))


ORACLES["op6_mixing"] = r"""
WITH texts AS (SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS size, md5(coalesce(text, '')) AS digest FROM documents),
sized AS (
  SELECT *, length(bin(size)) AS weight, (('0x' || substr(md5('42:' || coalesce(CAST(doc_id AS VARCHAR), 'text:' || digest)), 1, 12))::BIGINT + 0.5) / 281474976710656.0 AS u
  FROM texts),
strata AS (SELECT source, weight, CAST(sum(size) AS BIGINT) AS words FROM sized WHERE size > 0 GROUP BY source, weight),
sizes AS (SELECT source, CAST(sum(words) AS BIGINT) AS source_size FROM strata GROUP BY source),
placed AS (SELECT *, [5, 2, 1][CAST((row_number() OVER (ORDER BY source IS NULL, source) - 1) % 3 + 1 AS INT)] AS w, row_number() OVER (ORDER BY source IS NULL, source) AS place FROM sizes),
rated AS (
  SELECT *, CAST(150 * sum(source_size) OVER () - 200 * coalesce(sum(source_size) OVER f, 0) AS DOUBLE) / (100.0::DOUBLE * CAST(sum(w) OVER () - coalesce(sum(w) OVER f, 0) AS DOUBLE)) AS ratio
  FROM placed WINDOW f AS (ORDER BY source_size::DOUBLE / w::DOUBLE, place ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
lam AS (SELECT arg_min(ratio, (source_size::DOUBLE / w::DOUBLE, place)) AS l FROM rated WHERE ratio * w <= 2 * source_size),
goal AS (SELECT source, source_size, least(coalesce(l * w, 2.0::DOUBLE * source_size), 2.0::DOUBLE * source_size) AS target FROM rated, lam),
filled AS (
  SELECT s.*, g.source_size, g.target,
         (g.target - 2.0::DOUBLE * CAST(coalesce(sum(s.words) OVER (PARTITION BY s.source ORDER BY s.weight DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS DOUBLE))
         / CAST(sum(s.weight * s.words) OVER (PARTITION BY s.source ORDER BY s.weight ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS DOUBLE) AS factor
  FROM strata s JOIN goal g ON s.source IS NOT DISTINCT FROM g.source),
factors AS (SELECT source, arg_max(factor, weight) FILTER (WHERE factor * weight <= 2) AS factor FROM filled GROUP BY source),
rates AS (SELECT f.source, f.weight, f.words, f.source_size, f.target, least(coalesce(k.factor * f.weight, 2.0::DOUBLE), 2.0::DOUBLE) AS rate FROM filled f JOIN factors k ON f.source IS NOT DISTINCT FROM k.source),
plan AS (SELECT source, source_size, target, target - CAST(sum(CAST(floor(rate) * words AS BIGINT)) AS DOUBLE) AS wanted FROM rates GROUP BY source, source_size, target),
chances AS (
  SELECT s.*, p.source_size, p.target, p.wanted, floor(r.rate) AS whole, r.rate - floor(r.rate) AS p
  FROM sized s LEFT JOIN plan p ON s.source IS NOT DISTINCT FROM p.source LEFT JOIN rates r ON s.source IS NOT DISTINCT FROM r.source AND s.weight = r.weight AND s.size > 0),
ranked AS (SELECT *, (u / (1 - u)) / (p / (1 - p)) AS odds FROM chances WHERE p > 0),
summed AS (SELECT *, sum(size) OVER (PARTITION BY source ORDER BY odds, doc_id NULLS FIRST, digest ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS upto FROM ranked),
taken AS (
  SELECT doc_id, size, source_size, target, whole + CASE WHEN wanted > 0 AND upto - wanted <= wanted - (upto - size) THEN 1 ELSE 0 END AS copies FROM summed
  UNION ALL SELECT doc_id, size, source_size, target, coalesce(whole, 0) FROM chances WHERE p IS NULL OR p = 0)
SELECT doc_id, CAST(size AS BIGINT) AS size, coalesce(source_size, 0) AS source_size, coalesce(target, 0.0) AS target, CAST(size * copies AS BIGINT) AS taken FROM taken"""


@query
def op9_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    packed = packing.pack_tokens(read(spark, sf_dir, "documents"), width=2048)
    return packing.write_matrices(packed, f"{shared_dir(spark)}/packed-{uuid.uuid4().hex}", width=2048)


@query
def op8_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = read(spark, sf_dir, "pages").select("page_id", "url")
    return url_filter.judge(pages, url_filter.fit(url_filter.seeded(pages)))


@query
def op10_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_text.main_text(read(spark, sf_dir, "pages"))


@query
def op3_rotated_codes(spark: SparkSession, sf_dir: str) -> DataFrame:
    index, setting = rotated_codes.build(read(spark, sf_dir, "embeddings"))
    return rotated_codes.search(index, setting, index.filter("vec_id % 100 = 0"))


ORACLES["op3_rotated_codes"] = """
WITH v AS (SELECT row_number() OVER () AS n, vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings WHERE embedding IS NOT NULL AND list_sum(list_transform(embedding, lambda x: abs(x))) > 0),
d AS (SELECT q.n, q.vec_id AS query_id, c.vec_id, sqrt(list_sum(list_transform(list_zip(q.e, c.e), lambda z: (z[1] - z[2]) * (z[1] - z[2])))) AS score
      FROM v q JOIN v c ON q.vec_id % 100 = 0 AND q.n <> c.n),
r AS (SELECT *, CAST(row_number() OVER (PARTITION BY query_id, n ORDER BY score, vec_id) AS INT) AS rank FROM d)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 10"""


@query
def op1_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contamination.leaks(read(spark, sf_dir, "documents"), read(spark, sf_dir, "benchmark"))


@query
def op7_order_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return order_minhash.near_duplicates(read(spark, sf_dir, "documents"))


@query
def op2_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    store = shards.ShardStore(spark, f"{shared_dir(spark)}/shards-{uuid.uuid4().hex}")
    for arrival in shards.arrivals(read(spark, sf_dir, "documents"), "doc_id"):
        store.append(arrival)
    store.compact()
    store.vacuum()
    return store.read().select("doc_id", F.md5("text").alias("text_md5"), "lang", "source", "n_chars")


ORACLES["op2_shards"] = "SELECT doc_id, md5(text) AS text_md5, lang, source, n_chars FROM documents"


@query
def op5_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    files = licenses.document_paths(read(spark, sf_dir, "documents").select("doc_id", "source", "text")).drop("source")
    return licenses.licences(files)
