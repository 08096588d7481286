"""The thin queries of the training-data operators, and their SQL where SQL has a form of them."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spreadmax.llm.common import table
from spreadmax.llm.decontaminate import RESULT, find_contamination
from spreadmax.llm.exact_dedup import exact_dedup
from spreadmax.llm.license_scan import scan_licenses
from spreadmax.llm.mixing import replicate
from spreadmax.llm.pii import summary
from spreadmax.llm.quality import score_quality
from spreadmax.llm.sharding import shard_documents
from spreadmax.llm.simhash import near_duplicates
from spreadmax.llm.token_counts import token_counts
from spreadmax.llm.toxicity import score_toxicity

Query = Callable[[SparkSession, str], DataFrame]


def op1_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score_quality(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op2_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_licenses(table(spark, sf_dir, "documents"))


def op3_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup(table(spark, sf_dir, "documents"))


def op4_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))


def op5_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shard_documents(table(spark, sf_dir, "documents"))


def op6_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    return find_contamination(docs, table(spark, sf_dir, "benchmark")).select("doc_id", *[n for n, _ in RESULT])


def op7_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score_toxicity(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op8_surrogates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return summary(table(spark, sf_dir, "documents"))


def op9_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = near_duplicates(table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def op10_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "source", "text")
    out = replicate(docs).select(
        "doc_id",
        "source",
        F.octet_length(F.coalesce("text", F.lit(""))).cast("long").alias("n_bytes"),
        F.round("rate", 9).alias("rate"),
        F.col("copies").cast("long").alias("copies"),
        F.col("copy").cast("long").alias("copy"),
        "mix_key",
    )
    return out.repartition("mix_key").sortWithinPartitions("mix_key")


QUERIES: dict[str, Query] = {
    f.__name__: f for f in (op1_quality, op2_licenses, op3_exact_dedup, op4_token_counts, op5_sharding, op6_decontamination, op7_toxicity, op8_surrogates, op9_simhash, op10_mixing)
}

_OP3 = """
WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
     g AS (SELECT t, max(doc_id) AS keep_id, count(*) AS group_size FROM d GROUP BY t)
SELECT doc_id, keep_id, group_size, doc_id = keep_id AS kept, sha256(t) AS text_sha256
FROM d JOIN g USING (t)
"""

_OP6 = r"""
WITH dw AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'),
         '[^\x{0}-\x{2F}\x{3A}-\x{60}\x{7B}-\x{7F}]+') AS w FROM documents),
iw AS (
  SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'),
         '[^\x{0}-\x{2F}\x{3A}-\x{60}\x{7B}-\x{7F}]+') AS w FROM benchmark),
il AS (SELECT item_id, w, least(len(w), 13) AS k FROM iw WHERE len(w) > 0),
win AS (
  SELECT DISTINCT item_id, k, array_to_string(w[i : i + k - 1], ' ') AS g
  FROM (SELECT item_id, w, k, unnest(range(1, len(w) - k + 2)) AS i FROM il)),
ks AS (SELECT DISTINCT k FROM win),
dg AS (
  SELECT doc_id, k, i, array_to_string(w[i : i + k - 1], ' ') AS g
  FROM (SELECT doc_id, w, k, unnest(range(1, len(w) - k + 2)) AS i FROM dw, ks WHERE len(w) >= k)),
hit AS (SELECT doc_id, item_id, i, dg.k FROM dg JOIN win ON dg.k = win.k AND dg.g = win.g),
words AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + k)) AS p FROM (SELECT DISTINCT doc_id, i, k FROM hit)) GROUP BY doc_id),
items AS (
  SELECT doc_id, count(*) AS n_items, string_agg(s, ',' ORDER BY s) AS names
  FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS s FROM hit) GROUP BY doc_id)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items,
       sha256(coalesce(names, '')) AS items_sha256,
       coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(w) AS contaminated
FROM dw LEFT JOIN words USING (doc_id) LEFT JOIN items USING (doc_id)
"""

_OP10 = """
WITH s AS (SELECT source, sum(strlen(coalesce(text, '')) + 1) AS size FROM documents GROUP BY source),
t AS (SELECT source, size, sqrt(size) AS target FROM s),
r AS (SELECT source, target / (SELECT sum(target) FROM t) * (SELECT sum(size) FROM t) / size AS rate FROM t),
p AS (SELECT source, rate, greatest(1, ceil(rate / 16)) AS parts FROM r),
c AS (
  SELECT source, rate, parts, n, sum(exp(n * ln(rate / parts) - rate / parts - lgamma(n + 1))) OVER (PARTITION BY source ORDER BY n) AS upto
  FROM p, range(0, 81) AS k(n)),
d AS (SELECT doc_id, source, strlen(coalesce(text, '')) AS n_bytes, coalesce(CAST(doc_id AS VARCHAR), md5(coalesce(text, ''))) AS name FROM documents),
u AS (
  SELECT d.doc_id, d.source, d.n_bytes, d.name, j,
         CAST(('0x' || substr(md5('20:' || j || ':' || d.name), 1, 12)) AS BIGINT) / 281474976710656.0 AS u
  FROM d JOIN p ON d.source IS NOT DISTINCT FROM p.source, LATERAL (SELECT unnest(range(1, CAST(p.parts AS BIGINT) + 1)) AS j)),
m AS (
  SELECT u.doc_id, u.source, u.n_bytes, u.name, any_value(c.rate) AS rate, count(*) FILTER (c.upto <= u.u) AS copies
  FROM u JOIN c ON u.source IS NOT DISTINCT FROM c.source GROUP BY ALL)
SELECT doc_id, source, n_bytes, round(rate, 9) AS rate, copies, copy, substr(md5('order20:' || copy || ':' || name), 1, 16) AS mix_key
FROM (SELECT *, unnest(range(1, copies + 1)) AS copy FROM m)
"""

ORACLES: dict[str, str] = {"op3_exact_dedup": _OP3, "op6_decontamination": _OP6, "op10_mixing": _OP10}
