"""The queries over the given tables, one for each operator: (spark, sf_dir) -> DataFrame."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from . import bpe, minhash, mixing, quality, rangejoin, secrets, sharding, suffixes, suffixtree, toxicity
from .tables import table

BPE_FILE = "byte_bpe_50k.json"
SHARDS = 24
TARGETS = {"en": 0.4, "de": 0.2, "es": 0.2, "fr": 0.2}


def op1_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.digests(table(spark, sf_dir, "documents"), public_tokenizers.path(BPE_FILE))


def op2_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minhash.near_duplicates(table(spark, sf_dir, "documents"), k=4, least=80)


def op3_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.score_documents(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op4_rangejoin(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rangejoin.near_vectors(table(spark, sf_dir, "embeddings"), 0.95)


def op5_suffixes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffixes.remove_repeats(table(spark, sf_dir, "documents")).drop("kept")


def op6_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.judge(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op7_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard_documents(table(spark, sf_dir, "documents"), SHARDS)


def op8_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.spans_of_documents(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op9_suffixtree(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffixtree.score_documents(table(spark, sf_dir, "documents"))


def op10_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix_documents(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"), TARGETS)


QUERIES = {f.__name__: f for f in (op1_bpe, op2_minhash, op3_toxicity, op4_rangejoin, op5_suffixes, op6_quality, op7_sharding, op8_secrets, op9_suffixtree, op10_mixing)}
_COMPONENTS = """reach(id, root) AS (SELECT id, id FROM nodes UNION SELECT l.b, r.root FROM reach r JOIN links l ON l.a = r.id),
least AS (SELECT id, min(root) AS root FROM reach GROUP BY id)"""

ORACLES: dict[str, str] = {
    "op2_minhash": f"""WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x20\\x09-\\x0D]+') AS w FROM documents),
s AS (SELECT doc_id, CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 4 THEN [array_to_string(w, ' ')] ELSE list_distinct([w[i] || ' ' || w[i + 1] || ' ' || w[i + 2] || ' ' || w[i + 3] FOR i IN range(1, len(w) - 2)]) END AS s FROM w),
x AS (SELECT doc_id, len(s) AS n, unnest(s) AS g FROM s),
pairs AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c, min(a.n) AS na, min(b.n) AS nb FROM x a JOIN x b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY 1, 2),
links AS (SELECT a, b FROM pairs WHERE 100 * c >= 80 * (na + nb - c)), nodes AS (SELECT doc_id AS id FROM documents), {_COMPONENTS}
SELECT s.doc_id, CAST(len(s) AS BIGINT) AS n_shingles, root AS component_id, root = s.doc_id AS kept FROM s JOIN least ON least.id = s.doc_id""",
    "op4_rangejoin": f"""WITH RECURSIVE v AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings),
links AS (SELECT a.vec_id AS a, b.vec_id AS b FROM v a JOIN v b ON a.vec_id <> b.vec_id WHERE list_cosine_similarity(a.e, b.e) >= 0.95), nodes AS (SELECT vec_id AS id FROM v), {_COMPONENTS}
SELECT v.vec_id, (SELECT count(*) FROM links WHERE a = v.vec_id) AS n_links, root AS component_id, root = v.vec_id AS kept FROM v JOIN least ON least.id = v.vec_id""",
}
