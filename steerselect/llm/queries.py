"""The registered queries of this subpackage: each applies one operator to its whole table."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import tokens as T
from . import exact_dedup, packing, pii, piece_codec, sharding, similar, simhash, superkmer, topk_search, toxicity, warc


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def vocabulary(name: str) -> str:
    """The place of a public vocabulary file, the same on every machine."""
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(_table(spark, sf_dir, "documents"))


def op2_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return superkmer.digest(superkmer.remove_repeats(_table(spark, sf_dir, "documents")))


def op3_exact_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    return topk_search.exact_top_k(_table(spark, sf_dir, "embeddings"), F.pmod(F.col("vec_id"), F.lit(100)) == 0)


def op4_pii_surrogates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, the text with surrogates, and what was replaced in it."""
    docs = _table(spark, sf_dir, "documents").select("doc_id", "text")
    out = pii.replace_entities(docs, log_col="entities")
    return out.withColumn("n_entities", F.size("entities").cast("long"))


def op5_warc_transactions(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.round_trip(_table(spark, sf_dir, "pages"))


def op6_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents")
    return toxicity.scores(docs, toxicity.trained(docs, _table(spark, sf_dir, "labels")))


def op7_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(_table(spark, sf_dir, "documents"), vocabulary("word_bpe_49k.json"))


def op8_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    return piece_codec.encode_decode(_table(spark, sf_dir, "documents"), vocabulary("piece_bpe_32k.model"))


def op9_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_dedup(_table(spark, sf_dir, "documents"))


def op10_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    tree = sharding.regular_tree(8)
    return sharding.place(_table(spark, sf_dir, "documents"), tree, sharding.grown(tree, 8))


def near_dup_classes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(doc_id, class_id) of every document: classes of exact five-word Jaccard similarity 0.8 or more, short texts included.

    ``op_near_dups`` gives the candidates of equal MinHash values alone; words are runs of letters, as there.
    """
    docs = _table(spark, sf_dir, "documents").select("doc_id", F.array_join(T.words("text"), " ").alias("text"))
    roots = similar.similar_groups(docs)
    return docs.select("doc_id").join(roots, F.col("doc_id") == F.col("node"), "left").select("doc_id", F.coalesce("root", "doc_id").alias("class_id"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    every = (
        op1_simhash_near_dedup,
        op2_substring_dedup,
        op3_exact_topk,
        op4_pii_surrogates,
        op5_warc_transactions,
        op6_toxicity,
        op7_packing,
        op8_sentencepiece,
        op9_exact_dedup,
        op10_sharding,
        near_dup_classes,
    )
    return {f.__name__: f for f in every}


def oracle_sql() -> dict[str, str]:
    return {
        "op9_exact_dedup": r"""
            WITH t AS (
                SELECT doc_id, length(coalesce(text, '')) AS n,
                       sha256(regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]', '', 'g')) AS text_sha256
                FROM documents),
            r AS (
                SELECT *, first_value(doc_id) OVER w AS keep_id, row_number() OVER w AS k,
                       count(*) OVER (PARTITION BY text_sha256) AS group_size
                FROM t WINDOW w AS (PARTITION BY text_sha256 ORDER BY n DESC, doc_id))
            SELECT doc_id, keep_id, group_size, k = 1 AS kept, text_sha256 FROM r"""
    }
