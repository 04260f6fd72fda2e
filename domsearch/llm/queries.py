"""The registered queries of this subpackage: thin digests of what the operators return."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .substring_dedup import dedup_substrings

    return dedup_substrings(_table(spark, sf_dir, "documents"))


def op2_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .decontamination import find_contained

    return find_contained(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "benchmark"))


def op3_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .ngram_join import jaccard_components

    return jaccard_components(_table(spark, sf_dir, "documents"))


def op4_embedding_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .embedding_dedup import near_duplicates

    return near_duplicates(_table(spark, sf_dir, "embeddings"))


def op5_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .toxicity import ToxicityModel

    docs = _table(spark, sf_dir, "documents")
    return ToxicityModel.fit(docs, _table(spark, sf_dir, "labels")).score(docs)


def op6_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .line_quality import LineQuality, held_out

    docs = _table(spark, sf_dir, "documents")
    labels = _table(spark, sf_dir, "labels").where(~held_out("doc_id"))
    return LineQuality.fit(docs, labels).score(docs).select("doc_id", held_out("doc_id").alias("held_out"), "score", "predicted")


def op7_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .source_mix import mix_sources

    mix = mix_sources(_table(spark, sf_dir, "documents"))
    shards = F.transform("draws", lambda d: d["shard"]).alias("shards")
    return mix.select("doc_id", "size", "source_size", "target", "taken", shards)


def op8_warc_derivatives(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .warc_derivatives import build_derivatives

    return build_derivatives(_table(spark, sf_dir, "pages"))


def op9_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .secret_scan import scan_secrets

    return scan_secrets(_table(spark, sf_dir, "documents"))


def op10_token_counts(spark: SparkSession, sf_dir: str, vocabulary: str | None = None) -> DataFrame:
    from .token_counts import count_tokens

    if vocabulary is None:
        import public_tokenizers

        vocabulary = public_tokenizers.path("byte_bpe_50k.json")
    return count_tokens(_table(spark, sf_dir, "documents"), vocabulary)


QUERIES = {f.__name__: f for f in (op1_substring_dedup, op2_benchmark_decontamination, op3_ngram_jaccard_join, op4_embedding_near_dedup, op5_toxicity, op6_quality_classifier, op7_source_mixing, op8_warc_derivatives, op9_secret_scan, op10_token_counts)}
OP2_SQL = r"""
with d as (select doc_id, list_filter(string_split_regex(lower(text), '[\x20\x09-\x0D]+'), lambda x: x <> '') w from documents),
b as (select item_id, list_filter(string_split_regex(lower(text), '[\x20\x09-\x0D]+'), lambda x: x <> '') w from benchmark),
bs as (select item_id, len(w) nw, unnest(range(1, greatest(len(w) - 4, 1) + 1)) i, w from b where len(w) > 0),
items as (select distinct item_id, least(nw, 5) n, array_to_string(w[i:i + 4], ' ') g from bs),
q as (select item_id, count(*) n_shingles from items group by 1),
sizes as (select distinct n from items),
ds as (select doc_id, n, w, unnest(range(1, len(w) - n + 2)) i from d, sizes where len(w) >= n),
grams as (select distinct doc_id, n, array_to_string(w[i:i + n - 1], ' ') g from ds),
hits as (select doc_id, item_id, count(*) n_shared from grams join items using (n, g) group by 1, 2)
select doc_id, item_id, n_shingles, n_shared, round(n_shared / n_shingles, 6) as containment
from hits join q using (item_id) where n_shared * 100 >= n_shingles * 80
"""
ORACLES: dict[str, str] = {"op2_benchmark_decontamination": OP2_SQL}
