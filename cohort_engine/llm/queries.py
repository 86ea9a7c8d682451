"""The registered queries of the training-data operators, with production parameters."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import embed_graph, jaccard_tree, langid, mixing, packing, quality_rules, secrets, site_quality, suffix_dedup, warc
from .common import table


def op1_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.judge(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op2_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = warc.round_trip(table(spark, sf_dir, "pages"))
    return r.select(F.col("key").cast("long").alias("page_id"), "payload_bytes", "payload_digest", "record_type", F.col("refers_to").cast("long").alias("refers_to"))


def op3_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup.deduplicate(table(spark, sf_dir, "documents"))


def op4_embedding_graph(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embed_graph.links(table(spark, sf_dir, "embeddings"))


def op5_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_tree.link_components(table(spark, sf_dir, "documents"))


def op6_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


def op7_site_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hosts are sources and paths are a source's languages; bad means quality 0 or toxic 1."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", F.col("source").alias("host"), F.concat_ws("/", F.coalesce("source", F.lit("")), F.coalesce("lang", F.lit(""))).alias("path"))
    bad = ((F.col("quality") == 0) | (F.col("toxic") == 1)).cast("int")
    return site_quality.classify(docs, table(spark, sf_dir, "labels").select("doc_id", bad.alias("bad")))


def op8_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(table(spark, sf_dir, "documents"))


def op9_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return langid.learn_and_identify(table(spark, sf_dir, "documents"))


def op10_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    d = secrets.scan(docs, secrets.train(docs))
    n = lambda k: F.size(F.filter("base", lambda x: x["k"] == k)).cast("long")
    counts = [n(k).alias(f"n_{kind}") for k, kind in enumerate(secrets.KINDS[:3])]
    return d.select("doc.doc_id", *counts, F.sha2(secrets.joined(F.col("base")), 256).alias("base_sha256"), secrets.joined(F.col("all")).alias("spans"))


def queries():
    return {f.__name__: f for f in (op1_quality_rules, op2_warc, op3_suffix_dedup, op4_embedding_graph, op5_jaccard_join, op6_mixing, op7_site_quality, op8_packing, op9_language_id, op10_secret_scan)}


def oracle_sql() -> dict[str, str]:
    """DuckDB SQL, where SQL can express the result."""
    return {
        "op2_warc": """
            with p as (select page_id, encode(coalesce(html, '')) as b from pages),
                 q as (select page_id, octet_length(b) as n, sha1(b) as d from p),
                 r as (select *, max(page_id) over (partition by d, n) as top from q)
            select page_id, n as payload_bytes, d as payload_digest,
                   case when n >= 1000 and top <> page_id then 'revisit' else 'response' end as record_type,
                   case when n >= 1000 and top <> page_id then top end as refers_to
            from r""",
    }
