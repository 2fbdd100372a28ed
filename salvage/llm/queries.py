"""The queries of this subpackage and their SQL."""

from __future__ import annotations

from salvage.llm import language_id, license_scan, mixing, packing, sharding, simhash, syncmers, toxicity, url_filter, vector_search
from salvage.llm.common import table


def op1_exact_topk(spark, sf_dir):
    return vector_search.embedding_neighbours(table(spark, sf_dir, "embeddings"))


def op2_toxicity(spark, sf_dir):
    return toxicity.toxicity_digest(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op3_license_scan(spark, sf_dir):
    return license_scan.license_digest(table(spark, sf_dir, "documents"))


def op4_url_filter(spark, sf_dir):
    return url_filter.judge_urls(table(spark, sf_dir, "pages").select("page_id", "url")).drop("url")


def op5_source_mix(spark, sf_dir):
    return mixing.mix_digest(table(spark, sf_dir, "documents"))


def op6_syncmer_fingerprints(spark, sf_dir):
    return syncmers.fingerprint_digest(table(spark, sf_dir, "documents"))


def op7_language_id(spark, sf_dir):
    return language_id.identify_corpus(table(spark, sf_dir, "documents"), table(spark, sf_dir, "pages"))


def op8_bin_slack_packing(spark, sf_dir):
    return packing.pack_documents(table(spark, sf_dir, "documents"))


def op9_simhash_anchors(spark, sf_dir):
    return simhash.near_duplicate_digest(table(spark, sf_dir, "documents"))


def op10_feistel_sharding(spark, sf_dir):
    return sharding.document_shards(table(spark, sf_dir, "documents"))


def queries():
    named = [op1_exact_topk, op2_toxicity, op3_license_scan, op4_url_filter, op5_source_mix, op6_syncmer_fingerprints, op7_language_id, op8_bin_slack_packing, op9_simhash_anchors, op10_feistel_sharding]
    return {f.__name__: f for f in named}


def oracle_sql():
    return {"op1_exact_topk": vector_search.NEIGHBOURS_SQL, "op4_url_filter": url_filter.judge_sql()}
