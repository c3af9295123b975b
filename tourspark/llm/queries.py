"""The registered queries of this subpackage, each over its whole table, and their SQL."""

from __future__ import annotations

from tourspark.llm import blockjoin, bpe, langid, mtree, packing, quality, secrets, sharding, simhash, wordpiece
from tourspark.session import read_table


def op1_quality_nbsvm(spark, sf_dir):
    docs = read_table(spark, sf_dir, "documents")
    return quality.score(docs, quality.train(docs, read_table(spark, sf_dir, "labels")))


def op2_mtree_top_k(spark, sf_dir):
    return mtree.top_k(read_table(spark, sf_dir, "embeddings"))


def op3_secret_scan(spark, sf_dir):
    return secrets.digest(read_table(spark, sf_dir, "documents"))


def op4_language_backoff(spark, sf_dir):
    docs = read_table(spark, sf_dir, "documents")
    return langid.identify(docs, langid.train(docs))


def op5_simhash_near_duplicates(spark, sf_dir):
    return simhash.near_duplicates(read_table(spark, sf_dir, "documents"))


def op6_block_matrix_join(spark, sf_dir):
    return blockjoin.neighbours(read_table(spark, sf_dir, "embeddings"))


def op7_cost_balanced_packing(spark, sf_dir):
    return packing.pack(read_table(spark, sf_dir, "documents"))


def op8_wordpiece_counts(spark, sf_dir):
    return wordpiece.token_counts(read_table(spark, sf_dir, "documents"))


def op9_bpe_merge_replay(spark, sf_dir):
    return bpe.code(read_table(spark, sf_dir, "documents"))


def op10_rendezvous_shards(spark, sf_dir):
    return sharding.shard_documents(read_table(spark, sf_dir, "documents"), 40)


def queries():
    return {
        "op1_quality_nbsvm": op1_quality_nbsvm,
        "op2_mtree_top_k": op2_mtree_top_k,
        "op3_secret_scan": op3_secret_scan,
        "op4_language_backoff": op4_language_backoff,
        "op5_simhash_near_duplicates": op5_simhash_near_duplicates,
        "op6_block_matrix_join": op6_block_matrix_join,
        "op7_cost_balanced_packing": op7_cost_balanced_packing,
        "op8_wordpiece_counts": op8_wordpiece_counts,
        "op9_bpe_merge_replay": op9_bpe_merge_replay,
        "op10_rendezvous_shards": op10_rendezvous_shards,
    }


def oracle_sql():
    return {
        "op2_mtree_top_k": mtree.ORACLE,
        "op3_secret_scan": secrets.oracle(),
        "op6_block_matrix_join": blockjoin.ORACLE,
        "op10_rendezvous_shards": sharding.ORACLE,
    }
