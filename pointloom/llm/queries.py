"""The corpus operators' queries for the driver, and their SQL where SQL can express them."""

from __future__ import annotations

import public_tokenizers

from pointloom.llm import bpe, chat, egojoin, linededup, lm, mixing, quality, secrets, simhash, topk
from pointloom.llm.common import table

#: A parameter of the byte-level BPE operator.
VOCABULARY = "byte_bpe_50k.tiktoken"


def op1_quality(spark, sf_dir):
    return quality.quality_report(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op2_mix_sources(spark, sf_dir):
    return mixing.mix_report(table(spark, sf_dir, "documents").select("doc_id", "text", "source"))


def op3_simhash_groups(spark, sf_dir):
    return simhash.simhash_report(table(spark, sf_dir, "documents"))


def op4_embedding_dedup(spark, sf_dir):
    return egojoin.near_duplicates(table(spark, sf_dir, "embeddings"))


def op5_chat_format(spark, sf_dir):
    return chat.chat_report(table(spark, sf_dir, "conversations"))


def op6_bpe(spark, sf_dir):
    return bpe.bpe_report(table(spark, sf_dir, "documents"), public_tokenizers.path(VOCABULARY), public_tokenizers.PATTERN)


def op7_lm_score(spark, sf_dir):
    return lm.lm_report(table(spark, sf_dir, "documents"))


def op8_secret_scan(spark, sf_dir):
    return secrets.secret_report(table(spark, sf_dir, "documents"))


def op9_line_dedup(spark, sf_dir):
    return linededup.line_report(table(spark, sf_dir, "documents"))


def op10_topk_search(spark, sf_dir):
    return topk.top_k(table(spark, sf_dir, "embeddings"))


QUERIES = {
    f.__name__: f
    for f in (
        op1_quality, op2_mix_sources, op3_simhash_groups, op4_embedding_dedup, op5_chat_format, op6_bpe, op7_lm_score, op8_secret_scan, op9_line_dedup, op10_topk_search,
    )
}
ORACLES = {
    "op2_mix_sources": mixing.ORACLE,
    "op4_embedding_dedup": egojoin.ORACLE,
    "op5_chat_format": chat.ORACLE,
    "op9_line_dedup": linededup.ORACLE,
    "op10_topk_search": topk.ORACLE,
}
