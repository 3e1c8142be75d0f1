"""Queries and DuckDB oracles of the training-data operators."""

from __future__ import annotations

from . import chat, decontam, jaccard, pieces, secrets, shards, topk, toxicity, urls, warc

QUERIES = {
    "op1_sentencepiece": pieces.op1,
    "op2_ngram_jaccard_join": jaccard.op2,
    "op3_exact_topk": topk.op3,
    "op4_warc": warc.op4,
    "op5_decontamination": decontam.op5,
    "op6_secret_scan": secrets.op6,
    "op7_chat_format": chat.op7,
    "op8_toxicity": toxicity.op8,
    "op9_sharding": shards.op9,
    "op10_url_filter": urls.op10,
    "secret_base_columns": secrets.base_columns,
}

ORACLES = {
    "op2_ngram_jaccard_join": jaccard.OP2_SQL,
    "op3_exact_topk": topk.OP3_SQL,
    "op4_warc": warc.OP4_SQL,
    "op5_decontamination": decontam.OP5_SQL,
    "op7_chat_format": chat.OP7_SQL,
    "op9_sharding": shards.OP9_SQL,
    "op10_url_filter": urls.OP10_SQL,
    "secret_base_columns": secrets.BASE_SQL,
}
