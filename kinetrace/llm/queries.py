"""The queries of this subpackage: each applies an operator, with production parameters, to its whole table."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from kinetrace.llm import bpe, langid, maxscore, packing, pii, quality, simhash, toxicity, trie_join, warc


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _vocabulary() -> str:
    return public_tokenizers.path("byte_bpe_50k.json")


def queries() -> dict:
    docs = lambda s, d: _table(s, d, "documents")
    return {
        "op1_language_crf": lambda s, d: langid.predictions(docs(s, d)),
        "op2_best_fit_packing": lambda s, d: packing.pack(docs(s, d), _vocabulary()),
        "op3_simhash_trie_join": lambda s, d: trie_join.fingerprint_rows(docs(s, d)),
        "op4_quality_neighbours": lambda s, d: quality.predictions(docs(s, d), _table(s, d, "labels")),
        "op5_maxscore_topk": lambda s, d: maxscore.sampled_queries(_table(s, d, "embeddings")),
        "op6_warc_chunks": lambda s, d: warc.round_trip(_table(s, d, "pages")),
        "op7_bpe_backtracking": lambda s, d: bpe.round_trip_digests(docs(s, d), _vocabulary()),
        "op8_simhash_fingerprints": lambda s, d: simhash.edit_rows(docs(s, d)),
        "op9_disclosure_spans": lambda s, d: pii.span_rows(docs(s, d)),
        "op10_toxicity_pu": lambda s, d: toxicity.predictions(docs(s, d), _table(s, d, "labels")),
    }


def oracle_sql() -> dict[str, str]:
    return {"op5_maxscore_topk": maxscore.ORACLE_SQL, "op6_warc_chunks": warc.ORACLE_SQL}
