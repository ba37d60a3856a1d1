"""Queries of this subpackage, by name, and their SQL where DuckDB can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import cotraining, decontaminate, histogram_shards, licences, ngram_lm, sentencepiece_bpe, site_style_tree, toxicity_cnn, vector_graph
from .simhash import near_duplicates


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_histogram_shards": histogram_shards.sharded,
        "op2_cotraining": cotraining.quality,
        "op3_simhash": near_duplicates,
        "op4_decontaminate": decontaminate.decontamination,
        "op5_sentencepiece": sentencepiece_bpe.encoding,
        "op6_vector_graph": vector_graph.vector_duplicates,
        "op7_licences": licences.licence_scan,
        "op8_ngram_lm": ngram_lm.lm_scores,
        "op9_site_style_tree": site_style_tree.main_texts,
        "op10_toxicity": toxicity_cnn.toxicity,
    }


def oracle_sql() -> dict[str, str]:
    return {"op4_decontaminate": decontaminate.SQL, "op7_licences": licences.sql()}
