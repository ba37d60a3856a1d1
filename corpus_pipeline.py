"""The corpus pipeline: quality, toxicity, near-duplicates, benchmark contamination, tokens.

Each stage takes ``(spark, docs, sf_dir)``, works on all rows that its predecessor kept and returns
the columns of ``documents``; the last returns token ids. ``run`` writes each stage's result to the
shared folder and reads it again as the next stage's documents. Labels and benchmark items come
from the tables in ``sf_dir``. Null and empty texts, repeated rows and empty tables pass through
every stage as its operator defines for them.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from revnet.llm import cotraining, decontaminate, sentencepiece_bpe, simhash, toxicity_cnn
from revnet.llm._common import materialize

#: Result rows have no SQL form: two stages are learned models and one is a tokenizer.
ORACLE_SQL = None

_BROADCAST_IDS = 1_000_000


def _without(docs: DataFrame, rejected: DataFrame) -> DataFrame:
    """Rows whose doc_id is not in ``rejected``, which is broadcast only if proven small."""
    rejected = materialize(rejected.select("doc_id").where("doc_id is not null").distinct(), "rejected")
    if rejected.limit(_BROADCAST_IDS + 1).count() <= _BROADCAST_IDS:
        rejected = F.broadcast(rejected)
    return docs.join(rejected, "doc_id", "left_anti").select(docs.columns)


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep documents that the co-trained classifier takes for good ones."""
    model = cotraining.fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"), cotraining.learned_rows())
    return cotraining.scored(docs, model, prefix="_stage_").where("_stage_keep").select(docs.columns)


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep documents below the toxicity cut."""
    model = toxicity_cnn.fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"), toxicity_cnn.learned_rows())
    return toxicity_cnn.scored(docs, model, prefix="_stage_").where("_stage_predicted = 0").select(docs.columns)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep of each group of linked fingerprints the document of smallest id; a repeated id stays once."""
    comp = materialize(simhash.simhash_components(docs), "components")
    kept = _without(docs, comp.where("doc_id <> component_id"))
    if not comp.groupBy("doc_id").count().where("doc_id is not null and count > 1").isEmpty():
        kept = kept.where("doc_id is not null").dropDuplicates(["doc_id"]).unionByName(kept.where("doc_id is null"))
    return kept


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep documents that the benchmark does not contaminate."""
    marks = decontaminate.contamination(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
    return _without(docs, marks.where("contaminated"))


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of the kept documents, with digests of ids and decoded text."""
    return sentencepiece_bpe.encode_documents(docs, outputs=("ids", "ids_sha256", "decoded_sha256"))


STAGES = [
    ("quality classifier", quality),
    ("toxicity", toxicity),
    ("SimHash near-dedup", near_duplicates),
    ("benchmark decontamination", decontamination),
    ("SentencePiece encoding and decoding", tokens),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents in ``sf_dir``."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for i, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i < len(STAGES) - 1:
            docs = materialize(docs, f"stage{i}")
    return docs
