"""A corpus pipeline: language, quality, near copies, benchmark leaks, packed sequences.

Every stage but the last returns the columns of ``documents``. Each works on all that the one before it
kept: models are fitted on that, counts and candidates cover all of it. Each begins with the executors' heaps as small as they can be.
"""

from __future__ import annotations

from catchment.llm.common import hand_back, materialize
from catchment.llm.decontaminate import drop_contaminated
from catchment.llm.language_id import drop_unidentified
from catchment.llm.ngram_join import keep_one
from catchment.llm.packing import pack, vocabulary_path
from catchment.llm.quality import drop_poor


def language_id(spark, docs, sf_dir):
    """Documents without a language go."""
    hand_back(spark)
    return drop_unidentified(docs)


def quality_classifier(spark, docs, sf_dir):
    """Documents predicted as poor go."""
    hand_back(spark)
    return drop_poor(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def ngram_jaccard_join(spark, docs, sf_dir):
    """The document with the least id of each near-copy group stays."""
    hand_back(spark)
    return keep_one(docs)


def benchmark_decontamination(spark, docs, sf_dir):
    """Documents that hold a benchmark passage go."""
    hand_back(spark)
    return drop_contaminated(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def best_fit_packing(spark, docs, sf_dir):
    """Pieces of the remaining documents and their places in sequences."""
    hand_back(spark)
    return pack(docs.select("doc_id", "text"), vocabulary_path())


STAGES = [
    ("language ID", language_id),
    ("quality classifier", quality_classifier),
    ("n-gram Jaccard join", ngram_jaccard_join),
    ("benchmark decontamination", benchmark_decontamination),
    ("best-fit packing", best_fit_packing),
]
#: Learned models, latent retrieval and packing are beyond SQL; tests/llm holds the stages against brute force.
ORACLE_SQL = None


def run(spark, sf_dir):
    """All stages over ``documents``; each result is written to the shared folder and read by the next stage."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for number, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if number + 1 < len(STAGES):
            docs = materialize(docs, f"stage{number}")
    return docs
