"""From raw documents to packed training sequences.

Quality rules, one document of each group of near copies, repeated lines and passages out,
benchmark passages out, and the rest packed. Each stage works on all rows that
the one before kept, and all but the last return the columns of documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from tokenfold.llm import cgk_decontamination, chosen_path, compression_bands, line_dedup, packing, sparse_suffixes
from tokenfold.llm.common import settle, table


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the base rules or the compression bands reject go."""
    return compression_bands.keep_good(docs)


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of documents linked by a Jaccard similarity of 0.8 or more of their 5-word runs, the least id stays."""
    return chosen_path.drop_similar(docs)


def repeated_text(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines that an earlier document or line holds are cut out, and passages of 50 words or more that start anywhere in a line; n_chars follows."""
    passages = sparse_suffixes.later_passages(docs)
    return line_dedup.drop_repeated_units(docs, length="n_chars" if "n_chars" in docs.columns else None, passages=passages)


def benchmark_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with a benchmark item at up to a fifth of edits go."""
    return cgk_decontamination.drop_contaminated(docs, table(spark, sf_dir, "benchmark"))


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of documents in sequences of 2048 ids; text rows carry the ids themselves."""
    return packing.pack(docs)


STAGES = [
    ("quality rules", quality_rules),
    ("n-gram Jaccard join", near_copies),
    ("substring dedup", repeated_text),
    ("benchmark decontamination", benchmark_passages),
    ("packing", packed),
]

#: SQL has no tokenizer, zstandard or random walks; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; each result is written and read again as the next one's input."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = settle(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return STAGES[-1][1](spark, docs, sf_dir)
