"""Documents to token ids in five stages, each of which reads what the one before has written."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from claimfold.llm import minhash, mixing, quality, queries, substring
from claimfold.llm.shared import settle


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rejected documents go; so do null and empty texts, which have too few words.  Repeated rows are judged each alone."""
    return quality.screen(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of similarity 0.8 or more stays, the one of the smallest id; so does each row without an id.

    Rows that share an id are judged each by its text; of those with one text, one stays.
    """
    return minhash.deduplicate(docs, percent=80)


def substring_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Repeated passages leave the texts; n_chars follows.  A null text becomes an empty one; no row goes."""
    keep = tuple(c for c in docs.columns if c not in ("doc_id", "text"))
    cut = substring.remove_repeats(docs, keep=keep, kept="text")
    if "n_chars" in docs.columns:
        cut = cut.withColumn("n_chars", F.char_length("text").cast(docs.schema["n_chars"].dataType))
    return cut.select(*[F.col(f"`{c}`") for c in docs.columns])


def source_mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document as often as the mix takes it: never where it has no words.  A null source is a source."""
    return mixing.sample(docs)


def bpe_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256) of every row, repeated ones too; a null text counts as empty."""
    return queries.bpe_digests(docs)


STAGES = [
    ("quality_rules", quality_rules),
    ("near_duplicates", near_duplicates),
    ("substring_dedup", substring_dedup),
    ("source_mixing", source_mixing),
    ("bpe_tokens", bpe_tokens),
]

#: The mix draws by hashes, which SQL elsewhere lacks; tests hold each stage, and run(), against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = queries.documents(spark, sf_dir)
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = settle(docs, f"pipeline-{name}")
    return docs
