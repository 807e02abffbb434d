"""A corpus pipeline of five stages; each stage's rows are written as Parquet and reread by the next."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from kbmap.llm import mixing, pieces, pii, quality, simhash
from kbmap.llm.common import DOCUMENT_COLUMNS, Cut

#: Needs a tokenizer file; its place is a parameter.
PIECE_MODEL = "piece_bpe_32k.model"


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that every quality rule keeps."""
    return quality.keep_good(docs.select(*DOCUMENT_COLUMNS))


def simhash_near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies (five-word shingles, similarity 0.8)."""
    return simhash.keep_one_of_each(docs.select(*DOCUMENT_COLUMNS), 0.8)


def redact_pii(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with personal data, disguised or not, replaced by its kind."""
    return pii.redact_documents(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """A sample of the documents whose tokens follow the target weights."""
    return mixing.keep_mixed(docs.select(*DOCUMENT_COLUMNS), spark.read.parquet(f"{sf_dir}/embeddings.parquet"))


def sentencepiece_encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, piece ids, their number and checksum, and whether decoding gives the text back."""
    import public_tokenizers

    return pieces.encode(docs, public_tokenizers.path(PIECE_MODEL))


STAGES = [
    ("quality rules", quality_rules),
    ("SimHash near-dedup", simhash_near_dedup),
    ("PII", redact_pii),
    ("mixing sources to target weights", mix_sources),
    ("SentencePiece encoding and decoding", sentencepiece_encode),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages applied to ``documents``."""
    cut = Cut(spark)
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs = cut(docs)
    return docs


#: The stages fold, hash and sample in ways that SQL doesn't express; tests hold them against brute force.
ORACLE_SQL = None
