"""The corpus pipeline: toxicity, exact copies, near copies, mixing, byte-level BPE.

Each stage takes (spark, docs, sf_dir), works on all that its predecessor kept and
returns a DataFrame that is written as Parquet and read again for the next. All but
the last return the columns of documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame

from trianglestream.llm.bpe import token_digests
from trianglestream.llm.common import materialize
from trianglestream.llm.exact_dedup import drop_exact_copies
from trianglestream.llm.mixing import mix
from trianglestream.llm.near_dedup import drop_near_copies
from trianglestream.llm.toxicity import drop_toxic

VOCABULARY = "byte_bpe_multi_50k.tiktoken"


def toxicity(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents the network rejects go, at a score of 0.5; it learns from the labels of the table. Null and empty texts stay."""
    return drop_toxic(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def exact_dedup(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of texts equal but for the case of A-Z the row of the largest doc_id stays; rows without doc_id stand behind others."""
    return drop_exact_copies(docs)


def near_dedup(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each class of near duplicates the row of the least doc_id stays; empty texts and rows without doc_id all stay."""
    return drop_near_copies(docs)


def mixing(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents are drawn by calibrated probabilities towards tempered source, language and topic shares, 80 % of tokens."""
    return mix(docs)


def tokens(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens, ids_sha256 and decoded_sha256 of every row that is left."""
    import public_tokenizers

    return token_digests(docs, public_tokenizers.path(VOCABULARY), public_tokenizers.PATTERN)


STAGES = [("toxicity", toxicity), ("exact dedup", exact_dedup), ("near dedup", near_dedup), ("mixing", mixing), ("byte-level BPE", tokens)]

#: A trained network decides the first stage, which SQL cannot express.
ORACLE_SQL = None


def run(spark, sf_dir: str) -> DataFrame:
    """All stages over the whole table of documents; every stage but the last is written and read again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for n, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if n < len(STAGES) - 1:
            docs = materialize(docs, f"stage{n}")
    return docs
