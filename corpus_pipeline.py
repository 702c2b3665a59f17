"""The corpus pipeline: quality rules, exact dedup, near dedup, repeated passages, packing."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from walkengine.llm.exact_dedup import drop_copies
from walkengine.llm.minhash_forest import drop_near_copies
from walkengine.llm.packing import pack
from walkengine.llm.quality_rules import filter_documents
from walkengine.llm.suffix_dedup import remove_repeats
from walkengine.llm.vocab import SMALL
from walkengine.session import read_table, staged


def pack_documents(docs: DataFrame) -> DataFrame:
    """The pieces of all sequences, by the vocabulary that op10 uses."""
    import public_tokenizers

    return pack(docs, public_tokenizers.path("word_bpe_49k.json"), room=SMALL)


#: (name, function of (spark, docs, sf_dir)); each works on all that its predecessor kept.
STAGES = [
    ("quality_rules", lambda spark, docs, sf_dir: filter_documents(docs)),
    ("exact_dedup", lambda spark, docs, sf_dir: drop_copies(docs)),
    ("near_dedup", lambda spark, docs, sf_dir: drop_near_copies(docs)),
    ("repeated_passages", lambda spark, docs, sf_dir: remove_repeats(docs)),
    ("packing", lambda spark, docs, sf_dir: pack_documents(docs)),
]

#: SQL can't express all stages; tests hold run() against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The result of all stages over documents; each stage is written as Parquet and read again by the next."""
    docs = read_table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = staged(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
