"""Exact de-duplication by a Golomb-coded exchange of fingerprints.

1. Each source (scan partitions, cut by hash where they hold many documents) sorts the 64-bit fingerprints of its texts,
   codes the gaps of every owner's share with Golomb-Rice codes and sends one row per owner.
2. An owner merges the lists it got and answers each source with a bitmap over the list which that source sent:
   bit set = another source has the fingerprint too.
3. A source marks its documents whose bit is set, or whose fingerprint it holds twice itself, as suspects.
4. Only suspects are shuffled with their bytes: grouping by (digest, text) compares whole texts, and its partial
   aggregation leaves one row per task for a text however often it is repeated, so a hot group stays small.
5. Verified groups are joined back to their documents; the documents of a large group are dealt over several tasks.

Of equal texts the row with the largest doc_id stays.  A null text counts as empty, and empty texts are equal.
A null doc_id counts as smaller than any other.  Repeated rows (equal doc_id and text) count in ``group_size``; further columns pass through ``drop_copies``.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from walkengine.llm.common import only, read_table, shuffle_partitions, spread_join, staged, whole_text

#: Documents of a source, and fingerprints of an owner, on average at most.
SOURCE = 1 << 21


def rice_encode(values: np.ndarray) -> tuple[int, bytes]:
    """(k, code) of a sorted array of unsigned 64-bit numbers: quotients of the gaps in unary, then k low bits each."""
    gaps = np.diff(values.astype(np.uint64), prepend=np.uint64(0))
    mean = max(1.0, float(gaps.astype(np.float64).mean()))
    k = min(63, max(0, int(np.log2(mean * 0.6931)) if mean > 1.5 else 0))
    quotient = (gaps >> np.uint64(k)).astype(np.int64)
    ends = np.cumsum(quotient + 1)
    unary = np.zeros(int(ends[-1]), np.uint8)
    unary[ends - 1] = 1
    low = ((gaps[:, None] >> np.arange(k, dtype=np.uint64)) & np.uint64(1)).astype(np.uint8)
    return k, np.packbits(np.concatenate([unary, low.ravel()])).tobytes()


def rice_decode(code: bytes, k: int, n: int) -> np.ndarray:
    bits = np.unpackbits(np.frombuffer(code, np.uint8))
    ones = np.flatnonzero(bits)[:n]
    quotient = np.diff(ones, prepend=-1) - 1
    low = bits[ones[-1] + 1 : ones[-1] + 1 + n * k].reshape(n, k).astype(np.uint64)
    rest = (low << np.arange(k, dtype=np.uint64)).sum(axis=1, dtype=np.uint64) if k else np.zeros(n, np.uint64)
    return np.cumsum((quotient.astype(np.uint64) << np.uint64(k)) + rest, dtype=np.uint64)


def _owner_lists(prints: np.ndarray, owners: int) -> Iterator[tuple[int, np.ndarray]]:
    """Sorted distinct fingerprints by owner; an owner has an equal range of the fingerprints."""
    distinct = np.unique(prints)
    owner = ((distinct >> np.uint64(32)) * np.uint64(owners)) >> np.uint64(32)
    edges = np.flatnonzero(np.diff(owner.astype(np.int64))) + 1
    for part in np.split(distinct, edges):
        if len(part):
            yield int(((part[0] >> np.uint64(32)) * np.uint64(owners)) >> np.uint64(32)), part


def _prints(column) -> np.ndarray:
    return np.asarray(column).astype(np.int64).view(np.uint64)


def suspects(hashed: DataFrame, owners: int) -> DataFrame:
    """doc_id of the documents whose fingerprint occurs elsewhere.  ``hashed``: source, doc_id, fingerprint."""

    def send(rows: pd.DataFrame) -> pd.DataFrame:
        out = []
        for owner, values in _owner_lists(_prints(rows["fingerprint"]), owners):
            k, code = rice_encode(values)
            out.append((rows["source"].iloc[0], owner, k, len(values), code))
        return pd.DataFrame(out, columns=["source", "owner", "k", "n", "code"])

    def answer(rows: pd.DataFrame) -> pd.DataFrame:
        lists = [rice_decode(c, k, n) for c, k, n in zip(rows["code"], rows["k"], rows["n"])]
        values, counts = np.unique(np.concatenate(lists), return_counts=True)
        shared = values[counts > 1]
        bits = [np.packbits(np.isin(x, shared, assume_unique=True)).tobytes() for x in lists]
        return pd.DataFrame({"source": rows["source"], "owner": rows["owner"], "bits": bits})

    def mark(rows: pa.Table, answers: pa.Table) -> pa.Table:
        prints = _prints(rows["fingerprint"])
        flags = dict(zip(answers["owner"].to_pylist(), answers["bits"].to_pylist()))
        values, inverse, counts = np.unique(prints, return_inverse=True, return_counts=True)
        marked = counts > 1
        begin = 0
        for owner, part in _owner_lists(values, owners):
            bits = np.unpackbits(np.frombuffer(flags[owner], np.uint8))[: len(part)]
            marked[begin : begin + len(part)] |= bits.astype(bool)
            begin += len(part)
        return rows.select(["doc_id"]).filter(pa.array(marked[inverse]))

    id_type = hashed.schema["doc_id"].dataType.simpleString()
    sent = hashed.groupBy("source").applyInPandas(send, "source int, owner int, k int, n int, code binary")
    answers = sent.groupBy("owner").applyInPandas(answer, "source int, owner int, bits binary")
    return hashed.groupBy("source").cogroup(answers.groupBy("source")).applyInArrow(mark, f"doc_id {id_type}").distinct()


def groups(docs: DataFrame) -> DataFrame:
    """One row per document: doc_id, keep_id, group_size, kept, text_sha256."""
    spark = docs.sparkSession
    rows = only(docs, "doc_id", "text").select("doc_id", whole_text().alias("text"))
    digest = F.sha2(F.encode("text", "UTF-8"), 256)
    tasks = shuffle_partitions(spark)
    hashed = staged(
        rows.select("doc_id", digest.alias("text_sha256"), F.pmod(F.spark_partition_id(), F.lit(tasks)).alias("scan")).withColumn(
            "fingerprint", F.xxhash64("text_sha256")
        ),
        "fingerprints",
    )
    # a source and an owner are held whole by a task, so there are more of them where there are more documents
    parts = 1 + hashed.count() // (tasks * SOURCE)
    source = F.col("scan") * F.lit(parts) + F.pmod(F.xxhash64("fingerprint", "doc_id"), F.lit(parts))
    sent = hashed.select(source.cast("int").alias("source"), "doc_id", "fingerprint")
    suspect = suspects(sent, tasks * parts)
    verified = staged(
        rows.join(suspect.withColumnRenamed("doc_id", "_suspect"), F.col("doc_id").eqNullSafe(F.col("_suspect")), "left_semi")
        .groupBy(digest.alias("text_sha256"), "text")
        .agg(F.max("doc_id").alias("keep_id"), F.count("*").alias("group_size"))
        .where("group_size > 1")
        .select("text_sha256", "keep_id", "group_size"),
        "groups",
    )
    return (
        spread_join(hashed.select("doc_id", "text_sha256"), verified, "text_sha256", "group_size")
        .select(
            "doc_id",
            F.when(F.col("group_size").isNull(), F.col("doc_id")).otherwise(F.col("keep_id")).alias("keep_id"),
            F.coalesce("group_size", F.lit(1).cast("long")).alias("group_size"),
            "text_sha256",
        )
        .select("doc_id", "keep_id", "group_size", F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), "text_sha256")
    )


def drop_copies(docs: DataFrame) -> DataFrame:
    """The documents that stay, with their own columns.  Rows that share doc_id and text stay or go together."""
    keep = groups(docs).where("kept").select(F.col("doc_id").alias("_kept_id")).distinct()
    return docs.join(keep, docs["doc_id"].eqNullSafe(keep["_kept_id"]), "left_semi")


def op4_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return groups(read_table(spark, sf_dir, "documents"))


QUERIES = {"op4_exact_dedup": op4_exact_dedup}
ORACLES = {
    "op4_exact_dedup": """
SELECT doc_id, max(doc_id) OVER g AS keep_id, count(*) OVER g AS group_size,
       doc_id = max(doc_id) OVER g AS kept, sha256(coalesce(text, '')) AS text_sha256
FROM documents WINDOW g AS (PARTITION BY coalesce(text, ''))"""
}
