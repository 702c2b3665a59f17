"""Token ids as compressed binary shards with a shared dictionary and an index for single documents.

The corpus is encoded, each document's id array (little-endian, 2 or 4 bytes an id) becomes one zstandard frame of
its own, compressed with a dictionary that was trained on serialised id arrays, and frames are written in ascending
doc_id order.  Files hold blocks: the dictionary's hash, an index (doc_id, offset, number of ids), and the frames.
A reader finds a document by its block's first id and the offset index, and decompresses that frame alone.

The dictionary is trained on at most ``SAMPLE_DOCS`` whole documents, those with the smallest hash of their id, as far
as ``SAMPLE_CHARS`` characters go (a bound on the trainer's memory; every document is encoded, written and indexed).
Without enough samples it is empty.

A null text counts as empty and has the end id only.  Rows are ordered by doc_id, null ids first; rows that share one
stay side by side.  An empty table gives no rows.  Extra columns are not read.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from walkengine.llm.common import only, read_table, shuffle_partitions, staged
from walkengine.llm.vocab import library_encoder, load_tokenizer

SAMPLE_DOCS, SAMPLE_CHARS, DICTIONARY_BYTES, LEVEL = 1000, 16 << 20, 64 << 10, 3
#: Bytes of frames in a block.
BLOCK_BYTES = 1 << 20
END_ID = 0


def train_dictionary(samples: list[bytes], size: int = DICTIONARY_BYTES) -> bytes:
    """A zstandard dictionary, or none (empty bytes) when the samples are too few for the trainer."""
    import zstandard

    if len(samples) < 16:
        return b""
    try:
        return zstandard.train_dictionary(size, samples).as_bytes()
    except zstandard.ZstdError:
        return b""


def _dictionary(blob: bytes):
    import zstandard

    return zstandard.ZstdCompressionDict(blob) if blob else None


def _width(path: str) -> int:
    return 2 if load_tokenizer(path).get_vocab_size() <= 1 << 16 else 4


def sample_dictionary(docs: DataFrame, path: str, end_id: int = END_ID) -> bytes:
    """Trains on the documents whose id has one of the smallest hashes."""
    order = F.xxhash64(F.lit(7), "doc_id")
    sized = only(docs, "doc_id", "text").where("doc_id IS NOT NULL").select("doc_id", F.coalesce(F.length("text"), F.lit(0)).alias("n"))
    chosen, room = [], SAMPLE_CHARS
    for r in sized.orderBy(order, "doc_id", "n").limit(SAMPLE_DOCS).collect():
        if r.n <= room:
            chosen.append(r.doc_id)
            room -= r.n
    texts = only(docs, "doc_id", "text").where(F.col("doc_id").isin(chosen)).select("doc_id", "text")
    texts = texts.dropDuplicates(["doc_id"]).select("text")
    tokenizer, kind = load_tokenizer(path), f"<u{_width(path)}"
    texts = [r[0] or "" for r in texts.collect()]
    return train_dictionary(
        [np.array([*e.ids, end_id], kind).tobytes() for e in tokenizer.encode_batch_fast(texts, add_special_tokens=False)]
    )


FRAME = pa.schema([("doc_id", pa.int64()), ("n_tokens", pa.int64()), ("frame", pa.binary())])
BLOCK_DDL = (
    "shard int, block int, first_id long, n_docs int, n_null int, start long, n_tokens long, id_bytes int, dictionary string, "
    "index binary, frames binary"
)
BLOCK = pa.schema(
    [("shard", pa.int32()), ("block", pa.int32()), ("first_id", pa.int64()), ("n_docs", pa.int32()), ("n_null", pa.int32())]
    + [("start", pa.int64()), ("n_tokens", pa.int64()), ("id_bytes", pa.int32()), ("dictionary", pa.string())]
    + [("index", pa.binary()), ("frames", pa.binary())]
)


def frames(docs: DataFrame, path: str, dictionary: bytes, end_id: int = END_ID, spaced: bool = True) -> DataFrame:
    """doc_id, n_tokens and the compressed ids (with the end id) of every document."""
    width = _width(path)

    def compress(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import zstandard

        encoder = library_encoder(path, spaced)
        packer = zstandard.ZstdCompressor(level=LEVEL, dict_data=_dictionary(dictionary))
        end = np.array([end_id], f"<u{width}").tobytes()
        for batch in batches:
            for row, ids, bounds in encoder.encode(batch["text"]):
                raw, n = ids.astype(f"<u{width}").tobytes(), len(bounds) - 1
                coded = [packer.compress(raw[width * a : width * b] + end) for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist())]
                doc_ids = batch["doc_id"].slice(row, n).cast(pa.int64())
                yield pa.RecordBatch.from_arrays([doc_ids, pa.array(np.diff(bounds) + 1), pa.array(coded, pa.binary())], schema=FRAME)

    return only(docs, "doc_id", "text").mapInArrow(compress, "doc_id long, n_tokens long, frame binary")


def write_shards(docs: DataFrame, path: str, end_id: int = END_ID, spaced: bool = True) -> tuple[DataFrame, bytes]:
    """(written blocks in ascending doc_id order, dictionary).  Frames are staged first, so that sampling the range
    bounds and a lost executor cost no second encoding."""
    dictionary = sample_dictionary(docs, path, end_id)
    name, width = hashlib.sha256(dictionary).hexdigest(), _width(path)
    coded = staged(frames(docs, path, dictionary, end_id, spaced), "frames")

    def blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shard, block, start = TaskContext.get().partitionId(), 0, 0
        ids, sizes, held, weight = [], [], [], 0

        def close() -> pa.RecordBatch:
            offsets = np.cumsum([0, *map(len, held)])[:-1]
            known = [i for i in ids if i is not None]  # null ids come first and are written as 0
            index = np.array([[0] * (len(ids) - len(known)) + known, offsets, sizes], "<i8").tobytes()
            row = [shard, block, known[0] if known else None, len(ids), len(ids) - len(known), start, sum(sizes), width, name, index, b"".join(held)]
            return pa.RecordBatch.from_arrays([pa.array([v], t) for v, t in zip(row, BLOCK.types)], schema=BLOCK)

        for batch in batches:
            for doc_id, n, frame in zip(*(batch[c].to_pylist() for c in ("doc_id", "n_tokens", "frame"))):
                ids.append(doc_id)
                sizes.append(n)
                held.append(frame)
                weight += len(frame)
                if weight >= BLOCK_BYTES:
                    yield close()
                    block, start = block + 1, start + sum(sizes)
                    ids, sizes, held, weight = [], [], [], 0
        if ids:
            yield close()

    ordered = coded.repartitionByRange(shuffle_partitions(docs.sparkSession), F.asc_nulls_first("doc_id")).sortWithinPartitions(F.asc_nulls_first("doc_id"))
    return staged(ordered.mapInArrow(blocks, BLOCK_DDL), "token-shards"), dictionary


def read_block(index: bytes, n_docs: int, n_null: int, data: bytes, width: int, dictionary: bytes) -> Iterator[tuple[int | None, np.ndarray]]:
    """(doc_id, ids) of a block's documents; each frame is decompressed alone."""
    import zstandard

    unpack = zstandard.ZstdDecompressor(dict_data=_dictionary(dictionary))
    ids, offsets, sizes = np.frombuffer(index, "<i8").reshape(3, n_docs).tolist()
    view = memoryview(data)
    ids[:n_null] = [None] * n_null
    for doc_id, a, b, n in zip(ids, offsets, [*offsets[1:], len(data)], sizes):
        yield doc_id, np.frombuffer(unpack.decompress(view[a:b], max_output_size=n * width), f"<u{width}")


def read_document(blocks: DataFrame, dictionary: bytes, doc_id: int) -> np.ndarray | None:
    """The ids of one document: the block that may hold it is found by a pushed-down filter and its index."""
    row = blocks.where(F.col("first_id") <= doc_id).orderBy(F.desc("first_id")).limit(1).collect()
    found = dict(read_block(row[0]["index"], row[0]["n_docs"], row[0]["n_null"], row[0]["frames"], row[0]["id_bytes"], dictionary)) if row else {}
    return found.get(doc_id)


def read_shards(blocks: DataFrame, dictionary: bytes) -> DataFrame:
    """doc_id, start, n_tokens and ids_crc32 of every document, from the written blocks."""
    # one number for each file, so as many as there are shuffle partitions
    totals = dict(map(tuple, blocks.groupBy("shard").agg(F.sum("n_tokens")).collect()))
    shards = sorted(totals)
    base = dict(zip(shards, np.cumsum([0, *(totals[s] for s in shards)])[:-1].tolist()))
    expected = hashlib.sha256(dictionary).hexdigest()
    out = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("n_tokens", pa.int64()), ("ids_crc32", pa.int64())])

    def digest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):
                r = {name: batch[name][i].as_py() for name in batch.schema.names}
                if r["dictionary"] != expected:
                    raise ValueError(f"block {r['block']} of shard {r['shard']} was written with another dictionary")
                at, rows = base[r["shard"]] + r["start"], []
                for doc_id, ids in read_block(r["index"], r["n_docs"], r["n_null"], r["frames"], r["id_bytes"], dictionary):
                    rows.append((doc_id, at, len(ids), zlib.crc32(ids.astype("<u4").tobytes())))
                    at += len(ids)
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows)], schema=out)

    return blocks.mapInArrow(digest, "doc_id long, start long, n_tokens long, ids_crc32 long")


def op8_token_output(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    blocks, dictionary = write_shards(read_table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))
    return read_shards(blocks, dictionary)


QUERIES = {"op8_token_output": op8_token_output}
ORACLES: dict[str, str] = {}
