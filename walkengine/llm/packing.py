"""Packing documents into sequences of a fixed number of tokens.

Documents are dealt by a hash into groups of about ``GROUP_DOCS`` (the number of groups grows with the table), and
each group is packed alone.  A document's whole sequences are cut off first; the rests are placed first-fit
decreasing, where a tournament tree over bin capacities finds the first bin that still fits.  Then pieces of the
emptiest bins fill the gaps of the fuller ones, and the one bin that stays open is cut into powers of two, which
need no padding.  So a group has no padding at all, and only a bin's gap or the open bin ever cuts a rest.

A null text counts as empty: it has the end id only, which is packed like any other token.  Rows are packed one by
one, so repeated rows are packed as often as they come (equal rows share a group); an empty table gives no rows.  Extra columns are not read.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from walkengine.llm.common import only, read_table
from walkengine.llm.vocab import LARGE, Room, library_encoder

LENGTH, END_ID, GROUP_DOCS = 4096, 2, 1024
#: Groups that a task packs, one after the other.
GROUPS_A_TASK = 4

Piece = tuple[int, int, int]  # document of the group, first token, number of tokens


def first_fit_decreasing(sizes: list[int], capacity: int) -> list[list[int]]:
    """Bins of item numbers.  tree[1] is the root of a tournament over the room left in each bin."""
    leaves = 1 << max(0, len(sizes) - 1).bit_length()
    tree, bins = [capacity] * (2 * leaves), [[] for _ in range(leaves)]
    for item in sorted(range(len(sizes)), key=lambda i: -sizes[i]):
        size, node = sizes[item], 1
        while node < leaves:  # the left child if it fits: the first bin wins
            node *= 2
            if tree[node] < size:
                node += 1
        bins[node - leaves].append(item)
        tree[node] -= size
        while node > 1:
            node //= 2
            tree[node] = max(tree[2 * node], tree[2 * node + 1])
    return [b for b in bins if b]


def close_gaps(bins: list[list[Piece]], capacity: int) -> list[list[Piece]]:
    """Full sequences, then the open bin cut into powers of two (none if all are full)."""
    fill = lambda b: sum(p[2] for p in b)
    bins = sorted((list(b) for b in bins), key=fill, reverse=True)
    i, j = 0, len(bins) - 1
    room, left = (capacity - fill(b) for b in (bins[0], bins[-1])) if bins else (0, 0)
    while i < j:
        if room == 0:
            i += 1
            room = capacity - fill(bins[i])
            continue
        doc, start, n = bins[j].pop()
        take = min(n, room)
        bins[i].append((doc, start + n - take, take))
        room -= take
        if n > take:
            bins[j].append((doc, start, n - take))
        if not bins[j]:
            j -= 1
    bins = [b for b in bins if b]
    if bins and fill(bins[-1]) < capacity:
        rest = bins.pop()[::-1]
        total = fill(rest)
        for bit in reversed(range(total.bit_length())):
            if total >> bit & 1:
                want, part = 1 << bit, []
                while want:
                    doc, start, n = rest.pop()
                    part.append((doc, start, min(n, want)))
                    if n > want:
                        rest.append((doc, start + want, n - want))
                    want -= part[-1][2]
                bins.append(part)
    return bins


def pack_sizes(sizes: list[int], capacity: int = LENGTH) -> list[list[Piece]]:
    """Sequences of pieces for documents of these sizes."""
    whole = [[(d, k * capacity, capacity)] for d, n in enumerate(sizes) for k in range(n // capacity)]
    rests = [(d, n - n % capacity, n % capacity) for d, n in enumerate(sizes) if n % capacity]
    return whole + close_gaps([[rests[i] for i in b] for b in first_fit_decreasing([r[2] for r in rests], capacity)], capacity)


ENCODED = pa.schema(
    [("doc_id", pa.int64()), ("doc_tokens", pa.int64()), ("whole_crc", pa.list_(pa.int64())), ("rest", pa.binary())]
)


def encode(docs: DataFrame, path: str, length: int = LENGTH, end_id: int = END_ID, spaced: bool = False, room: Room = LARGE) -> DataFrame:
    """doc_id, doc_tokens, the CRC of each whole sequence, and the ids after these (only they are shuffled)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = library_encoder(path, spaced, room)
        end = np.array([end_id], "<u4").tobytes()
        for batch in batches:
            for row, ids, bounds in encoder.encode(batch["text"]):
                raw, crcs, rests = ids.astype("<u4").tobytes(), [], []
                for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist()):
                    one = raw[4 * a : 4 * b] + end
                    cut = len(one) - len(one) % (4 * length)
                    crcs.append([zlib.crc32(one[k : k + 4 * length]) for k in range(0, cut, 4 * length)])
                    rests.append(one[cut:])
                n = len(rests)
                columns = [batch["doc_id"].slice(row, n).cast(pa.int64()), pa.array(np.diff(bounds) + 1)]
                columns += [pa.array(crcs, pa.list_(pa.int64())), pa.array(rests, pa.binary())]
                yield pa.RecordBatch.from_arrays(columns, schema=ENCODED)

    ddl = "doc_id long, doc_tokens long, whole_crc array<long>, rest binary"
    return only(docs, "doc_id", "text").mapInArrow(run, ddl)


def pack(docs: DataFrame, path: str, length: int = LENGTH, end_id: int = END_ID, spaced: bool = False, seed: int = 11, room: Room = LARGE) -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset."""
    groups = max(1, -(-docs.count() // GROUP_DOCS))
    coded = encode(docs, path, length, end_id, spaced, room)
    deal = F.xxhash64("doc_id", "doc_tokens", "whole_crc", "rest", F.lit(seed))  # ids may be null or repeat
    coded = coded.withColumn("deal", F.pmod(deal, F.lit(groups))).repartition(-(-groups // GROUPS_A_TASK), "deal")

    def run(group: pa.Table) -> pa.Table:
        doc_ids, tokens, crcs, rests, deal = (group[c].to_pylist() for c in ("doc_id", "doc_tokens", "whole_crc", "rest", "deal"))
        rows = []
        for k, sequence in enumerate(pack_sizes(tokens, length)):
            offset = 0
            for d, start, n in sequence:
                cut = tokens[d] - tokens[d] % length
                crc = crcs[d][start // length] if start < cut else zlib.crc32(rests[d][4 * (start - cut) : 4 * (start - cut + n)])
                rows.append((doc_ids[d], start, n, crc, tokens[d], (deal[0] << 32) + k, offset))
                offset += n
        return pa.Table.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows)], names=COLUMNS)

    return coded.groupBy("deal").applyInArrow(run, ", ".join(f"{c} long" for c in COLUMNS))


COLUMNS = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]


def op10_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return pack(read_table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))


QUERIES = {"op10_packing": op10_packing}
ORACLES: dict[str, str] = {}
