"""Removal of repeated passages by a sparse, range-partitioned suffix array.

Every byte that a 100-byte string covers which also starts earlier (smaller doc_id, or earlier in the document) goes.

1. Of every 100-byte window the 32-byte string with the smallest hash is its anchor, so equal windows have equal
   anchors at equal places, and only suffixes at anchors need sorting (about one in 35).
2. Anchors whose 32 bytes occur once in the corpus can't lie in a repeat; a count by hash drops them.
3. The remaining suffixes carry the bytes of all windows that share the anchor.  Suffixes with equal bytes collapse
   within a task to the earliest.  The rest is range-partitioned by leading bytes with sampled splitters (ties go on
   to the bytes before the anchor and the place, so that a bucket is never one key), and each bucket is sorted by
   multikey quicksort.  Suffixes that share 32 leading bytes are neighbours then; windows among them meet by their
   hashes and count as equal if their bytes are.
4. A run of neighbours at a bucket's border may go on in the next bucket: its windows are compared across buckets by
   a minimum over equal windows, with partial aggregation.

A null text counts as empty.  Matches never cross documents.  Rows that repeat doc_id and text are one document; a
document with a null doc_id takes no part.  Texts under 100 bytes never change.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from walkengine.llm.common import free_name, only, read_table, shuffle_partitions, spread_join, staged, whole_text
from walkengine.llm.minhash_forest import _mix
from walkengine.llm.vocab import byte_slices, worker_state

#: Bytes of a repeated string, of an anchor, and anchors in a window.
REPEAT, ANCHOR = 100, 32
SPREAD = REPEAT - ANCHOR + 1
SLICE = 2 << 20
#: Bytes of windows in a bucket: comparing them takes about 60 times as much memory (130 MB for 2 MB, 404 MB for 8 MB).
BUCKET = 2 << 20
#: Bytes of suffixes that a task remembers.
SEEN = 32 << 20
#: Buckets and their parts this small are sorted by comparing whole suffixes.
SMALL = 48

_BASE = 0x9E3779B97F4A7C15  # odd, so it has an inverse modulo 2**64
_OF_BYTE = np.random.default_rng(21).integers(0, 2**63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse."""
    held = worker_state(("powers",), dict)
    if len(held.get("up", ())) < n:
        size = max(n, SLICE + (SLICE >> 3))
        for name, step in (("up", _BASE), ("down", pow(_BASE, -1, 1 << 64))):
            steps = np.full(size, step, np.uint64)
            steps[0] = 1
            held[name] = np.cumprod(steps, dtype=np.uint64)
    return held["up"], held["down"]


class Buffer:
    """The bytes of some documents in a row, with hashes of all their substrings."""

    def __init__(self, texts: pa.Array):
        texts = texts.cast(pa.large_binary())
        offsets = np.frombuffer(texts.buffers()[1], np.int64)[texts.offset : texts.offset + len(texts) + 1]
        data = texts.buffers()[2]
        whole = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
        self.bytes = whole[offsets[0] : offsets[-1]]
        self.bounds = offsets - offsets[0]
        up, self.down = _powers(len(self.bytes) + 1)
        self.prefix = np.zeros(len(self.bytes) + 1, np.uint64)
        np.cumsum(_OF_BYTE[self.bytes] * up[: len(self.bytes)], out=self.prefix[1:])

    def hashes(self, begin: np.ndarray, end: np.ndarray) -> np.ndarray:
        return _mix((self.prefix[end] - self.prefix[begin]) * self.down[begin])

    def anchors(self) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(document, place of the anchor, first and last window of it), in order of place."""
        n = len(self.bytes)
        none = np.zeros(0, np.int64)
        if n < REPEAT:
            return none, none, none, none
        grams = n - ANCHOR + 1
        # 32 bits of a hash, then the place: the least of a stretch is its anchor, and the first of equal hashes wins
        value = (self.prefix[ANCHOR:] - self.prefix[:grams]) * self.down[:grams]
        value &= np.uint64(0xFFFFFFFF00000000)
        value |= np.arange(grams, dtype=np.uint64)
        width = 1
        while width < SPREAD:  # stretches twice as wide, then the rest
            step = min(width, SPREAD - width)
            value = np.minimum(value[:-step], value[step:])
            width += step
        place = value.astype(np.uint32)
        ends = self.bounds[1:] - REPEAT
        fresh = np.flatnonzero(place[1:] != place[:-1]) + 1
        first = np.unique(np.concatenate([fresh, self.bounds[:-1][self.bounds[:-1] <= ends]]))
        doc = np.searchsorted(self.bounds, first, "right") - 1
        inside = first <= ends[np.minimum(doc, len(ends) - 1)]
        first, doc = first[inside], doc[inside]
        last = np.minimum(np.append(first[1:] - 1, n), ends[doc])
        return doc, place[first].astype(np.int64), first, last


def buffers(batch: pa.RecordBatch) -> Iterator[tuple[int, Buffer]]:
    texts = pc.fill_null(batch["text"].cast(pa.large_string()), "")
    for row, part in byte_slices(texts, SLICE):
        yield row, Buffer(part)


def anchor_hashes(docs: DataFrame, places: bool) -> DataFrame:
    """gram (hash of an anchor's bytes) and, if asked for, doc_id and place of every anchor."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = np.asarray(batch["doc_id"]).astype(np.int64)
            for row, buffer in buffers(batch):
                doc, anchor, _, _ = buffer.anchors()
                columns = [pa.array(buffer.hashes(anchor, anchor + ANCHOR).view(np.int64))]
                if places:
                    columns += [pa.array(ids[row + doc]), pa.array((anchor - buffer.bounds[doc]).astype(np.int32))]
                yield pa.RecordBatch.from_arrays(columns, names=["gram", "doc_id", "place"][: len(columns)])

    return docs.mapInArrow(run, "gram long" + ", doc_id long, place int" * places)


SPAN = pa.schema([("doc_id", pa.int64()), ("begin", pa.int32()), ("end", pa.int32())])
SUFFIX = pa.schema(
    [("suffix", pa.binary()), ("lead", pa.binary()), ("doc_id", pa.int64()), ("begin", pa.int32()), ("end", pa.int32())]
)
SUFFIX_DDL = "suffix binary, lead binary, doc_id long, begin int, end int"


def _joined(begin: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Maximal runs of intervals that are in order of begin and overlap or touch."""
    if not len(begin):
        return begin, end
    reach = np.maximum.accumulate(end)
    fresh = np.flatnonzero(begin[1:] > reach[:-1]) + 1
    return begin[np.concatenate([[0], fresh])], reach[np.concatenate([fresh, [len(begin)]]) - 1]


def suffixes(docs: DataFrame, places: DataFrame) -> DataFrame:
    """Suffixes at the given places (doc_id, places), with the bytes of their windows; rows without a suffix are spans
    that a suffix of equal bytes earlier in the task covers."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: dict[tuple[int, bytes], tuple[int, int]] = {}
        held = 0
        for batch in batches:
            ids, wanted = batch["doc_id"].to_pylist(), batch["places"]
            for row, buffer in buffers(batch):
                doc, anchor, low, high = buffer.anchors()
                lists = wanted.slice(row, len(buffer.bounds) - 1)
                sizes = np.asarray(pc.list_value_length(lists))
                own = np.asarray(lists.flatten()).astype(np.int64) + np.repeat(buffer.bounds[:-1], sizes)
                take = np.isin(anchor, own)
                doc, anchor, low, high = (x[take] for x in (doc, anchor, low, high))
                data, out = buffer.bytes.tobytes(), ([], [], [], [], [])
                for d, a, lo, hi in zip(doc.tolist(), anchor.tolist(), low.tolist(), high.tolist()):
                    at = ids[row + d], lo - int(buffer.bounds[d])
                    windows = a - lo, data[lo : hi + REPEAT]
                    if seen.setdefault(windows, at) == at:
                        held += len(windows[1])
                        out[0].append(data[a : hi + REPEAT])
                        out[1].append(data[lo:a])
                    else:
                        out[0].append(None)
                        out[1].append(None)
                    out[2].append(at[0])
                    out[3].append(at[1])
                    out[4].append(at[1] + hi - lo + REPEAT)
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(out, SUFFIX.types)], schema=SUFFIX)
                if held > SEEN:  # what is forgotten goes on as one more suffix, and the buckets compare it
                    seen.clear()
                    held = 0

    joined = docs.join(places, "doc_id").select("doc_id", "text", "places").sortWithinPartitions("doc_id")
    return joined.mapInArrow(run, SUFFIX_DDL)


def multikey_quicksort(keys: list[bytes]) -> list[int]:
    """Positions of the keys in order: three-way partitions by eight bytes at a time, small parts by whole keys."""
    if len(keys) <= SMALL:
        return sorted(range(len(keys)), key=keys.__getitem__)
    longest = max(map(len, keys))
    depth = -(-max(1, longest) // 8)
    table = np.frombuffer(b"".join(k.ljust(8 * depth, b"\0") for k in keys), ">u8").reshape(len(keys), depth)
    out: list[int] = []
    work = [(np.arange(len(keys)), 0)]
    while work:
        rows, level = work.pop()
        if len(rows) <= SMALL or level == depth:
            out += sorted(rows.tolist(), key=keys.__getitem__)
            continue
        word = table[rows, level]
        pivot = np.partition(word[:: max(1, len(word) // 9)], len(word[:: max(1, len(word) // 9)]) // 2)
        pivot = pivot[len(pivot) // 2]
        less, more = word < pivot, word > pivot
        for part, at in ((rows[more], level), (rows[~(less | more)], level + 1), (rows[less], level)):
            if len(part):
                work.append((part, at))
    return out


def repeats(found: DataFrame) -> DataFrame:
    """Spans (doc_id, begin, end) that repeat earlier bytes, from suffixes."""
    spark = found.sparkSession
    none = pa.nulls

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = pa.Table.from_batches([b.cast(SUFFIX) for b in batches], schema=SUFFIX)  # a bucket: about BUCKET bytes, whatever the table's size
        if not rows.num_rows:
            return
        suffix, lead = rows["suffix"].to_pylist(), rows["lead"].to_pylist()
        ids, begins = np.asarray(rows["doc_id"]), np.asarray(rows["begin"]).astype(np.int64)
        order = multikey_quicksort(suffix)
        heads = [suffix[i][:ANCHOR] for i in order]
        edges = [0] + [i for i in range(1, len(order)) if heads[i] != heads[i - 1]] + [len(order)]
        # runs that may go on beyond the bucket: the first and the last; a closed run of one suffix repeats nothing
        open_rows = sorted({*order[: edges[1]], *order[edges[-2] :]})
        inner = [order[k] for a, b in zip(edges[1:-2], edges[2:-1]) if b - a > 1 for k in range(a, b)]
        rows_in = inner + open_rows
        spans, firsts = _equal_windows([lead[i] + suffix[i] for i in rows_in], ids[rows_in], begins[rows_in], len(inner))
        yield spans
        # of each window of an open run, the earliest place in this bucket goes on
        out = ([], [], [])
        for row, shift in firsts:
            i = rows_in[row]
            out[0].append(int(ids[i]))
            out[1].append(int(begins[i]) + shift)
            out[2].append(hashlib.blake2b((lead[i] + suffix[i])[shift : shift + REPEAT], digest_size=16).digest())
        columns = [pa.array(out[0], pa.int64()), pa.array(out[1], pa.int32()), none(len(out[0]), pa.int32()), pa.array(out[2], pa.binary())]
        yield pa.RecordBatch.from_arrays(columns, schema=REPEATED)

    size = found.agg(F.sum(F.col("end").cast("long") - F.col("begin"))).first()[0] or 0
    ranged = found.repartitionByRange(max(shuffle_partitions(spark) * 2, -(-size // BUCKET)), "suffix", "lead", "doc_id", "begin")
    out = staged(ranged.mapInArrow(run, "doc_id long, begin int, end int, window binary"), "repeats")
    open_runs = out.where("window IS NOT NULL").select("doc_id", "begin", "window")
    first = open_runs.groupBy("window").agg(F.min(F.struct("doc_id", "begin")).alias("first"), F.count("*").alias("n")).where("n > 1")
    across = (
        open_runs.join(first.select("window", "first"), "window")
        .where("doc_id <> first.doc_id OR begin <> first.begin")
        .select("doc_id", "begin", (F.col("begin") + REPEAT).alias("end"))
    )
    return out.where("window IS NULL").select("doc_id", "begin", "end").union(across)


REPEATED = pa.schema([("doc_id", pa.int64()), ("begin", pa.int32()), ("end", pa.int32()), ("window", pa.binary())])


def same_bytes(data: np.ndarray, left: np.ndarray, right: np.ndarray) -> np.ndarray:
    """Whether the REPEAT bytes from ``left`` on are those from ``right`` on, eight at a time."""
    out = np.ones(len(left), bool)
    if len(left):
        words = np.ndarray(len(data) - 7, np.uint64, np.ascontiguousarray(data), strides=(1,))
        for at in [*range(0, REPEAT - 8, 8), REPEAT - 8]:
            out &= words[left + at] == words[right + at]
    return out


def _equal_windows(whole: list[bytes], ids: np.ndarray, begins: np.ndarray, open_from: int) -> tuple[pa.RecordBatch, list[tuple[int, int]]]:
    """(spans of windows that equal an earlier one here, (row, shift) of the earliest of each window from row
    ``open_from`` on)."""
    # a window belongs to one row, so windows of sorted rows are in order of place, and a stable sort by hash keeps it
    by_place = np.lexsort((begins, ids))
    buffer = Buffer(pa.array([whole[i] for i in by_place.tolist()], pa.large_binary()))
    counts = np.maximum(0, np.diff(buffer.bounds) - REPEAT + 1)
    row = np.repeat(np.arange(len(whole)), counts)
    shift = np.arange(len(row)) - np.repeat(np.cumsum(counts) - counts, counts)
    start = buffer.bounds[:-1][row] + shift
    row = by_place[row]
    doc, place = ids[row], begins[row] + shift
    value = buffer.hashes(start, start + REPEAT)
    order = np.argsort(value, kind="stable")
    value = value[order]
    fresh = np.ones(len(value), bool)
    fresh[1:] = value[1:] != value[:-1]
    again = np.flatnonzero(~fresh)
    unlike = ~same_bytes(buffer.bytes, start[order[again]], start[order[again - 1]])
    if unlike.any():  # windows of equal hashes and other bytes: these hashes' windows are grouped by their bytes
        twins = np.flatnonzero(np.isin(value, value[again[unlike]]))
        number: dict[bytes, int] = {}
        kind = np.array([number.setdefault(buffer.bytes[b : b + REPEAT].tobytes(), len(number)) for b in start[order[twins]].tolist()])
        by_kind = np.argsort(kind, kind="stable")
        order[twins] = order[twins][by_kind]
        fresh[twins] = np.diff(kind[by_kind], prepend=-1) != 0
        again = np.flatnonzero(~fresh)
    opened = order[np.flatnonzero(fresh)]
    opened = opened[row[opened] >= open_from]
    firsts = list(zip(row[opened].tolist(), shift[opened].tolist()))
    head = np.maximum.accumulate(np.where(fresh, np.arange(len(value)), 0))[again] if len(value) else again
    again, head = order[again], order[head]
    again = np.sort(again[(doc[again] != doc[head]) | (place[again] != place[head])])
    doc, place = doc[again], place[again]
    cut = np.flatnonzero((np.diff(doc) != 0) | (np.diff(place) > REPEAT)) + 1
    first = np.concatenate([[0], cut]).astype(np.int64)[: len(cut) + bool(len(doc))]
    last = np.concatenate([cut, [len(doc)]]).astype(np.int64)[: len(first)] - 1
    columns = [pa.array(doc[first], pa.int64()), pa.array(place[first].astype(np.int32)), pa.array((place[last] + REPEAT).astype(np.int32))]
    return pa.RecordBatch.from_arrays([*columns, pa.nulls(len(first), pa.binary())], schema=REPEATED), firsts


def removed_spans(docs: DataFrame) -> DataFrame:
    """doc_id and spans (arrays of begin, end in order, in bytes; they may overlap) of documents that lose bytes."""
    rows = only(docs, "doc_id", "text").where("doc_id IS NOT NULL").select("doc_id", whole_text().alias("text"))
    frequent = staged(anchor_hashes(rows, places=False).groupBy("gram").count().where("count > 1"), "anchors")
    places = spread_join(anchor_hashes(rows, places=True), frequent, "gram", "count", "left_semi")
    places = places.groupBy("doc_id").agg(F.collect_set("place").alias("places"))
    found = staged(suffixes(rows, places), "suffixes")
    here = found.where("suffix IS NULL").select("doc_id", "begin", "end")
    spans = repeats(found.where("suffix IS NOT NULL")).union(here)
    return spans.groupBy("doc_id").agg(F.sort_array(F.collect_list(F.struct("begin", "end"))).alias("spans"))


def with_spans(docs: DataFrame) -> DataFrame:
    """doc_id, text and spans (null: nothing is removed)."""
    spans = removed_spans(docs).select(F.col("doc_id").alias("_span_id"), "spans")
    rows = only(docs, "doc_id", "text").select("doc_id", whole_text().alias("text"))
    return rows.join(spans, F.col("doc_id") == F.col("_span_id"), "left").select("doc_id", "text", "spans")


def _kept(text: bytes, spans: list[dict] | None) -> tuple[bytes, int]:
    """(the bytes that stay, number of maximal removed runs)."""
    if not spans:
        return text, 0
    begin, end = _joined(np.array([s["begin"] for s in spans]), np.array([s["end"] for s in spans]))
    parts, at = [], 0
    for a, b in zip(begin.tolist(), end.tolist()):
        parts.append(text[at:a])
        at = b
    return b"".join([*parts, text[at:]]), len(begin)


DIGEST = pa.schema(
    [("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("n_removed", pa.int64()), ("n_spans", pa.int64()), ("kept_sha256", pa.string())]
)


def digests(docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 of every document."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for doc_id, text, spans in zip(*(batch[c].to_pylist() for c in ("doc_id", "text", "spans"))):
                data = text.encode()
                kept, n = _kept(data, spans)
                out.append((doc_id, len(data), len(data) - len(kept), n, hashlib.sha256(kept).hexdigest()))
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out) if out else [[]] * 5, DIGEST.types)], schema=DIGEST)

    ddl = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string"
    return with_spans(docs).mapInArrow(run, ddl)


def remove_repeats(docs: DataFrame) -> DataFrame:
    """The documents without repeated passages, n_chars set anew.  A character that loses a byte goes as a whole;
    documents of which no word is left go."""

    key, cuts = free_name(docs, "_span_id"), free_name(docs, "_spans")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch["text"].to_pylist()
            for i, spans in enumerate(batch[cuts].to_pylist()):
                if spans:
                    texts[i] = _kept((texts[i] or "").encode(), spans)[0].decode("utf-8", "ignore")
            columns = dict(zip(batch.schema.names, batch.columns)) | {"text": pa.array(texts, pa.string())}
            if "n_chars" in columns:
                sizes = pa.array([None if t is None else len(t) for t in texts]).cast(columns["n_chars"].type)
                columns["n_chars"] = pc.if_else(pc.is_null(columns[cuts]), columns["n_chars"], sizes)
            blank = [s is not None and not (t or "").strip() for s, t in zip(columns.pop(cuts), texts)]
            kept = pa.RecordBatch.from_arrays(list(columns.values()), names=list(columns))
            yield kept.filter(pa.array([not b for b in blank], pa.bool_()))

    spans = removed_spans(docs).select(F.col("doc_id").alias(key), F.col("spans").alias(cuts))
    joined = docs.join(spans, docs["doc_id"] == spans[key], "left").drop(key)
    return joined.mapInArrow(run, docs.schema)


def op9_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digests(read_table(spark, sf_dir, "documents"))


QUERIES = {"op9_suffix_dedup": op9_suffix_dedup}
ORACLES: dict[str, str] = {}
