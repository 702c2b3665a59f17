"""Near-duplicate documents by an LSH forest over MinHash signatures.

1. Words are lower-cased (A-Z) and cut at ASCII white space; a document's set holds its distinct 5-word shingles.
   Documents with equal sets collapse to the one with the smallest doc_id.
2. Each representative is put into several sorted orders, every one by another permutation of its signature.  An order
   is range-partitioned with sampled splitters and sorted, so a dense region is cut into deeper prefixes instead of
   becoming one bucket.  Neighbours within a window whose common prefix is long enough are candidates if their
   signatures agree often enough; ends of adjacent partitions are compared in a step of their own.
3. Candidates are confirmed on the full sets: first each document with its best candidate, then the candidates whose
   ends are not connected yet.
4. The window and the number of candidates kept cut long runs of equal prefixes off.  So every run whose rows are still
   in more than one component is compared whole, in pairs of blocks, and what agrees often enough is confirmed on the
   full sets too, inside the block: pairs of a run are never written as rows.  Confirmed links make the components.

The set of a document without words is empty and linked with nothing; a null text counts as empty.  A null doc_id is
never linked.  Rows that repeat are equal sets.  Further columns pass through ``drop_near_copies``.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from walkengine.llm.common import only, read_table, shuffle_partitions, spread_join, staged
from walkengine.llm.components import components
from walkengine.llm.vocab import LARGE, byte_slices

#: Words in a shingle; per cent of the union that linked sets share.
SHINGLE, PERCENT = 5, 75
#: Values of a signature, sorted orders, least common prefix, neighbours looked at on either side.
VALUES, ORDERS, PREFIX, WINDOW = 64, 16, 2, 32
#: Share of equal values from which a pair is a candidate: four standard deviations below the wanted similarity.
AGREE = 0.53
#: Candidates that a document keeps in one order besides its direct neighbour.
BEST = 3
#: Rows and shingles in a block of a run that is compared whole (a task holds two blocks).
BLOCK_ROWS, BLOCK_SHINGLES = 1024, 1 << 20

_ODD = np.random.default_rng(77).integers(1, 2**63, SHINGLE + 1, dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def _mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit numbers that spreads every bit."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def shingle_sets(texts: pa.Array) -> Iterator[np.ndarray]:
    """Sorted distinct 64-bit shingle hashes of every text, in order."""
    from pandas.util import hash_array

    for _, part in byte_slices(pc.fill_null(texts.cast(pa.large_string()), ""), LARGE.slice_bytes):
        lists = pc.ascii_split_whitespace(pc.ascii_lower(part))
        bounds = np.asarray(lists.offsets).astype(np.int64)
        coded = lists.flatten().dictionary_encode()
        words = np.array(coded.dictionary.to_pylist(), dtype=object)
        of_word = hash_array(words, categorize=False) if len(words) else np.zeros(0, np.uint64)
        index = np.asarray(coded.indices)
        real = (words != "")[index] if len(words) else np.zeros(0, bool)
        ends = np.concatenate([[0], np.cumsum(real)])[bounds - bounds[0]]
        hashes = of_word[index[real]]
        n = len(hashes)
        grams = np.zeros(max(0, n - SHINGLE + 1), np.uint64)
        for j in range(SHINGLE):
            grams += hashes[j : j + len(grams)] * _ODD[j]
        grams = _mix(grams)
        for a, b in zip(ends[:-1].tolist(), ends[1:].tolist()):
            if b - a >= SHINGLE:
                yield np.unique(grams[a : b - SHINGLE + 1])
            elif b > a:
                length = _ODD[SHINGLE:] * np.array([b - a], np.uint64)
                yield _mix((hashes[a:b] * _ODD[: b - a]).sum(dtype=np.uint64, keepdims=True) + length)
            else:
                yield np.zeros(0, np.uint64)


def signature(grams: np.ndarray) -> np.ndarray:
    """16 bits of the smallest value under each of ``VALUES`` multiplications."""
    draw = np.random.default_rng(3)
    times = draw.integers(1, 2**63, VALUES, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
    plus = draw.integers(0, 2**63, VALUES, dtype=np.uint64)
    least = np.full(VALUES, np.uint64(2**64 - 1))
    for begin in range(0, len(grams), 4096):
        np.minimum(least, (grams[begin : begin + 4096, None] * times + plus).min(axis=0), out=least)
    return (_mix(least) & np.uint64(0xFFFF)).astype(">u2")


def orders() -> np.ndarray:
    """One permutation of the signature for each order."""
    draw = np.random.default_rng(13)
    return np.array([draw.permutation(VALUES) for _ in range(ORDERS)])


def sets(docs: DataFrame) -> DataFrame:
    """doc_id, n_shingles, digest of the set, signature."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from xxhash import xxh3_128_digest

        for batch in batches:
            found = [(len(g), xxh3_128_digest(g.tobytes()), signature(g).tobytes()) for g in shingle_sets(batch["text"])]
            if found:
                n, digest, values = zip(*found)
                columns = [batch["doc_id"].cast(pa.int64()), pa.array(n, pa.int64()), pa.array(digest), pa.array(values)]
                yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "n_shingles", "digest", "sig"])

    return only(docs, "doc_id", "text").mapInArrow(run, "doc_id long, n_shingles long, digest binary, sig binary")


def _neighbours(ids: np.ndarray, keys: np.ndarray, order: np.ndarray, fresh: int) -> dict[tuple[int, int], int]:
    """Candidate pairs of rows in sorted order, of which at least one is at or after ``fresh``; value: equal values."""
    found: list[tuple[int, int, int]] = []
    for lag in range(1, min(WINDOW, len(ids) - 1) + 1):
        near = (keys[lag:, :PREFIX] == keys[:-lag, :PREFIX]).all(axis=1) & (order[lag:] == order[:-lag])
        near[: max(0, fresh - lag)] = False
        rows = np.flatnonzero(near)
        if len(rows):
            same = (keys[rows + lag] == keys[rows]).sum(axis=1)
            good = same >= AGREE * VALUES
            found += zip(rows[good].tolist(), (rows[good] + lag).tolist(), same[good].tolist())
    held: dict[int, int] = {}
    out: dict[tuple[int, int], int] = {}
    for i, j, same in sorted(found, key=lambda x: (-x[2], x[1] - x[0])):
        if held.get(i, 0) < BEST or held.get(j, 0) < BEST or j - i == 1:
            held[i], held[j] = held.get(i, 0) + 1, held.get(j, 0) + 1
            a, b = int(ids[i]), int(ids[j])
            if a != b:
                out[min(a, b), max(a, b)] = same
    return out


def matrix(keys: list[bytes]) -> np.ndarray:
    return np.frombuffer(b"".join(keys), ">u2").reshape(-1, VALUES)


def candidates(reps: DataFrame) -> tuple[DataFrame, DataFrame]:
    """a, b (a < b) and the number of equal signature values, from the sorted orders of ``reps`` (doc_id, sig,
    n_shingles); and the rows of the orders: tree, key, doc_id, size."""
    permuted = orders()
    spark = reps.sparkSession

    def crown(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                values = np.frombuffer(b"".join(batch["sig"].to_pylist()), ">u2").reshape(-1, VALUES).astype(np.int64)
                for k, p in enumerate(permuted):
                    prefix = sum(values[:, p[j]] << (16 * (PREFIX - 1 - j)) for j in range(PREFIX)) | (k << 16 * PREFIX)
                    yield pa.RecordBatch.from_arrays([pa.array(prefix), batch["doc_id"]], names=["crown", "doc_id"])

    # a document that shares its least prefix with no other in an order has no neighbour there, and stays out of it
    crowns = reps.mapInArrow(crown, "crown long, doc_id long")
    shared = staged(crowns.groupBy("crown").count().where("count > 1"), "crowns")
    trees = spread_join(crowns, shared, "crown", "count", "left_semi").groupBy("doc_id").agg(F.collect_set(F.shiftright("crown", 16 * PREFIX).cast("int")).alias("trees"))
    reps = reps.join(trees, "doc_id")

    def plant(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                values = np.frombuffer(b"".join(batch["sig"].to_pylist()), ">u2").reshape(-1, VALUES)
                rows = np.repeat(np.arange(len(values)), np.asarray(pc.list_value_length(batch["trees"])))
                number = np.asarray(batch["trees"].flatten())
                for k, p in enumerate(permuted):
                    own = rows[number == k]
                    keys = pa.array([r.tobytes() for r in np.ascontiguousarray(values[own][:, p])], pa.binary())
                    at = pa.array(own)
                    columns = [pa.array(np.full(len(own), k, np.int32)), keys, batch["doc_id"].take(at), batch["n_shingles"].take(at)]
                    yield pa.RecordBatch.from_arrays(columns, names=["tree", "key", "doc_id", "size"])

    def walk(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Pairs; besides the first and last rows, as rows with a key, for the border before and after."""
        part = TaskContext.get().partitionId()
        ids, trees, keys = np.zeros(0, np.int64), np.zeros(0, np.int32), []
        first = True

        def border(number: int, rows: slice) -> pa.RecordBatch:
            n = len(keys[rows])
            side = pa.array([part] * n, pa.int32())
            return pa.RecordBatch.from_arrays(
                [pa.array(ids[rows]), pa.nulls(n, pa.int64()), side, pa.array([number] * n, pa.int32()), pa.array(trees[rows]), pa.array(keys[rows], pa.binary())],
                schema=WALKED,
            )

        for batch in batches:
            if not batch.num_rows:
                continue
            kept = len(keys)
            ids = np.concatenate([ids, np.asarray(batch["doc_id"]).astype(np.int64)])
            trees = np.concatenate([trees, np.asarray(batch["tree"]).astype(np.int32)])
            keys = keys + batch["key"].to_pylist()
            if first:
                yield border(part - 1, slice(0, WINDOW))
                first = False
            pairs = _neighbours(ids, matrix(keys), trees, kept)
            a, b = zip(*pairs) if pairs else ((), ())
            none = pa.nulls(len(pairs), pa.int32())
            yield pa.RecordBatch.from_arrays(
                [pa.array(a, pa.int64()), pa.array(b, pa.int64()), pa.array(pairs.values(), pa.int32()), none, none, pa.nulls(len(pairs), pa.binary())],
                schema=WALKED,
            )
            ids, trees, keys = ids[-WINDOW:], trees[-WINDOW:], keys[-WINDOW:]
        if not first:
            yield border(part, slice(-WINDOW, None))

    def meet(rows: pa.Table) -> pa.Table:
        rows = rows.sort_by([("same", "ascending"), ("tree", "ascending"), ("key", "ascending"), ("a", "ascending")])
        side = np.asarray(rows["same"])
        pairs = {}
        if side[0] != side[-1]:
            pairs = _neighbours(np.asarray(rows["a"]), matrix(rows["key"].to_pylist()), np.asarray(rows["tree"]), 0)
        a, b = zip(*pairs) if pairs else ((), ())
        return pa.table([pa.array(a, pa.int64()), pa.array(b, pa.int64()), pa.array(pairs.values(), pa.int32())], names=["a", "b", "same"])

    planted = staged(reps.mapInArrow(plant, "tree int, key binary, doc_id long, size long"), "planted")
    sorted_rows = planted.drop("size").repartitionByRange(shuffle_partitions(spark) * 2, "tree", "key", "doc_id").sortWithinPartitions("tree", "key", "doc_id")
    walked = staged(sorted_rows.mapInArrow(walk, "a long, b long, same int, border int, tree int, key binary"), "forest")
    across = walked.where("border IS NOT NULL").groupBy("border").applyInArrow(meet, "a long, b long, same int")
    inside = walked.where("border IS NULL").select("a", "b", "same")
    return inside.union(across).groupBy("a", "b").agg(F.max("same").alias("same")), planted


WALKED = pa.schema(
    [("a", pa.int64()), ("b", pa.int64()), ("same", pa.int32()), ("border", pa.int32()), ("tree", pa.int32()), ("key", pa.binary())]
)


def confirm(pairs: DataFrame, texts: DataFrame) -> DataFrame:
    """The pairs (a, b) whose full sets are similar enough; ``texts``: doc_id, text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            left, right = shingle_sets(batch["text_a"]), shingle_sets(batch["text_b"])
            shared = [(len(np.intersect1d(x, y, assume_unique=True)), len(x) + len(y)) for x, y in zip(left, right)]
            good = pa.array([100 * n >= PERCENT * (total - n) and n > 0 for n, total in shared], pa.bool_())
            yield pa.RecordBatch.from_arrays([batch["a"].filter(good), batch["b"].filter(good)], names=["a", "b"])

    side = lambda end: texts.select(F.col("doc_id").alias(end), F.col("text").alias(f"text_{end}"))
    both = pairs.select("a", "b").join(side("a"), "a").join(side("b"), "b")
    return both.select("a", "b", "text_a", "text_b").mapInArrow(run, "a long, b long")


def tile_pairs(tile: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    """Rows (a, b) of the tile, ids of a below those of b, that share a prefix and agree often enough, but are in different
    components and were not compared before (``known``).  Of a pair that shares prefixes in several orders only the first
    counts."""
    permuted = orders()
    ids, trees, size, block, component = (np.asarray(tile[c]) for c in ("doc_id", "tree", "size", "block", "component"))
    keys = matrix(tile["key"].to_pylist())
    crossed = tile["p"][0].as_py() != tile["q"][0].as_py()
    by_run = np.lexsort((ids, *(keys[:, j] for j in range(PREFIX)), trees))
    ids, trees, size, block, component, keys = (x[by_run] for x in (ids, trees, size, block, component, keys))
    starts = np.flatnonzero((trees[1:] != trees[:-1]) | (keys[1:, :PREFIX] != keys[:-1, :PREFIX]).any(axis=1)) + 1
    known = [None if k is None else np.array(k, np.int64) for k in tile["known"].take(pa.array(by_run)).to_pylist()]
    a, b = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
    for begin, end in zip([0, *starts.tolist()], [*starts.tolist(), len(ids)]):
        # where the values of the first places of all earlier orders are in the keys of this one
        back = np.argsort(permuted[trees[begin]])
        earlier = [back[permuted[k][:PREFIX]] for k in range(trees[begin])]
        for i in range(begin, end - 1):  # ids of a run are in order
            rest = slice(i + 1, end)
            open_ = (component[rest] != component[i]) & (ids[rest] != ids[i])
            open_ &= 100 * np.minimum(size[rest], size[i]) >= PERCENT * np.maximum(size[rest], size[i])
            if crossed:
                open_ &= block[rest] != block[i]
            js = np.flatnonzero(open_) + i + 1
            if known[i] is not None:
                js = js[~np.isin(ids[js], known[i])]
            equal = keys[js] == keys[i]
            good = equal.sum(axis=1) >= AGREE * VALUES
            for places in earlier:
                good &= ~equal[:, places].all(axis=1)
            js = js[good]
            a.append(np.full(len(js), i))
            b.append(js)
    return by_run[np.concatenate(a)], by_run[np.concatenate(b)]


def whole_runs(planted: DataFrame, at: DataFrame, compared: DataFrame) -> DataFrame:
    """part, p, q and the row of ``planted`` of all rows that have a pair in their tile (part, p, q), see ``tile_pairs``.
    Pairs never become rows: a large run has far more of them than rows.  ``compared``: a, b (a < b), done before."""
    run = ["tree", "head"]
    known = compared.groupBy(F.col("a").alias("doc_id")).agg(F.collect_list("b").alias("known"))
    rows = planted.withColumn("head", F.substring("key", 1, 2 * PREFIX)).join(at.withColumnRenamed("node", "doc_id"), "doc_id", "left")
    rows = staged(rows.withColumn("component", F.coalesce("component", "doc_id")).join(known, "doc_id", "left"), "runs")
    mixed = rows.groupBy(*run).agg(F.count("*").alias("n"), F.sum("size").alias("w"), F.min("component").alias("x"), F.max("component").alias("y")).where("x <> y")
    mixed = staged(mixed.select(*run, "n", "w", F.greatest(F.ceil(F.col("n") / BLOCK_ROWS), F.ceil(F.col("w") / BLOCK_SHINGLES)).cast("int").alias("blocks")), "mixed-runs")
    # runs of one block share tiles, so that a tile is worth a call
    n, w = mixed.where("blocks = 1").agg(F.sum("n"), F.sum("w")).first()
    shared = 1 + max((n or 0) // BLOCK_ROWS, (w or 0) // BLOCK_SHINGLES)
    rows = spread_join(rows, mixed.select(*run, "blocks", "n"), run, "n", "inner").drop("n")
    hashed = F.xxhash64(*run)
    rows = rows.withColumn("part", F.when(F.col("blocks") == 1, F.pmod(hashed, F.lit(shared))).otherwise(hashed))
    rows = rows.withColumn("block", F.pmod(F.xxhash64("doc_id"), F.col("blocks")).cast("int"))
    rows = rows.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    rows = rows.withColumn("p", F.least("block", "other")).withColumn("q", F.greatest("block", "other"))

    def open_rows(tile: pa.Table) -> pa.Table:
        return tile.take(pa.array(np.unique(np.concatenate(tile_pairs(tile)))))

    rows = rows.select("part", "p", "q", "tree", "key", "doc_id", "size", "block", "component", "known")
    return rows.groupBy("part", "p", "q").applyInArrow(open_rows, rows.schema)


def confirm_tiles(rows: DataFrame, docs: DataFrame) -> DataFrame:
    """Links (a, b) that connect what all pairs of ``rows`` (see ``whole_runs``) with similar enough sets would connect.  A
    text comes once for a tile, however many pairs of the tile it is in."""
    tile = ["part", "p", "q"]
    ends = rows.select(*tile, "doc_id").distinct().toDF(*tile, "doc_id")
    texts = only(docs, "doc_id", "text").join(ends.select("doc_id").distinct().hint("merge"), "doc_id", "left_semi").dropDuplicates(["doc_id"])
    texts = ends.join(texts.hint("merge"), "doc_id").select(*tile, "doc_id", "text")

    def run(rows: pa.Table, texts: pa.Table) -> pa.Table:
        ids = np.asarray(texts["doc_id"])
        by_id = np.argsort(ids)
        sets_ = [g for chunk in texts["text"].chunks for g in shingle_sets(chunk)]
        lengths = np.array([len(g) for g in sets_], np.int64)
        starts = np.cumsum(lengths) - lengths
        _, grams = np.unique(np.concatenate(sets_), return_inverse=True)
        marked, label = np.zeros(len(grams), bool), np.arange(len(ids))
        place = by_id[np.searchsorted(ids, np.asarray(rows["doc_id"]), sorter=by_id)]
        left, right = (place[x] for x in tile_pairs(rows))
        order = np.argsort(left, kind="stable")
        left, right = left[order], right[order]
        found: list[tuple[int, int]] = []
        cuts = np.flatnonzero(np.diff(left)) + 1
        for js, i in zip(np.split(right, cuts), left[np.concatenate([[0], cuts])].tolist() if len(left) else ()):
            js = js[label[js] != label[i]]
            if not len(js):
                continue
            own = grams[starts[i] : starts[i] + lengths[i]]
            marked[own] = True
            ends_ = np.cumsum(lengths[js])
            at = np.arange(ends_[-1]) + np.repeat(starts[js] - ends_ + lengths[js], lengths[js])
            n = np.add.reduceat(marked[grams[at]], ends_ - lengths[js], dtype=np.int64)
            marked[own] = False
            for j in js[(n > 0) & (100 * n >= PERCENT * (lengths[js] + lengths[i] - n))].tolist():
                if label[j] != label[i]:
                    label[label == label[j]] = label[i]
                    found.append((min(ids[i], ids[j]), max(ids[i], ids[j])))
        a, b = zip(*found) if found else ((), ())
        return pa.table([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])

    return rows.groupBy(*tile).cogroup(texts.groupBy(*tile)).applyInArrow(run, "a long, b long")


def links(reps: DataFrame, docs: DataFrame) -> DataFrame:
    """Confirmed links (a, b) that connect all that candidates connect; ``reps``: doc_id, sig, n_shingles."""
    pairs, planted = candidates(reps)
    pairs = staged(pairs, "candidates")
    ends = pairs.select(F.explode(F.array("a", "b")).alias("doc_id")).distinct()
    texts = staged(only(docs, "doc_id", "text").join(ends.hint("merge"), "doc_id", "left_semi").dropDuplicates(["doc_id"]), "candidate-texts")
    sided = pairs.select("a", "b", "same").union(pairs.select("b", "a", "same"))
    best = sided.groupBy("a").agg(F.max(F.struct("same", (-F.col("b")).alias("b"))).alias("x")).select("a", (-F.col("x.b")).alias("b"))
    best = best.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    first = staged(confirm(best, texts), "links")
    at = staged(components(first), "components")
    on = lambda end: at.select(F.col("node").alias(end), F.col("component").alias(f"at_{end}"))
    rest = pairs.join(best, ["a", "b"], "left_anti").join(on("a"), "a", "left").join(on("b"), "b", "left")
    rest = rest.where("at_a IS NULL OR at_b IS NULL OR at_a <> at_b").select("a", "b")
    near = staged(first.union(confirm(rest, texts)), "near-links")
    cut = whole_runs(planted, staged(components(near), "components"), pairs.select("a", "b"))
    return near.union(confirm_tiles(staged(cut, "cut-rows"), docs))


def classes(docs: DataFrame) -> DataFrame:
    """One row per document: doc_id, n_shingles, component_id, kept."""
    found = staged(sets(docs), "shingle-sets")
    linked = found.where("n_shingles > 0 AND doc_id IS NOT NULL")
    same = staged(linked.groupBy("digest").agg(F.min(F.struct("doc_id", "sig", "n_shingles")).alias("r")).select("digest", "r.*"), "representatives")
    at = components(links(same.drop("digest"), docs))
    of_set = same.select("digest", F.col("doc_id").alias("rep")).join(at, F.col("rep") == F.col("node"), "left")
    of_set = of_set.select("digest", F.coalesce("component", "rep").alias("component"))
    joined = found.join(of_set, "digest", "left")
    own = F.when((F.col("n_shingles") > 0) & F.col("doc_id").isNotNull(), F.col("component")).otherwise(F.col("doc_id"))
    return joined.select("doc_id", "n_shingles", own.alias("component_id")).withColumn("kept", F.col("doc_id").eqNullSafe(F.col("component_id")))


def drop_near_copies(docs: DataFrame) -> DataFrame:
    """The documents without near copies: of each component the one with the smallest doc_id stays."""
    keep = classes(docs).where("kept").select(F.col("doc_id").alias("_kept_id")).distinct()
    return docs.join(keep, docs["doc_id"].eqNullSafe(keep["_kept_id"]), "left_semi")


def op2_minhash_forest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return classes(read_table(spark, sf_dir, "documents"))


QUERIES = {"op2_minhash_forest": op2_minhash_forest}
ORACLES: dict[str, str] = {}
