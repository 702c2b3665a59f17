"""Operators on a small table with nulls, empty, long, repeated and near-equal texts and clashing further columns."""

import hashlib
import random
import re
import zlib

import numpy as np
import public_tokenizers as public
import pytest
import tiktoken
from pyspark.sql import functions as F

from walkengine.llm import (
    bpe_codec, exact_dedup, html_extract, license_scan, minhash_forest, packing, quality_classifier, quality_rules, suffix_dedup, token_output,
)
from walkengine.llm.common import spread_join
from walkengine.llm.components import components
from walkengine.llm.vocab import load_tokenizer

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, kept boolean, words string, word_count int, keep_id long"


def _docs():
    r = random.Random(5)
    vocabulary = ["".join(r.choice("abcdefghiéß") for _ in range(r.randint(2, 9))) for _ in range(400)] + ["the", "of", "de", "und"] * 30
    prose = lambda n: " ".join(r.choice(vocabulary) + ("." if r.random() < 0.1 else "") for _ in range(n))
    base = [prose(r.randint(60, 200)) for _ in range(12)]
    near = base[3].split()
    near[20] = "changed"
    shared = prose(40)
    texts = [*base, base[0], base[0], base[5], " ".join(near), None, "", None, "one", "one two", "  ", prose(30_000), base[1] + "\n" + shared, shared + " " + base[2]]
    texts += ["A the, " * 70, "Line of words\n" * 12, "w&&& x### " * 60, "Released under the MIT License.\n" + base[7], "LICENSED under cc by-nc 4.0 " + base[8]]
    texts += ["a  b   c\t\td \n\n e  <|endoftext|>  x", "\x1c\x1d" + base[9], "漢字 😀 é" * 20, "ab" * 300, "x" * 5000]
    rows = [(i * 3 % 101, t, "en", "src0", None if t is None else len(t), True, "clash", 1, 7) for i, t in enumerate(texts)]
    return rows


ROWS = _docs()
TEXTS = {i: t or "" for i, t, *_ in ROWS}


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(ROWS, SCHEMA)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def by_id(df):
    return {r.doc_id: r for r in df.collect()}


def words(text):
    return re.findall("[^\x20\x09-\x0d]+", text)


def test_empty_tables(empty, spark):
    pages = spark.createDataFrame([], "page_id long, html string")
    labels = spark.createDataFrame([], "doc_id long, quality int")
    for df in (
        quality_rules.judge(empty), quality_rules.filter_documents(empty), exact_dedup.groups(empty), exact_dedup.drop_copies(empty), minhash_forest.classes(empty),
        license_scan.scan(empty), html_extract.extract(pages), suffix_dedup.digests(empty), suffix_dedup.remove_repeats(empty), quality_classifier.classify(empty, labels),
        packing.pack(empty, public.path("word_bpe_49k.json")), bpe_codec.round_trip_digests(empty, public.path("byte_bpe_multi_50k.tiktoken"), public.PATTERN),
    ):
        assert df.count() == 0
    blocks, dictionary = token_output.write_shards(empty, public.path("byte_bpe_50k.json"))
    assert token_output.read_shards(blocks, dictionary).count() == 0 and dictionary == b""


def test_quality_rules(docs):
    got = by_id(quality_rules.judge(docs))
    for i, text in TEXTS.items():
        w = words(text)
        windows = [tuple(w[k : k + 3]) for k in range(len(w) - 2)]
        covered = {k + j for k, x in enumerate(windows) if windows.count(x) > 1 for j in range(3)} if len(w) < 3000 else None
        lines = [x for x in text.split("\n") if words(x)]
        g = got[i]
        assert (g.n_words, g.word_chars, g.n_symbols) == (len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in text))
        assert g.n_dup_lines == len(lines) - len(set(lines))
        if covered is not None:
            assert g.n_repeat_words == len(covered)
            assert g.base_failed == (len(w) < 50 or 100 * len(covered) > 50 * len(w))
        assert g.kept == (not g.base_failed and g.failed_rules == "")
    kept = quality_rules.filter_documents(docs)
    assert kept.columns == docs.columns and {r.doc_id for r in kept.collect()} == {i for i, g in got.items() if g.kept}


def test_verdicts_can_be_filtered(spark, docs):
    """A filter on computed columns must not make Spark compute the steps below it again and again."""
    verdicts = quality_rules.judge(docs)
    every = verdicts.collect()
    for condition in ("kept", "base_failed", "n_repeat_words > 3 AND dup_line_ratio < 0.9"):
        plan = verdicts.where(condition)._jdf.queryExecution().executedPlan().toString()
        assert plan.index("Filter") < plan.index("Generate") and plan.count("Filter") == 1
    assert {r.doc_id for r in verdicts.where("kept").collect()} == {r.doc_id for r in every if r.kept}


def test_windows_that_share_hash_bits_are_told_apart(docs):
    starts = quality_rules._exact_starts(quality_rules.words_of(quality_rules.whole_text()))
    rows = docs.where("length(text) BETWEEN 100 AND 4000 AND length(text) <> 600").select("doc_id", starts.alias("s")).collect()
    for r in rows:
        w = words(TEXTS[r.doc_id])
        windows = [tuple(w[k : k + 3]) for k in range(len(w) - 2)]
        assert r.s == [k for k, x in enumerate(windows) if windows.count(x) > 1]


def test_exact_dedup(docs):
    got = by_id(exact_dedup.groups(docs))
    for i, text in TEXTS.items():
        same = [j for j, t in TEXTS.items() if t == text]
        g = got[i]
        assert (g.keep_id, g.group_size, g.kept) == (max(same), len(same), i == max(same))
        assert g.text_sha256 == hashlib.sha256(text.encode()).hexdigest()
    assert exact_dedup.drop_copies(docs).count() == len(set(TEXTS.values()))


def test_rice_codes():
    r = np.random.default_rng(1)
    for n in (1, 2, 1000):
        values = np.unique(r.integers(0, 2**64, n, dtype=np.uint64))
        k, code = exact_dedup.rice_encode(values)
        assert (exact_dedup.rice_decode(code, k, len(values)) == values).all()
    values = np.arange(100, dtype=np.uint64)
    assert (exact_dedup.rice_decode(exact_dedup.rice_encode(values)[1], 0, 100) == values).all()


def _classes():
    lower = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    sets = {}
    for i, text in TEXTS.items():
        w = words(text.translate(lower))
        sets[i] = {tuple(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set()
    at = {i: i for i in sets}
    changed = True
    while changed:
        changed = False
        for i in sets:
            for j in sets:
                both = len(sets[i] & sets[j])
                if both and 100 * both >= 75 * len(sets[i] | sets[j]) and at[i] != at[j]:
                    at[i] = at[j] = min(at[i], at[j])
                    changed = True
    return sets, at


def test_near_duplicates(docs):
    sets, at = _classes()
    got = by_id(minhash_forest.classes(docs))
    assert {i: (g.n_shingles, g.component_id, g.kept) for i, g in got.items()} == {i: (len(sets[i]), at[i], at[i] == i) for i in sets}


def test_many_near_copies_are_one_class(spark):
    r = random.Random(2)
    base = [f"w{r.randrange(5000)}" for _ in range(120)]
    rows = []
    for i in range(300):
        w = list(base)
        w[r.randrange(120)] = f"own{i}"
        rows.append((i, " ".join(w)))
    got = minhash_forest.classes(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert {g.component_id for g in got} == {0}


def test_hub_with_more_near_copies_than_the_windows_reach(spark):
    r = random.Random(8)
    hub, texts = [f"w{i}" for i in range(400)], {5000: None}
    texts[5000] = " ".join(hub)
    for i in range(1100):
        w = list(hub)
        for k in r.sample(range(1, 79), 11):
            w[5 * k] = f"own{i}x{k}"
        texts[i] = " ".join(w)
    sets = {i: {tuple(w[k : k + 5]) for k in range(len(w) - 4)} for i, w in ((i, t.split()) for i, t in texts.items())}
    similar = lambda x, y: 100 * len(x & y) >= 75 * len(x | y)
    assert all(similar(sets[5000], s) for s in sets.values()) and not similar(sets[0], sets[1])
    got = minhash_forest.classes(spark.createDataFrame(list(texts.items()), "doc_id long, text string")).collect()
    assert {(g.doc_id, g.component_id, g.kept) for g in got} == {(i, 0, i == 0) for i in texts}


def test_a_large_run_of_unlinked_rows_makes_no_row_for_each_pair(spark, monkeypatch):
    r, texts = random.Random(8), {}
    hub = [f"w{i}" for i in range(400)]
    for i in range(400):
        w = list(hub)
        for k in r.sample(range(1, 79), 11):
            w[5 * k] = f"own{i}x{k}"
        texts[i] = " ".join(w)
    counts, confirm = [], minhash_forest.confirm_tiles
    monkeypatch.setattr(minhash_forest, "confirm_tiles", lambda rows, docs: counts.append(rows.count()) or confirm(rows, docs))
    got = minhash_forest.classes(spark.createDataFrame(list(texts.items()), "doc_id long, text string")).collect()
    sets = {i: {tuple(w[k : k + 5]) for k in range(len(w) - 4)} for i, w in ((i, t.split()) for i, t in texts.items())}
    at = {i: i for i in sets}
    for i in sets:
        for j in range(i):
            if at[i] != at[j] and 100 * len(sets[i] & sets[j]) >= 75 * len(sets[i] | sets[j]):
                at = {k: min(at[i], at[j]) if x in (at[i], at[j]) else x for k, x in at.items()}
    assert {g.doc_id: g.component_id for g in got} == at
    assert counts and counts[0] <= 400 * minhash_forest.ORDERS


def test_license_scan(docs):
    got = by_id(license_scan.scan(docs))
    for i, text in TEXTS.items():
        w = re.findall("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+", text.translate(str.maketrans(license_scan.UPPER, license_scan.LOWER)))
        places = [(k, label) for p, label in license_scan.PHRASES.items() for k in range(len(w)) if w[k : k + len(p.split())] == p.split()]
        g = got[i]
        assert (g.n_words, g.n_base) == (len(w), len(places))
        assert (g.first_word, g.last_word) == (min((k for k, _ in places), default=None), max((k for k, _ in places), default=None))
        assert g.base_labels == ",".join(sorted({x for _, x in places})) and set(filter(None, g.base_labels.split(","))) <= set(g.labels.split(","))
    assert any(g.labels == "cc-by,cc-by-nc" for g in got.values())


def test_license_notice_with_a_lost_word_and_a_gap(spark):
    notice = license_scan.TEMPLATES[1][1].split()
    changed = notice[:6] + ["extra"] + notice[6:]
    got = by_id(license_scan.scan(spark.createDataFrame([(1, " ".join(changed)), (2, " ".join(notice[:4]))], "doc_id long, text string")))
    assert got[1].labels == "bsd" and got[2].labels == ""


def test_bpe_codec_equals_the_library(docs):
    path = public.path("byte_bpe_multi_50k.tiktoken")
    library = tiktoken.Encoding("own", pat_str=public.PATTERN, mergeable_ranks=bpe_codec.load_ranks(path), special_tokens={})
    got = by_id(bpe_codec.round_trip_digests(docs, path, public.PATTERN))
    for i, text in TEXTS.items():
        ids = library.encode_ordinary(text)
        g = got[i]
        assert g.n_tokens == len(ids) and g.ids_sha256 == hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest()
        assert g.decoded_sha256 == hashlib.sha256(text.encode()).hexdigest()
    back = by_id(bpe_codec.decode_ids(bpe_codec.encode_texts(docs, path, public.PATTERN), path))
    assert {i: r.text for i, r in back.items()} == TEXTS


def test_transducer_pairs_and_decoder():
    ranks = bpe_codec.load_ranks(public.path("byte_bpe_multi_50k.tiktoken"))
    t, r = bpe_codec.MergeTransducer(ranks), random.Random(3)
    tokens = list(ranks)
    for _ in range(2000):
        a, b = r.choice(tokens), r.choice(tokens)
        parts = [bytes([x]) for x in a + b]
        while len(parts) > 1:
            rank, k = min((ranks.get(x + y, 1 << 40), k) for k, (x, y) in enumerate(zip(parts, parts[1:])))
            if rank == 1 << 40:
                break
            parts[k : k + 2] = [parts[k] + parts[k + 1]]
        assert (parts == [a, b]) == t.adjacent(ranks[a], ranks[b])
    single = {i: bytes([i]) for i in range(256)}
    for _ in range(500):
        data = bytes(r.choice([0x41, 0xC3, 0xA9, 0xE2, 0x82, 0xAC, 0xF0, 0x9F, 0x98, 0x80, 0xED, 0xA0, 0xFF]) for _ in range(r.randint(0, 12)))
        stream, out, at = bpe_codec.StreamDecoder(single), "", 0
        while at < len(data):
            n = r.randint(1, 4)
            out += stream.feed(data[at : at + n])
            at += n
        assert out + stream.close() == data.decode("utf-8", "replace")


def test_html():
    page = """<title>t</title><style>.no{display:none}</style><h1>Head</h1><p>One <b>two</b><p>Three<br>four &amp; five<ul><li>a<li>b<ol><li>x<li>y</ol></ul>
    <div class="no">gone</div><span hidden>gone</span><p style="display:none">gone</p><table><tr><th>Name<th>N<tr><td>a<td>1</table>end<script>var t="</p>"</script> 3 < 4"""
    assert html_extract.render(page) == "Head\n\nOne two\n\nThree\nfour & five\n\n- a\n- b\n  1. x\n  2. y\n\nName | N\na    | 1\n\nend 3 < 4"
    assert html_extract.render(None) == html_extract.render("") == ""
    assert html_extract.render("<div>" * 5000 + "deep") == "deep"
    assert html_extract.render("<p>a</b></i><!-- x <p>") == "a"
    assert html_extract.render("<a href='x>y'>l</a> <b") == "l"


def test_hostile_markup():
    assert html_extract.render('<ol start="--5"><li>a</ol>') == "1. a" == html_extract.render(f'<ol start="{"1" * 5000}"><li>a</ol>')
    assert html_extract.render(f'<table><tr><td colspan="{"9" * 5000}">x</table>') == "x"
    assert html_extract.render("<table><tr><td>" * 1500 + "deep") == "deep"
    assert html_extract.render("<table><tbody>" * 1500 + "<tr><td>deep") == "deep"
    assert html_extract.render("<math><mi>x</mi></math> <svg><title>t</title><text>label</text></svg>") == "x label"
    sheet = "<style>@media print{.a{display:none}} @media screen{.b{display:none}} .c{display:none}</style>"
    assert html_extract.render(sheet + "<p class=a>a<p class=b>b<p class=c>c") == "a"


@pytest.fixture(scope="module")
def loose_ids(spark):
    """Null ids, ids that repeat with the same and with another text, null texts, and columns with clashing names."""
    rows = [(None, "under the apache license", "x"), (None, None, "y"), (7, "the mit license", "z"), (7, "nothing here", "z"), (7, "the mit license", "z"), (8, None, None)]
    return spark.createDataFrame([(*r, 1, 2) for r in rows], "doc_id long, text string, words string, row int, hash int")


def test_license_scan_of_loose_ids(loose_ids):
    found = sorted((r.doc_id or 0, r.n_words, r.n_base, r.first_word or -1, r.base_labels) for r in license_scan.scan(loose_ids).collect())
    assert found == [(0, 0, 0, -1, ""), (0, 4, 1, 2, "apache"), (7, 2, 0, -1, ""), (7, 3, 1, 1, "mit"), (7, 3, 1, 1, "mit"), (8, 0, 0, -1, "")]


def test_token_output_and_packing_of_loose_ids(loose_ids):
    blocks, dictionary = token_output.write_shards(loose_ids, public.path("byte_bpe_50k.json"))
    rows = sorted(token_output.read_shards(blocks, dictionary).collect(), key=lambda r: r.start)
    assert [r.doc_id for r in rows] == [None, None, 7, 7, 7, 8]
    assert [r.start for r in rows] == [sum(x.n_tokens for x in rows[:k]) for k in range(6)] and rows[-1].n_tokens == 1
    assert list(token_output.read_document(blocks, dictionary, 8)) == [0] and token_output.read_document(blocks, dictionary, 9) is None
    pieces = packing.pack(loose_ids, public.path("word_bpe_49k.json")).collect()
    assert sum(p.doc_id is None for p in pieces) >= 2 and {p.doc_id for p in pieces} == {None, 7, 8}


def test_rules_codec_and_dedup_of_loose_ids(loose_ids):
    assert sorted(r.n_words for r in quality_rules.judge(loose_ids).collect()) == [0, 0, 2, 3, 3, 4]
    assert quality_rules.filter_documents(loose_ids).columns == loose_ids.columns
    digests = bpe_codec.round_trip_digests(loose_ids, public.path("byte_bpe_multi_50k.tiktoken"), public.PATTERN).collect()
    assert len(digests) == 6 and sum(r.doc_id is None for r in digests) == 2
    assert exact_dedup.drop_copies(loose_ids).columns == loose_ids.columns


def test_html_table(spark):
    pages = spark.createDataFrame([(1, "<p>a<p>b", "clash"), (2, None, "x"), (3, "", "y")], "page_id long, html string, text string")
    assert {r.page_id: (r.text, r.n_lines, r.n_chars) for r in html_extract.extract(pages).collect()} == {1: ("a\n\nb", 3, 4), 2: ("", 0, 0), 3: ("", 0, 0)}


def test_token_output(docs):
    path = public.path("byte_bpe_50k.json")
    blocks, dictionary = token_output.write_shards(docs, path)
    got, tokenizer, start = by_id(token_output.read_shards(blocks, dictionary)), load_tokenizer(path), 0
    for i in sorted(TEXTS):
        ids = [*tokenizer.encode(TEXTS[i], add_special_tokens=False).ids, 0]
        assert tuple(got[i]) == (i, start, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
        start += len(ids)
        if i % 9 == 0:
            assert token_output.read_document(blocks, dictionary, i).tolist() == ids
    assert token_output.read_document(blocks, dictionary, 10**9) is None


def test_packing(docs):
    path = public.path("word_bpe_49k.json")
    rows, tokenizer = packing.pack(docs, path).collect(), load_tokenizer(path)
    pieces, sequences = {}, {}
    for r in rows:
        pieces.setdefault(r.doc_id, []).append(r)
        sequences.setdefault(r.sequence_id, []).append(r)
    for i, text in TEXTS.items():
        ids, at = [*tokenizer.encode(text, add_special_tokens=False).ids, 2], 0
        for p in sorted(pieces[i], key=lambda p: p.start):
            assert p.start == at and p.doc_tokens == len(ids)
            at += p.length
            assert p.ids_crc32 == zlib.crc32(np.array(ids[p.start : at], "<u4").tobytes())
        assert at == len(ids)
    for s in sequences.values():
        at = 0
        for p in sorted(s, key=lambda p: p.offset):
            assert p.offset == at
            at += p.length
        assert at == 4096 or at & (at - 1) == 0 and at < 4096


def test_first_fit_decreasing_is_first_fit():
    r = random.Random(4)
    for _ in range(20):
        sizes = [r.randint(1, 100) for _ in range(r.randint(0, 60))]
        bins: list[list[int]] = []
        for i in sorted(range(len(sizes)), key=lambda i: -sizes[i]):
            place = next((b for b in bins if sum(sizes[j] for j in b) + sizes[i] <= 100), None)
            bins.append([i]) if place is None else place.append(i)
        assert packing.first_fit_decreasing(sizes, 100) == bins


def _removed():
    seen, out = set(), {}
    for i in sorted(TEXTS):
        data = TEXTS[i].encode()
        gone = bytearray(len(data))
        for p in range(len(data) - 99):
            window = data[p : p + 100]
            if window in seen:
                gone[p : p + 100] = b"\1" * 100
            seen.add(window)
        out[i] = data, gone
    return out


def test_suffix_dedup(docs):
    got = by_id(suffix_dedup.digests(docs))
    for i, (data, gone) in _removed().items():
        kept = bytes(x for x, g in zip(data, gone) if not g)
        n_spans = sum(1 for k, g in enumerate(gone) if g and (k == 0 or not gone[k - 1]))
        assert tuple(got[i]) == (i, len(data), sum(gone), n_spans, hashlib.sha256(kept).hexdigest())
    cut = {r.doc_id: r for r in suffix_dedup.remove_repeats(docs).collect()}
    assert cut[3].text == TEXTS[3] and suffix_dedup.remove_repeats(docs).columns == docs.columns


def test_suffix_dedup_of_clashing_names(spark, docs):
    named = docs.withColumn("_span_id", F.lit(-1)).withColumn("_SPANS", F.lit("x"))
    got = suffix_dedup.remove_repeats(named)
    assert got.columns == named.columns
    assert {r.doc_id: r.text for r in got.collect()} == {r.doc_id: r.text for r in suffix_dedup.remove_repeats(docs).collect()}


def test_windows_with_equal_hashes_are_told_apart_by_bytes(monkeypatch):
    r = random.Random(9)
    shared = bytes(r.choice(b"abc") for _ in range(160))
    whole = [bytes(r.choice(b"abc") for _ in range(r.randint(100, 300))) + shared * (k % 3 > 0) for k in range(12)]
    ids, begins = np.arange(12) + 50, np.arange(12) * 7

    def spans():
        batch, firsts = suffix_dedup._equal_windows(whole, ids, begins, 0)
        return batch.to_pylist(), {whole[i][s : s + 100]: (i, s) for i, s in firsts}

    exact = spans()
    assert exact[0]
    monkeypatch.setattr(suffix_dedup.Buffer, "hashes", lambda self, begin, end: np.asarray(self.bytes[begin] % 2, np.uint64))
    assert spans() == exact


def test_suffix_dedup_with_little_memory(docs, monkeypatch):
    want = by_id(suffix_dedup.digests(docs))
    monkeypatch.setattr(suffix_dedup, "SEEN", 100)
    assert by_id(suffix_dedup.digests(docs)) == want


def test_spread_join_deals_a_hot_key(spark, request):
    left = spark.range(4000).select(F.col("id").alias("x"), F.when(F.col("id") % 3 > 0, 7).otherwise(F.col("id") % 500).alias("k"))
    left = left.union(spark.sql("SELECT 9999L, CAST(NULL AS LONG)"))
    right = left.where("k < 400").groupBy("k").agg(F.count("*").alias("n"), F.max("x").alias("y"))
    got = spread_join(left, right, "k", "n").select("x", "k", "y")
    assert sorted(map(str, got.collect())) == sorted(map(str, left.join(right, "k", "left").select("x", "k", "y").collect()))
    for name, value in (("spark.sql.adaptive.enabled", "false"), ("spark.sql.shuffle.partitions", "64"), ("spark.sql.autoBroadcastJoinThreshold", "-1")):
        before = spark.conf.get(name)
        request.addfinalizer(lambda name=name, before=before: spark.conf.set(name, before))
        spark.conf.set(name, value)
    tasks = spread_join(left, right, "k", "n", "inner").groupBy(F.spark_partition_id().alias("p")).count()
    assert max(r["count"] for r in tasks.collect()) < 600
    assert spread_join(left, right.limit(0), "k", "n").count() == 4001


def test_components_of_a_hub_and_a_path(spark):
    edges = [(5, k) for k in range(100, 1600)] + [(k, k + 1) for k in range(5000, 5200)] + [(3, 2)]
    got = {r.node: r.component for r in components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {5: 5, 2: 2, 3: 2} | {k: 5 for k in range(100, 1600)} | {k: 5000 for k in range(5000, 5201)}


def test_multikey_quicksort():
    r = random.Random(6)
    keys = [bytes(r.choice(b"ab\0") for _ in range(r.randint(0, 40))) for _ in range(2000)] + [b"a" * 30] * 200
    assert [keys[i] for i in suffix_dedup.multikey_quicksort(keys)] == sorted(keys)


def test_classifier(spark):
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.01/{n}.parquet") for n in ("documents", "labels"))
    got = by_id(quality_classifier.classify(docs, labels))
    held = [(r.quality, got[r.doc_id]) for r in labels.collect() if got[r.doc_id].held_out]
    assert len(got) == docs.count() and all(0 <= g.score <= 1 and g.predicted == (g.score >= 0.5) for g in got.values())
    assert sum(q == g.predicted for q, g in held) / len(held) > 0.93
    assert all(g.held_out == (zlib.crc32(str(i).encode()) % 3 == 1) for i, g in got.items())


def test_classifier_against_a_plain_version(spark, loose_ids):
    """Moments, random features, normal equations, ridge weights and calibration once more, over rows in memory."""
    r = np.random.default_rng(4)
    n = len(quality_classifier.STATISTICS)
    stats, y = r.normal(3, 2, (700, n)), r.integers(0, 2, 700)
    stats[:, 0] += 3 * y
    stats[:5] = stats[5]  # repeated rows
    keep = r.random(700) < 0.3
    rows = spark.createDataFrame([(s.tolist(), float(v), bool(k)) for s, v, k in zip(stats, y, keep)], "stats array<double>, y double, calibrate boolean").repartition(5)
    model = quality_classifier.fit(rows)
    train, d = stats[~keep], np.random.default_rng(quality_classifier.SEED)
    width, m = quality_classifier.WIDTH, quality_classifier.FEATURES
    directions, phases = d.standard_normal((n, m)) / width, d.uniform(0, 2 * np.pi, m)

    def features(x):
        x = np.clip((x - train.mean(0)) / train.std(0), -6, 6)
        return np.array([[*(np.sqrt(2 / m) * np.cos(row @ directions + phases)), 1.0] for row in x])

    z = features(train)
    square, side = sum(np.outer(a, a) for a in z), sum(a * b for a, b in zip(z, y[~keep]))
    weights = np.linalg.solve(square + quality_classifier.PENALTY * len(train) * np.eye(m + 1) / m, side)
    assert np.allclose(model.raw(stats), features(stats) @ weights, atol=1e-6)
    score = model.score(stats)
    order = np.argsort(model.raw(stats))
    assert (np.diff(score[order]) >= -1e-12).all() and ((score >= 0.5) == y)[keep].mean() > 0.7
    # nulls, ids that repeat, clashing columns, and labels that are missing or unknown
    labels = spark.createDataFrame([(7, 1, 0), (8, None, 0), (None, 1, 0), (99, 0, 0)], "doc_id long, quality int, stats int")
    got = quality_classifier.classify(loose_ids, labels).collect()
    assert len(got) == 6 and all(0 <= g.score <= 1 for g in got) and sum(g.doc_id is None for g in got) == 2


def test_isotonic():
    x, y = quality_classifier.isotonic(np.arange(6.0), np.array([0, 1, 0, 1, 1, 0.5]), np.ones(6))
    assert (np.diff(y) >= 0).all() and len(x) == len(y)


def test_suffix_buckets_grow_in_number_and_not_in_size(spark, monkeypatch):
    r = random.Random(4)
    passage = [" ".join(f"w{r.randrange(9999)}" for _ in range(60)) for _ in range(40)]
    docs = spark.createDataFrame([(i, f"{i} " + passage[i % 40] + f" {i}") for i in range(160)], "doc_id long, text string").repartition(4)
    whole = {x.doc_id: tuple(x) for x in suffix_dedup.digests(docs).collect()}
    numbers, ranged = [], type(docs).repartitionByRange
    monkeypatch.setattr(type(docs), "repartitionByRange", lambda df, n, *cols: numbers.append(n) or ranged(df, n, *cols))
    monkeypatch.setattr(suffix_dedup, "BUCKET", 2048)
    assert {x.doc_id: tuple(x) for x in suffix_dedup.digests(docs).collect()} == whole
    assert max(numbers) > 8 and sum(x[2] > 0 for x in whole.values()) == 120
