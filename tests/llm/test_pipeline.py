"""The pipeline's rows against a brute-force version of its stages, written without the operators."""

import re
import zlib
from collections import defaultdict

import public_tokenizers as public
import pytest
from tokenizers import Tokenizer

import corpus_pipeline
from walkengine.llm.quality_rules import RULES, STOP_WORDS, SYMBOLS

BLANK = re.compile(r"[\x20\x09-\x0D]+")


def words(text):
    return [w for w in BLANK.split(text) if w]


def passes(text):
    w, lines = words(text), [x for x in text.split("\n") if words(x)]
    windows = [tuple(w[k : k + 3]) for k in range(len(w) - 2)]
    at = defaultdict(list)
    for k, x in enumerate(windows):
        at[x].append(k)
    repeated = {k + j for places in at.values() if len(places) > 1 for k in places for j in range(3)}
    if len(w) < 50 or 100 * len(repeated) > 50 * len(w):
        return False
    share = lambda xs, of: len(xs) / len(of) if of else 0.0
    metrics = {
        "mean_word_chars": sum(map(len, w)) / len(w), "symbols_per_word": sum(c in SYMBOLS for c in text) / len(w),
        "stop_word_ratio": share([x for x in w if x in STOP_WORDS], w), "upper_word_ratio": share([x for x in w if x.upper() == x and x.lower() != x], w),
        "dup_line_ratio": (len(lines) - len(set(lines))) / len(lines), "bullet_line_ratio": share([x for x in lines if re.match(r"\s*[-*•]", x)], lines),
        "ellipsis_line_ratio": share([x for x in lines if re.search(r"(\.\.\.|…)\s*$", x)], lines),
    }
    return all((r.least is None or metrics[r.metric] >= r.least) and (r.most is None or metrics[r.metric] <= r.most) for r in RULES)


def brute(docs):
    """{doc_id: text} after each stage but the last, by the contracts of the stages."""
    docs = {i: t for i, t in docs.items() if passes(t or "")}
    yield docs
    last = {}
    for i in sorted(docs):
        last[docs[i]] = i
    docs = {i: docs[i] for i in last.values()}
    yield docs
    lower = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    sets = {i: {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} for i, t in docs.items() for w in [words(t.translate(lower))]}
    holders, at = defaultdict(list), {i: i for i in docs}
    for i, s in sets.items():
        for x in s:
            holders[x].append(i)
    shared = defaultdict(int)
    for group in holders.values():
        for a in range(len(group)):
            for b in range(a):
                shared[group[a], group[b]] += 1
    links = [p for p, n in shared.items() if 100 * n >= 75 * (len(sets[p[0]]) + len(sets[p[1]]) - n)]
    changed = True
    while changed:
        changed = False
        for a, b in links:
            if at[a] != at[b]:
                at[a] = at[b] = min(at[a], at[b])
                changed = True
    docs = {i: t for i, t in docs.items() if at[i] == i}
    yield docs
    seen, out = set(), {}
    for i in sorted(docs):
        data = docs[i].encode()
        gone = bytearray(len(data))
        for p in range(len(data) - 99):
            window = data[p : p + 100]
            if window in seen:
                gone[p : p + 100] = b"\1" * 100
            seen.add(window)
        out[i] = bytes(x for x, g in zip(data, gone) if not g)
    yield out


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    """The smallest documents, further copies of some of them, and a null text."""
    path = tmp_path_factory.mktemp("tables")
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    rows = docs.collect()
    more = [r.asDict() | {"doc_id": 100_000 + r.doc_id} for r in rows[:20]]
    more += [r.asDict() | {"doc_id": 200_000 + r.doc_id, "text": (r.text or "") + " and one more word"} for r in rows[:40]]
    more += [rows[0].asDict() | {"doc_id": 300_000, "text": None}]
    docs.unionByName(spark.createDataFrame(more, docs.schema)).write.parquet(str(path / "documents.parquet"))
    return str(path)


def test_stages_and_result(spark, folder, tmp_path):
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality_rules", "exact_dedup", "near_dedup", "repeated_passages", "packing"]
    columns, expected = docs.columns, brute({r.doc_id: r.text for r in docs.collect()})
    for name, stage in corpus_pipeline.STAGES[:-1]:
        stage(spark, docs, folder).write.parquet(str(tmp_path / name))
        docs = spark.read.parquet(str(tmp_path / name))
        want = next(expected)
        got = {r.doc_id: r.text for r in docs.collect()}
        assert docs.columns == columns and got.keys() == want.keys(), name
        if name == "repeated_passages":
            # a cut may fall inside a character; then its bytes are no text and the stage may drop what is left of it
            assert all(t.encode() == want[i] for i, t in got.items() if want[i].decode("utf-8", "ignore").encode() == want[i])
        else:
            assert got == want, name
    tokenizer = Tokenizer.from_file(public.path("word_bpe_49k.json"))
    tokenizer.encode_special_tokens = True
    ids = {i: [*tokenizer.encode(t, add_special_tokens=False).ids, 2] for i, t in got.items()}
    pieces = corpus_pipeline.run(spark, folder).collect()
    held, sequences = defaultdict(list), defaultdict(list)
    for p in pieces:
        own = ids[p.doc_id][p.start : p.start + p.length]
        assert p.doc_tokens == len(ids[p.doc_id]) and p.ids_crc32 == zlib.crc32(b"".join(x.to_bytes(4, "little") for x in own))
        held[p.doc_id] += range(p.start, p.start + p.length)
        sequences[p.sequence_id].append((p.offset, p.length))
    assert {i: sorted(x) for i, x in held.items()} == {i: list(range(len(x))) for i, x in ids.items()}
    for parts in sequences.values():
        assert [a for a, _ in sorted(parts)] == [sum(n for _, n in sorted(parts)[:k]) for k in range(len(parts))]
        assert sum(n for _, n in parts) <= 4096
