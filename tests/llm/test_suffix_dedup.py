"""Suffix sorting and removal of repeats against brute force, and edge cases."""

import hashlib
import random
from collections import Counter

import duckdb
import numpy as np
import pytest

from boxmdl.llm import induced, suffix_dedup

random.seed(11)


@pytest.mark.parametrize("seed", range(120))
def test_suffix_order_and_common_prefixes(seed, monkeypatch):
    rng = random.Random(seed)
    text = [rng.randrange(1, rng.choice([2, 3, 4, 7])) for _ in range(rng.randrange(1, 70))] + [0]
    monkeypatch.setattr(induced, "BLOCK", rng.choice([1, 2, 5, 1 << 16]))
    spill = induced.Spill()
    blocks = list(induced.sorted_suffixes(np.array(text, np.uint16), symbols=9, depth=250, budget=rng.choice([0, 64, 300, 1 << 20]), memory=rng.choice([0, 3, 1 << 20]), spill=spill))
    spill.close()
    order = np.concatenate([p for p, _ in blocks]).tolist()
    assert order == sorted(range(len(text)), key=lambda i: text[i:], reverse=True)
    values = np.concatenate([v for _, v in blocks]).tolist()
    for k in range(1, len(order)):
        a, b = text[order[k - 1] :], text[order[k] :]
        assert values[k] == next(i for i in range(len(text)) if i >= min(len(a), len(b)) or a[i] != b[i])


def test_a_shard_far_larger_than_its_memory(tmp_path):
    """Every queue and tape holds 4 KB; the names are sorted by two further levels; files are gone afterwards."""
    rng = random.Random(3)
    words = ["".join(rng.choices("abcd", k=rng.randrange(2, 9))) for _ in range(40)]
    data = [" ".join(rng.choices(words, k=400)).encode() for _ in range(40)]
    data += [data[3][200:900], data[5][:500] + b"end"]
    levels, deepest = [], induced._suffix_order
    induced._suffix_order = lambda text, *rest: levels.append(len(text)) or deepest(text, *rest)
    written = []
    write = induced.Spill.write
    induced.Spill.write = lambda self, *c: written.append(sum(x.nbytes for x in c)) or write(self, *c)
    try:
        found = induced.repeated_starts(data, 40, budget=4096, memory=2000, folder=f"file://{tmp_path}")
    finally:
        induced._suffix_order, induced.Spill.write = deepest, write
    assert len(levels) >= 2 and levels[0] > levels[1] and len(written) > 50 and sum(written) > 50 * 4096
    assert list(tmp_path.iterdir()) == []
    seen = Counter(w for d in data for w in windows(d, 40))
    for d, s in zip(data, found, strict=True):
        assert s.tolist() == [i for i, w in enumerate(windows(d, 40)) if seen[w] > 1]


def windows(data, n):
    return (data[i : i + n] for i in range(len(data) - n + 1))


def brute(datas, n):
    seen = Counter(w for d in datas for w in windows(d, n))
    out = []
    for d in datas:
        gone = bytearray(len(d))
        for i, w in enumerate(windows(d, n)):
            if seen[w] > 1:
                gone[i : i + n] = b"\1" * n
        runs = sum(1 for k in range(len(d)) if gone[k] and not (k and gone[k - 1]))
        out.append((sum(gone), runs, bytes(c for c, g in zip(d, gone) if not g)))
    return out


def test_given_documents(spark):
    sf = "/root/testdata/sf0.001"
    rows = duckdb.sql(f"select doc_id, text from '{sf}/documents.parquet' order by doc_id").fetchall()
    got = suffix_dedup.op7_induced_suffix_dedup(spark, sf).toPandas().set_index("doc_id")
    for (i, text), (removed, runs, kept) in zip(rows, brute([t.encode() for _, t in rows], 200)):
        r = got.loc[i]
        assert (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) == (len(text.encode()), removed, runs, hashlib.sha256(kept).hexdigest())


def test_many_ways_to_repeat(spark):
    word = lambda: random.choice(["ab", "é", "the", "zq", "x"])
    text = lambda n: " ".join(word() for _ in range(n))
    passage = text(60)
    texts = [text(random.randrange(0, 90)) + passage[random.randrange(20) :] + text(random.randrange(0, 40)) for _ in range(25)]
    texts += [texts[0], texts[1][:150], "=" * 300, "ab" * 200, None, "", text(30), "y" + passage + "z" + passage]
    docs = spark.createDataFrame([(i, t, 5, "k") for i, t in enumerate(texts)], "doc_id long, text string, n_chars long, anchor string").repartition(3)
    datas = [(t or "").encode() for t in texts]
    for length, gram in ((40, 16), (40, 40)):
        want = brute(datas, length)
        marked = suffix_dedup.with_spans(docs, "doc_id", "text", length=length, gram=gram, batch_bytes=500)
        for r in marked.collect():
            kept, runs = suffix_dedup.cut((r.text or "").encode(), r["__spans"], length)
            removed, spans, left = want[r.doc_id]
            assert (kept, runs) == (left, spans), r.doc_id


def test_segments_of_a_hot_anchor_are_not_sorted_in_one_task(spark, monkeypatch):
    rng = random.Random(5)
    text = lambda n: "".join(rng.choices("abcdefgh", k=n))
    passage = text(90)
    texts = [text(rng.randrange(30, 60)) + passage[rng.randrange(10) :] + text(rng.randrange(30, 60)) for _ in range(60)] + [text(150)] * 2
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    share, dealt = suffix_dedup._shared_strings, []

    def watched(segments, length):
        dealt.extend(segments.groupBy("anchor").count().collect())
        return share(segments, length)

    monkeypatch.setattr(suffix_dedup, "_shared_strings", watched)
    want = brute([t.encode() for t in texts], 40)
    for r in suffix_dedup.with_spans(docs, "doc_id", "text", length=40, gram=16, batch_bytes=500, hot_segments=10).collect():
        kept, runs = suffix_dedup.cut(r.text.encode(), r["__spans"], 40)
        removed, spans, left = want[r.doc_id]
        assert (kept, runs) == (left, spans), r.doc_id
    assert any(r["count"] > 10 for r in dealt)  # without the bound, all these would be sorted together


def test_segments_cover_all_starts():
    data = bytes(random.choice(b"abcd") for _ in range(3000))
    lo, hi, anchor = suffix_dedup.segments(data, 60, 20)
    assert lo[0] == 0 and hi[-1] == 2940 and (lo[1:] == hi[:-1] + 1).all()
    again = suffix_dedup.segments(b"zz" + data[500:700] + b"z", 60, 20)[2]
    assert set(suffix_dedup.segments(data[500:700], 60, 20)[2].tolist()) <= set(again.tolist()) and set(suffix_dedup.segments(data[520:600], 60, 20)[2].tolist()) <= set(anchor.tolist())


def test_long_documents_are_read_in_pieces(monkeypatch):
    data = bytes(random.choice(b"abcd") for _ in range(5000))
    whole = suffix_dedup.segments(data, 60, 20)
    monkeypatch.setattr(suffix_dedup, "CHUNK", 700)
    lo, hi, anchor = suffix_dedup.segments(data, 60, 20)
    by_start = lambda a, b, c: {i: h for x, y, h in zip(a, b, c) for i in range(x, y + 1)}
    assert by_start(lo, hi, anchor) == by_start(*whole)


def test_edges(spark):
    passage = "ü" * 150
    docs = spark.createDataFrame([(1, passage + "a", 151), (1, passage + "a", 151), (None, "b" + passage, 151), (4, None, 0), (5, "", 0)], "doc_id long, text string, n_chars int")
    got = suffix_dedup.without_repeats(docs)
    rows = {(r.doc_id, r.text, r.n_chars) for r in got.collect()}
    assert got.columns == docs.columns and rows == {(1, "", 0), (None, "b", 1), (4, None, 0), (5, "", 0)}
    assert suffix_dedup.without_repeats(docs.limit(0)).count() == 0
