"""Fingerprints and line rules against brute force, and their edge cases."""

import hashlib

import duckdb
import pytest

from boxmdl.llm import fingerprint, line_rules

SF = "/root/testdata/sf0.001"
DOCS = "doc_id long, text string, source string, line string, words string, __row int, digest string"


def small(spark, rows):
    return spark.createDataFrame([(i, t, s, "x", "y", 1, "z") for i, t, s in rows], DOCS)


def test_edited_texts(spark):
    got = fingerprint.op10_canonical_digest(spark, SF).toPandas().set_index("doc_id")
    docs = duckdb.sql(f"select doc_id, text from '{SF}/documents.parquet' order by doc_id desc").fetchall()
    assert len(got) == len(docs)
    for k, (i, text) in enumerate(docs):
        after, half = docs[(k + 1) % len(docs)][1], len(text) // 2
        edited = text[: len(text) - half] + after[:half]
        row = got.loc[i]
        assert row.edited_sha256 == hashlib.sha256(edited.encode()).hexdigest() and row.n_chars == len(text)
        assert row.near_next == (fingerprint.canonical(text) == fingerprint.canonical(after))
        assert row.near_edited == (fingerprint.canonical(text) == fingerprint.canonical(edited))
        assert row.fingerprint == fingerprint.digest(fingerprint.canonical(text)).hex()


def test_fingerprint_edges(spark):
    docs = small(spark, [(5, "A  b", "s"), (5, "a B", "s"), (None, None, "s"), (2, "", "s"), (9, "ﬁn Straße", "s"), (3, "FIN strasse\n", "s")])
    got = fingerprint.edit_probe(docs).toPandas()
    assert len(got) == 6 and got.fingerprint.nunique() == 3
    assert fingerprint.edit_probe(docs.limit(0)).count() == 0
    one = fingerprint.edit_probe(small(spark, [(1, "abcd", "s")])).toPandas().iloc[0]
    assert one.near_next == 1.0 and one.edited_sha256 == hashlib.sha256(b"abab").hexdigest()
    assert fingerprint.fingerprints(docs).toPandas().fingerprint.nunique() == 3


def test_colliding_digests_are_told_apart(spark):
    poor = lambda canon: bytes([len(canon)]) * 16
    docs = small(spark, [(1, "aa", "s"), (2, "bb", "s"), (3, "aa", "s"), (4, "ccc", "s")])
    known = spark.createDataFrame([(i, poor(t)) for i, t in ((1, b"aa"), (2, b"bb"), (3, b"aa"), (4, b"ccc"))], "doc_id long, digest binary")
    clashing = fingerprint.collisions(docs, known, digest_of=poor)
    assert clashing == {poor(b"aa"): b"aa"}
    names = {t: fingerprint.fingerprint_of(t, clashing, poor) for t in (b"aa", b"bb", b"ccc")}
    assert len(set(names.values())) == 3


def brute_repeat(words):
    windows = [tuple(words[i : i + 3]) for i in range(len(words) - 2)]
    return len({p for i, w in enumerate(windows) if windows.count(w) > 1 for p in (i, i + 1, i + 2)})


def test_repeated_words():
    import random

    random.seed(5)
    for n in (0, 2, 3, 4, 5, 30, 200):
        words = [random.choice([b"a", b"b", b"c", b"d"]) for _ in range(n)]
        assert line_rules.repeated_words(words) == brute_repeat(words)


def test_lines_above_the_limit_are_removed(spark):
    rows = [(i, f"Read more at 1{i % 10}\n" + f"unique {i} " * 30, "h") for i in range(30)] + [(100 + i, "READ MORE AT 77\n" * 40 + "tail word " * 12 + str(i), "h") for i in range(3)] + [(200, None, None), (201, "", None), (202, " \t\n", "h")]
    got = line_rules.line_rules(small(spark, rows)).toPandas().set_index("doc_id")
    assert (got.words_removed.loc[range(30)] == 4).all() and got.words_removed[100] == 160 and not got.kept[100]
    assert got.n_words[200] == 0 and not got.kept[200]
    assert line_rules.line_rules(small(spark, rows).limit(0)).count() == 0


def test_a_line_of_many_documents_of_a_large_host(spark):
    rows = [(i, ("Read more here\n" if i < 40 else "") + "unique " + " ".join("abcdefghij"[int(c)] * 3 for c in f"{i:04d}") + " tail" * 50, "h") for i in range(5000)]
    for many, gone in ((40, 0), (39, 3)):
        got = line_rules.line_rules(small(spark, rows), many_docs=many).toPandas().set_index("doc_id")
        assert got.words_removed[0] == gone and got.words_removed[4999] == 0


def test_repeated_ids_and_very_long_texts(spark):
    long = "a line of its own\n" * 100_000 + " ".join(f"w{i}" for i in range(400_000))
    rows = [(7, long, "h"), (7, long, "h"), (7, "other words " * 40, "h"), (8, "word " * 500_000, "h")]
    got = line_rules.line_rules(small(spark, rows)).toPandas().sort_values("n_words")
    assert got.doc_id.tolist() == [7, 8, 7, 7] and got.n_words.tolist() == [80, 500_000, 900_000, 900_000]
    assert got.n_dup_lines.tolist() == [0, 0, 99_999, 99_999] and got.n_repeat_words.tolist()[:2] == [80, 500_000] and got.base_failed.tolist() == [True, True, True, True]


def test_copies_are_no_boilerplate(spark):
    text = "\n".join(f"line {c} of a clean text with words {c}{c}" for c in "abcdefghijklmnop")
    got = line_rules.line_rules(small(spark, [(i, text, "h") for i in range(60)])).toPandas()
    assert got.words_removed.sum() == 0 and (got.kept == ~got.base_failed).all()


def test_measures():
    (n, chars, symbols, again, repeat), lines = line_rules.measure("a b#\na b#\n\né x |")
    assert (n, chars, symbols, again) == (6, 10, 3, 1) and sum(lines.values()) == 6


@pytest.mark.parametrize("broadcast", [200_000, 0])
def test_frequent_lines_leave_the_text(spark, monkeypatch, broadcast):
    monkeypatch.setattr(line_rules, "BROADCAST_LINES", broadcast)
    own = lambda i: " ".join(f"{chr(97 + i // 10)}{chr(97 + i % 10)}x{chr(65 + j)}" for j in range(57))  # noqa: E731  digits are folded
    rows = [(i, f"{own(i)}\n\nShare page {i % 10}\nend {i}{own(i)}", "h") for i in range(60)] + [(100, "share Page 7", "g"), (101, None, None), (102, " share\tPAGE 3 \nx", "h")]
    got = line_rules.line_rules(small(spark, rows)).toPandas().set_index("doc_id")
    for i in range(60):
        assert got.loc[i, "clean_text"] == f"{own(i)}\n\nend {i}{own(i)}" and got.loc[i, "words_removed"] == 3
    assert got.loc[100, "clean_text"] == "share Page 7" and got.loc[101, "clean_text"] is None and got.loc[102, "clean_text"] == "x"
    assert got["words_removed"].loc[[100, 101, 102]].tolist() == [0, 0, 3]
