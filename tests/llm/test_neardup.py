"""Near-duplicates against brute force over all pairs, and edge cases."""

import random

import duckdb
import numpy as np
import pytest

from boxmdl.llm import neardup


def brute(texts):
    """Least id of each component under 100 * intersection >= 75 * union, ids by position."""
    low = "".join(chr(c + 32) if 65 <= c <= 90 else chr(c) for c in range(128))
    sets = []
    for t in texts:
        words = (t or "").translate(low).encode().split()
        sets.append({tuple(words[i : i + 5]) for i in range(max(1, len(words) - 4))} if words else set())
    root = list(range(len(texts)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in range(len(texts)):
        for b in range(a):
            x, y = sets[a], sets[b]
            if x and y and 100 * len(x & y) >= 75 * len(x | y):
                p, q = find(a), find(b)
                root[max(p, q)] = min(p, q)
    return [find(x) for x in range(len(texts))], [len(s) for s in sets]


def check(spark, texts):
    docs = spark.createDataFrame([(i, t, "x") for i, t in enumerate(texts)], "doc_id long, text string, node string").repartition(5)
    got = neardup.near_duplicates(docs).toPandas().set_index("doc_id").loc[range(len(texts))]
    root, sizes = brute(texts)
    assert got.component_id.tolist() == root and got.n_shingles.tolist() == sizes
    assert (got.kept == (got.index == got.component_id)).all()


def test_given_documents(spark):
    rows = duckdb.sql("select text from '/root/testdata/sf0.001/documents.parquet' order by doc_id").fetchall()
    check(spark, [r[0] for r in rows])


def test_families_chains_and_short_texts(spark):
    random.seed(4)
    words = [f"w{i}" for i in range(4000)]
    base = [random.choice(words) for _ in range(200)]

    def edited(source, n):
        out = list(source)
        for _ in range(n):
            out[random.randrange(len(out))] = random.choice(words)
        return " ".join(out)

    texts = [edited(base, random.randrange(0, 14)) for _ in range(60)]
    chain = [random.choice(words) for _ in range(150)]
    for _ in range(12):
        chain[random.randrange(150)] = random.choice(words)
        texts += [" ".join(chain)] * random.randrange(1, 3)
    shared = " ".join(random.choice(words) for _ in range(60))
    texts += [shared + " " + " ".join(random.choice(words) for _ in range(random.randrange(5, 60))) for _ in range(30)]
    texts += ["One two", "one  TWO", "two one", "a", None, "", " \t", "É a", "é a", "x y z v", "x y z v w"]
    random.shuffle(texts)
    check(spark, texts)


@pytest.mark.parametrize("n", [1, 4, 5, 3000])
def test_shingles(n):
    random.seed(n)
    words = [random.choice("abcdefghij") for _ in range(n)]
    s = neardup.Shingler()(" ".join(words))
    assert len(s) == len({tuple(words[i : i + 5]) for i in range(max(1, n - 4))}) and (np.diff(s.astype(object)) > 0).all()


def test_components_of_a_path(spark):
    edges = spark.createDataFrame([(i, i + 1) for i in range(40)] + [(100, 101), (105, 101), (7, 7)], "a long, b long")
    got = {r.node: r.root for r in neardup.components(edges).collect()}
    assert all(got[i] == 0 for i in range(41)) and got[101] == got[105] == 100


def test_edges(spark):
    docs = spark.createDataFrame([(1, "a b c d e f", 0), (1, "a b c d e f", 0), (None, "A B C D E F", 0), (None, None, 0), (3, None, 0)], "doc_id long, text string, row int")
    got = neardup.near_duplicates(docs).collect()
    assert len(got) == 5 and sorted(str(r.component_id) for r in got) == ["1", "1", "1", "3", "None"]
    assert neardup.near_duplicates(docs.limit(0)).count() == 0
    kept = neardup.without_near_duplicates(docs)
    assert kept.columns == docs.columns and sorted((str(r.doc_id), r.text) for r in kept.filter("text is not null").collect()) == [("1", "a b c d e f")]
    assert kept.filter("text is null").count() == 2
    # rows of one id with different texts are told apart
    mixed = spark.createDataFrame([(5, "a b c d e f", 0), (7, "a b c d e f", 0), (7, "q r s t u v", 0), (5, "k l m n o p", 0)], docs.schema)
    assert sorted((r.doc_id, r.text[0]) for r in neardup.without_near_duplicates(mixed).collect()) == [(5, "a"), (5, "k"), (7, "q")]
