"""The pipeline's stages against brute force, stage by stage, and its edge cases."""

import corpus_pipeline

from boxmdl.llm.common import documents
from tests.llm.test_neardup import brute as components
from tests.llm.test_suffix_dedup import brute as repeats

SF = "/root/testdata/sf0.001"


def test_stages(spark):
    docs = documents(spark, SF)
    columns = docs.columns
    outs = []
    for k, (_, stage) in enumerate(corpus_pipeline.STAGES):
        docs = corpus_pipeline.stored(stage(spark, docs, SF), "test")
        outs.append(docs)
        if k < 4:
            assert docs.columns == columns
    clean, distinct, cut, mixed, packed = (x.toPandas() for x in outs)
    toxic = spark.read.parquet(f"{SF}/labels.parquet").filter("toxic = 0").toPandas()
    everything = documents(spark, SF).toPandas()
    assert len(clean) < len(everything) and set(toxic.doc_id) & set(everything.doc_id) <= set(clean.doc_id)
    clean = clean.sort_values("doc_id")
    root, _ = components(clean.text.tolist())
    assert sorted(distinct.doc_id) == [i for i, (k, r) in zip(clean.doc_id, enumerate(root)) if k == r]
    distinct, cut = distinct.sort_values("doc_id"), cut.sort_values("doc_id")
    left = [kept.decode("utf-8", "ignore") for _, _, kept in repeats([t.encode() for t in distinct.text], 200)]
    assert cut.text.tolist() == left and cut.n_chars.tolist() == [len(t) for t in left]
    texts = dict(zip(cut.doc_id, cut.text))
    assert all(texts[i] == t for i, t in zip(mixed.doc_id, mixed.text)) and mixed.doc_id.value_counts().max() <= 3
    tokens = packed.groupby("doc_id").length.sum()
    assert set(packed.doc_id) == set(mixed.doc_id) and (packed.groupby("doc_id").doc_tokens.first() * mixed.doc_id.value_counts()).sort_index().equals(tokens.sort_index())
    run = corpus_pipeline.run(spark, SF)
    assert run.count() == len(packed)


def test_empty(spark):
    docs = documents(spark, SF).limit(0)
    for _, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, SF)
        assert docs.count() == 0


def test_nulls_ties_copies_long_texts_and_clashing_columns(spark):
    import random

    rng = random.Random(6)
    words = ["".join(rng.choices("abcdefghijklmnop", k=rng.randrange(2, 9))) for _ in range(3000)]
    say = lambda n: " ".join(rng.choices(words, k=n))
    passage, long, twin = say(80), say(40_000), say(60)
    rows = [(i, say(50), "en", rng.choice(["a", "b", None]), 1) for i in range(30)]
    rows += [(40, None, None, None, None), (41, "", "en", "a", 0), (42, " \t ", None, "b", 0), (None, say(40), "en", "a", 1), (None, None, None, None, None)]
    rows += [(50, long, "en", "a", 1), (51, twin, "de", "a", 1), (51, twin, "de", "a", 1), (52, twin, "de", "b", 1), (53, twin.upper(), None, "b", 1)]
    rows += [(60 + i, say(30) + " " + passage + " " + say(30), "en", "a", 1) for i in range(4)]
    names = "doc_id long, text string, lang string, source string, n_chars long"
    clashing = ["anchor", "node", "root", "segment", "score", "host", "size", "row", "salt", "key", "toxic"]
    docs = spark.createDataFrame([(*r, *range(len(clashing))) for r in rows], names + "".join(f", {c} int" for c in clashing)).repartition(3)
    columns = docs.columns
    outs = []
    for k, (_, stage) in enumerate(corpus_pipeline.STAGES):
        docs = corpus_pipeline.stored(stage(spark, docs, SF), "edges")
        outs.append(docs.collect())
        if k < 4:
            assert docs.columns == columns and all(tuple(r)[5:] == tuple(range(len(clashing))) for r in outs[-1])
    clean, distinct, cut, mixed, packed = outs
    assert sorted(map(str, clean)) == sorted(str(r) for r in spark.createDataFrame([(*r, *range(len(clashing))) for r in rows], names + "".join(f", {c} int" for c in clashing)).collect())
    by_id = {}
    for r in distinct:
        by_id.setdefault(r.doc_id, []).append(r.text)
    assert by_id[51] == [twin] and 52 not in by_id and 53 not in by_id and {40, 41, 42, 50, 60, 61, 62, 63} <= set(by_id) and len(by_id[None]) == 2
    texts = {r.doc_id: r.text for r in cut}
    assert texts[50] == long and texts[40] is None and texts[41] == "" and all(passage not in texts[60 + i] and len(texts[60 + i]) > 200 for i in range(4))
    assert all(r.text == texts[r.doc_id] for r in mixed if r.doc_id is not None)
    assert sum(r.length for r in packed if r.doc_id == 50) == sum(r.doc_id == 50 for r in mixed) * next((r.doc_tokens for r in packed if r.doc_id == 50), 0)
    again = corpus_pipeline.STAGES[1][1](spark, spark.createDataFrame([(*r, *range(len(clashing))) for r in rows], names + "".join(f", {c} int" for c in clashing)), SF)
    assert sorted(map(str, again.collect())) == sorted(map(str, distinct))
