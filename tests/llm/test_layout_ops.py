"""Packing, sharding and mixing against brute force, and their edge cases."""

import zlib

import numpy as np
import pandas as pd
import pytest

from boxmdl.llm import mixing, packing, sharding

SF = "/root/testdata/sf0.001"
DOCS = "doc_id long, text string, lang string, source string, n_chars long, ids string, shard string, __x int"


def small(spark, rows):
    return spark.createDataFrame([(i, t, None, s, 0, "x", "y", 1) for i, t, s in rows], DOCS)


def test_packing_covers_every_id_once(spark):
    from tokenizers import Tokenizer
    import public_tokenizers

    tok = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    got = packing.op1_cost_balanced_packing(spark, SF).toPandas()
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text").toPandas()
    for doc_id, text in zip(docs.doc_id, docs.text):
        ids = tok.encode(text or "", add_special_tokens=False).ids + [1]
        own = got[got.doc_id == doc_id].sort_values("start")
        assert own.start.tolist() == [0, *own.length.cumsum()[:-1]] and own.length.sum() == len(ids) == own.doc_tokens.iloc[0]
        for r in own.itertuples():
            assert zlib.crc32(np.array(ids[r.start : r.start + r.length], "<u4").tobytes()) == r.ids_crc32
    for _, s in got.sort_values("offset").groupby("sequence_id"):
        assert s.offset.tolist() == [0, *s.length.cumsum()[:-1]]
        n = s.length.sum()
        assert n <= 2048 and (n == 2048 or n & (n - 1) == 0)


def test_packing_edges(spark):
    docs = small(spark, [(1, None, "a"), (1, None, "a"), (2, "", "a"), (3, "word " * 30000, "b"), (4, "a <|endoftext|> b", "b")])
    got = packing.pack(docs).toPandas()
    assert got.groupby("doc_id").length.sum()[1] == 2
    assert 50256 in np.frombuffer(b"".join(got[got.doc_id == 4].ids), "<u4")
    assert packing.pack(docs.limit(0)).count() == 0


def test_packing_balances_cost():
    rng = np.random.default_rng(1)
    window = packing.Window(2048, 1 << 18, 1.0, 1 / 4096)
    made = [s for n in rng.integers(1, 1500, 2000) for s in window.add(0, np.zeros(n, "<u4"))]
    costs = [sum(window.cost(p[3]) for p in s) for s in made]
    assert all(sum(p[3] for p in s) == 2048 for s in made) and np.std(costs) / np.mean(costs) < 0.12


def test_shards_are_contiguous_and_near_equal(spark):
    got = sharding.op4_prefix_sum_shards(spark, SF).toPandas().sort_values("doc_id")
    size, edges = got["size"].to_numpy(), got.groupby("shard")["size"].sum()
    before = size.cumsum() - size
    assert (got.shard == np.minimum(39, (2 * before + size) * 40 // (2 * size.sum()))).all()
    assert got.shard.is_monotonic_increasing and abs(edges - size.sum() / 40).max() <= size.max()
    for _, s in got.groupby("shard"):
        assert s.slot.tolist() == list(range(len(s)))


def test_shard_edges(spark):
    docs = small(spark, [(1, None, "a"), (1, None, "a"), (None, "x", "b"), (2, "y" * 1000, None)]).drop("shard")
    sized = docs.selectExpr("*", "coalesce(octet_length(text), 0) AS size")
    got = sharding.shard(sized, "size", ["doc_id"], 3)
    assert got.count() == 4 and set(docs.columns) < set(got.columns)
    assert sharding.shard(sized.limit(0), "size", ["doc_id"], 3).count() == 0
    nothing = sharding.shard(sized.withColumn("size", sized["size"] * 0), "size", ["doc_id"], 3).toPandas()
    assert set(nothing["shard"]) == {0} and sorted(nothing.slot) == [0, 1, 2, 3]


def water_level(size, weight, limit=3.0):
    """Targets by resharing the excess again and again."""
    target, free, left = {}, set(size), float(sum(size.values()))
    while free:
        share = {s: left * weight[s] / sum(weight[x] for x in free) for s in free}
        over = {s for s in free if share[s] > limit * size[s]}
        if not over:
            return target | share
        target |= {s: limit * size[s] for s in over}
        left -= sum(target[s] for s in over)
        free -= over
    return target


@pytest.mark.parametrize("seed", range(4))
def test_targets_match_repeated_resharing(spark, seed):
    rng = np.random.default_rng(seed)
    size = {f"s{i:02d}": int(x) for i, x in enumerate(rng.pareto(0.6, 11) * 50)} | {"s50": 0}
    names = sorted(size)
    expected = water_level(size, {s: mixing.WEIGHTS[i % 3] for i, s in enumerate(names)})
    frame = spark.createDataFrame([(False, s, n) for s, n in size.items()], "__null boolean, __src string, source_size long")
    got = {r["__src"]: r.target for r in mixing.source_targets(frame).collect()}
    assert got == pytest.approx(expected)


def test_mix_takes_what_it_says(spark):
    taken = mixing.op5_weighted_fair_mix(spark, SF).toPandas()
    per = taken.groupby("source").agg({"taken": "sum", "target": "first"})
    assert abs(per.taken - per.target).max() <= 1 and (taken.taken <= 3 * taken["size"]).all()
    docs = spark.read.parquet(f"{SF}/documents.parquet").withColumn("size", mixing.word_count("text"))
    cut = mixing.mix(docs, "size", whole=False).toPandas()
    assert cut.groupby("doc_id").words.sum().to_dict() == {d: t for d, t in zip(taken.doc_id, taken.taken) if t}
    assert cut.finish.is_monotonic_increasing
    assert mixing.mix(docs, "size").columns == docs.columns


def test_mix_edges(spark):
    docs = small(spark, [(1, "a b", "s"), (1, "a b", "s"), (None, "c", None), (3, None, "t"), (4, "", "s"), (5, "d " * 5000, "s")])
    sized = docs.withColumn("size", mixing.word_count("text"))
    got = mixing.serve(sized, "size").groupBy("__key").agg({"words": "sum"}).toPandas()
    assert len(got) == 6 and got["sum(words)"].sum() <= 5005
    assert mixing.mix(sized.limit(0), "size").count() == 0
    zero = mixing.mix(sized.filter("size = 0"), "size")
    assert zero.count() == 2
    assert isinstance(zero.toPandas(), pd.DataFrame)


def test_mixing_of_many_sources(spark, monkeypatch):
    rows = [(i, " ".join(["w"] * (1 + (i * 7 % 23) ** 2 // 4)), None if i % 29 == 0 else f"host{i * 7 % 23}") for i in range(300)]
    sized = spark.createDataFrame(rows, "doc_id long, text string, source string").withColumn("size", mixing.word_count("text"))
    columns = ["doc_id", "epoch", "target", "words", "finish"]
    few = mixing.serve(sized, "size").select(*columns).toPandas()
    monkeypatch.setattr(mixing, "BROADCAST_SOURCES", 5)
    many = mixing.serve(sized, "size").select(*columns).toPandas()
    key = ["doc_id", "epoch"]
    assert few.sort_values(key).values.tolist() == many.sort_values(key).values.tolist()
    assert few.target.nunique() > 5
    assert mixing.mix(sized.limit(0), "size").count() == 0
