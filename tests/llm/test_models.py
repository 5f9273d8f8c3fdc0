"""Toxicity grammar and language models: held-out accuracy, properties and edge cases."""

import duckdb
import numpy as np
import pytest

from boxmdl.llm import langid, toxicity
from boxmdl.llm.common import train_split

SF = "/root/testdata/sf0.01"


def test_split_follows_the_checksum(spark):
    import zlib

    rows = spark.range(-5, 200).select("id", train_split(langid.F.col("id")).alias("t")).collect()
    assert all(r.t == (zlib.crc32(str(r.id).encode()) % 4 != 2) for r in rows)


def test_languages_held_out(spark):
    got = langid.op9_kneser_ney_languages(spark, SF).toPandas()
    lang = duckdb.sql(f"select doc_id, lang from '{SF}/documents.parquet'").df()
    both = got.merge(lang, on="doc_id")
    assert len(got) == len(lang) and got.score.between(0, 1).all()
    held = both[both.held_out]
    assert (held.lang_pred == held.lang).mean() > 0.97


def model(texts):
    counts = {}
    for lang, text in texts:
        keys = langid.encoded(text)
        for c, x in zip(langid.triples(keys)[:-1].tolist(), keys[3:].tolist(), strict=True):
            counts[lang, c, x] = counts.get((lang, c, x), 0) + 1
    lang, context, symbol = zip(*counts)
    return langid.Models.fit(np.array(lang, object), np.array(context), np.array(symbol), np.array(list(counts.values())))


def pack(context):
    out = 0
    for c in context:
        out = out << langid.BITS | ord(c)
    return out


class PlainKneserNey:
    """Interpolated Kneser-Ney of one language straight from its definition, with dictionaries of strings."""

    def __init__(self, texts, n_seen):
        self.counts = {4: {}, 3: {}, 2: {}, 1: {}}
        for t in texts:
            s = "".join(map(chr, langid.encoded(t).tolist()))
            for i in range(3, len(s)):
                self.counts[4][s[i - 3 : i + 1]] = self.counts[4].get(s[i - 3 : i + 1], 0) + 1
        for m in (3, 2, 1):
            for gram in self.counts[m + 1]:
                self.counts[m][gram[1:]] = self.counts[m].get(gram[1:], 0) + 1
        self.discount, self.n_seen = {}, n_seen
        for m, c in self.counts.items():
            once, twice = list(c.values()).count(1), list(c.values()).count(2)
            self.discount[m] = min(0.95, max(0.05, once / (once + 2 * twice))) if once else 0.5

    def prob(self, context, x):
        m = len(context) + 1
        below = self.prob(context[1:], x) if context else 1 / (self.n_seen + 1)
        after = {g: c for g, c in self.counts[m].items() if g[:-1] == context}
        if not after:
            return below
        total, d = sum(after.values()), self.discount[m]
        return max(0, after.get(context + x, 0) - d * (context + x in after)) / total + d * len(after) / total * below


TEXTS = [("a", "the cat sat on the mat with that hat"), ("a", "the dog 日本語 sat 日本 𐐷 there"), ("b", "die katze sitzt auf der matte mit dem hut"), ("b", "日の katze")]


def test_models_equal_a_plain_kneser_ney():
    m = model(TEXTS)
    seen = {c for _, t in TEXTS for c in langid.encoded(t).tolist()}
    plain = [PlainKneserNey([t for x, t in TEXTS if x == lang], len(seen)) for lang in ("a", "b")]
    alphabet = sorted({chr(c) for c in seen} | {"q", "語", "𐐀"})
    rng = np.random.default_rng(5)
    texts = ["the mat", "日本語", "katze 𐐷", "qqq", "xthe"]
    contexts = ["   ", *("".join(rng.choice(alphabet, 3)) for _ in range(120)), *(t[i : i + 3] for _, t in TEXTS for i in range(0, 20, 3))]
    for c in contexts:
        c = "".join(chr(x) for x in [*c.lower().encode("utf-32-le")[:0], *map(ord, c.lower())]).ljust(3)
        logs = m.logs(np.full(len(alphabet), pack(c)), np.array([ord(x.lower()) for x in alphabet]))
        for k in range(2):
            assert np.exp2(logs[:, k].astype(float)) == pytest.approx([plain[k].prob(c, x.lower()) for x in alphabet], rel=1e-4)
    entropy, size = m.entropies(texts)
    for r, t in enumerate(texts):
        s = "".join(map(chr, langid.encoded(t).tolist()))
        for k in range(2):
            bits = [-np.log2(plain[k].prob(s[i - 3 : i], s[i])) for i in range(3, len(s))]
            assert size[r] == len(bits) and entropy[r, k] == pytest.approx(np.mean(bits), rel=1e-4)


def test_counting_by_either_packing(monkeypatch):
    keys = langid.encoded("abc abd 日本語 abc " * 20)
    context, symbol = langid.triples(keys)[:-1], keys[3:]
    get = lambda: sorted(zip(*(x.tolist() for x in langid.counted(context, symbol))))
    one = get()
    monkeypatch.setattr(langid, "PACKED_KINDS", 0)
    assert get() == one and sum(n for *_, n in one) == len(symbol)


def test_probabilities_sum_to_one():
    m = model(TEXTS[:1] + TEXTS[2:3])
    known = m.keys[1].tolist() + [5]  # the unigram floor leaves room for one unseen character
    for context in ("the", "xqz", "th ", "zzz"):
        logs = m.logs(np.full(len(known), pack(context)), np.array(known))
        assert np.exp2(logs.astype(float)).sum(axis=0) == pytest.approx([1, 1], abs=1e-4)


def test_long_texts_and_ties(monkeypatch):
    m = model(TEXTS)
    text = "the cat 日本 sat " * 50
    whole = m.entropies([text, "die matte", None, "12"])
    monkeypatch.setattr(langid, "CHUNK", 64)
    parts = m.entropies([text, "die matte", None, "12"])
    assert np.allclose(whole[0], parts[0]) and whole[1].tolist() == parts[1].tolist() and whole[1][2:].tolist() == [0, 0]
    even = model([("y", "same words"), ("x", "same words")])
    assert even.predict(["same words", "other"])[0] == ["x", "x"]


def test_language_edges(spark):
    rows = [(1, "hello there my friend", "en", 0), (1, "hello there my friend", "en", 0), (3, None, "en", 0), (4, "12 34", None, 0), (5, "日本語の文章", None, 0), (6, "guten tag mein freund", "de", 0)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, gram int")
    models = langid.train(docs)
    got = {r.doc_id: r for r in langid.identify(docs, models).collect()}
    assert got[3].lang_pred == got[4].lang_pred == "und" and got[3].score == 0
    assert got[1].lang_pred == "en" and got[6].lang_pred == "de" and got[5].rejected
    nothing = langid.train(docs.filter("lang = 'xx'"))
    assert {r.lang_pred for r in langid.identify(docs, nothing).collect()} == {"und"}
    assert langid.identify(docs.limit(0), models).count() == 0


def test_rejection_levels_are_quantiles_of_texts_held_out(spark):
    import random

    rng = random.Random(8)
    say = lambda letters: " ".join("".join(rng.choices(letters, k=rng.randrange(2, 7))) for _ in range(6))
    rows = [(i, say("abcde"), "many") for i in range(9000)] + [(9000 + i, say("vwxyz"), "few") for i in range(3)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    models = langid.train(docs)
    aside = {r.doc_id for r in docs.filter(langid.F.expr("pmod(xxhash64(text, 'held out'), 10) = 0")).collect()}
    assert 700 < len(aside) < 1100
    for k, name in enumerate(models.langs):
        theirs = [(i, t) for i, t, x in rows if x == name]
        own = np.sort(models.entropies([t for i, t in theirs if i in aside] or [t for _, t in theirs])[0][:, k])
        assert models.limits[k] == pytest.approx(1.02 * own[int(np.ceil(langid.REJECT_QUANTILE * len(own))) - 1], rel=1e-3)
    learned = {c for i, t, _ in rows if i not in aside for c in langid.triples(langid.encoded(t)).tolist()}
    assert set(models.keys[3].tolist()) == learned
    for text in {t for i, t, _ in rows if i in aside and i < 9000}:
        alone = langid.train(spark.createDataFrame([(1, text, "one")], "doc_id long, text string, lang string"))
        assert alone.langs == ["one"] and np.isfinite(alone.limits[0])
        break


def test_no_ngram_is_left_out_of_a_large_table(spark):
    letters = np.array([c for c in range(0x61, 0x600) if chr(c).isalpha() and chr(c).lower() == chr(c)])
    texts = ["".join(map(chr, np.random.default_rng(k).choice(letters, 60_000))) for k in range(40)]
    docs = spark.createDataFrame([(k, t, "x") for k, t in enumerate(texts)], "doc_id long, text string, lang string").repartition(8)
    aside = {r.doc_id for r in docs.filter(langid.F.expr("pmod(xxhash64(text, 'held out'), 10) = 0")).collect()}
    seen = set()
    for k, t in enumerate(texts):
        if k not in aside:
            keys = langid.encoded(t)
            seen.update(zip(langid.triples(keys)[:-1].tolist(), keys[3:].tolist()))
    models = langid.train(docs)
    assert len(seen) > 1_500_000 and len(models.keys[langid.ORDER]) == len(seen)


def test_marks_are_part_of_words_and_every_character_is_itself():
    assert len(langid.encoded("हिन्दी")) == langid.ORDER + len("हिन्दी")
    text = "".join(chr(c) for c in [*range(0xE01, 0xE2F), *range(0x4E00, 0x9000), *range(0x20000, 0x20400)])
    assert len(set(langid.encoded(text).tolist())) == len(text) + 1


def test_toxicity_held_out(spark):
    got = toxicity.op8_clause_grammar_toxicity(spark, SF).toPandas()
    labels = duckdb.sql(f"select doc_id, toxic from '{SF}/labels.parquet'").df()
    both = got.merge(labels, on="doc_id")
    held = both[both.held_out]
    hit = (held.predicted == 1) & (held.toxic == 1)
    assert hit.sum() >= 0.6 * held.toxic.sum() and ((held.predicted == 1) & (held.toxic == 0)).sum() <= 1
    assert ((got.score >= 0.3) == got.predicted.astype(bool)).all()


def test_grammar_marks_matches():
    g = toxicity.Grammar(words={"idiot": 4.0}, beginnings={"lowei": 3.0})
    marks = lambda text: [m for _, c in g.clauses(text) for m in c]
    weight = lambda text: sum(w for w, _ in g.clauses(text))
    assert marks("You are an idiot.") == [("idiot", 4.0, False, True, False, False)]
    assert marks("what an idiot you are") == [("idiot", 4.0, False, True, False, False)]
    assert marks("idiot of the very worst sort ever, you") == [("idiot", 4.0, False, False, False, False)]
    assert marks("he is not an idiot") == [("idiot", 4.0, False, True, True, False)]
    assert marks('the paper said "idiot" today') == [("idiot", 4.0, False, False, False, True)]
    assert marks("said nothing. what idiot") == [("idiot", 4.0, False, False, False, False)]
    assert marks("das loweischaft war") == [("loweischaft", 3.0, False, False, False, False)]
    assert marks("idiotic or flowei") == [] and marks("") == []
    assert marks("i will kill you") == [("kill", toxicity.THREAT_WEIGHT, True, True, False, False)] and weight("i will kill you") == 5.0
    assert weight("you, i will kill") == 5.0 and marks("to kill time on a rainy afternoon at home") == [] and weight("i will not kill you") == 3.0
    assert marks("kill or destroy you") == [("kill", 4.0, True, True, False, False), ("destroy", 4.0, True, True, False, False)]
    assert weight("you idiot") > weight("an idiot") > weight("not idiot")


def test_heaviest_path_by_enumeration():
    """All readings of all words, every reading judged on its own from the whole clause."""
    import itertools
    import random

    rng = random.Random(2)
    machine = toxicity.grammar()
    T = toxicity

    def weight_of(symbols):
        total, marks, kind = 0.0, [], [s for s, _ in symbols]
        for i, (s, w) in enumerate(symbols):
            total += w
            if s in (T.INSULT, T.THREAT):
                before = T.TARGET in kind[max(0, i - T.TARGET_REACH) : i]
                after = T.TARGET in kind[i + 1 : i + 1 + T.TARGET_REACH]
                if s == T.THREAT and not (before or after):
                    return -np.inf, None
                negated = T.NEGATION in kind[max(0, i - T.NEGATION_REACH) : i]
                said = T.REPORT in kind[:i] or kind[:i].count(T.QUOTE) % 2 == 1
                total += T.TARGETED * (before or after) + T.NEGATED * negated + T.REPORTED * said
                marks.append((i, before or after, negated, said))
        return total, marks

    for _ in range(400):
        readings = []
        for _ in range(rng.randrange(1, 12)):
            kind = rng.choice([T.WORD, T.WORD, T.WORD, T.INSULT, T.THREAT, T.TARGET, T.NEGATION, T.REPORT, T.QUOTE])
            readings.append([(kind, round(rng.uniform(0.5, 5), 3)), (T.WORD, 0.0)] if kind in (T.INSULT, T.THREAT) else [(kind, 0.0)])
        best = max((weight_of(p) for p in itertools.product(*readings)), key=lambda x: x[0])
        weight, path = machine.best(readings)
        assert weight == pytest.approx(best[0])
        assert [(i, *o[1:]) for i, o in enumerate(path) if o[0] in (T.INSULT, T.THREAT)] == best[1]


def test_composition_has_the_paths_of_its_parts():
    import random

    rng = random.Random(3)
    parts = toxicity.targets(), toxicity.negations(), toxicity.reports()
    whole = toxicity.grammar()
    for _ in range(60):
        symbols = [rng.randrange(7) for _ in range(rng.randrange(1, 9))]
        paths = [((), 0.0, tuple(p.start for p in parts))]
        for x in symbols:
            ahead = []
            for outs, w, (a, b, c) in paths:
                for o, u, a2 in parts[0].arcs(a, x):
                    for q, v, b2 in parts[1].arcs(b, o):
                        ahead += [((*outs, r), w + u + v + z, (a2, b2, c2)) for r, z, c2 in parts[2].arcs(c, q)]
            paths = ahead
        ours = [((), 0.0, whole.start)]
        for x in symbols:
            ours = [((*outs, o), w + u, to) for outs, w, state in ours for o, u, to in whole.arcs(state, x)]
        ends = lambda found, ok: sorted((o, round(w, 9)) for o, w, s in found if ok(s))
        assert ends(ours, whole.final) == ends(paths, lambda s: all(p.final(x) for p, x in zip(parts, s)))


def test_copies_do_not_make_a_lexicon():
    found = [{"=idiot": 1, "idio": 1, "=scum": 2} for _ in range(40)] + [{"=idiot": 3, "=copyword": 1} for _ in range(30)]
    assert "=copyword" not in toxicity.cover(found, dict.fromkeys(("=idiot", "idio", "=scum", "=copyword"), 4.0), 3)


def test_rare_insults_are_scored_beside_many_common_words(spark):
    import random

    rng = random.Random(4)
    common = " ".join("".join(rng.choices("abcdefghijklmnopqrstuvwxyz", k=9)) for _ in range(6000))
    rows = [(common + (" zyxgrobble" if i < 10 else ""), 1) for i in range(40)] + [(common, 0)] * 100
    words, beginnings = toxicity._lexicon(spark.createDataFrame(rows, "text string, toxic int"), 40, 100)
    assert "zyxgrobble" in words and not any(p in common for p in words if p not in toxicity.INSULTS)


def test_toxicity_edges(spark):
    docs = spark.createDataFrame([(1, None, 7), (2, "", 7), (2, "", 7), (3, "word " * 50000, 7)], "doc_id long, text string, score int")
    labels = spark.createDataFrame([(1, 0, None), (2, None, 1), (99, 1, 1)], "doc_id long, quality int, toxic int")
    model = toxicity.learn(docs, labels)
    assert {r.score for r in toxicity.scores(docs, model).collect()} == {0.0}
    assert toxicity.scores(docs.limit(0), model).count() == 0
    kept = toxicity.without_toxic(docs, toxicity.Grammar(words={"word": 9.0}, coef=np.ones(8), bias=0.0))
    assert kept.columns == docs.columns and kept.count() == 0  # a bias of 0 puts even clean text at one half
