"""Language identification with character n-gram language models.

Each language has an interpolated Kneser-Ney model of order 4 over normalised
characters (lower case, letters and their marks only, everything else folded to one space).
Counts are taken in Spark over all training documents but a held-out share; the
models are kept together in sorted key arrays, one row of log probabilities (a
value for each language) for every n-gram that any language has seen, with
back-off rows for the rest.  A text goes to the language of the lowest
cross-entropy for each character.  The confidence is the posterior of that
language at a temperature that grows with the square root of the length, and is
halved for texts whose cross-entropy is above the language's rejection level: a
high quantile over the training documents held out (one in `HELD_OUT`, by a
hash of the text, so copies stay on one side), which the models have not seen.  A
language of which none is held out takes its other documents.

No n-gram is left out and every character is itself: n-grams of up to three
characters are one number of 21 bits for each, and longest n-grams are the
place of their first three characters in the sorted array beside the last one.
A model grows with the languages' spelling (4 bytes for each language and each
n-gram that any of them has).  Combining marks count as letters.

Edge cases: a null text or one without a letter is `und` with score 0, as is
everything when there was nothing to learn from; documents without a language
are not learned from; repeated rows count again; of languages with equal
cross-entropy the first by name is taken; very long texts are worked through
in pieces; an empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

import unicodedata
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import documents, pieces, train_split

ORDER = 4
#: Bits of a character: every code point has its own.
BITS = 21
SYMBOL = (1 << BITS) - 1
SPACE = 32
#: One in so many training documents is held out to set the rejection levels.
HELD_OUT = 10
#: Quantile of a language's held-out texts that its rejection level is set at, and the accuracy it is found with.
REJECT_QUANTILE = 0.995
ACCURACY = 10_000
#: Characters worked on at once.
CHUNK = 1 << 21
#: Kinds of characters in a chunk up to which an n-gram is counted as one number.
PACKED_KINDS = 1 << 15

_table: np.ndarray | None = None


def symbols() -> np.ndarray:
    """Every letter or mark as itself, SPACE for any other code point."""
    global _table
    if _table is None:
        codes = np.arange(0x110000, dtype=np.int32)
        letter = np.fromiter((unicodedata.category(chr(c))[0] in "LM" for c in range(0x110000)), dtype=bool, count=0x110000)
        _table = np.where(letter, codes, SPACE).astype(np.int32)
    return _table


def encoded(text: str) -> np.ndarray:
    """The normalised text's characters, led by ORDER - 1 spaces and closed by one; empty without a letter."""
    codes = np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), dtype=np.uint32)
    keys = symbols()[codes]
    gap = keys == SPACE
    if gap.all():
        return keys[:0]
    keep = ~gap
    keep[1:] |= ~gap[:-1]
    keys = keys[keep]
    keys = keys[1:] if keys[0] == SPACE else keys
    keys = keys[:-1] if keys[-1] == SPACE else keys
    return np.concatenate([np.full(ORDER - 1, SPACE, np.int32), keys, np.full(1, SPACE, np.int32)])


def triples(keys: np.ndarray) -> np.ndarray:
    """Packed groups of ORDER - 1 characters, one for each place that one starts at; the last but one and so on are the contexts of the characters from ORDER - 1 on."""
    k = keys.astype(np.int64)
    packed = k[: len(k) - ORDER + 2].copy()
    for j in range(1, ORDER - 1):
        packed <<= BITS
        packed |= k[j : len(k) - ORDER + 2 + j]
    return packed


def counted(context: np.ndarray, symbol: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Different (context, character) pairs and their numbers."""
    used = np.bincount(symbol, minlength=1)
    for j in range(ORDER - 1):
        part = np.bincount((context >> (BITS * j)) & SYMBOL)
        wide = max(len(used), len(part))
        used = np.pad(used, (0, wide - len(used))) + np.pad(part, (0, wide - len(part)))
    kinds = np.flatnonzero(used)
    if len(kinds) <= PACKED_KINDS:
        dense = np.cumsum(used > 0) - 1
        packed = np.zeros(len(context), np.int64)
        for j in range(ORDER - 2, -1, -1):
            packed = packed << 15 | dense[(context >> (BITS * j)) & SYMBOL]
        gram, n = np.unique(packed << 15 | dense[symbol], return_counts=True)
        low = (1 << 15) - 1
        context = np.zeros(len(gram), np.int64)
        for j in range(ORDER - 1, 0, -1):
            context = context << BITS | kinds[(gram >> (15 * j)) & low]
        return context, kinds[gram & low].astype(np.int64), n
    contexts, place = np.unique(context, return_inverse=True)
    gram, n = np.unique(place << BITS | symbol, return_counts=True)
    return contexts[gram >> BITS], gram & SYMBOL, n


def count_ngrams(docs: DataFrame, text_col: str = "text", lang_col: str = "lang") -> DataFrame:
    """``lang``, ``context`` (the first characters, packed), ``symbol`` (the last), ``n``: occurrences over all given documents."""

    def run(batches):
        held: dict[str, list[tuple[np.ndarray, np.ndarray]]] = {}
        size = 0

        def out():
            for lang, parts in held.items():
                context, symbol, n = counted(*(np.concatenate(x) for x in zip(*parts, strict=True)))
                yield pa.RecordBatch.from_arrays([pa.array([lang] * len(n), pa.string()), pa.array(context), pa.array(symbol.astype(np.int32)), pa.array(n.astype(np.int64))], names=["lang", "context", "symbol", "n"])
            held.clear()

        for b in pieces(batches):
            for text, lang in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                keys = encoded(text or "")
                if len(keys):
                    held.setdefault(lang, []).append((triples(keys)[:-1], keys[ORDER - 1 :]))
                    size += len(keys)
                if size > CHUNK:
                    yield from out()
                    size = 0
        yield from out()

    parts = docs.filter(F.col(lang_col).isNotNull()).select(F.col(text_col), F.col(lang_col).cast("string")).mapInArrow(run, "lang string, context long, symbol int, n long")
    return parts.groupBy("lang", "context", "symbol").agg(F.sum("n").alias("n"))


def _discount(n: np.ndarray) -> float:
    once, twice = int((n == 1).sum()), int((n == 2).sum())
    return min(0.95, max(0.05, once / (once + 2 * twice))) if once else 0.5


def _find(keys: np.ndarray, wanted: np.ndarray) -> np.ndarray:
    """Places of the wanted keys in the sorted array; -1 where they are not."""
    if not len(keys):
        return np.full(len(wanted), -1)
    at = np.searchsorted(keys, wanted)
    at[at == len(keys)] = 0
    at[keys[at] != wanted] = -1
    return at


@dataclass
class Models:
    """Models of all languages in sorted arrays.

    ``keys[m]`` are the m-grams: packed characters up to ORDER - 1, and for the
    longest the place of the first characters in ``keys[ORDER - 1]`` beside the
    last.  ``probs[m]`` are their log2 probabilities (a column for each
    language) and ``weights[m]`` the log2 weights with which an unseen character
    after such an m-gram falls back.
    """

    langs: list[str]
    keys: dict[int, np.ndarray]
    probs: dict[int, np.ndarray]
    weights: dict[int, np.ndarray]
    floor: float
    limits: np.ndarray | None = None

    @classmethod
    def fit(cls, lang: np.ndarray, context: np.ndarray, symbol: np.ndarray, n: np.ndarray) -> Models:
        langs = sorted(set(lang.tolist()))
        top = ORDER - 1
        mask = lambda m: (1 << BITS * m) - 1
        counts: dict[int, list] = {m: [] for m in range(1, ORDER)}
        longest = []
        for name in langs:
            own = lang == name
            longest.append((context[own], symbol[own].astype(np.int64), n[own]))
            # continuation counts: how many different characters come before the m-gram
            g, c = np.unique((context[own] & mask(top - 1)) << BITS | symbol[own], return_counts=True)
            counts[top].append((g, c))
            for m in range(top - 1, 0, -1):
                g, c = np.unique(g & mask(m), return_counts=True)
                counts[m].append((g, c))
        seen = np.unique(np.concatenate([g for g, _ in counts[1]])) if langs else np.zeros(0, np.int64)
        floor = -np.log2(len(seen) + 1)
        empty = [np.zeros(0, np.int64)]
        keys: dict[int, np.ndarray] = {}
        for m in range(top, 0, -1):  # contexts are among the keys, also where they only begin a text
            longer = [x for x, _, _ in longest] if m == top else [keys[m + 1] >> BITS]
            keys[m] = np.unique(np.concatenate([*(g for g, _ in counts[m]), *longer, *empty]))
        keys[ORDER] = np.unique(np.concatenate([*(_find(keys[top], x) << BITS | y for x, y, _ in longest), *empty]))
        probs, weights = {}, {}
        below, below_at = np.full((1, len(langs)), 2.0**floor), None
        for m in range(1, ORDER + 1):
            contexts = np.zeros(1, np.int64) if m == 1 else keys[m - 1]
            out = np.zeros((len(keys[m]), len(langs)))
            fall = np.ones((len(contexts), len(langs)))
            of = keys[m] >> BITS if m == ORDER else np.zeros(len(keys[m]), np.int64) if m == 1 else np.searchsorted(contexts, keys[m] >> BITS)
            for k in range(len(langs)):
                if m == ORDER:
                    x, y, c = longest[k]
                    at = np.searchsorted(keys[m], _find(keys[top], x) << BITS | y)
                else:
                    g, c = counts[m][k]
                    at = np.searchsorted(keys[m], g)
                d = _discount(c)
                total = np.bincount(of[at], c, len(contexts))
                kinds = np.bincount(of[at], minlength=len(contexts))
                has = total > 0
                fall[has, k] = d * kinds[has] / total[has]
                out[at, k] = (c - d) / total[of[at]]
            if m == ORDER:
                shorter = np.searchsorted(keys[top], (keys[top][of] & mask(top - 1)) << BITS | keys[m] & SYMBOL)
            else:
                shorter = np.searchsorted(keys[m - 1], keys[m] & mask(m - 1)) if m > 1 else np.zeros(len(keys[m]), int)
            out += fall[of] * below[shorter]
            below = out
            probs[m], weights[m - 1] = np.log2(np.maximum(out, 1e-300)).astype(np.float32), np.log2(fall).astype(np.float32)
        return cls(langs, keys, probs, weights, floor)

    def logs(self, context: np.ndarray, symbol: np.ndarray) -> np.ndarray:
        """log2 probability of each character after its packed context of ORDER - 1 characters, for each language."""
        top = ORDER - 1
        place = _find(self.keys[top], context)
        at = np.where(place >= 0, _find(self.keys[ORDER], place << BITS | symbol), -1)
        return self._fallen(at, place, (context << BITS | symbol) & ((1 << BITS * top) - 1), ORDER)

    def _fallen(self, at: np.ndarray, place: np.ndarray, shorter: np.ndarray, m: int) -> np.ndarray:
        """Rows `at` of the m-grams; for those unseen (-1) the weight of the context's `place` and what the `shorter` (m - 1)-gram has."""
        out = self.probs[m][at] if len(self.keys[m]) else np.zeros((len(at), len(self.langs)), np.float32)
        new = np.flatnonzero(at < 0)
        if not len(new):
            return out
        weight = np.where(place[new, None] >= 0, self.weights[m - 1][place[new]], np.float32(0))
        if m == 1:
            out[new] = np.float32(self.floor) + weight
            return out
        rest = shorter[new]
        context = _find(self.keys[m - 2], rest >> BITS) if m > 2 else np.zeros(len(rest), np.int64)
        out[new] = weight + self._fallen(_find(self.keys[m - 1], rest), context, rest & ((1 << BITS * (m - 2)) - 1), m - 1)
        return out

    def entropies(self, texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
        """Cross-entropy for each character (a row for each text, a column for each language) and numbers of characters."""
        size = np.zeros(len(texts), np.int64)
        total = np.zeros((len(texts), len(self.langs)))
        rows: list[int] = []
        parts: list[tuple[np.ndarray, np.ndarray]] = []

        def settle():
            context, symbol = (np.concatenate(x) for x in zip(*parts, strict=True))
            starts = np.cumsum([0, *(len(c) for c, _ in parts[:-1])])
            np.add.at(total, rows, np.add.reduceat(self.logs(context, symbol).astype(np.float64), starts))
            rows.clear()
            parts.clear()

        held = 0
        for r, text in enumerate(texts):
            keys = encoded(text or "")
            if not len(keys):
                continue
            size[r] = len(keys) - ORDER + 1
            context, symbol = triples(keys)[:-1], keys[ORDER - 1 :].astype(np.int64)
            for at in range(0, len(context), CHUNK // 4):
                rows.append(r)
                parts.append((context[at : at + CHUNK // 4], symbol[at : at + CHUNK // 4]))
                held += len(parts[-1][0])
                if held > CHUNK // 4:
                    settle()
                    held = 0
        if parts:
            settle()
        return -total / np.maximum(size, 1)[:, None], size

    def predict(self, texts: list[str | None]) -> tuple[list[str], np.ndarray, np.ndarray]:
        """Language, score and whether the text is above the rejection level."""
        if not self.langs:
            return ["und"] * len(texts), np.zeros(len(texts)), np.ones(len(texts), bool)
        entropy, size = self.entropies(texts)
        best = entropy.argmin(axis=1)
        least = entropy[np.arange(len(texts)), best]
        spread = np.exp2(-(entropy - least[:, None]) * np.sqrt(np.maximum(size, 1))[:, None])
        score = 1.0 / spread.sum(axis=1)
        rejected = least > (self.limits[best] if self.limits is not None else np.inf)
        score = np.where(size > 0, np.where(rejected, score / 2, score), 0.0)
        return [self.langs[b] if n else "und" for b, n in zip(best, size, strict=True)], score, rejected | (size == 0)


def train(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> Models:
    """Models from the given documents with a language, of all their n-grams; rejection levels from those held out."""
    own = docs.filter(F.col(lang_col).isNotNull()).select(F.col(text_col), F.col(lang_col).cast("string").alias(lang_col))
    aside = F.pmod(F.xxhash64(F.coalesce(text_col, F.lit("")), F.lit("held out")), F.lit(HELD_OUT)) == 0
    kinds = own.groupBy(lang_col).agg(F.count_if(~aside).alias("rest")).collect()  # a row for each language
    few = [r[lang_col] for r in kinds if not r.rest]
    if few:  # of a language that would be held out whole, nothing is
        aside = aside & ~F.col(lang_col).isin(few)
    learned = own.filter(~aside)
    found = count_ngrams(learned, text_col, lang_col).toArrow()
    lang = found["lang"].combine_chunks().dictionary_encode()
    names = np.array(lang.dictionary.to_pylist(), dtype=object)
    models = Models.fit(names[lang.indices.to_numpy(zero_copy_only=False)], found["context"].to_numpy(), found["symbol"].to_numpy(), found["n"].to_numpy())
    shared = docs.sparkSession.sparkContext.broadcast(models)

    def levels(rows: DataFrame) -> dict[str, float]:
        scores = rows.select(text_col, lang_col).mapInArrow(_own_entropy(shared), "lang string, entropy double")
        return {r["lang"]: r["level"] * 1.02 for r in scores.groupBy("lang").agg(F.percentile_approx("entropy", REJECT_QUANTILE, ACCURACY).alias("level")).collect()}

    level = levels(own.filter(aside))
    missing = [x for x in models.langs if x not in level]
    if missing:
        level |= levels(learned.filter(F.col(lang_col).isin(missing)))
    models.limits = np.array([level.get(x, np.inf) for x in models.langs])
    return models


def _own_entropy(models):
    def run(batches):
        for b in pieces(batches):
            texts, langs = b.column(0).to_pylist(), b.column(1).to_pylist()
            at = {x: k for k, x in enumerate(models.value.langs)}
            entropy, size = models.value.entropies(texts)
            rows = [(x, float(entropy[r, at[x]])) for r, x in enumerate(langs) if size[r] and x in at]
            yield pa.RecordBatch.from_arrays([pa.array([x for x, _ in rows], pa.string()), pa.array([e for _, e in rows], pa.float64())], names=["lang", "entropy"])

    return run


def identify(docs: DataFrame, models: Models, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id``, ``lang_pred``, ``score``, ``rejected`` of every document."""
    shared = docs.sparkSession.sparkContext.broadcast(models)

    def run(batches):
        for b in pieces(batches):
            langs, score, rejected = shared.value.predict(b.column(1).to_pylist())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(langs, pa.string()), pa.array(score, pa.float64()), pa.array(rejected, pa.bool_())], names=["doc_id", "lang_pred", "score", "rejected"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col)).mapInArrow(run, "doc_id long, lang_pred string, score double, rejected boolean")


def op9_kneser_ney_languages(spark, sf_dir) -> DataFrame:
    """Languages of all documents, by models of the training part."""
    docs = documents(spark, sf_dir)
    models = train(docs.filter(train_split(F.col("doc_id"))))
    return identify(docs, models).select("doc_id", (~train_split(F.col("doc_id"))).alias("held_out"), "lang_pred", "score", "rejected")
