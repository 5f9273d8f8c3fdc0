"""Toxicity by a weighted finite-state grammar over clauses.

Texts are cut into clauses.  In each clause that holds a word of the lexicon,
the words are read by a cascade of weighted transducers, composed into one:

*   lexical transducers, tries over the letters of a word, read a word as an
    insult or threat (at the weight of the word), a target, a negation, a verb
    of reporting or a quotation mark; every word can also be read as any other,
    at no weight;
*   the target transducer marks a match that has a target within reach before
    it, or promises one within reach after it; a path whose promise is not kept
    has no end.  A threat is only a match with a target;
*   the negation transducer marks matches just after a negation, and the
    reported-speech transducer those after a verb of reporting or in quotes.

Every arc has a weight in log odds, a path weighs the sum of its arcs, and a
clause has the matches of its heaviest path.  So the same word counts
differently in "you are a ...", "not a ..." and "he said that ...".

The target, negation, report and threat words, and some insults, are fixed
lists in four languages.  Further insult patterns (whole words, or beginnings
of words) and all their weights are learned from labelled documents as log
odds; a logistic model over the sums of the marked matches then turns a
document's clauses into a score.  Learning uses at most `max_labelled` labelled
documents, those of the lowest hash.

Edge cases: a null or empty text has no match and gets the score of clean
text; documents without a label are not learned from; without labels of both
kinds nothing is learned and every score is that of clean text (0.0); repeated
rows are scored one by one; an empty table gives no rows; other columns are
not read.
"""

from __future__ import annotations

import heapq
import re
from collections import Counter
from collections.abc import Callable, Iterable
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import documents, pieces, train_split

#: Labelled documents that learning may use.
MAX_LABELLED = 30_000
MIN_LOG_ODDS = 3.0
#: Least likelihood-ratio statistic of a pattern, so that chance finds among many candidates stay out.
MIN_EVIDENCE = 20.0
#: Weight of a listed insult that the labels say nothing about.
LISTED_WEIGHT = 4.0
PREFIX_LENGTHS = (4, 5, 6, 7)
THRESHOLD = 0.3

# Fixed word lists (en, de, fr, es).
TARGETS = frozenset("you your yours u ur he she they them him her this that these those people du dich dir ihr euch er sie ihn tu toi vous il elle ils elles lui tú te ti usted ustedes él ella ellos vosotros".split())
NEGATIONS = frozenset("not no never n't neither nor without nicht kein keine keinen nie niemals ne pas jamais aucun aucune ni nunca jamás sin tampoco".split())
REPORTS = frozenset("said says say told claimed claims wrote writes reported reports quoted called sagte sagt schrieb behauptet dit disait écrit affirme dijo dice escribió afirma".split())
THREATS = frozenset("kill murder hurt destroy shoot stab beat strangle burn töten umbringen verletzen schlagen vernichten tuer frapper détruire brûler matar golpear destruir quemar".split())
INSULTS = frozenset(
    "idiot moron stupid dumb imbecile loser scum trash clown worthless pathetic disgusting bastard bitch retard asshole jerk "
    "idiotin dummkopf blöd blödmann abschaum versager arschloch trottel widerlich wertlos erbärmlich "
    "idiote crétin imbécile débile ordure minable connard connasse raclure répugnant "
    "idiota estúpido estúpida imbécil basura escoria payaso patético asqueroso inútil cabrón gilipollas".split()
)

WORD, INSULT, THREAT, TARGET, NEGATION, REPORT, QUOTE = range(7)
CLAUSE_END = re.compile(r"[.!?;:\n]+")
TOKEN = re.compile(r"[^\W\d_]+(?:['’][^\W\d_]+)?|[\"“”«»]")
#: How far a target or a negation reaches, in words.
TARGET_REACH, NEGATION_REACH = 5, 2
#: Arc weights, in log odds: of a threat, and what a target, a negation and reported speech add to a match.
THREAT_WEIGHT, TARGETED, NEGATED, REPORTED = 4.0, 1.0, -2.0, -2.0


@dataclass(frozen=True)
class Transducer:
    """A weighted letter transducer: ``arcs(state, symbol)`` gives (output, weight, next state); ``final(state)`` whether a path may end there."""

    start: object
    arcs: Callable[[object, object], Iterable[tuple]]
    final: Callable[[object], bool] = lambda state: True

    def __matmul__(self, other: Transducer) -> Transducer:
        """Composition: `other` reads what this one writes."""

        def arcs(state, symbol):
            for middle, w, a in self.arcs(state[0], symbol):
                for out, v, b in other.arcs(state[1], middle):
                    yield out, w + v, (a, b)

        return Transducer((self.start, other.start), arcs, lambda state: self.final(state[0]) and other.final(state[1]))

    def compiled(self, alphabet: Iterable) -> Transducer:
        """Its reachable states numbered, its arcs in one table."""
        number, table, ends, todo = {self.start: 0}, {}, [self.final(self.start)], [self.start]
        alphabet = list(alphabet)
        while todo:
            state = todo.pop()
            for symbol in alphabet:
                found = []
                for out, w, to in self.arcs(state, symbol):
                    if to not in number:
                        number[to] = len(number)
                        ends.append(self.final(to))
                        todo.append(to)
                    found.append((out, w, number[to]))
                table[number[state], symbol] = tuple(found)
        return Transducer(0, lambda state, symbol: table[state, symbol], ends.__getitem__)

    def best(self, readings: list[list[tuple]]) -> tuple[float, list]:
        """Weight and outputs of the heaviest path over a sequence of readings, each a choice of (symbol, weight); earlier arcs win ties."""
        front: dict = {self.start: (0.0, None)}
        for choice in readings:
            ahead: dict = {}
            for state, (w, path) in front.items():
                for symbol, v in choice:
                    for out, u, to in self.arcs(state, symbol):
                        if to not in ahead or w + v + u > ahead[to][0] + 1e-12:
                            ahead[to] = w + v + u, (path, out)
            front = ahead
        weight, path = max(((w, p) for s, (w, p) in front.items() if self.final(s)), key=lambda x: x[0], default=(-np.inf, None))
        out = []
        while path is not None:
            path, last = path
            out.append(last)
        return weight, out[::-1]


def targets(reach: int = TARGET_REACH) -> Transducer:
    """Reads word classes; writes (class, targeted).  State: words for which a target before still counts, and words left to keep a promise in."""

    def arcs(state, symbol):
        seen, promised = state
        if symbol == TARGET:
            yield (symbol, False), 0.0, (reach, 0)
            return
        if promised == 1:
            return  # the last word in which the target could have come
        after = max(0, seen - 1), max(0, promised - 1)
        if symbol in (INSULT, THREAT):
            if seen:
                yield (symbol, True), TARGETED, after
            else:
                yield (symbol, True), TARGETED, (0, after[1] or reach)
                if symbol == INSULT:
                    yield (symbol, False), 0.0, after
        else:
            yield (symbol, False), 0.0, after

    return Transducer((0, 0), arcs, lambda state: not state[1])


def negations(reach: int = NEGATION_REACH) -> Transducer:
    """Reads (class, targeted); writes (class, targeted, negated)."""

    def arcs(left, symbol):
        negated = symbol[0] in (INSULT, THREAT) and left > 0
        yield (*symbol, negated), NEGATED if negated else 0.0, reach if symbol[0] == NEGATION else max(0, left - 1)

    return Transducer(0, arcs)


def reports() -> Transducer:
    """Reads (class, targeted, negated); writes (class, targeted, negated, reported): in quotes, or after a verb of reporting."""

    def arcs(state, symbol):
        said, quoted = state
        reported = symbol[0] in (INSULT, THREAT) and (said or quoted)
        yield (*symbol, reported), REPORTED if reported else 0.0, (said or symbol[0] == REPORT, quoted ^ (symbol[0] == QUOTE))

    return Transducer((False, False), arcs)


def grammar() -> Transducer:
    return (targets() @ negations() @ reports()).compiled(range(7))


class Lexicon:
    """The lexical transducers in one trie over letters: a word's readings as (class, weight)."""

    def __init__(self, words: dict[str, float], beginnings: dict[str, float]):
        self.root: dict = {}
        for word, weight in beginnings.items():
            node = self._at(word)
            node["begin"] = max(weight, node.get("begin", 0.0))
        for word, weight in words.items():
            self._at(word)["insult"] = weight
        for kind, listed in ((THREAT, THREATS), (TARGET, TARGETS), (NEGATION, NEGATIONS), (REPORT, REPORTS), (QUOTE, "\"“”«»")):
            for word in listed:
                self._at(word).setdefault("kind", kind)

    def _at(self, word: str) -> dict:
        node = self.root
        for letter in word:
            node = node.setdefault((letter,), {})
        return node

    def readings(self, word: str) -> list[tuple[int, float]]:
        """As an insult (of the whole word, or of its heaviest beginning) or the listed class first; a match can always be read as no match."""
        node, weight = self.root, 0.0
        for letter in word:
            weight = max(weight, node.get("begin", 0.0))
            node = node.get((letter,))
            if node is None:
                return [(INSULT, weight), (WORD, 0.0)] if weight else [(WORD, 0.0)]
        weight = max(weight, node.get("begin", 0.0), node.get("insult", 0.0))
        if weight:
            return [(INSULT, weight), (WORD, 0.0)]
        kind = node.get("kind", WORD)
        return [(THREAT, THREAT_WEIGHT), (WORD, 0.0)] if kind == THREAT else [(kind, 0.0)]


#: Features of a document: the summed insult weights plain, with a target, negated, reported; threats; the heaviest clause; all clauses; number of insults.
N_FEATURES = 8


@dataclass
class Grammar:
    """A lexicon of insult patterns with weights, and the logistic model over the marked sums."""

    words: dict[str, float] = field(default_factory=dict)
    beginnings: dict[str, float] = field(default_factory=dict)
    coef: np.ndarray = field(default_factory=lambda: np.zeros(N_FEATURES))
    bias: float = -np.inf
    _ready: tuple | None = None

    def __getstate__(self):
        return {k: v for k, v in self.__dict__.items() if k != "_ready"}

    def __setstate__(self, state):
        self.__dict__ |= state | {"_ready": None}

    def _compiled(self):
        if self._ready is None:
            import ahocorasick

            scan = ahocorasick.Automaton()
            for pattern in {*self.words, *self.beginnings, *THREATS}:
                scan.add_word(pattern, len(pattern))
            scan.make_automaton()
            self._ready = scan, Lexicon(self.words, self.beginnings), grammar()
        return self._ready

    def clauses(self, text: str) -> list[tuple[float, list[tuple]]]:
        """The clauses with a match: weight of the heaviest path and its matches (word, weight, threat, targeted, negated, reported)."""
        scan, lexicon, machine = self._compiled()
        text = text.lower()
        if next(scan.iter(text), None) is None:
            return []
        found = []
        for clause in CLAUSE_END.split(text):
            if next(scan.iter(clause), None) is None:
                continue
            words = TOKEN.findall(clause)
            readings = [lexicon.readings(w) for w in words]
            if all(len(r) == 1 for r in readings):
                continue
            weight, path = machine.best(readings)
            matches = [(word, r[0][1], out[0] == THREAT, *out[1:]) for word, r, out in zip(words, readings, path, strict=True) if out[0] in (INSULT, THREAT)]
            if matches:
                found.append((weight, matches))
        return found

    def features(self, text: str | None) -> np.ndarray:
        out = np.zeros(N_FEATURES)
        clauses = self.clauses(text or "")
        if not clauses:
            return out
        for _, matches in clauses:
            for _, weight, threat, targeted, negated, reported in matches:
                if threat:
                    out[4] += not negated and not reported
                else:
                    out[2 if negated else 3 if reported else 1 if targeted else 0] += weight
                    out[7] += 1
        out[5] = max(s for s, _ in clauses)
        out[6] = sum(s for s, _ in clauses)
        return np.log1p(out)

    def score(self, text: str | None) -> float:
        z = self.bias + float(self.features(text) @ self.coef)
        return float(1 / (1 + np.exp(-np.clip(z, -50, 50)))) if np.isfinite(self.bias) else 0.0


def patterns(text: str | None) -> Counter:
    """Candidate patterns of a text, with the number of its words that each covers: words ("=word") and beginnings."""
    words = set(re.findall(r"[^\W\d_]{3,}", (text or "").lower()))
    found = Counter("=" + w for w in words)
    for w in words:
        found.update(w[:n] for n in PREFIX_LENGTHS if len(w) > n)
    return found


def _pattern_counts(docs: DataFrame) -> DataFrame:
    """Numbers of the given documents that hold each pattern."""

    def run(batches):
        held = Counter()

        def out():
            batch = pa.RecordBatch.from_arrays([pa.array(list(held), pa.string()), pa.array(list(held.values()), pa.int64())], names=["pattern", "n"])
            held.clear()
            return batch

        for b in pieces(batches):
            for text in b.column(0).to_pylist():
                held.update(patterns(text).keys())
                if len(held) > 100_000:
                    yield out()
        if held:
            yield out()

    return docs.select("text").mapInArrow(run, "pattern string, n long").groupBy("pattern").agg(F.sum("n").alias("n"))


def _pattern_lists(docs: DataFrame, only: frozenset) -> list[dict[str, int]]:
    """For each of the given documents, the words covered by each of the patterns."""
    shared = docs.sparkSession.sparkContext.broadcast(only)

    def run(batches):
        for b in pieces(batches):
            found = [[(k, n) for k, n in patterns(t).items() if k in shared.value] for t in b.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array([[k for k, _ in x] for x in found], pa.list_(pa.string())), pa.array([[n for _, n in x] for x in found], pa.list_(pa.int64()))], names=["pattern", "n"])

    return [dict(zip(r.pattern, r.n, strict=True)) for r in docs.select("text").mapInArrow(run, "pattern array<string>, n array<long>").collect()]


def cover(found: list[dict[str, int]], odds: dict[str, float], least: float, enough: int = 3) -> list[str]:
    """Patterns picked one by one, each for the documents that do not yet hold `enough` words of those picked before.

    So a word that is only in toxic documents because some of them are copies
    of each other is not picked once their insults are; of patterns that do the
    same a whole word is picked, or the longest beginning.
    """
    holders: dict[str, list[int]] = {}
    for k, held in enumerate(found):
        for p in held:
            holders.setdefault(p, []).append(k)
    words, picked = [0] * len(found), []
    gain = lambda p: sum(max(0, min(found[k][p], enough - words[k])) for k in holders[p])
    rank = lambda n, p: (-n, -odds[p], p[0] != "=", -len(p), tuple(-ord(c) for c in p))
    # a gain never grows, so only the pattern in front has to be looked at again
    queue = [(rank(gain(p), p), p) for p in holders]
    heapq.heapify(queue)
    while queue:
        (before, *_), p = queue[0]
        now = gain(p)
        if now != -before:
            heapq.heapreplace(queue, (rank(now, p), p))
            continue
        if now < least:
            break
        heapq.heappop(queue)
        picked.append(p)
        for k in holders[p]:
            words[k] += found[k][p]
    return picked


def _lexicon(labelled: DataFrame, n_toxic: int, n_clean: int) -> tuple[dict, dict]:
    """Patterns with high log odds and enough evidence that cover the toxic documents, and the listed insults that the labels do not contradict."""
    least = max(3, int(0.002 * n_toxic))
    toxic = labelled.filter("toxic = 1")
    names = ["=" + w for w in INSULTS]
    positive = _pattern_counts(toxic).filter(F.col("n") >= least).withColumnRenamed("n", "a")
    counts = positive.join(_pattern_counts(labelled.filter("toxic = 0")).withColumnRenamed("n", "b"), "pattern", "left").na.fill(0, ["b"])
    a, b, share = F.col("a"), F.col("b"), n_toxic / (n_toxic + n_clean)
    weight = F.log((a + 0.5) / (n_toxic + 1)) - F.log((b + 0.5) / (n_clean + 1))
    evidence = 2 * (a * F.log(a / ((a + b) * share)) + F.when(b > 0, b * F.log(b / ((a + b) * (1 - share)))).otherwise(0.0))
    # All patterns are judged in Spark; only those that pass (and the listed) are collected.
    judged = counts.select("pattern", weight.alias("odds"), ((weight >= MIN_LOG_ODDS) & (evidence >= MIN_EVIDENCE)).alias("passes"))
    found = judged.filter(F.col("passes") | F.col("pattern").isin(names)).collect()
    known = {r.pattern: r.odds for r in found}
    odds = {r.pattern: r.odds for r in found if r.passes}
    listed = {p: known.get(p, LISTED_WEIGHT) for p in names}
    chosen = {p: odds[p] for p in cover(_pattern_lists(toxic, frozenset(odds)), odds, least)}
    chosen |= {p: w for p, w in listed.items() if w >= MIN_LOG_ODDS}
    return {p[1:]: w for p, w in chosen.items() if p[0] == "="}, {p: w for p, w in chosen.items() if p[0] != "="}


def _logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1.0, rounds: int = 60) -> tuple[np.ndarray, float]:
    """Damped Newton steps for a ridge-penalised logistic model whose weights are kept from going below 0."""
    design = np.column_stack([x, np.ones(len(x))])
    penalty = np.append(np.full(x.shape[1], ridge), 1e-3)

    def loss(beta):
        z = design @ beta
        return np.logaddexp(0, z).sum() - y @ z + 0.5 * penalty @ beta**2

    beta = np.zeros(design.shape[1])
    beta[-1] = np.log((y.sum() + 0.5) / (len(y) - y.sum() + 0.5))
    now = loss(beta)
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(design @ beta, -30, 30)))
        slope = design.T @ (y - p) - penalty * beta
        curve = (design * (p * (1 - p))[:, None]).T @ design + np.diag(penalty)
        step, size = np.linalg.solve(curve, slope), 1.0
        while size > 1e-4:
            to = beta + size * step
            to[:-1] = np.maximum(to[:-1], 0)
            if (new := loss(to)) < now - 1e-9:
                break
            size /= 2
        else:
            break
        beta, now = to, new
    return beta[:-1], float(beta[-1])


def learn(docs: DataFrame, labels: DataFrame, max_labelled: int = MAX_LABELLED) -> Grammar:
    """A grammar from the labelled documents of the training part (`max_labelled` at most)."""
    marked = labels.filter(F.col("toxic").isNotNull() & train_split(F.col("doc_id"))).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    chosen = marked.orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_labelled)
    # The labelled rows are bounded, so the documents need not move to meet them.
    labelled = docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id").select("text", F.col("toxic").cast("int").alias("toxic")).dropDuplicates().persist()
    try:
        sizes = {r.toxic: r["count"] for r in labelled.groupBy("toxic").count().collect()}
        if not (sizes.get(1) and sizes.get(0)):
            return Grammar()
        words, beginnings = _lexicon(labelled, sizes[1], sizes[0])
        found = Grammar(words, beginnings)
        shared = docs.sparkSession.sparkContext.broadcast(found)

        def run(batches):
            for b in pieces(batches):
                x = [shared.value.features(t).tolist() for t in b.column(0).to_pylist()]
                yield pa.RecordBatch.from_arrays([pa.array(x, pa.list_(pa.float64())), b.column(1)], names=["x", "toxic"])

        seen = labelled.mapInArrow(run, "x array<double>, toxic int").toPandas()
    finally:
        labelled.unpersist()
    found.coef, found.bias = _logistic(np.array(seen["x"].tolist()), seen["toxic"].to_numpy(float))
    return found


def scores(docs: DataFrame, model: Grammar, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """`docs` columns `id_col` and ``score`` of every document."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        for b in pieces(batches):
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([shared.value.score(t) for t in b.column(1).to_pylist()], pa.float64())], names=["doc_id", "score"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col)).mapInArrow(run, "doc_id long, score double")


def without_toxic(docs: DataFrame, model: Grammar, threshold: float = THRESHOLD, text_col: str = "text") -> DataFrame:
    """The rows of `docs` that score below `threshold`, with all their columns."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    at = docs.columns.index(text_col)

    def run(batches):
        for b in pieces(batches):
            yield b.filter(pa.array([shared.value.score(t) < threshold for t in b.column(at).to_pylist()], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)


def op8_clause_grammar_toxicity(spark, sf_dir) -> DataFrame:
    """Scores of all documents, by a grammar learned from the training part."""
    docs = documents(spark, sf_dir)
    model = learn(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return scores(docs, model).select("doc_id", (~train_split(F.col("doc_id"))).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
