"""Near-duplicate documents by an inverted join over MinHash signature coordinates.

1.  Every document becomes its set of word shingles, a digest of the set and a
    MinHash signature of `K` coordinates.  Equal sets form one class; only one
    document of a class, its representative, goes on.
2.  Each representative is posted under its coordinate-value pairs.  Lists of
    one posting say nothing.  A pair of at least `T` equal coordinates must
    meet in one of any K - T + 1 lists, so each document keeps the shortest of
    its lists (the prefix) and skips the long ones.
3.  Shingles that no other posted document has can be part of no intersection.
    What is left of a document's set bounds its intersection with any other:
    documents left with too little are taken off the lists, and pairs are
    skipped where the bound of either rules out the similarity asked for.
4.  Postings are merged without writing out all pairs of a list: every list has
    two pivots, and each of its documents meets the pivots only.  The collisions
    of a pair that meets are counted over all coordinates, merged and skipped
    lists alike; pairs with at least `T` are confirmed on the full shingle sets,
    and confirmed links join components.  Then the documents outside a list's
    largest component meet the members of other components where a longer
    signature of `LONG_K` coordinates lets them, so a link between two documents
    can only be left out when they already are connected.
5.  Components are labelled by alternating star contractions.

With K = 64 and T = 31, as with LONG_K = 512 and LONG_T = 337, a pair of
similarity 0.75 is missed with a probability of about 1e-6.

Edge cases: a null text, or one without words, has an empty set and is linked
with nothing; with fewer words than a shingle the whole sequence is the one
shingle; repeated rows are classes of copies like any other; rows without an
id are labelled by the ids of others in their component and not kept beside
them; where there are none, the label is null and they are kept; an empty
table gives no rows; other columns are not read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import documents, pieces, stored
from .fingerprint import BLOOM_PROBES, BLOOM_WORDS

SHINGLE = 5
PERCENT = 75
K = 64
T = 31
#: Parts that the classes of one component are spread over when they get its label.
SALTS = 32
LONG_K = 512
LONG_T = 337

_FOLD = bytes.maketrans(b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"abcdefghijklmnopqrstuvwxyz")
_rng = np.random.default_rng(20240611)
_PLACE = _rng.integers(1 << 62, size=SHINGLE, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_MULT = _rng.integers(1 << 62, size=K, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_ADD = _rng.integers(1 << 63, size=K, dtype=np.uint64)
_LONG_MULT = _rng.integers(1 << 62, size=LONG_K, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_LONG_ADD = _rng.integers(1 << 63, size=LONG_K, dtype=np.uint64)


def _mixed(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(31))) * np.uint64(0x9E3779B97F4A7C15)
    h = (h ^ (h >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    return h ^ (h >> np.uint64(32))


class Shingler:
    """Shingle sets as sorted arrays of 64-bit hashes; remembers the hashes of words."""

    def __init__(self, size: int = SHINGLE):
        self.size, self.words = size, {}

    def __call__(self, text: str | None) -> np.ndarray:
        words = (text or "").encode("utf-8", "surrogatepass").translate(_FOLD).split()
        n, known = len(words), self.words
        if not n:
            return np.zeros(0, np.uint64)
        if len(known) > 100_000:
            known.clear()
        for w in set(words).difference(known):
            known[w] = xxhash.xxh3_64_intdigest(w)
        h = np.fromiter(map(known.__getitem__, words), dtype=np.uint64, count=n)
        if n < self.size:
            return _mixed(np.array([int((h * _PLACE[:n]).sum(dtype=np.uint64)) + n & (1 << 64) - 1], np.uint64))
        total = h[: n - self.size + 1] * _PLACE[0]
        for j in range(1, self.size):
            total = total + h[j : n - self.size + 1 + j] * _PLACE[j]
        return np.unique(_mixed(total))


def signature(shingles: np.ndarray) -> np.ndarray:
    """The K least values of a set under K hash functions, as signed 32-bit numbers."""
    least = np.full(K, np.iinfo(np.uint64).max, np.uint64)
    for at in range(0, len(shingles), 4096):
        part = shingles[at : at + 4096, None] * _MULT + _ADD
        np.minimum(least, part.min(axis=0), out=least)
    return (least >> np.uint64(32)).astype(np.uint32).view(np.int32)


def long_signature(shingles: np.ndarray) -> np.ndarray:
    """LONG_K coordinates of 16 bits (from the middle of the least values: their upper bits are all small)."""
    least = np.full(LONG_K, np.iinfo(np.uint64).max, np.uint64)
    for at in range(0, len(shingles), 1024):
        part = shingles[at : at + 1024, None] * _LONG_MULT + _LONG_ADD
        np.minimum(least, part.min(axis=0), out=least)
    return (least >> np.uint64(20)).astype(np.uint16).view(np.int16)


def similar(a: np.ndarray, b: np.ndarray, percent: int = PERCENT) -> bool:
    if 100 * min(len(a), len(b)) < percent * max(len(a), len(b)):
        return False
    both = len(np.intersect1d(a, b, assume_unique=True))
    return 100 * both >= percent * (len(a) + len(b) - both)


def signatures(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """``row`` (a number of its own for every row), ``doc_id``, ``n_shingles``, ``set_digest``, ``sig``, ``text_hash``."""

    def run(batches):
        shingler, at = Shingler(), TaskContext.get().partitionId() << 33
        for b in pieces(batches):
            ids, sizes, digests, sigs = b.column(0), [], [], []
            for text in b.column(1).to_pylist():
                s = shingler(text)
                sizes.append(len(s))
                digests.append(xxhash.xxh3_128_digest(s.tobytes()))
                sigs.append(signature(s) if len(s) else np.zeros(0, np.int32))
            offsets = np.cumsum([0, *map(len, sigs)])
            flat = np.concatenate(sigs) if sigs else np.zeros(0, np.int32)
            yield pa.RecordBatch.from_arrays(
                [pa.array(range(at, at + len(sizes)), pa.int64()), ids, pa.array(sizes, pa.int64()), pa.array(digests, pa.binary()), pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(flat)), b.column(2)],
                names=["row", "doc_id", "n_shingles", "set_digest", "sig", "text_hash"],
            )
            at += len(sizes)

    keyed = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col), _text_hash(text_col))
    return keyed.mapInArrow(run, "row long, doc_id long, n_shingles long, set_digest binary, sig array<int>, text_hash long")


def _text_hash(text_col: str):
    """With the id, the key by which verdicts find their rows again."""
    return F.xxhash64(F.coalesce(F.col(text_col), F.lit(""))).alias("text_hash")


def prefix_postings(reps: DataFrame, threshold: int = T) -> DataFrame:
    """``key``, ``count`` (the list's length), ``node``: each representative under the shortest lists it must share with any partner."""
    posted = reps.select("node", F.posexplode("sig").alias("at", "value")).select("node", (F.shiftleft(F.col("at").cast("long"), 32) + (F.col("value").cast("long") + (1 << 31))).alias("key"))
    lists = posted.groupBy("key").count().filter("count > 1")
    shared = posted.join(lists, "key").groupBy("node").agg(F.array_sort(F.collect_list(F.struct("count", "key"))).alias("lists"))  # at most K entries a document
    kept = shared.filter(F.size("lists") >= threshold).select("node", F.explode(F.slice("lists", 1, F.size("lists") - threshold + 1)).alias("list"))
    return kept.select("list.key", "list.count", "node")


def _bloom(ids: DataFrame) -> np.ndarray:
    """Bloom filter of fixed size over the ids."""
    probe = [F.xxhash64("doc_id", F.lit(k)) for k in range(BLOOM_PROBES)]
    bits = ids.select(F.explode(F.array(*probe)).alias("h")).select(F.pmod(F.shiftright("h", 6), F.lit(BLOOM_WORDS)).cast("int").alias("word"), F.expr("shiftleft(1L, cast(pmod(h, 64) as int))").alias("bit"))
    rows = bits.groupBy("word").agg(F.bit_or("bit").alias("bits")).toPandas()
    words = np.zeros(BLOOM_WORDS, np.int64)
    words[rows["word"].to_numpy()] = rows["bits"].to_numpy()
    return words.view(np.uint64)


def candidate_texts(docs: DataFrame, reps: DataFrame, postings: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """``node``, ``text`` of the representatives in `postings`."""
    wanted = reps.join(postings.select("node").distinct(), "node").select("node", "doc_id", "set_digest")
    shared = docs.sparkSession.sparkContext.broadcast(_bloom(wanted.select("doc_id")))
    word = [F.xxhash64("doc_id", F.lit(k)) for k in range(BLOOM_PROBES)]

    def run(batches):
        shingler, bloom = Shingler(), shared.value
        for b in pieces(batches):
            ids, texts = b.column(0).to_pylist(), b.column(1).to_pylist()
            hit = np.ones(len(ids), bool)
            for k in range(BLOOM_PROBES):
                h = b.column(2 + k).to_numpy(zero_copy_only=False).astype(np.int64)
                hit &= (bloom[(h >> 6) % BLOOM_WORDS] >> (h % 64).astype(np.uint64)) & np.uint64(1) == 1
            rows = [(ids[r], xxhash.xxh3_128_digest(shingler(texts[r]).tobytes()), texts[r]) for r in np.flatnonzero(hit)]
            yield pa.RecordBatch.from_arrays([pa.array([x[k] for x in rows], t) for k, t in enumerate((pa.int64(), pa.binary(), pa.string()))], names=["id", "digest", "text"])

    found = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).select("doc_id", "text", *word).mapInArrow(run, "id long, digest binary, text string")
    return wanted.join(found, wanted["doc_id"].eqNullSafe(found["id"]) & (wanted["set_digest"] == found["digest"])).select("node", "text").dropDuplicates(["node"])


def likely(pairs: DataFrame, reps: DataFrame, threshold: int = T) -> DataFrame:
    """Of the pairs (``a``, ``b``), those with `threshold` equal coordinates."""
    sig = lambda x: reps.select(F.col("node").alias(x), F.col("sig").alias(f"sig_{x}"))
    equal = F.aggregate(F.zip_with("sig_a", "sig_b", lambda x, y: (x == y).cast("int")), F.lit(0), lambda s, x: s + x)
    return pairs.join(sig("a"), "a").join(sig("b"), "b").filter(equal >= threshold).select("a", "b")


def confirmed(pairs: DataFrame, texts: DataFrame, percent: int = PERCENT) -> DataFrame:
    """Of the pairs (``a``, ``b``), those of `percent` similarity on the full sets."""
    text = lambda x: texts.select(F.col("node").alias(x), F.col("text").alias(f"text_{x}"))

    def run(batches):
        shingler, last = Shingler(), (None, None)
        for batch in pieces(batches):
            keep = []
            for b, text_a, text_b in zip(*(batch.column(k).to_pylist() for k in (1, 2, 3)), strict=True):
                if last[0] != b:
                    last = b, shingler(text_b)
                keep.append(similar(shingler(text_a), last[1], percent))
            yield batch.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return pairs.join(text("a"), "a").join(text("b"), "b").select("a", "b", "text_a", "text_b").mapInArrow(run, "a long, b long")


def shared_parts(texts: DataFrame, reps: DataFrame, percent: int = PERCENT) -> DataFrame:
    """``node``, ``n`` (set size) and ``e`` (shingles that another posted document has too) of the documents that may have a link."""

    def run(batches):
        shingler = Shingler()
        for b in pieces(batches):
            sets = [shingler(t) for t in b.column(1).to_pylist()]
            nodes = np.repeat(b.column(0).to_numpy(zero_copy_only=False), [len(s) for s in sets])
            flat = np.concatenate(sets) if sets else np.zeros(0, np.uint64)
            yield pa.RecordBatch.from_arrays([pa.array(nodes, pa.int64()), pa.array(flat.view(np.int64))], names=["node", "shingle"])

    alone = texts.mapInArrow(run, "node long, shingle long").groupBy("shingle").agg(F.count(F.lit(1)).alias("c"), F.min("node").alias("node")).filter("c = 1").groupBy("node").agg(F.count(F.lit(1)).alias("own"))
    sizes = reps.select("node", F.col("n_shingles").alias("n")).join(texts.select("node"), "node").join(alone, "node", "left")
    return sizes.select("node", "n", (F.col("n") - F.coalesce("own", F.lit(0))).alias("e")).filter(100 * F.col("e") >= percent * F.col("n"))


def long_signatures(texts: DataFrame) -> DataFrame:
    """``node``, ``long`` of the posted documents."""

    def run(batches):
        shingler = Shingler()
        for b in pieces(batches):
            sigs = [long_signature(shingler(t)) for t in b.column(1).to_pylist()]
            flat = np.concatenate(sigs) if sigs else np.zeros(0, np.int16)
            offsets = pa.array(np.arange(len(sigs) + 1) * LONG_K, pa.int32())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.ListArray.from_arrays(offsets, pa.array(flat))], names=["node", "long"])

    return texts.mapInArrow(run, "node long, long array<smallint>")


def _possible(x: str, y: str, percent: int):
    """Whether the shared parts of two documents leave room for the similarity."""
    return (100 + percent) * F.least(F.col(f"{x}e"), F.col(f"{y}e")) >= percent * (F.col(f"{x}n") + F.col(f"{y}n"))


def components(edges: DataFrame) -> DataFrame:
    """``node``, ``root`` (the least node reachable) of every node in `edges` (``a``, ``b``), by large-star and small-star rounds."""
    now = stored(edges.filter("a != b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "edges")
    state = None
    while True:
        both = now.unionByName(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("m"))
        large = both.filter("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).filter("a != b")
        least = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(least, "a").filter("b != m").select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(least.select("a", F.col("m").alias("b")))
        now = stored(small.distinct(), "edges")
        new = tuple(now.agg(F.count(F.lit(1)), F.coalesce(F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")), F.lit(0))).first())
        if new == state or not new[0]:
            break
        state = new
    return now.select(F.col("a").alias("node"), F.col("b").alias("root")).unionByName(now.select(F.col("b").alias("node"), F.col("b").alias("root")).distinct())


def _with_pivots(postings: DataFrame, percent: int) -> DataFrame:
    """Pairs of each posting with its list's pivots: the document with the largest shared part, and one by hash."""
    pivot = F.struct("node", "n", "e")
    lists = postings.groupBy("key").agg(F.max_by(pivot, F.struct(F.col("e") / F.col("n"), F.xxhash64("node"))).alias("p0"), F.min_by(pivot, F.xxhash64("node", F.lit(1))).alias("p1"))
    met = postings.join(lists, "key").select("node", "n", "e", F.explode(F.array("p0", "p1")).alias("p")).select("node", "n", "e", F.col("p.node").alias("p"), F.col("p.n").alias("pn"), F.col("p.e").alias("pe"))
    return met.filter((F.col("node") != F.col("p")) & _possible("", "p", percent)).select(F.greatest("node", "p").alias("a"), F.least("node", "p").alias("b")).distinct()


def _between_components(labelled: DataFrame, texts: DataFrame, percent: int) -> DataFrame:
    """Pairs of different components on a list: of the postings outside the list's largest component with all others."""
    held = labelled.groupBy("key", "root").count()
    main = held.groupBy("key").agg(F.max_by("root", F.struct("count", "root")).alias("main"), F.sum("count").alias("all"), F.max("count").alias("most")).filter("`all` > most").select("key", "main")
    # a document's lists in one order for all, shortest first: a pair is made in the first list that it shares, and only there
    order = labelled.groupBy("node").agg(F.array_sort(F.collect_list(F.struct("count", "key"))).getField("key").alias("lists"))
    apart = labelled.join(main, "key")
    facts = texts.join(apart.select("node").distinct(), "node")
    apart = stored(apart.join(order, "node").join(long_signatures(facts), "node"), "apart")
    x, y = (apart.select("key", *(F.col(c).alias(side + c) for c in ("node", "n", "e", "root", "main", "lists", "long"))) for side in "xy")
    possible = (F.col("xroot") != F.col("yroot")) & ((F.col("yroot") == F.col("ymain")) | (F.col("xnode") > F.col("ynode"))) & _possible("x", "y", percent)
    equal = F.aggregate(F.zip_with("xlong", "ylong", lambda p, q: (p == q).cast("int")), F.lit(0), lambda t, v: t + v)
    meet = x.filter("xroot != xmain").join(y, "key").filter(possible & (F.get(F.array_intersect("xlists", "ylists"), 0) == F.col("key")) & (equal >= LONG_T))
    return meet.select(F.greatest("xnode", "ynode").alias("a"), F.least("xnode", "ynode").alias("b")).distinct()


def link(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", percent: int = PERCENT, threshold: int = T) -> tuple[DataFrame, DataFrame, DataFrame | None]:
    """The rows (``doc_id``, ``n_shingles``, ``text_hash``, ``set_digest``), the classes of equal sets (``set_digest``, ``node``: its representative, ``least_id``), and ``node``, ``root`` of the linked representatives (None without links)."""
    rows = stored(signatures(docs, id_col, text_col), "signatures")
    full = rows.filter("n_shingles > 0")
    classes = stored(full.groupBy("set_digest").agg(F.min("row").alias("node"), F.min("doc_id").alias("least_id")), "classes")
    reps = stored(full.join(classes.select(F.col("node").alias("row")), "row", "left_semi").select(F.col("row").alias("node"), "doc_id", "n_shingles", "set_digest", "sig"), "representatives")
    members = rows.select("doc_id", "n_shingles", "text_hash", "set_digest")
    posted = stored(prefix_postings(reps, threshold), "postings")
    if posted.isEmpty():
        return members, classes, None
    texts = stored(candidate_texts(docs, reps, posted, id_col, text_col), "texts")
    postings = stored(posted.join(shared_parts(texts, reps, percent), "node").select("key", "count", "node", "n", "e"), "shared")
    links = stored(confirmed(likely(_with_pivots(postings, percent), reps, threshold), texts, percent), "links")
    roots = components(links)
    labelled = stored(postings.join(roots, "node", "left").withColumn("root", F.coalesce("root", "node")), "labelled")
    more = stored(confirmed(_between_components(labelled, texts, percent), texts, percent), "links")
    if not more.isEmpty():
        roots = components(roots.select(F.col("node").alias("a"), F.col("root").alias("b")).unionByName(more))
    return members, classes, roots


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", percent: int = PERCENT) -> DataFrame:
    """``doc_id``, ``n_shingles``, ``component_id`` (the least id in the component), ``kept``, ``text_hash``."""
    members, classes, roots = link(docs, id_col, text_col, percent)
    # labels are worked out for classes, so a group of copies is one row until the last join
    labels = classes.select("set_digest", F.col("least_id").alias("component_id"))
    if roots is not None:
        least = roots.join(classes.select("node", "least_id"), "node").groupBy("root").agg(F.min("least_id").alias("least"))
        salted = least.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        named = roots.withColumn("salt", F.pmod(F.xxhash64("node"), F.lit(SALTS)).cast("int")).join(salted, ["root", "salt"]).select("node", "least")
        labels = classes.join(named, "node", "left").select("set_digest", F.coalesce("least", "least_id").alias("component_id"))
    out = members.join(labels, "set_digest", "left").withColumn("component_id", F.coalesce("component_id", "doc_id"))
    return out.select("doc_id", "n_shingles", "component_id", F.coalesce(F.col("doc_id") == F.col("component_id"), F.col("component_id").isNull()).alias("kept"), "text_hash")


def without_near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of `docs` whose id is the least of its component; of rows that repeat an id and a shingle set, one stays."""
    verdict = stored(near_duplicates(docs, id_col, text_col).filter("kept").groupBy("doc_id", "text_hash").agg(F.count(F.lit(1)).alias("n"), F.max("n_shingles").alias("n_shingles")), "kept")
    keep = verdict.select(F.col("doc_id").alias("__kept"), F.col("text_hash").alias("__kept_text"))
    marked = docs.withColumn("__text", _text_hash(text_col))
    out = marked.join(keep, marked[id_col].eqNullSafe(keep["__kept"]) & (marked["__text"] == keep["__kept_text"]), "left_semi").drop("__text")
    if verdict.filter("n > 1 AND n_shingles > 0").isEmpty():
        return out
    words = F.coalesce(F.col(text_col).rlike(r"[^\x20\x09-\x0D]"), F.lit(False))
    return out.filter(words).dropDuplicates([id_col, text_col]).unionByName(out.filter(~words))


def op2_coordinate_join_neardup(spark, sf_dir) -> DataFrame:
    """Components of near-duplicates among all documents."""
    return near_duplicates(documents(spark, sf_dir)).drop("text_hash")
