"""Removal of long byte strings that occur more than once in a corpus.

A string of `LENGTH` bytes is a repeat if it also starts anywhere else, in any
document.  Two equal strings have the same anchor: the place of the least hash
among their K-grams, which depends on their bytes alone.  So

1.  each document is cut into segments, maximal runs of string starts with one
    anchor; Spark counts the anchors and keeps those seen twice or more;
2.  where all segments of an anchor are equal, all their strings are repeats;
    so are those of a segment that is itself found twice;
3.  the other segments of repeated anchors (around the ends of copied passages)
    are dealt out by anchor, one of each kind, and sorted in shards by external
    induced suffix sorting (`induced`); neighbours in suffix order with a
    common prefix of LENGTH bytes are repeats;
4.  the bytes under all repeats are removed.

A shard is read as a stream of anchors and sorted in batches of at least
`batch_bytes`; only the segments of one anchor must be in one batch.  The sort
holds its queues in bounded memory and writes runs to the folder that executors
share beyond it.  The segments of anchors seen more than `hot_segments` times
are not sorted: their strings are grouped by content (a 128-bit hash), over all
tasks.  Which segments step 1 can skip is told during the scan by a Bloom filter
sized by the number of repeated anchors, up to `MOST_WORDS`; a filter that is too full
lets more segments through, never fewer.  Places of anchors seen more than
`SALTED` times meet their verdicts under salted keys.  Segments are compared by
64-bit hashes beside the 64-bit hash of their anchor.

Edge cases: a null text counts as empty; texts below LENGTH bytes are left
alone; every byte of a text that has a copy goes, in all the copies; repeated
rows are copies; an empty table gives no rows; other columns are kept, and
helper columns have names with "__".
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import documents, pieces, shared_dir, stored
from .induced import repeated_starts

LENGTH = 200
GRAM = 48
#: Words of 64 bits in a Bloom filter: one for every four anchors, within these bounds (32 KB and 32 MB).
LEAST_WORDS, MOST_WORDS = 1 << 12, 1 << 22
#: Occurrences of an anchor from which on its places are salted, and the number of salts.
SALTED, SALTS = 500, 64
BATCH_BYTES = 2 << 20
#: Occurrences of an anchor up to which one task sorts its segments.
HOT_SEGMENTS = 10_000
#: Bytes of a document worked on at once (places in it take 24 bits of a sort key).
CHUNK = 1 << 22
#: Segments whose bytes a task remembers to have sent.
REMEMBERED = 1 << 18

_BASE = 0x9E3779B97F4A7C15
_INVERSE = pow(_BASE, -1, 1 << 64)
_PLACE_BITS = 24
_powers = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse modulo 2**64, for exponents below n at least."""
    while len(_powers[0]) < n:
        size = len(_powers[0])
        for k, base in enumerate((_BASE, _INVERSE)):
            _powers[k] = np.concatenate([_powers[k], _powers[k] * np.uint64(pow(base, size, 1 << 64))])
    return _powers[0], _powers[1]


def _gram_hashes(data: np.ndarray, gram: int) -> np.ndarray:
    up, down = _power_tables(len(data) + 1)
    total = np.zeros(len(data) + 1, np.uint64)
    np.cumsum((data.astype(np.uint64) + np.uint64(1)) * up[: len(data)], out=total[1:])
    h = (total[gram:] - total[:-gram]) * down[: len(data) - gram + 1]
    h ^= h >> np.uint64(32)
    h *= np.uint64(0xD6E8FEB86659FD93)
    h ^= h >> np.uint64(29)
    return h


def _sliding_min(values: np.ndarray, width: int) -> np.ndarray:
    """Least of each `width` neighbours, from running minima within blocks."""
    n = len(values)
    pad = -n % width
    blocks = np.concatenate([values, np.full(pad, np.iinfo(values.dtype).max, values.dtype)]).reshape(-1, width)
    ahead = np.minimum.accumulate(blocks, axis=1).ravel()
    back = np.minimum.accumulate(blocks[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(back[: n - width + 1], ahead[width - 1 : n])


def segments(data: bytes, length: int = LENGTH, gram: int = GRAM) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """First and last string start of each segment, and its anchor's hash."""
    whole = np.frombuffer(data, np.uint8)
    parts = []
    for at in range(0, max(0, len(whole) - length + 1), CHUNK):
        piece = whole[at : at + CHUNK + length - 1]
        h = _gram_hashes(piece, gram)
        key = (h & ~np.uint64((1 << _PLACE_BITS) - 1)) | np.arange(len(h), dtype=np.uint64)
        least = _sliding_min(key, length - gram + 1)
        first = np.flatnonzero(np.append(True, least[1:] != least[:-1]))
        place = (least[first] & np.uint64((1 << _PLACE_BITS) - 1)).astype(np.int64)
        parts.append((first + at, np.append(first[1:], len(least)) - 1 + at, h[place].view(np.int64)))
    if not parts:
        none = np.zeros(0, np.int64)
        return none, none, none
    return tuple(np.concatenate(x) for x in zip(*parts, strict=True))


def _segment_hash(data: bytes, lo: int, hi: int, length: int) -> int:
    return xxhash.xxh3_64_intdigest(data[lo : hi + length]) - (1 << 63)


def _utf8(text: str | None) -> bytes:
    return (text or "").encode("utf-8", "surrogatepass")


def _bloom(anchors: DataFrame) -> np.ndarray:
    """Bloom filter over anchors (two probes each), sized by their number; at most MOST_WORDS rows come to the driver."""
    size = LEAST_WORDS
    n = anchors.count()
    while size < MOST_WORDS and 4 * size < n:
        size *= 2
    probe = lambda word, bit: F.struct(F.pmod(F.shiftright("anchor", word), F.lit(size)).alias("w"), F.pmod(F.shiftright("anchor", bit), F.lit(64)).alias("b"))
    bits = anchors.select(F.explode(F.array(probe(6, 0), probe(36, 30))).alias("p")).groupBy(F.col("p.w").cast("int").alias("w")).agg(F.bit_or(F.expr("shiftleft(1L, cast(p.b as int))")).alias("bits")).toArrow()
    words = np.zeros(size, np.int64)
    words[bits["w"].to_numpy()] = bits["bits"].to_numpy()
    return words.view(np.uint64)


def _hits(words: np.ndarray, anchors: np.ndarray) -> np.ndarray:
    one, size = np.uint64(1), len(words)
    first = words[(anchors >> 6) % size] >> (anchors % 64).astype(np.uint64) & one
    return (first & (words[(anchors >> 36) % size] >> ((anchors >> 30) % 64).astype(np.uint64)) & one).astype(bool)


def _keyed(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """A document's key is its id and a hash of its text: rows that share both are copies, and treated alike."""
    return docs.select(F.col(id_col).alias("__id"), F.xxhash64(F.coalesce(text_col, F.lit(""))).alias("__text"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))


def repeated_anchors(docs: DataFrame, text_col: str = "text", length: int = LENGTH, gram: int = GRAM) -> DataFrame:
    """``anchor``, ``mixed`` (whether its segments differ), ``held`` (how often it is seen) of the anchors seen twice or more."""

    def run(batches):
        for b in pieces(batches):
            anchors, hashes = [np.zeros(0, np.int64)], []
            for text in b.column(0).to_pylist():
                data = _utf8(text)
                lo, hi, anchor = segments(data, length, gram)
                anchors.append(anchor)
                hashes += [_segment_hash(data, x, y, length) for x, y in zip(lo.tolist(), hi.tolist(), strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(anchors)), pa.array(hashes, pa.int64())], names=["anchor", "segment"])

    seen = docs.select(F.col(text_col)).mapInArrow(run, "anchor long, segment long")
    return seen.groupBy("anchor").agg(F.count(F.lit(1)).alias("n"), F.min("segment").alias("x"), F.max("segment").alias("y")).filter("n > 1").select("anchor", (F.col("x") != F.col("y")).alias("mixed"), F.col("n").alias("held"))


def _shared_strings(segments: DataFrame, length: int) -> DataFrame:
    """``anchor``, ``segment``, ``starts`` of the strings that are in two or more of the different segments of an anchor."""

    def run(batches):
        for b in pieces(batches, 64):
            row, at, digests = [], [], []
            for k, data in enumerate(b.column(2).to_pylist()):
                n = len(data) - length + 1
                row += [k] * n
                at += range(n)
                digests += [xxhash.xxh3_128_digest(data[i : i + length]) for i in range(n)]
            of = pa.array(row, pa.int64())
            yield pa.RecordBatch.from_arrays([b.column(0).take(of), b.column(1).take(of), pa.array(at, pa.int64()), pa.array(digests, pa.binary())], names=["anchor", "segment", "at", "string"])

    strings = stored(segments.select("anchor", "segment", "bytes").mapInArrow(run, "anchor long, segment long, at long, string binary"), "strings")
    again = strings.groupBy("string").agg(F.count(F.lit(1)).alias("__n")).filter("__n > 1").select("string")
    return strings.join(again, "string").groupBy("anchor", "segment").agg(F.collect_list(F.struct(F.col("at").alias("lo"), F.col("at").alias("hi"))).alias("starts"))  # at most a segment's own strings


def repeated_spans(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", length: int = LENGTH, gram: int = GRAM, batch_bytes: int = BATCH_BYTES, hot_segments: int = HOT_SEGMENTS) -> DataFrame:
    """``__id``, ``__text`` (hash) and ``spans`` (first and last starts of repeated strings) of the documents that hold any."""
    spark = docs.sparkSession
    again = stored(repeated_anchors(docs, text_col, length, gram), "anchors")
    any_words = spark.sparkContext.broadcast(_bloom(again))
    mixed_words = spark.sparkContext.broadcast(_bloom(again.filter("mixed")))
    hot_words = spark.sparkContext.broadcast(_bloom(again.filter(F.col("held") > SALTED)))
    folder = shared_dir(spark)
    keyed = _keyed(docs, id_col, text_col)
    id_type = dict(keyed.dtypes)["__id"]

    def find(batches):
        sent: set[tuple[int, int]] = set()
        for b in pieces(batches):
            row, rows = [], []
            for k, text in enumerate(b.column(2).to_pylist()):
                data = _utf8(text)
                lo, hi, anchor = segments(data, length, gram)
                hit = np.flatnonzero(_hits(any_words.value, anchor))
                if not len(hit):
                    continue
                lo, hi, anchor = lo[hit], hi[hit], anchor[hit]
                mixed = _hits(mixed_words.value, anchor).tolist()
                salt = np.where(_hits(hot_words.value, anchor), (lo * 31 + hi + xxhash.xxh3_64_intdigest(data) % SALTS) % SALTS, 0).tolist()
                for x, y, a, m, z in zip(lo.tolist(), hi.tolist(), anchor.tolist(), mixed, salt, strict=True):
                    s, own = _segment_hash(data, x, y, length), None
                    if m and (a, s) not in sent:
                        if len(sent) >= REMEMBERED:
                            sent.clear()
                        sent.add((a, s))
                        own = data[x : y + length]
                    row.append(k)
                    rows.append((x, y, a, s, z, own))
            at = pa.array(row, pa.int64())
            rest = [pa.array(c, t) for c, t in zip(zip(*rows, strict=True) if rows else [[]] * 6, (*[pa.int64()] * 4, pa.int32(), pa.binary()), strict=True)]
            yield pa.RecordBatch.from_arrays([b.column(0).take(at), b.column(1).take(at), *rest], names=["__id", "__text", "lo", "hi", "anchor", "segment", "salt", "bytes"])

    found = stored(keyed.mapInArrow(find, f"__id {id_type}, __text long, lo long, hi long, anchor long, segment long, salt int, bytes binary"), "segments")
    # one row for each kind of segment from here on; anchors that only the filter let through go in the join
    kinds = found.groupBy("anchor", "segment").agg(F.count(F.lit(1)).alias("n"), F.collect_set("salt").alias("salts")).join(again.select("anchor", "mixed"), "anchor")

    def sort_shard(batches):
        held: list[tuple[int, int, bytes]] = []
        size = 0

        def settle(rows):
            starts = repeated_starts([x[2] for x in rows], length, folder=folder)
            out = []
            for (anchor, segment, _), s in zip(rows, starts, strict=True):
                if len(s):
                    cut = np.flatnonzero(np.append(True, np.diff(s) > 1))
                    out.append((anchor, segment, [{"lo": int(s[i]), "hi": int(s[j])} for i, j in zip(cut, np.append(cut[1:], len(s)) - 1, strict=True)]))
            kinds = (pa.int64(), pa.int64(), pa.list_(pa.struct([("lo", pa.int64()), ("hi", pa.int64())])))
            columns = list(zip(*out, strict=True)) if out else [[]] * 3
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, kinds, strict=True)], names=["anchor", "segment", "starts"])

        for b in pieces(batches):
            for anchor, segment, data in zip(*(c.to_pylist() for c in b.columns), strict=True):
                if size >= batch_bytes and anchor != held[-1][0]:
                    yield settle(held)
                    held, size = [], 0
                held.append((anchor, segment, data))
                size += len(data)
        if held:
            yield settle(held)

    hot = f"mixed and held > {int(hot_segments)}"
    once = found.filter("bytes is not null").select("anchor", "segment", "bytes").dropDuplicates(["anchor", "segment"])
    unlike = once.join(again.filter(f"mixed and not ({hot})").select("anchor"), "anchor")
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    shards = unlike.repartition(parts, "anchor").sortWithinPartitions("anchor").select("anchor", "segment", "bytes").mapInArrow(sort_shard, "anchor long, segment long, starts array<struct<lo:long,hi:long>>")
    if not again.filter(hot).isEmpty():
        shards = shards.unionByName(_shared_strings(once.join(again.filter(hot).select("anchor"), "anchor"), length))
    judged = kinds.join(shards, ["anchor", "segment"], "left").filter("not mixed or n > 1 or starts is not null")
    whole = ~F.col("mixed") | (F.col("n") > 1)
    verdicts = stored(judged.select("anchor", "segment", F.explode("salts").alias("salt"), F.when(~whole, F.col("starts")).alias("starts")), "verdicts")

    placed = found.select("__id", "__text", "lo", "hi", "anchor", "segment", "salt").join(verdicts, ["anchor", "segment", "salt"])
    every = placed.filter("starts is null").select("__id", "__text", "lo", "hi")
    partly = placed.filter("starts is not null").select("__id", "__text", F.col("lo").alias("at"), F.explode("starts").alias("s")).select("__id", "__text", (F.col("at") + F.col("s.lo")).alias("lo"), (F.col("at") + F.col("s.hi")).alias("hi"))
    spans = every.unionByName(partly)
    return spans.groupBy("__id", "__text").agg(F.collect_list(F.struct("lo", "hi")).alias("spans"))  # at most a document's own segments


def cut(data: bytes, spans, length: int = LENGTH) -> tuple[bytes, int]:
    """The bytes outside all strings that start in `spans`, and the number of maximal removed runs."""
    kept, at, runs, end = [], 0, 0, -1
    for lo, hi in sorted((s["lo"], s["hi"]) for s in spans or ()):
        if lo > end:
            runs += 1
            kept.append(data[at:lo])
        end = max(end, hi + length)
        at = end
    kept.append(data[at:])
    return b"".join(kept), runs


def with_spans(docs: DataFrame, id_col: str, text_col: str, **options) -> DataFrame:
    """`docs` with the column ``__spans``, null where nothing is repeated."""
    spans = repeated_spans(docs, id_col, text_col, **options)
    keyed = docs.withColumn("__text", F.xxhash64(F.coalesce(text_col, F.lit(""))))
    return keyed.join(spans.select(F.col("__id").alias("__sid"), F.col("__text").alias("__stext"), F.col("spans").alias("__spans")), F.col(id_col).eqNullSafe(F.col("__sid")) & (F.col("__text") == F.col("__stext")), "left").drop("__text", "__sid", "__stext")


def without_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", size_col: str | None = "n_chars", **options) -> DataFrame:
    """`docs` with repeated strings cut out of the texts (a character cut in part goes as a whole), and `size_col` brought up to date."""
    names = docs.columns
    marked = with_spans(docs, id_col, text_col, **options)
    at = names.index(text_col)

    def run(batches):
        for b in pieces(batches):
            texts = [t if s is None or t is None else cut(_utf8(t), s)[0].decode("utf-8", "ignore") for t, s in zip(b.column(at).to_pylist(), b.column(len(names)).to_pylist(), strict=True)]
            columns = list(b.columns[: len(names)])
            columns[at] = pa.array(texts, pa.string())
            yield pa.RecordBatch.from_arrays(columns, names=names)

    out = marked.select(*names, "__spans").mapInArrow(run, docs.schema)
    if size_col and size_col in names:
        kind = dict(docs.dtypes)[size_col]
        out = out.withColumn(size_col, F.when(F.col(text_col).isNotNull(), F.length(text_col).cast(kind)).otherwise(F.col(size_col)))
    return out


def op7_induced_suffix_dedup(spark, sf_dir) -> DataFrame:
    """What is left of every document, with repeated strings removed."""
    marked = with_spans(documents(spark, sf_dir).select("doc_id", "text"), "doc_id", "text")

    def run(batches):
        for b in pieces(batches):
            rows = []
            for text, spans in zip(b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True):
                data = _utf8(text)
                kept, runs = cut(data, spans)
                rows.append((len(data), len(data) - len(kept), runs, hashlib.sha256(kept).hexdigest()))
            columns = list(zip(*rows, strict=True)) if rows else [[]] * 4
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.string())
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array(c, t) for c, t in zip(columns, kinds, strict=True))], names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"])

    return marked.select("doc_id", "text", "__spans").mapInArrow(run, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string")
