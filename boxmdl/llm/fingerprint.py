"""Canonical exact fingerprints of texts.

A text is normalised (Unicode NFKC), case-folded and its white space folded to
single spaces; the fingerprint is the 128-bit xxhash of the result.  Equal
digests only say that two texts are probably equal, so the canonical bytes
inside each bucket of equal digests are compared: a bucket whose least and
greatest bytes differ holds a collision, and then every text of it other than
the least gets a longer fingerprint.  Only texts in buckets of two or more
rows are compared; a Bloom filter of fixed size picks them out during the scan
(a filter that is too full lets more texts through, never fewer).

Likeness of two fingerprints is 1 if they are equal and 0 otherwise: this is
an exact method.

Edge cases: a null text counts as empty; empty texts share one fingerprint;
rows with equal ids keep an order of their own (by digest of the text), rows
without an id come last; with one row, the next document is the row itself; an
empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

import hashlib
import unicodedata

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import documents, pieces, stored

#: Words of 64 bits in the Bloom filter (4 MB) and probes for each digest.
BLOOM_WORDS = 1 << 19
BLOOM_PROBES = 3
#: Text bytes aimed at in a range of documents.
RANGE_BYTES = 16 << 20


def canonical(text: str | None) -> bytes:
    text = text or ""
    if not text.isascii():
        text = unicodedata.normalize("NFKC", unicodedata.normalize("NFKC", text).casefold())
    else:
        text = text.lower()
    return " ".join(text.split()).encode("utf-8", "surrogatepass")


def digest(canon: bytes) -> bytes:
    return xxhash.xxh3_128_digest(canon)


def _batch(schema: pa.Schema, rows: list) -> pa.RecordBatch:
    columns = list(zip(*rows, strict=True)) if rows else [[] for _ in schema]
    return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(columns, schema, strict=True)], schema=schema)


def digests(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id``, ``n_bytes`` of the text and ``digest`` of its canonical form."""

    def run(batches):
        schema = pa.schema([("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("digest", pa.binary())])
        for b in pieces(batches):
            yield _batch(schema, [(i, len((t or "").encode("utf-8", "surrogatepass")), digest(canonical(t))) for i, t in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True)])

    return docs.select(F.col(id_col).cast("long"), F.col(text_col)).mapInArrow(run, "doc_id long, n_bytes long, digest binary")


def _probe(d: bytes) -> list[tuple[int, int]]:
    x = int.from_bytes(d, "little")
    return [((x >> (32 * k + 6)) % BLOOM_WORDS, (x >> (32 * k)) & 63) for k in range(BLOOM_PROBES)]


def _bloom(repeated: DataFrame) -> np.ndarray:
    """The filter as an array of at most BLOOM_WORDS words, whatever the number of digests."""

    def run(batches):
        schema = pa.schema([("word", pa.int32()), ("bits", pa.int64())])
        for b in pieces(batches):
            yield _batch(schema, [(w, (1 << bit) - (1 << 64 if bit == 63 else 0)) for d in b.column(0).to_pylist() for w, bit in _probe(d)])

    rows = repeated.mapInArrow(run, "word int, bits long").groupBy("word").agg(F.bit_or("bits").alias("bits")).toPandas()
    words = np.zeros(BLOOM_WORDS, dtype=np.int64)
    words[rows["word"].to_numpy()] = rows["bits"].to_numpy()
    return words.view(np.uint64)


def collisions(docs: DataFrame, known: DataFrame, id_col: str = "doc_id", text_col: str = "text", digest_of=digest) -> dict[bytes, bytes]:
    """Digests shared by different canonical texts, each with the least of these texts.

    Empty unless the hash collides, so it can be held by every task.
    """
    sc = docs.sparkSession.sparkContext
    repeated = known.groupBy("digest").count().filter("count > 1").select("digest")
    bloom = sc.broadcast(_bloom(repeated))

    def run(batches):
        schema = pa.schema([("digest", pa.binary()), ("canon", pa.binary())])
        words = bloom.value
        for b in pieces(batches):
            rows = []
            for t in b.column(0).to_pylist():
                canon = canonical(t)
                d = digest_of(canon)
                if all((int(words[w]) >> bit) & 1 for w, bit in _probe(d)):
                    rows.append((d, canon))
            yield _batch(schema, rows)

    seen = docs.select(F.col(text_col)).mapInArrow(run, "digest binary, canon binary")
    extremes = seen.groupBy("digest").agg(F.min("canon").alias("least"), F.max("canon").alias("most"))
    return {bytes(r.digest): bytes(r.least) for r in extremes.filter("least != most").select("digest", "least").toLocalIterator()}


def fingerprint_of(canon: bytes, clashing: dict[bytes, bytes], digest_of=digest) -> str:
    d = digest_of(canon)
    if d in clashing and clashing[d] != canon:
        return f"{d.hex()}-{hashlib.sha256(canon).hexdigest()}"
    return d.hex()


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id`` and ``fingerprint`` of every row, collisions told apart."""
    clashing = collisions(docs, stored(digests(docs, id_col, text_col), "digests"), id_col, text_col)

    def run(batches):
        schema = pa.schema([("doc_id", pa.int64()), ("fingerprint", pa.string())])
        for b in pieces(batches):
            yield _batch(schema, [(i, fingerprint_of(canonical(t), clashing)) for i, t in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True)])

    return docs.select(F.col(id_col).cast("long"), F.col(text_col)).mapInArrow(run, "doc_id long, fingerprint string")


def edit_probe(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Fingerprints of the texts, of their edited forms, and likeness to these and to the next document.

    The rows are cut into ranges of ids; the first row of the following range
    is sent along with each range, so every range can be read as a stream that
    holds two texts at a time.
    """
    known = stored(digests(docs, id_col, text_col), "digests")
    clashing = collisions(docs, known, id_col, text_col)
    weight = known.agg(F.sum("n_bytes")).first()[0] or 0
    n = max(4 * int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), weight // RANGE_BYTES)
    n = int(min(n, 50_000))
    cuts = known.agg(F.percentile_approx("doc_id", [k / n for k in range(1, n)], 20 * n)).first()[0] if n > 1 else []
    cuts = np.unique(np.array(cuts or [], dtype=np.int64))

    def place(ids):
        """Range of each id: 1 and up, in ascending order; 0 for none."""
        return [0 if i is None else int(np.searchsorted(cuts, i, side="right")) + 1 for i in ids]

    def tops(batches):
        schema = pa.schema([("range", pa.int32()), ("top", pa.int64())])
        for b in pieces(batches):
            ids = b.column(0).to_pylist()
            best: dict[int, int | None] = {}
            for r, i in zip(place(ids), ids, strict=True):
                best[r] = i if i is None else max(best.get(r, i), i)
            yield _batch(schema, list(best.items()))

    top = {r["range"]: r.top for r in known.select("doc_id").mapInArrow(tops, "range int, top long").groupBy("range").agg(F.max("top").alias("top")).collect()}
    down = sorted(top, reverse=True)
    # A range's first row also closes the range before it; the very first closes the last.
    closes = {r: down[k - 1] for k, r in enumerate(down)}

    def deal(batches):
        schema = pa.schema([("range", pa.int32()), ("halo", pa.bool_()), ("doc_id", pa.int64()), ("tie", pa.int64()), ("text", pa.string())])
        for b in pieces(batches):
            ids, rows = b.column(0).to_pylist(), []
            for r, i, t in zip(place(ids), ids, b.column(1).to_pylist(), strict=True):
                tie = xxhash.xxh3_64_intdigest((t or "").encode("utf-8", "surrogatepass")) >> 1
                rows.append((r, False, i, tie, t))
                if i == top[r]:
                    rows.append((closes[r], True, i, tie, t))
            yield _batch(schema, rows)

    def edit(batches):
        schema = pa.schema([("doc_id", pa.int64()), ("n_chars", pa.int64()), ("edited_sha256", pa.string()), ("fingerprint", pa.string()), ("edited_fingerprint", pa.string()), ("near_edited", pa.float64()), ("near_next", pa.float64())])
        last = None

        def row(i, text, own, following, after):
            half = len(text) // 2
            edited = text[: len(text) - half] + following[:half]
            changed = fingerprint_of(canonical(edited), clashing)
            return i, len(text), hashlib.sha256(edited.encode("utf-8", "surrogatepass")).hexdigest(), own, changed, float(own == changed), float(own == after)

        for b in pieces(batches):
            rows = []
            for r, halo, i, text in zip(*(b.column(k).to_pylist() for k in (0, 1, 2, 4)), strict=True):
                text = text or ""
                own = fingerprint_of(canonical(text), clashing)
                if last is not None and last[0] == r:
                    rows.append(row(*last[1:], text, own))
                last = None if halo else (r, i, text, own)
            yield _batch(schema, rows)

    dealt = docs.select(F.col(id_col).cast("long"), F.col(text_col)).mapInArrow(deal, "range int, halo boolean, doc_id long, tie long, text string")
    parts = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ordered = dealt.repartition(max(parts, weight // (8 * RANGE_BYTES)), "range").sortWithinPartitions("range", "halo", F.col("doc_id").desc_nulls_last(), "tie")
    return ordered.mapInArrow(edit, "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double")


def op10_canonical_digest(spark, sf_dir) -> DataFrame:
    """Fingerprints of all documents and of their edited texts."""
    return edit_probe(documents(spark, sf_dir))
