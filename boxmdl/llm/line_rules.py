r"""Quality rules on line frequency across the documents of a host.

Lines are normalised (ASCII lower case, digits to 0, white space folded) and
hashed; for each host the number of distinct documents that hold a line is
counted (exact copies of a document count once: they are no sign of a
boilerplate line).  Lines above the limit are removed from the text
(``clean_text``, the other lines as they were), and a document is rejected if
too few words, or too small a share of them, are left.  The base rules (length
and repeated word windows) come first.

A line is above the limit if it is in more than `least_docs` documents and in
more than `share` of the host's distinct documents, or in more than `many_docs`
of them, however large the host is.

Up to `BROADCAST_LINES` lines above the limit go to every task, which reads the
texts a second time; more meet the documents by a join.  Both give the same rows.

Edge cases: a null text has no words, fails the base rules and stays null; a
null host is a host of its own; lines without a word stay; repeated rows are judged one by one; an empty table gives
no rows; extra columns are not read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import documents, pieces, stored

SPACE = b" \t\n\x0b\x0c\r"
SYMBOLS = b"#*$%&|<>"
_FOLD = bytes.maketrans(b"ABCDEFGHIJKLMNOPQRSTUVWXYZ123456789", b"abcdefghijklmnopqrstuvwxyz000000000")

MIN_WORDS = 50
MAX_REPEAT_PERCENT = 50
LEAST_DOCS = 20
SHARE = 0.01
MANY_DOCS = 1_000
MIN_LEFT = 0.5
#: Lines above the limit that are sent to every task (16 bytes each).
BROADCAST_LINES = 200_000


def repeated_words(words: list[bytes]) -> int:
    """Words that lie in a window of three words which is found twice or more in `words`."""
    n = len(words)
    if n < 4:
        return 0
    number: dict[bytes, int] = {}
    ids = np.fromiter((number.setdefault(w, len(number)) for w in words), dtype=np.int64, count=n)
    base = len(number)
    pairs = ids[:-1] * base + ids[1:]
    if base >= 1 << 20:
        pairs = np.unique(pairs, return_inverse=True)[1]
    keys = pairs[:-1] * base + ids[2:]
    order = np.argsort(keys, kind="stable")
    ranked = keys[order]
    same = ranked[1:] == ranked[:-1]
    if not same.any():
        return 0
    twice = np.zeros(n - 2, dtype=bool)
    twice[order[1:][same]] = True
    twice[order[:-1][same]] = True
    covered = np.zeros(n, dtype=bool)
    covered[:-2] |= twice
    covered[1:-1] |= twice
    covered[2:] |= twice
    return int(covered.sum())


def line_key(found: list[bytes]) -> int:
    """Hash of a normalised line, given by its words."""
    return xxhash.xxh3_64_intdigest(b" ".join(found).translate(_FOLD)) - (1 << 63)


def without_lines(text: str | None, often) -> tuple[str | None, int]:
    """The text without the lines whose keys are in `often`, and the words that went with them."""
    if not often or not text:
        return text, 0
    left, gone = [], 0
    for line in text.encode("utf-8", "surrogatepass").split(b"\n"):
        found = line.split()
        if found and line_key(found) in often:
            gone += len(found)
        else:
            left.append(line)
    return (b"\n".join(left).decode("utf-8", "surrogatepass"), gone) if gone else (text, 0)


def measure(text: str | None) -> tuple[tuple[int, int, int, int, int], dict[int, int]]:
    """Base measures, and the words held by each normalised line (by its hash)."""
    data = (text or "").encode("utf-8", "surrogatepass")
    words = data.split()
    word_chars = len(text or "") - (len(data) - len(data.translate(None, SPACE)))
    symbols = len(data) - len(data.translate(None, SYMBOLS))
    seen: set[bytes] = set()
    again, lines = 0, {}
    for line in data.split(b"\n"):
        found = line.split()
        if not found:
            continue
        if line in seen:
            again += 1
        seen.add(line)
        key = line_key(found)
        lines[key] = lines.get(key, 0) + len(found)
    return (len(words), word_chars, symbols, again, repeated_words(words)), lines


BASE = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
LINES = "__row long, host string, text_hash binary, lines array<long>"
CLEANED = f"doc_id long, host string, {', '.join(f'{c} long' for c in BASE)}, clean_text string, words_removed long"


def document_lines(texts: DataFrame) -> DataFrame:
    """The different normalised lines (`LINES`) of rows ``__row, host, text``."""

    def run(batches):
        kinds = [pa.int64(), pa.string(), pa.binary(), pa.list_(pa.int64())]
        for b in pieces(batches):
            rows = []
            for at, h, t in zip(*(b.column(k).to_pylist() for k in range(3)), strict=True):
                data = (t or "").encode("utf-8", "surrogatepass")
                found = {line_key(w) for line in data.split(b"\n") if (w := line.split())}
                rows.append((at, h, xxhash.xxh3_128_digest(data), list(found)))
            columns = list(zip(*rows, strict=True)) if rows else [[] for _ in kinds]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names=["__row", "host", "text_hash", "lines"])

    host = F.struct(F.col("host").isNull().alias("none"), F.coalesce("host", F.lit("")).alias("name"))
    return texts.select("__row", "host", "text").mapInArrow(run, LINES).withColumn("__host", host)


def _cleaned(docs: DataFrame, often_of) -> DataFrame:
    """`CLEANED` of rows ``doc_id, host, text, ...``; `often_of(host, more)` gives the keys to remove, where `more` is what the row has beyond these."""

    def run(batches):
        kinds = [pa.int64(), pa.string(), *[pa.int64()] * len(BASE), pa.string(), pa.int64()]
        for b in pieces(batches):
            columns = [b.column(k).to_pylist() for k in range(b.num_columns)]
            rows = []
            for i, h, t, *more in zip(*columns, strict=True):
                rows.append((i, h, *measure(t)[0], *without_lines(t, often_of(h, more))))
            out = list(zip(*rows, strict=True)) if rows else [[] for _ in kinds]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(out, kinds, strict=True)], names=["doc_id", "host", *BASE, "clean_text", "words_removed"])

    return docs.mapInArrow(run, CLEANED)


def _cleaned_by_broadcast(docs: DataFrame, often: DataFrame) -> DataFrame:
    held = often.select("__host.none", "__host.name", "line").toArrow()  # at most BROADCAST_LINES
    by_host: dict[str | None, list[int]] = {}
    for none, name, line in zip(*(held[c].to_pylist() for c in ("none", "name", "line")), strict=True):
        by_host.setdefault(None if none else name, []).append(line)
    shared = docs.sparkSession.sparkContext.broadcast({h: np.array(x, np.int64) for h, x in by_host.items()})
    sets: dict[str | None, frozenset[int]] = {}

    def often_of(host, more):
        if host not in sets:
            sets[host] = frozenset(shared.value[host].tolist()) if host in shared.value else frozenset()
        return sets[host]

    return _cleaned(docs, often_of)


def _cleaned_by_join(texts: DataFrame, lines: DataFrame, often: DataFrame) -> DataFrame:
    held = lines.select("__row", "__host", F.explode("lines").alias("line"))
    gone = held.join(often.select("__host", "line"), ["__host", "line"]).groupBy("__row").agg(F.collect_list("line").alias("gone"))
    return _cleaned(texts.join(gone, "__row", "left").select("doc_id", "host", "text", "gone"), lambda host, more: frozenset(more[0] or ()))


def frequent_lines(rows: DataFrame, least_docs: int = LEAST_DOCS, share: float = SHARE, many_docs: int = MANY_DOCS) -> DataFrame:
    """``__host``, ``line``, ``n_docs`` of the lines above the limit."""
    first = rows.groupBy("__host", "text_hash").agg(F.min("__row").alias("__row"))
    held = first.groupBy("__host").agg(F.count(F.lit(1)).alias("host_docs"))
    lines = rows.select("__row", "__host", F.explode("lines").alias("line")).join(first.select("__row"), "__row", "left_semi")
    counts = lines.groupBy("__host", "line").agg(F.count(F.lit(1)).alias("n_docs")).filter(F.col("n_docs") > least_docs)
    return counts.join(held, "__host").filter((F.col("n_docs") > share * F.col("host_docs")) | (F.col("n_docs") > many_docs)).select("__host", "line", "n_docs")


def line_rules(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", host_col: str = "source", least_docs: int = LEAST_DOCS, share: float = SHARE, min_left: float = MIN_LEFT, many_docs: int = MANY_DOCS) -> DataFrame:
    """Measures of every document, its text without the frequent lines, the words removed with them, and the verdict."""
    given = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(host_col).cast("string").alias("host"), F.col(text_col).alias("text"))
    numbered = given.withColumn("__row", F.monotonically_increasing_id())
    often = stored(frequent_lines(stored(document_lines(numbered), "lines"), least_docs, share, many_docs), "often")
    if often.count() <= BROADCAST_LINES:
        judged = _cleaned_by_broadcast(given, often)
    else:
        texts = stored(numbered, "texts")  # a table read twice need not number its rows alike
        judged = _cleaned_by_join(texts, document_lines(texts), often)
    failed = (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > MAX_REPEAT_PERCENT * F.col("n_words"))
    left = F.col("n_words") - F.col("words_removed")
    return judged.withColumn("base_failed", failed).withColumn("kept", ~failed & (left >= MIN_WORDS) & (left >= min_left * F.col("n_words")))


def op6_line_frequency_rules(spark, sf_dir) -> DataFrame:
    """Base measures and verdicts of all documents."""
    judged = line_rules(documents(spark, sf_dir))
    return judged.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "words_removed")


OP6_SQL = rf"""
WITH d AS (SELECT doc_id, source, coalesce(text, '') AS text FROM documents),
w AS (SELECT doc_id, source, text, regexp_extract_all(text, '[^\x20\x09-\x0D]+') AS words, string_split(text, chr(10)) AS lines FROM d),
pos AS (SELECT doc_id, words, unnest(range(1, len(words) - 1)) AS i FROM w WHERE len(words) > 2),
tri AS (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, words[i], words[i + 1], words[i + 2]) AS c FROM pos),
rep AS (SELECT doc_id, count(DISTINCT p) AS n FROM (SELECT doc_id, unnest([i, i + 1, i + 2]) AS p FROM tri WHERE c > 1) GROUP BY doc_id),
ln AS (SELECT doc_id, source, text, line, len(regexp_extract_all(line, '[^\x20\x09-\x0D]+')) AS k,
              translate(array_to_string(regexp_extract_all(line, '[^\x20\x09-\x0D]+'), ' '), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ123456789', 'abcdefghijklmnopqrstuvwxyz000000000') AS norm
       FROM (SELECT doc_id, source, text, unnest(lines) AS line FROM w)),
wl AS (SELECT * FROM ln WHERE k > 0),
dup AS (SELECT doc_id, count(*) - count(DISTINCT line) AS n FROM wl GROUP BY doc_id),
hosts AS (SELECT source, count(DISTINCT text) AS docs FROM d GROUP BY source),
often AS (SELECT wl.source, norm FROM wl JOIN hosts ON wl.source IS NOT DISTINCT FROM hosts.source
          GROUP BY wl.source, norm, docs HAVING count(DISTINCT text) > {LEAST_DOCS} AND (count(DISTINCT text) > {SHARE} * docs OR count(DISTINCT text) > {MANY_DOCS})),
gone AS (SELECT doc_id, sum(k) AS n FROM wl WHERE EXISTS (SELECT 1 FROM often o WHERE o.source IS NOT DISTINCT FROM wl.source AND o.norm = wl.norm) GROUP BY doc_id),
b AS (SELECT w.doc_id, len(words)::BIGINT AS n_words, length(array_to_string(words, ''))::BIGINT AS word_chars,
             (length(text) - length(translate(text, '#*$%&|<>', '')))::BIGINT AS n_symbols,
             coalesce(dup.n, 0)::BIGINT AS n_dup_lines, coalesce(rep.n, 0)::BIGINT AS n_repeat_words, coalesce(gone.n, 0)::BIGINT AS words_removed
      FROM w LEFT JOIN dup USING (doc_id) LEFT JOIN rep USING (doc_id) LEFT JOIN gone USING (doc_id))
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words,
       n_words < {MIN_WORDS} OR 100 * n_repeat_words > {MAX_REPEAT_PERCENT} * n_words AS base_failed,
       NOT (n_words < {MIN_WORDS} OR 100 * n_repeat_words > {MAX_REPEAT_PERCENT} * n_words)
         AND n_words - words_removed >= {MIN_WORDS} AND n_words - words_removed >= {MIN_LEFT} * n_words AS kept, words_removed
FROM b
"""
