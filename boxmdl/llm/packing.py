"""Cost-balanced packing of documents into fixed-length token sequences.

The cost of a piece of n tokens is ``linear * n + quadratic * n**2`` (matrix
work grows with n, attention with its square).  Each task reads its documents
as a stream and keeps a window of them: full-length chunks leave at once, the
rest are assigned in descending order of cost to the sequence of lowest cost
that still has room; what fits nowhere whole is cut into the room that is
left, cheapest sequence first.  So every sequence of a window is filled to the
last token, and no data moves between tasks.  The tokens left when a task ends
(fewer than one sequence) go to sequences whose lengths are powers of two,
which need no padding.

Edge cases: a null text counts as empty and a document then is its closing
token alone; repeated rows and ties are packed as separate documents (ties in
order of arrival); an empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

import base64
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import pieces

SEQ_LEN = 2048
END_ID = 1
SCHEMA = "doc_id long, start long, length long, ids binary, doc_tokens long, sequence_id long, offset long, sequence_tokens long, cost double"


class ByteBpe:
    """Ids of the public byte-level BPE.

    The rank file holds the same vocabulary as the JSON file and encodes some
    four times as fast; texts in which the special token is spelled out go
    through the JSON tokenizer, which treats that string apart.
    """

    SPECIAL = "<|endoftext|>"

    def __init__(self, json_path: str | None = None, rank_path: str | None = None):
        import public_tokenizers
        import tiktoken

        self._json_path = json_path or public_tokenizers.path("byte_bpe_50k.json")
        with open(rank_path or public_tokenizers.path("byte_bpe_50k.tiktoken"), "rb") as f:
            ranks = {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, f)}
        self._fast = tiktoken.Encoding("byte_bpe", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
        self._plain = None

    def __call__(self, text: str) -> np.ndarray:
        if self.SPECIAL in text:
            if self._plain is None:
                from tokenizers import Tokenizer

                self._plain = Tokenizer.from_file(self._json_path)
            return np.array(self._plain.encode(text, add_special_tokens=False).ids, dtype="<u4")
        return np.array(self._fast.encode_ordinary(text), dtype="<u4")


class Window:
    """Sequences of one stream of documents; ``add`` and ``finish`` yield (sequence, pieces)."""

    def __init__(self, seq_len: int, window_tokens: int, linear: float, quadratic: float):
        self.seq_len, self.window_tokens, self.linear, self.quadratic = seq_len, window_tokens, linear, quadratic
        self.rest: list[tuple] = []  # (doc id, ids, start, length, document tokens)
        self.tokens = 0

    def cost(self, n):
        return self.linear * n + self.quadratic * n * n

    def add(self, doc_id, ids: np.ndarray) -> Iterator[list[tuple]]:
        n = len(ids)
        whole = n - n % self.seq_len
        for start in range(0, whole, self.seq_len):
            yield [(doc_id, ids, start, self.seq_len, n)]
        if whole < n:
            self.rest.append((doc_id, _Shifted(ids[whole:].copy(), whole) if whole else ids, whole, n - whole, n))
            self.tokens += n - whole
            if self.tokens >= self.window_tokens:
                yield from self._close(self.tokens // self.seq_len)

    def finish(self) -> Iterator[list[tuple]]:
        if self.tokens >= self.seq_len:
            yield from self._close(self.tokens // self.seq_len)
        left, room = self.rest, 0
        self.rest, self.tokens = [], 0
        total = sum(p[3] for p in left)
        sequence: list[tuple] = []
        for doc_id, ids, start, length, n in left:
            while length:
                if not room:
                    if sequence:
                        yield sequence
                    sequence, room = [], 1 << (total.bit_length() - 1)
                    total -= room
                take = min(room, length)
                sequence.append((doc_id, ids, start, take, n))
                start, length, room = start + take, length - take, room - take
        if sequence:
            yield sequence

    def _close(self, count: int) -> Iterator[list[tuple]]:
        """Fill `count` sequences completely; the tokens beyond them stay for the next window."""
        room = np.full(count, self.seq_len, dtype=np.int64)
        spent = np.zeros(count)
        held: list[list[tuple]] = [[] for _ in range(count)]
        late = []
        for piece in sorted(self.rest, key=lambda p: -p[3]):
            length = piece[3]
            at = int(np.where(room >= length, spent, np.inf).argmin())
            if room[at] < length:
                late.append(piece)
                continue
            held[at].append(piece)
            room[at] -= length
            spent[at] += self.cost(length)
        order = iter(np.argsort(spent, kind="stable") if late else ())
        self.rest, at = [], None
        for doc_id, ids, start, length, n in late:
            while length:
                while at is None or not room[at]:
                    at = next(order, None)
                    if at is None:
                        break
                if at is None:
                    self.rest.append((doc_id, ids, start, length, n))
                    break
                take = min(int(room[at]), length)
                held[at].append((doc_id, ids, start, take, n))
                room[at] -= take
                start, length = start + take, length - take
        self.tokens = sum(p[3] for p in self.rest)
        yield from held


class _Shifted:
    """The tail of a long document's ids, addressed by positions in the whole document."""

    def __init__(self, ids: np.ndarray, shift: int):
        self.ids, self.shift = ids, shift

    def __getitem__(self, s: slice) -> np.ndarray:
        return self.ids[s.start - self.shift : s.stop - self.shift]


def pack(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", seq_len: int = SEQ_LEN, window_tokens: int = 1 << 20, linear: float = 1.0, quadratic: float = 1.0 / 4096, tokenizer=ByteBpe) -> DataFrame:
    """One row per piece: the document's id, the piece's token range and ids, its sequence and its place there.

    `ids` holds little-endian unsigned 32-bit ids; `cost` is the estimated cost
    of the piece.  `window_tokens` bounds what a task holds (4 bytes a token).
    """

    def run(batches):
        encode, window, made = tokenizer(), Window(seq_len, window_tokens, linear, quadratic), 0
        base = TaskContext.get().partitionId() << 33
        rows: list[tuple] = []
        held = 0

        def put(sequence):
            nonlocal made, held
            at, size = 0, sum(p[3] for p in sequence)
            for doc_id, ids, start, length, n in sequence:
                rows.append((doc_id, start, length, ids[start : start + length].tobytes(), n, base + made, at, size, window.cost(length)))
                at += length
            made += 1
            held += size

        def flush():
            nonlocal held
            columns = list(zip(*rows, strict=True))
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.float64())
            out = pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, kinds, strict=True)], names=[x.split()[0] for x in SCHEMA.split(", ")])
            rows.clear()
            held = 0
            return out

        for batch in pieces(batches):
            for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                ids = np.append(encode(text or ""), np.uint32(END_ID)).astype("<u4", copy=False)
                for sequence in window.add(doc_id, ids):
                    put(sequence)
                    if held >= window_tokens:
                        yield flush()
        for sequence in window.finish():
            put(sequence)
        if rows:
            yield flush()

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, SCHEMA)


def op1_cost_balanced_packing(spark, sf_dir) -> DataFrame:
    """Pieces of all documents with the checksum of their ids."""
    pieces = pack(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return pieces.select("doc_id", "start", "length", F.crc32("ids").alias("ids_crc32"), "doc_tokens", "sequence_id", "offset", "sequence_tokens", "cost")
