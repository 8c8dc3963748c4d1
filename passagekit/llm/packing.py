"""Best-fit packing: documents become sequences of at most `size` tokens.

Every task packs its own documents as they come, and takes `task_bytes` of text however small the partitions of the input are, so that
few bins stay open at the ends of tasks: a fixed number of bins is open, and a bitset (a Python integer)
has bit f set while some open bin has f tokens free. The best fit for a piece of n tokens is the lowest set bit at
or above n. When no bin fits and all are open, the fullest (lowest bit) closes. Longer documents are cut first, with
the short piece in front; whole pieces of `size` tokens are sequences of their own.

Tokens: the vocabulary of byte_bpe_50k, run by tiktoken over the same ranks (same ids, about six times as fast; a test
holds them to those of tokenizers), with the special string read as id 50256 as tokenizers does. A null text is empty: a
document of one token, id 0. Repeated rows are packed once each. An empty table gives no sequences.
"""

from __future__ import annotations

import zlib

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import slices

SIZE, OPEN, END, TASK_BYTES = 2048, 1024, 0, 16 << 20


class Bins:
    """A fixed number of open bins, in a bitset keyed by free space."""

    def __init__(self, size: int, most: int, first: int = 0):
        self.size, self.most, self.open, self.next = size, most, 0, first
        self.bits = 0
        self.by_free: list[list[int]] = [[] for _ in range(size + 1)]

    def _take(self, free: int) -> int:
        own = self.by_free[free]
        at = own.pop()
        if not own:
            self.bits &= ~(1 << free)
        self.open -= 1
        return at

    def _put(self, at: int, free: int) -> None:
        if free:
            self.by_free[free].append(at)
            self.bits |= 1 << free
            self.open += 1

    def place(self, n: int) -> tuple[int, int]:
        """(bin, offset) for n tokens."""
        fits = self.bits >> n
        if n < self.size and fits:
            free = n + (fits & -fits).bit_length() - 1
            at = self._take(free)
        else:
            if n < self.size and self.open >= self.most:
                self._take((self.bits & -self.bits).bit_length() - 1)  # the fullest closes
            free, at = self.size, self.next
            self.next += 1
        self._put(at, free - n)
        return at, self.size - free


def cuts(n: int, size: int) -> list[tuple[int, int]]:
    """(start, length) of the pieces of n tokens: the first may be shorter, the others are whole."""
    if n <= size:
        return [(0, n)]
    first = n % size
    return ([(0, first)] if first else []) + [(s, size) for s in range(first, n, size)]


def encoder(path: str | None = None):
    """str -> ids, the ids that tokenizers gives for byte_bpe_50k.json without special tokens added."""
    import base64

    import public_tokenizers as P
    import tiktoken

    with open(path or P.path("byte_bpe_50k.tiktoken"), "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    return tiktoken.Encoding("byte_bpe_50k", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={"<|endoftext|>": 50256})


SCHEMA = "piece int, start long, length long, ids_crc32 long, sequence_id long, `offset` long"


def pack(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = SIZE, bins: int = OPEN, tokenizer: str | None = None, with_ids: bool = False, task_bytes: int = TASK_BYTES) -> DataFrame:
    """One row per piece: document, piece, its place in its document and in its sequence; with_ids adds the ids themselves."""
    schema = f"`{id_col}` {dict(docs.dtypes)[id_col]}, {SCHEMA}" + ", ids array<int>" * with_ids

    def run(it):
        import numpy as np
        import pyarrow as pa
        from pyspark import TaskContext

        enc = encoder(tokenizer)
        # sequence numbers of a task are apart from those of all others
        store = Bins(size, bins, TaskContext.get().partitionId() << 40)
        for batch in slices(it):
            who, cols, ids_col = [], [[] for _ in range(6)], []
            for i, text in enumerate(batch.column(1).to_pylist()):
                ids = np.array([*enc.encode(text, allowed_special="all"), END] if text else [END], dtype="<u4")
                for piece, (start, n) in enumerate(cuts(len(ids), size)):
                    at, offset = store.place(n)
                    own = ids[start : start + n]
                    who.append(i)
                    for c, v in zip(cols, (piece, start, n, zlib.crc32(own.tobytes()), at, offset), strict=True):
                        c.append(v)
                    if with_ids:
                        ids_col.append(own.astype("i4"))
            kinds = (pa.int32(), *[pa.int64()] * 5)
            arrays = [batch.column(0).take(pa.array(who, pa.int64())), *(pa.array(c, k) for c, k in zip(cols, kinds, strict=True))]
            names = [id_col, "piece", "start", "length", "ids_crc32", "sequence_id", "offset"]
            if with_ids:
                arrays, names = [*arrays, pa.array(ids_col, pa.list_(pa.int32()))], [*names, "ids"]
            yield pa.RecordBatch.from_arrays(arrays, names=names)

    # an empty text is a token too
    mass = docs.agg(F.sum(F.octet_length(F.coalesce(F.col(text_col), F.lit(""))).cast("long") + 4).alias("b")).first()["b"] or 0
    return docs.select(F.col(id_col), F.col(text_col)).coalesce(max(1, -(-mass // task_bytes))).mapInArrow(run, schema)


def query(spark, sf_dir: str) -> DataFrame:
    from .common import table

    return pack(table(spark, sf_dir, "documents"))
