"""Language identification by prediction by partial matching.

For each language a tree of byte contexts (up to `order` bytes) is counted on the training texts. Escapes follow method
C: in a context seen n times with q different next bytes, a byte seen c times has c/(n+q) and the escape q/(n+q); an escape goes
to the context shortened by its oldest byte, where the bytes that the longer one has seen are excluded from all counts; below the empty context
the bytes that are left are alike. Coding begins at the longest context visited `least` times. The statistics are then frozen
and folded into one table [context, next byte, language] of exact code lengths in bits, so that a text is scored by two
array look-ups per byte. The shortest code wins (ties: the smaller name); score is the winner's posterior share.

The training texts are a bounded sample: `per_language` documents of each language, those with the smallest hash of their
id. Null languages and null texts are not learned from; without any training text every answer is `und`. Null texts
and texts without a letter are `und` with score 0. Long texts are scored whole, in windows. Repeated rows give
repeated answers.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

ORDER, WINDOW = 3, 1 << 20


def fold(text: str) -> bytes:
    return text.lower().encode("utf-8", "surrogatepass")


def count_grams(texts, order: int = ORDER):
    """Keys of (order+1)-byte stretches (oldest byte in front, texts padded by zero bytes) and their counts."""
    import numpy as np

    all_keys, all_counts = [], []
    for text in texts:
        b = np.frombuffer(bytes(order) + fold(text), dtype=np.uint8).astype(np.int64)
        key = np.zeros(len(b) - order, dtype=np.int64)
        for k in range(order + 1):
            key = key * 256 + b[k : len(b) - order + k]
        k, c = np.unique(key, return_counts=True)
        all_keys.append(k)
        all_counts.append(c)
    if not all_keys:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    keys, inverse = np.unique(np.concatenate(all_keys), return_inverse=True)
    return keys, np.bincount(inverse, np.concatenate(all_counts)).astype(np.int64)


def shares(counts):
    """Method C for rows of counts: each byte's chance, and the chance of an escape (1 where nothing is left to be seen)."""
    import numpy as np

    visits, kinds = counts.sum(1, keepdims=True), (counts > 0).sum(1, keepdims=True)
    return counts / np.maximum(visits + kinds, 1), np.where(visits > 0, kinds / np.maximum(visits + kinds, 1), 1.0)


class Model:
    """Code lengths of frozen context trees."""

    def __init__(self, grams: dict[str, tuple], order: int = ORDER, least: int = 2):
        """grams: per language, keys and counts of count_grams. least: fewest visits of a context that gets a row."""
        import numpy as np

        self.order, self.langs = order, sorted(grams)
        byte = np.zeros(256, dtype=np.int64)  # 0: not seen in training
        # the zero byte stands before every text
        seen = np.unique(np.concatenate([np.zeros(1, np.int64), *(np.unique(k % 256) for k, _ in grams.values())]))
        byte[seen] = np.arange(1, len(seen) + 1)
        self.byte, a = byte, len(seen) + 1
        self.a = a
        codes = {}
        for lang in self.langs:
            k, c = grams[lang]
            code = np.zeros(len(k), np.int64)
            for i in range(order, -1, -1):
                code = code * a + byte[(k >> (8 * i)) % 256]
            codes[lang] = (code, c)
        # contexts of each length that some language has visited often enough; row 0 is the empty one
        rows, first = {0: np.zeros(1, np.int64)}, {0: 0}
        total = 1
        for n in range(1, order + 1):
            ctx = np.concatenate([(code // a) % a**n for code, _ in codes.values()] or [np.zeros(0, np.int64)])
            cnt = np.concatenate([c for _, c in codes.values()] or [np.zeros(0, np.int64)])
            u, inv = np.unique(ctx, return_inverse=True)
            rows[n] = u[np.bincount(inv, cnt, len(u)) >= least] if len(u) else u
            first[n] = total
            total += len(rows[n])
        bits = np.empty((total, a, len(self.langs)), dtype=np.float32)
        self.row = np.zeros(a**order, dtype=np.int32)  # full context -> row of its longest kept suffix
        full = np.arange(a**order)
        for n in range(1, order + 1):
            if len(rows[n]):
                at = np.minimum(np.searchsorted(rows[n], full % a**n), len(rows[n]) - 1)
                hit = rows[n][at] == full % a**n
                self.row[hit] = first[n] + at[hit]
        for j, lang in enumerate(self.langs):
            code, c = codes[lang]
            below = counts_below = None
            for n in range(order + 1):
                ctx, sym = (code // a) % a**n, code % a
                at = np.searchsorted(rows[n], ctx)
                ok = (at < len(rows[n])) & (rows[n][np.minimum(at, len(rows[n]) - 1)] == ctx) if len(rows[n]) else np.zeros(len(ctx), bool)
                counts = np.zeros((len(rows[n]), a))
                np.add.at(counts, (at[ok], sym[ok]), c[ok])
                # rest: chances of the bytes not seen here once this context is escaped from, those seen here excluded
                if n == 0:
                    rest = np.full((1, a), 1.0) / np.maximum(256 - (counts > 0).sum(1, keepdims=True), 1)
                else:
                    # a kept context's suffix is visited at least as often, so it is kept
                    pos = np.searchsorted(rows[n - 1], rows[n] % a ** (n - 1))
                    shorter = np.where(counts > 0, 0, counts_below[pos])
                    own, escape = shares(shorter)
                    rest = np.where(shorter > 0, own, escape * below[pos])
                own, escape = shares(counts)
                bits[first[n] : first[n] + len(rows[n]), :, j] = -np.log2(np.where(counts > 0, own, escape * rest))
                below, counts_below = rest, counts
        self.bits = bits

    def lengths(self, text: str):
        """Code length in bits of the whole text for each language."""
        import numpy as np

        raw, out = fold(text), np.zeros(len(self.langs))
        pad = bytes(self.order)
        for at in range(0, len(raw), WINDOW):
            part = (pad if not at else raw[at - self.order : at]) + raw[at : at + WINDOW]
            b = self.byte[np.frombuffer(part, dtype=np.uint8)]
            n = len(b) - self.order
            ctx = np.zeros(n, np.int64)
            for k in range(self.order):
                ctx = ctx * self.a + b[k : n + k]
            out += self.bits[self.row[ctx], b[self.order :]].sum(0, dtype=np.float64)
        return out

    def predict(self, text: str | None) -> tuple[str, float]:
        import numpy as np

        if not text or not self.langs or not any(map(str.isalpha, text)):
            return "und", 0.0
        bits = self.lengths(text)
        best = int(np.argmin(bits))
        return self.langs[best], float(1 / np.exp2(np.maximum(bits[best] - bits, -1000)).sum())


def fit(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", per_language: int = 1500, order: int = ORDER) -> Model:
    """A model of at most per_language documents of each language; they are counted on the executors."""
    import numpy as np

    train = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"), F.col(lang_col).alias("lang")).where("lang is not null and text is not null")
    # first within shares of a language, so that a very common one is not one task's work
    few = train.select("id", "lang", F.xxhash64("id").alias("h")).withColumn("share", F.pmod("h", F.lit(64)))
    for by in (("lang", "share"), ("lang",)):
        few = few.withColumn("n", F.row_number().over(W.partitionBy(*by).orderBy("h", "id"))).where(F.col("n") <= per_language)
    ids = few.select("id", "lang").distinct()

    def run(it):
        import pyarrow as pa

        for batch in it:
            by = {}
            for text, lang in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                by.setdefault(lang, []).append(text)
            for lang, texts in by.items():
                k, c = count_grams(texts, order)
                yield pa.RecordBatch.from_arrays([pa.array([lang] * len(k), pa.string()), pa.array(k), pa.array(c)], names=["lang", "gram", "n"])

    # the ids are at most per_language a language, so this side may be broadcast
    own = train.join(F.broadcast(ids), ["id", "lang"], "left_semi").select("text", "lang").mapInArrow(run, "lang string, gram long, n long")
    got = own.groupBy("lang", "gram").agg(F.sum("n").alias("n")).toArrow()
    langs, keys, counts = np.array(got["lang"].to_pylist(), dtype=object), got["gram"].to_numpy(), got["n"].to_numpy()
    return Model({lang: (keys[langs == lang], counts[langs == lang]) for lang in sorted(set(langs))}, order)


def predict(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(it):
        import pyarrow as pa

        for batch in it:
            said = [sent.value.predict(t) for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([x for x, _ in said], pa.string()), pa.array([x for _, x in said], pa.float64())], names=[id_col, "lang_pred", "score"])

    return docs.select(F.col(id_col), F.col(text_col)).mapInArrow(run, f"`{id_col}` {dict(docs.dtypes)[id_col]}, lang_pred string, score double")


def query(spark, sf_dir: str) -> DataFrame:
    from .common import crc, table

    docs = table(spark, sf_dir, "documents")
    held = crc(F.col("doc_id")) % 4 == 2
    model = fit(docs.where(~held))
    return predict(docs, model).withColumn("held_out", held).select("doc_id", "held_out", "lang_pred", "score")
