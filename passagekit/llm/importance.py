"""Quality classifier by importance resampling.

Two generative models over hashed word and word-pair features: one of target text (labelled good), one of the raw text.
A document's log weight is the sum of log ratios of its features; Gumbel noise is added and the k largest keys stay, which
samples k documents without replacement in proportion to their weights. k is the expected number of target-like documents,
the sum over all documents of min(1, share of target labels x weight).

Raw counts cover every document, target counts every document labelled as target; the ids of these go to all tasks (8 bytes
each). A ratio is shrunk to 1 where the target has little to say: (seen + tau) / (expected + tau).

Null and empty texts have no features and weight 1 (log 0), so they stay if k allows. Without target labels all weights
are 1 and everything is kept. Rows that repeat have the same key; ties at the k-th key are all kept. Long texts are read whole.
"""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialise, slices

BUCKETS = 1 << 15
_PARTS = re.compile(r"\w+|[^\w\s]+")


def features(text: str | None, cache: dict, buckets: int = BUCKETS):
    """Hashed words and word pairs (runs of other characters are words too), lower-cased, as bucket numbers."""
    import numpy as np

    if not text:
        return np.zeros(0, dtype=np.int64)
    one = np.array([cache[w] for w in _PARTS.findall(text.lower())], dtype=np.uint64)
    two = one[:-1] * np.uint64(0x9E3779B97F4A7C15) + one[1:]
    two ^= two >> np.uint64(29)
    two *= np.uint64(0xBF58476D1CE4E5B9)
    two ^= two >> np.uint64(32)
    return (np.concatenate([one, two]) % np.uint64(buckets)).astype(np.int64)


class Hashes(dict):
    """Hash of each word, kept for the words seen lately."""

    def __missing__(self, word):
        import xxhash

        if len(self) > 100_000:
            self.clear()
        self[word] = h = xxhash.xxh3_64_intdigest(word)
        return h


def fit(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", tau: float = 8.0, buckets: int = BUCKETS):
    """(log ratio of each bucket, share of target labels). labels: id_col and target (boolean)."""
    import numpy as np

    known = labels.where("target is not null")
    n = known.agg(F.count(F.lit(1)).alias("all"), F.count_if("target").alias("good")).first()
    ids = np.sort(known.where("target").where(F.col(id_col).isNotNull()).select(id_col).distinct().toArrow()[id_col].to_numpy())
    sent = docs.sparkSession.sparkContext.broadcast(ids)

    def targets(col):
        """Which values are ids of target documents."""
        known, out = np.asarray(col.is_valid()), np.zeros(len(col), bool)
        if known.any() and len(sent.value):
            v = col.drop_null().to_numpy(zero_copy_only=False)
            out[known] = sent.value[np.minimum(np.searchsorted(sent.value, v), len(sent.value) - 1)] == v
        return out

    def run(it):
        import pyarrow as pa

        raw, own, cache = np.zeros(buckets, np.int64), np.zeros(buckets, np.int64), Hashes()
        for batch in slices(it):
            for target, text in zip(targets(batch.column(0)).tolist(), batch.column(1).to_pylist(), strict=True):
                f = features(text, cache, buckets)
                if len(f) < buckets >> 3:
                    np.add.at(raw, f, 1)
                    if target:
                        np.add.at(own, f, 1)
                else:
                    c = np.bincount(f, minlength=buckets)
                    raw += c
                    if target:
                        own += c
        at = np.flatnonzero(raw)
        yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(raw[at]), pa.array(own[at])], names=["bucket", "raw", "own"])

    got = docs.select(F.col(id_col), F.col(text_col)).mapInArrow(run, "bucket int, raw long, own long").groupBy("bucket").agg(F.sum("raw").alias("raw"), F.sum("own").alias("own")).toArrow()
    raw, own = np.zeros(buckets), np.zeros(buckets)
    at = got["bucket"].to_numpy()
    raw[at], own[at] = got["raw"].to_numpy(), got["own"].to_numpy()
    expected = raw / max(raw.sum(), 1) * own.sum()
    return np.log((own + tau) / (expected + tau)), (n["good"] / n["all"] if n["all"] and len(ids) else 1.0)


def gumbel(id_col: str, seed: int) -> Column:
    """Gumbel noise drawn from the id."""
    u = (F.shiftrightunsigned(F.xxhash64(F.lit(seed), F.col(id_col)), 11) + F.lit(0.5)) / F.lit(2.0**53)
    return -F.ln(-F.ln(u))


def weigh(docs: DataFrame, ratio, text_col: str = "text", out: str = "log_weight") -> DataFrame:
    """docs with the log weight of each row as column `out`; an input column of that name is replaced."""
    sent = docs.sparkSession.sparkContext.broadcast(ratio)
    docs = docs.drop(out)
    names = docs.columns
    at = names.index(text_col)

    def run(it):
        import pyarrow as pa

        cache, r = Hashes(), sent.value
        for batch in slices(it):
            w = [float(r[features(t, cache, len(r))].sum()) for t in batch.column(at).to_pylist()]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(w, pa.float64())], names=[*names, out])

    return docs.mapInArrow(run, ", ".join(f"`{n}` {t}" for n, t in docs.dtypes) + f", `{out}` double")


def kth_largest(keys: DataFrame, col: str, k: int, bins: int = 4096, few: int = 10_000) -> float:
    """The k-th largest value: histograms narrow the range until few values are left, and those are sorted."""
    ends = keys.agg(F.count(col).alias("n"), F.min(col).alias("lo"), F.max(col).alias("hi")).first()
    if k >= ends["n"]:
        return ends["lo"] if ends["lo"] is not None else 0.0
    lo, hi, above, inside = ends["lo"], ends["hi"], 0, ends["n"]
    while inside > few and hi > lo:
        step = (hi - lo) / bins
        if lo + step <= lo:
            break
        at = F.least(F.lit(bins - 1), F.floor((F.col(col) - F.lit(lo)) / F.lit(step))).cast("int")
        rows = keys.where(F.col(col).between(lo, hi)).groupBy(at.alias("b")).agg(F.count(F.lit(1)).alias("n"), F.min(col).alias("lo"), F.max(col).alias("hi")).collect()
        for r in sorted(rows, key=lambda r: -r["b"]):
            if above + r["n"] >= k:
                lo, hi, inside = r["lo"], r["hi"], r["n"]
                break
            above += r["n"]
        else:
            break
    if lo == hi:
        return lo
    left = keys.where(F.col(col).between(lo, hi)).orderBy(F.col(col).desc()).limit(max(1, k - above)).agg(F.min(col).alias("x")).first()
    return left["x"]


def _bar(docs: DataFrame, labels: DataFrame, id_col: str, text_col: str, k: int | None, seed: int, fit_args: dict):
    """(log ratios, keys of all rows, the key of the last document that stays)."""
    ratio, share = fit(docs, labels, id_col, text_col, **fit_args)
    log_weights = weigh(docs.select(F.col(id_col), F.col(text_col)), ratio, text_col)
    keys = materialise(log_weights.select(id_col, "log_weight", (F.col("log_weight") + gumbel(id_col, seed)).alias("key")))
    if k is None:
        k = round(keys.agg(F.sum(F.least(F.lit(1.0), F.lit(share) * F.exp(F.least(F.col("log_weight"), F.lit(50.0))))).alias("k")).first()["k"] or 0)
    return ratio, keys, kth_largest(keys, "key", max(1, k))


def resample(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", k: int | None = None, seed: int = 23, **fit_args) -> DataFrame:
    """id, log_weight, key and kept of every row. k: documents to keep; None: the expected number of target-like ones."""
    _, keys, bar = _bar(docs, labels, id_col, text_col, k, seed, fit_args)
    return keys.withColumn("kept", F.col("key") >= F.lit(bar))


def keep(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", k: int | None = None, seed: int = 23, **fit_args) -> DataFrame:
    """The rows of docs that resample keeps, with their columns. Texts are weighed again rather than joined with the keys."""
    ratio, _, bar = _bar(docs, labels, id_col, text_col, k, seed, fit_args)
    own = weigh(docs, ratio, text_col, "_log_weight")
    return own.where(F.col("_log_weight") + gumbel(id_col, seed) >= F.lit(bar)).select(*docs.columns)


def target_labels(spark, sf_dir: str) -> DataFrame:
    from .common import table

    return table(spark, sf_dir, "labels").select("doc_id", (F.col("quality") == 1).alias("target"))


def query(spark, sf_dir: str) -> DataFrame:
    from .common import table

    return resample(table(spark, sf_dir, "documents"), target_labels(spark, sf_dir))
