"""Transit deduplication: nomination, spectral texture, waveform correlation, rules, null checks, closure and the gate.

Recordings are rows of rid, hull, x (array of doubles). A hull's recordings form pairs, as the method demands; hulls are small,
and their number is what grows. Across hulls only recordings that share a rare metadata key are paired.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..functions.vectors import dot, unit
from ..stage import discard, settled
from .augment import znorm


@dataclass(frozen=True)
class Rule:
    """Same transit at texture >= alone, or at texture >= both and waveform >= wave; same capture at waveform >= capture."""

    name: str = "joint"
    alone: float = 0.40
    both: float | None = 0.20
    wave: float | None = 0.15
    capture: float = 0.80

    def verdict(self, t: Column, w: Column) -> Column:
        same = t >= self.alone
        if self.both is not None:
            same = same | ((t >= self.both) & (w >= self.wave))
        return F.when(w >= self.capture, "same capture").when(same, "same transit").otherwise("distinct")


def histogram_residual(rec: DataFrame, width: float, bins: int) -> DataFrame:
    """Adds res: the unit residual of a recording's value histogram from the mean histogram of all recordings."""
    at = lambda v: F.least(F.floor(v / width), F.lit(bins - 1))
    share = F.transform(F.sequence(F.lit(0), F.lit(bins - 1)), lambda b: F.size(F.filter("x", lambda v: at(v) == b)) / F.size("x"))
    return residual(rec.withColumn("h", share), bins)


def residual(h: DataFrame, bins: int) -> DataFrame:
    """Replaces the histogram h by res: its unit residual from the mean of all rows."""
    mean = h.agg(F.array(*(F.avg(F.col("h")[b]) for b in range(bins))).alias("mean_h"))
    # one row of `bins` numbers
    return h.crossJoin(F.broadcast(mean)).withColumn("res", unit(F.zip_with("h", "mean_h", lambda a, b: a - b))).drop("h", "mean_h")


def metadata_key(rec: DataFrame, step: float) -> DataFrame:
    """Adds key: duration and the closest approach in steps."""
    return rec.withColumn("key", F.concat_ws("|", F.size("x"), F.floor(F.array_max("x") / step).cast("long")))


def nominate(rec: DataFrame, rare_max: int = 4, carry: tuple = ()) -> DataFrame:
    """a < b, their hulls, whether their keys agree, and the reason: every pair within a hull, and pairs across hulls whose key or whose duration at most rare_max recordings share."""
    side = lambda s: rec.select(F.col("rid").alias(s), F.col("hull").alias(f"{s}_hull"), F.col("key").alias(f"{s}_key"), *(F.col(c).alias(f"{s}_{c}") for c in carry))
    own = side("a").join(side("b"), (F.col("a_hull") == F.col("b_hull")) & (F.col("a") < F.col("b"))).withColumn("reason", F.lit("same hull"))
    rare = rec.groupBy("key").agg(F.count(F.lit(1)).alias("n")).where(F.col("n").between(2, rare_max)).select("key")
    few = rec.join(rare, "key", "left_semi")
    side = lambda s: few.select(F.col("rid").alias(s), F.col("hull").alias(f"{s}_hull"), F.col("key").alias(f"{s}_key"), *(F.col(c).alias(f"{s}_{c}") for c in carry))
    cross = side("a").join(side("b"), (F.col("a_key") == F.col("b_key")) & (F.col("a_hull") != F.col("b_hull")) & (F.col("a") < F.col("b"))).withColumn("reason", F.lit("rare key"))
    # a copy whose peak falls in another step shares no key, but a rare duration gives it away
    n = F.size("x")
    odd = rec.groupBy(n.alias("len")).agg(F.count(F.lit(1)).alias("n")).where(F.col("n").between(2, rare_max)).select("len")
    few = rec.join(odd, n == F.col("len"))
    side = lambda s: few.select(F.col("rid").alias(s), F.col("hull").alias(f"{s}_hull"), F.col("key").alias(f"{s}_key"), F.col("len").alias(f"{s}_len"), *(F.col(c).alias(f"{s}_{c}") for c in carry))
    lengths = side("a").join(side("b"), (F.col("a_len") == F.col("b_len")) & (F.col("a_hull") != F.col("b_hull")) & (F.col("a") < F.col("b")) & (F.col("a_key") != F.col("b_key"))).drop("a_len", "b_len").withColumn("reason", F.lit("rare length"))
    return own.unionByName(cross).unionByName(lengths).withColumn("same_key", F.col("a_key") == F.col("b_key")).drop("a_key", "b_key")


def peak_correlation(a: str, b: str, lag: int) -> Column:
    """Largest absolute correlation of two standardised series over lags of at most `lag`, by the lengths' geometric mean."""

    def at(k: int) -> Column:
        x, y = (a, b) if k >= 0 else (b, a)
        m = F.greatest(F.lit(0), F.least(F.size(x), F.size(y) - abs(k)))
        return F.abs(dot(F.slice(x, F.lit(1), m), F.slice(y, F.lit(abs(k) + 1), m)))

    return F.greatest(*(at(k) for k in range(-lag, lag + 1))) / F.sqrt(F.size(a) * F.size(b).cast("double"))


def evidence(pairs: DataFrame, lag: int = 3) -> DataFrame:
    """Adds t (texture) and w (waveform) to pairs that carry res and z (standardised x) of both sides."""
    t = F.round(dot("a_res", "b_res"), 6)
    return pairs.withColumn("t", t).withColumn("w", F.round(peak_correlation("a_z", "b_z", lag), 6)).drop("a_res", "b_res", "a_z", "b_z")


def prepared(rec: DataFrame, width: float, bins: int, step: float) -> DataFrame:
    return metadata_key(histogram_residual(rec, width, bins), step).withColumn("z", znorm(F.col("x")))


def null_pairs(rec: DataFrame, n: int) -> DataFrame:
    """Up to n cross-hull pairs of neighbours in md5 order: a fixed-size sample, whatever the number of recordings."""
    some = rec.withColumn("u", F.md5(F.col("rid").cast("string"))).orderBy("u").limit(2 * n)
    at = W.orderBy("u")
    p = some.select(F.col("rid").alias("a"), F.col("hull").alias("a_hull"), F.col("res").alias("a_res"), F.col("z").alias("a_z"), *(F.lead(c).over(at).alias(f"b_{c}") for c in ("hull", "res", "z")), F.lead("rid").over(at).alias("b"), "u")
    p = p.where("b is not null and a_hull <> b_hull").withColumn("k", F.row_number().over(at)).where(F.col("k") <= n)
    return p.drop("u", "k")


def null_bars(null: DataFrame, factor: float = 4.0) -> DataFrame:
    """p99 of texture and factor times p95 of waveform among pairs that cannot be one transit."""
    return null.agg(F.count(F.lit(1)).alias("n_null"), F.round(F.percentile("t", F.lit(0.99)), 6).alias("texture_bar"), F.round(factor * F.percentile("w", F.lit(0.95)), 6).alias("wave_bar"))


def gate(ev: DataFrame, known: DataFrame, bars: DataFrame, rules: list[Rule]) -> DataFrame:
    """rule, known, recalled, texture_bar, wave_bar, approved: a rule must find every known pair and stand above the bars."""
    k = ev.join(known, ["a", "b"], "left_semi")
    out = None
    for r in rules:
        one = k.agg(F.count(F.lit(1)).alias("known"), F.count_if(r.verdict(F.col("t"), F.col("w")) != "distinct").alias("recalled")).crossJoin(F.broadcast(bars))
        ok = (F.col("known") == F.col("recalled")) & (F.lit(r.alone) > F.col("texture_bar")) & (F.lit(r.capture) >= F.col("wave_bar"))
        one = one.select(F.lit(r.name).alias("rule"), "known", "recalled", "texture_bar", "wave_bar", ok.alias("approved"))
        out = one if out is None else out.unionByName(one)
    return out


def require(measures: DataFrame, verdict: DataFrame, rule: str) -> DataFrame:
    """measures, or an error when it is read, unless the gate approved the rule that made the transit map."""
    ok = verdict.where(F.col("rule") == rule).agg(F.coalesce(F.bool_and("approved"), F.lit(False)).alias("ok"))
    stop = F.when(F.col("ok"), F.lit(True)).otherwise(F.raise_error(F.lit(f"no approved transit map by the rule {rule}")))
    return measures.crossJoin(F.broadcast(ok)).where(stop).drop("ok")


def transits(edges: DataFrame, rec: DataFrame) -> DataFrame:
    """rid, hull, transit_id (smallest rid reachable by edges a-b). Labels halve their distance by pointer jumps each round."""
    both = settled(edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct())
    label = settled(both.groupBy(F.col("a").alias("rid")).agg(F.least(F.col("rid"), F.min("b")).alias("to")))
    old = None
    while True:
        near = both.join(label.select(F.col("rid").alias("b"), "to"), "b").groupBy(F.col("a").alias("rid")).agg(F.min("to").alias("seen"))
        hop = label.select(F.col("rid").alias("to"), F.col("to").alias("far"))
        new = settled(label.join(near, "rid").join(hop, "to", "left").select("rid", F.least("to", "seen", F.coalesce("far", "to")).alias("new"), F.col("to").alias("old")))
        if old is not None:
            discard(old)
        old, label = new, new.select("rid", F.col("new").alias("to"))
        if new.where("new <> old").isEmpty():
            return rec.select("rid", "hull").join(label, "rid", "left").select("rid", "hull", F.coalesce("to", "rid").alias("transit_id"))


def representatives(rec: DataFrame, moved: DataFrame) -> DataFrame:
    """One recording per transit: the longest, then the smallest id."""
    r = rec.select("rid", F.size("x").cast("long").alias("n")).join(moved, "rid")
    return r.groupBy("transit_id", "hull").agg(F.min_by("rid", F.struct(-F.col("n"), F.col("rid"))).alias("rid"), F.count(F.lit(1)).alias("recordings"))


def residual_spectrum(x: np.ndarray, lines: float = 3.0, smooth: int = 9) -> np.ndarray:
    """Log power of a recording without its broadband rise and fall and without its lines, centred and of length one."""
    x = np.asarray(x, float)
    env = np.convolve(np.abs(x - x.mean()), np.ones(smooth) / smooth, "same")
    power = np.abs(np.fft.rfft((x - x.mean()) / np.maximum(env, 1e-9), 256)[1:]) ** 2
    background = np.convolve(np.pad(power, smooth // 2, "edge"), np.ones(smooth) / smooth, "valid")
    level = np.log(np.maximum(np.where(power > lines * background, background, power), 1e-12))
    level -= np.convolve(np.pad(level, 16, "edge"), np.ones(33) / 33, "valid")
    level -= level.mean()
    return level / max(np.linalg.norm(level), 1e-12)


def waveform_peak(a: np.ndarray, b: np.ndarray) -> float:
    """Largest absolute normalised cross-correlation over all lags."""
    a, b = np.asarray(a, float) - np.mean(a), np.asarray(b, float) - np.mean(b)
    size = 1 << (len(a) + len(b)).bit_length()
    c = np.fft.irfft(np.fft.rfft(a, size) * np.conj(np.fft.rfft(b, size)), size)
    return float(np.abs(c).max() / max(np.linalg.norm(a) * np.linalg.norm(b), 1e-12))


def fft_evidence(pairs: DataFrame, gate_at: float = 0.10) -> DataFrame:
    """a, b, reason, t, w of pairs that carry x: spectral texture, and the waveform only above a low texture gate."""

    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for part in parts:
            t = [float(residual_spectrum(p) @ residual_spectrum(q)) for p, q in zip(part["a_x"], part["b_x"], strict=True)]
            w = [waveform_peak(p, q) if s >= gate_at else None for p, q, s in zip(part["a_x"], part["b_x"], t, strict=True)]
            yield pd.DataFrame({"a": part["a"], "b": part["b"], "reason": part["reason"], "t": t, "w": pd.Series(w, dtype="Float64")})

    return pairs.select("a", "b", "reason", "a_x", "b_x").mapInPandas(run, "a long, b long, reason string, t double, w double")


def finding_class(pairs: DataFrame, reach: int = 1) -> DataFrame:
    """Cross-hull confirmations by what they are: byte-identical files, clusters of neighbouring ids, or scenes with two hulls in them.
    pairs: a, b, a_digest, b_digest. They are reported as label noise and never merged."""
    kind = F.when(F.col("a_digest") == F.col("b_digest"), "identical file").when(F.abs(F.col("a") - F.col("b")) <= reach, "neighbouring ids").otherwise("shared scene")
    return pairs.withColumn("finding", kind)


def islands(ids: DataFrame, by: str, col: str) -> DataFrame:
    """by, first, last, n: runs of consecutive ids."""
    run = F.col(col) - F.row_number().over(W.partitionBy(by).orderBy(col))
    return ids.withColumn("run", run).groupBy(by, "run").agg(F.min(col).alias("first"), F.max(col).alias("last"), F.count(F.lit(1)).alias("n")).drop("run")


def audit_report(pairs: DataFrame) -> DataFrame:
    """Nominated pairs by partition and by who confirms them (metadata, audio, both), with the totals of each. pairs: part, same_key, confirmed."""
    who = F.when(F.col("same_key") & F.col("confirmed"), "both").when(F.col("confirmed"), "audio only").when(F.col("same_key"), "metadata only").otherwise("neither")
    return pairs.withColumn("who", who).cube("part", "who").agg(F.count(F.lit(1)).alias("pairs"))


def acceptance(report: DataFrame, expected: DataFrame, on: list[str]) -> DataFrame:
    """Expected values that were written down beforehand against the report: on, expected, got, ok. Both have `value`."""
    both = expected.select(*on, F.col("value").alias("expected")).join(report.select(*on, F.col("value").alias("got")), on, "left")
    return both.withColumn("ok", F.col("expected").eqNullSafe(F.col("got")))
