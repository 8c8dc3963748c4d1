"""Narrowband lines: spectrum, two-pass split-window whitening, peaks, persistence and matching."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..stage import settled


def spectrum(frames: DataFrame, n: int, bins: int) -> DataFrame:
    """rec, frame, bin, power of frames with x (array of n doubles)."""
    turn = lambda f: F.aggregate(F.transform("x", lambda v, i: v * f(F.lit(2 * math.pi) * F.col("bin") * i / F.lit(float(n)))), F.lit(0.0), lambda a, b: a + b)
    e = frames.withColumn("bin", F.explode(F.sequence(F.lit(1), F.lit(bins))))
    power = F.transform(F.array(F.struct(turn(F.cos).alias("re"), turn(F.sin).alias("im"))), lambda c: c["re"] * c["re"] + c["im"] * c["im"])[0]
    return e.select("rec", "frame", F.col("bin").cast("long").alias("bin"), power.alias("power"))


def whiten(spec: DataFrame, w: int = 4, g: int = 1, alpha: float = 2.0) -> DataFrame:
    """Ratio of power to a background that leaves the bin's neighbourhood out and, in a second pass, the lines too."""
    at = W.partitionBy("rec", "frame").orderBy("bin")
    sides = lambda c: (F.coalesce(F.sum(c).over(at.rowsBetween(-(g + w), -(g + 1))), F.lit(0.0)) + F.coalesce(F.sum(c).over(at.rowsBetween(g + 1, g + w)), F.lit(0.0))) / (F.count(c).over(at.rowsBetween(-(g + w), -(g + 1))) + F.count(c).over(at.rowsBetween(g + 1, g + w)))
    one = spec.withColumn("m", sides("power")).withColumn("c", F.when(F.col("power") > alpha * F.col("m"), F.col("m")).otherwise(F.col("power")))
    return one.withColumn("ratio", F.col("power") / F.nullif(sides("c"), F.lit(0.0))).select("rec", "frame", "bin", "ratio")


def lines(white: DataFrame, level: float = 1.5) -> DataFrame:
    at = W.partitionBy("rec", "frame").orderBy("bin")
    up = white.withColumn("a", F.coalesce(F.lag("ratio").over(at), F.lit(0.0))).withColumn("b", F.coalesce(F.lead("ratio").over(at), F.lit(0.0)))
    return up.where((F.col("ratio") >= level) & (F.col("ratio") > F.col("a")) & (F.col("ratio") >= F.col("b"))).select("rec", "frame", "bin", "ratio")


def persistent(found: DataFrame, frames: DataFrame, rho: float = 0.5) -> DataFrame:
    """rec, bin and the share of frames in which the bin is a line."""
    n = frames.groupBy("rec").agg(F.count_distinct("frame").alias("n"))
    by = found.groupBy("rec", "bin").agg(F.count(F.lit(1)).alias("k"))
    return by.join(n, "rec").withColumn("persistence", F.col("k") / F.col("n")).where(F.col("persistence") >= rho).select("rec", "bin", "persistence")


def line_sets(found: DataFrame) -> DataFrame:
    """rec and bits: the bins (1 to 62) of its lines as one number."""
    return found.groupBy("rec").agg(F.expr("bit_or(shiftleft(1L, cast(bin as int)))").alias("bits"))


def spread(bits: Column, tol: int) -> Column:
    """bits and all within tol bins of them."""
    out = bits
    for k in range(1, tol + 1):
        out = out.bitwiseOR(F.shiftleft(bits, k)).bitwiseOR(F.shiftright(bits, k))
    return out


def fraction(q: Column, g: Column, tol: int = 1) -> Column:
    """Share of q's lines with a line of g within tol bins."""
    return F.bit_count(q.bitwiseAND(spread(g, tol))) / F.bit_count(q)


def symmetric(q: Column, g: Column, tol: int = 1) -> Column:
    """The same from both sides: matched lines of both over all lines of both."""
    return (F.bit_count(q.bitwiseAND(spread(g, tol))) + F.bit_count(g.bitwiseAND(spread(q, tol)))) / (F.bit_count(q) + F.bit_count(g))


def matched_fraction(q: DataFrame, g: DataFrame, tol: int = 1) -> DataFrame:
    """Share of a query's lines with a gallery line within tol bins, for pairs that share one.

    Recordings with the same lines score alike, so scores are computed between distinct line sets, and pairs come of those.
    """
    q, g = line_sets(q).withColumnRenamed("rec", "query_id"), line_sets(g).withColumnRenamed("rec", "gallery_id")
    kinds = q.select(F.col("bits").alias("qb")).distinct().crossJoin(g.select(F.col("bits").alias("gb")).distinct())
    kinds = kinds.withColumn("sim", fraction(F.col("qb"), F.col("gb"), tol)).where("sim > 0")
    return kinds.join(q.withColumnRenamed("bits", "qb"), "qb").join(g.withColumnRenamed("bits", "gb"), "gb").where("query_id <> gallery_id").select("query_id", "gallery_id", "sim")


def common_lines(found: DataFrame, a: int, b: int, tol: int = 1) -> DataFrame:
    """The lines of recording a that recording b has too, with their persistence."""
    x, y = found.where(F.col("rec") == a), found.where(F.col("rec") == b).select(F.explode(F.sequence(F.col("bin") - tol, F.col("bin") + tol)).alias("bin")).distinct()
    return x.join(y, "bin", "left_semi")


def _sims(q: Column, g: Column) -> Column:
    """method and sim of two line sets, by both scores."""
    one, two = F.round(fraction(q, g), 9), F.round(symmetric(q, g), 9)
    return F.inline(F.array(F.struct(F.lit("one side").alias("method"), one.alias("sim")), F.struct(F.lit("both sides").alias("method"), two.alias("sim"))))


def _sims_of(q: int, g: np.ndarray) -> dict[str, np.ndarray]:
    """The scores of one line set against many."""
    near = lambda b: b | b << 1 | b >> 1
    a, b = np.bitwise_count(q & near(g)).astype(float), np.bitwise_count(g & near(q)).astype(float)
    n, m = float(int(q).bit_count()), np.bitwise_count(g).astype(float)
    return {"one side": np.round(a / n, 9), "both sides": np.round((a + b) / (n + m), 9)}


def line_measures(p: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(method, query_id, rank; points for measures.curve_of_points) of leave-one-out over passages p: passage_id, hull_id, bits (not 0).

    Passages with the same lines score alike, so scores are computed between distinct line sets (at most two to the number of bins) and
    counted as often as passages have them; only the pairs of a hull are rows. Every line set goes to every task.
    """
    p = settled(p)
    side = lambda i, b: p.select(F.col("passage_id").alias(i), "hull_id", F.col("bits").alias(b))
    own = settled(side("query_id", "qb").join(side("gallery_id", "gb"), "hull_id").where("query_id <> gallery_id").select("query_id", "qb", _sims(F.col("qb"), F.col("gb"))))
    q = settled(own.groupBy("method", "query_id", "qb").agg(F.max("sim").alias("best")))
    kinds = p.groupBy("bits").agg(F.count(F.lit(1)).alias("n")).toPandas()
    bits, n = kinds["bits"].to_numpy(), kinds["n"].to_numpy()

    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        pooled = {}
        for part in parts:
            out = []
            for qb, queries, bests in zip(part["qb"], part["queries"], part["bests"], strict=True):
                for m, s in _sims_of(qb, bits).items():
                    at, of = np.unique(s, return_inverse=True)
                    k = np.bincount(of, n).astype(int)  # counts stay whole far beyond any number of passages
                    total = pooled.setdefault(m, {})
                    for x, c in zip(at.tolist(), k.tolist(), strict=True):
                        total[x] = total.get(x, 0) + c * int(queries)
                    upto = np.concatenate([[0], np.cumsum(k)])
                    out += [(m, qb, b["best"], int(upto[-1] - upto[np.searchsorted(at, b["best"], "right")])) for b in bests if b["method"] == m]
            yield pd.DataFrame(out, columns=["method", "qb", "sim", "k"]).assign(pooled=False)
        for m, total in pooled.items():
            yield pd.DataFrame({"method": m, "qb": 0, "sim": list(total), "k": list(total.values()), "pooled": True})

    asked = q.groupBy("qb").agg(F.count_distinct("query_id").alias("queries"), F.collect_set(F.struct("method", "best")).alias("bests"))
    found = settled(asked.repartition(int(p.sparkSession.conf.get("spark.sql.shuffle.partitions")), "qb").mapInPandas(run, "method string, qb long, sim double, k long, pooled boolean"))
    # a passage is not its own candidate: against itself it scores 1
    above = found.where("not pooled").select("method", "qb", F.col("sim").alias("best"), (F.col("k") - (F.col("sim") < 1).cast("long")).alias("above"))
    ranks = q.join(above, ["method", "qb", "best"]).select("method", "query_id", (F.col("above") + 1).alias("rank"))
    none = F.lit(0).cast("long")
    every = found.where("pooled").select("method", "sim", none.alias("g"), F.col("k").alias("i"))
    own = own.groupBy("method", "sim").agg((-F.count(F.lit(1))).alias("i")).select("method", "sim", none.alias("g"), "i")
    self_ = q.groupBy("method").agg((-F.count(F.lit(1))).alias("i")).select("method", F.lit(1.0).alias("sim"), none.alias("g"), "i")
    best = q.groupBy("method", F.col("best").alias("sim")).agg(F.count(F.lit(1)).alias("g")).select("method", "sim", "g", none.alias("i"))
    points = every.unionByName(own).unionByName(self_).unionByName(best).groupBy("method", "sim").agg(F.sum("g").alias("g"), F.sum("i").alias("i")).where("g > 0 or i > 0")
    upto = W.partitionBy("method").orderBy(F.col("sim").desc())
    return ranks, points.select("method", "sim", "g", "i", (F.sum("i").over(upto) - F.col("i")).alias("above"), F.sum("i").over(W.partitionBy("method")).alias("ti"))
