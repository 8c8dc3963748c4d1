"""Gallery, scores and ranks of the cross-passage protocol."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..functions.vectors import dot, unit


#: Shares of the queries that are joined apart, as all passages may be of one source.
SHARES = 16


def _dealt(q: DataFrame, g: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Queries in shares and the gallery once for each of them: an equality that no single source makes hot."""
    parts = int(q.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    q = q.repartition(max(SHARES, min(parts, 256)), "query_id").withColumn("share", F.pmod(F.xxhash64("query_id"), F.lit(SHARES)).cast("int"))
    return q, g.withColumn("g_share", F.explode(F.sequence(F.lit(0), F.lit(SHARES - 1))))


def leave_one_out(p: DataFrame, pure: bool = True, keep_singletons: bool = True, method: str = "a") -> DataFrame:
    """Scores of every passage of a hull with several against all others; pure: of the same source only."""
    many = p.groupBy("hull_id").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("hull_id")
    pool = p if keep_singletons else p.join(many, "hull_id", "left_semi")
    q = p.join(many, "hull_id", "left_semi").select(F.col("passage_id").alias("query_id"), F.col("hull_id").alias("q_hull"), "source", F.col("vec").alias("qv"))
    g = pool.select(F.col("passage_id").alias("gallery_id"), F.col("hull_id").alias("g_hull"), F.col("source").alias("g_source"), F.col("vec").alias("gv"))
    q, g = _dealt(q, g)
    on = (F.col("share") == F.col("g_share")) & (F.col("query_id") != F.col("gallery_id"))
    pairs = q.join(g, on & (F.col("source") == F.col("g_source")) if pure else on)
    return pairs.select(F.lit(method).alias("method"), "query_id", "gallery_id", "q_hull", "g_hull", F.round(dot("qv", "gv"), 9).alias("sim"))


def fuse(*scores: DataFrame, method: str = "fused") -> DataFrame:
    """Mean over methods of each query's z-scored row (population deviation; a constant row gives 0)."""
    every = scores[0]
    for s in scores[1:]:
        every = every.unionByName(s)
    row = W.partitionBy("method", "query_id")
    z = F.coalesce((F.col("sim") - F.avg("sim").over(row)) / F.nullif(F.stddev_pop("sim").over(row), F.lit(0.0)), F.lit(0.0))
    out = every.withColumn("z", z).groupBy("query_id", "gallery_id", "q_hull", "g_hull").agg(F.avg("z").alias("z"))
    return out.select(F.lit(method).alias("method"), "query_id", "gallery_id", "q_hull", "g_hull", F.round("z", 9).alias("sim"))


def true_rank(scores: DataFrame) -> DataFrame:
    """1 + number of impostor passages strictly above the best passage of the query's own hull; only where it has one."""
    best = F.max(F.when(F.col("q_hull") == F.col("g_hull"), F.col("sim"))).over(W.partitionBy("method", "query_id"))
    out = scores.withColumn("best", best).where("best is not null").groupBy("method", "query_id", "q_hull", "best")
    return out.agg((F.count_if(F.col("sim") > F.col("best")) + 1).alias("rank"), F.count(F.lit(1)).alias("candidates"))


def shortlist(scores: DataFrame, k: int = 10) -> DataFrame:
    place = F.row_number().over(W.partitionBy("method", "query_id").orderBy(F.col("sim").desc(), "gallery_id"))
    return scores.withColumn("place", place.cast("long")).where(F.col("place") <= k)


def decide(scores: DataFrame, tau: float) -> DataFrame:
    """Each query's top passage, accepted at tau or unknown."""
    top = shortlist(scores, 1).drop("place")
    return top.withColumn("verdict", F.when(F.col("sim") >= tau, F.lit("accept")).otherwise(F.lit("unknown")))


def collapse(p: DataFrame) -> DataFrame:
    """One unit mean vector per hull."""
    at = p.select("hull_id", "source", F.posexplode("vec")).groupBy("hull_id", "source", "pos").agg(F.avg("col").alias("x"))
    rows = at.groupBy("hull_id", "source").agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "x"))), lambda s: s["x"]).alias("v"))
    return rows.select("hull_id", "source", unit(F.col("v")).alias("vec"))


def fixed_gallery(queries: DataFrame, gallery: DataFrame, method: str = "fixed", source: bool = False) -> DataFrame:
    """Scores of a query set of its own against a gallery that stays as it is; a passage is never scored against itself."""
    q = queries.select(F.col("passage_id").alias("query_id"), F.col("hull_id").alias("q_hull"), "source", F.col("vec").alias("qv"))
    g = gallery.select(F.col("passage_id").alias("gallery_id"), F.col("hull_id").alias("g_hull"), F.col("source").alias("g_source"), F.col("vec").alias("gv"))
    q, g = _dealt(q, g)
    on = (F.col("share") == F.col("g_share")) & (F.col("query_id") != F.col("gallery_id"))
    pairs = q.join(g, on & (F.col("source") == F.col("g_source")) if source else on)
    return pairs.select(F.lit(method).alias("method"), "query_id", "gallery_id", "q_hull", "g_hull", F.round(dot("qv", "gv"), 9).alias("sim"))


def cross_passage(scores: DataFrame, spans: DataFrame) -> DataFrame:
    """scores without pairs of one passage or of captures that overlap in time. spans: passage_id, first, last."""
    side = lambda i, p: spans.select(F.col("passage_id").alias(i), F.col("first").alias(f"{p}_first"), F.col("last").alias(f"{p}_last"))
    both = scores.where("query_id <> gallery_id").join(side("query_id", "q"), "query_id").join(side("gallery_id", "g"), "gallery_id")
    return both.where("q_last < g_first or g_last < q_first").select(*scores.columns)


def fuse_weighted(weights: dict[str, float], scores: DataFrame, method: str = "weighted") -> DataFrame:
    """Weighted mean of each query's z-scored rows over any number of methods."""
    row = W.partitionBy("method", "query_id")
    z = F.coalesce((F.col("sim") - F.avg("sim").over(row)) / F.nullif(F.stddev_pop("sim").over(row), F.lit(0.0)), F.lit(0.0))
    share = F.coalesce(*(F.when(F.col("method") == m, F.lit(float(w))) for m, w in weights.items()))
    out = scores.where(F.col("method").isin(*weights)).withColumn("z", z * share).withColumn("w", share)
    out = out.groupBy("query_id", "gallery_id", "q_hull", "g_hull").agg((F.sum("z") / F.sum("w")).alias("z"))
    return out.select(F.lit(method).alias("method"), "query_id", "gallery_id", "q_hull", "g_hull", F.round("z", 9).alias("sim"))


def pool_passages(segments: DataFrame) -> DataFrame:
    """passage_id, n, vec: the renormalised mean of a passage's unit segment vectors. segments: passage_id, vec."""
    at = segments.select("passage_id", F.posexplode(unit(F.col("vec")))).groupBy("passage_id", "pos").agg(F.avg("col").alias("m"), F.count(F.lit(1)).alias("n"))
    rows = at.groupBy("passage_id").agg(F.max("n").alias("n"), F.transform(F.array_sort(F.collect_list(F.struct("pos", "m"))), lambda s: s["m"]).alias("v"))
    return rows.select("passage_id", "n", unit(F.col("v")).alias("vec"))


def apply_map(p: DataFrame, moved: DataFrame) -> DataFrame:
    """Passages under a transit map (passage_id, transit_id): a transit's first passage stays for all of it."""
    return p.join(moved.groupBy("transit_id").agg(F.min("passage_id").alias("passage_id")), "passage_id", "left_semi")


def true_rank_of_hulls(scores: DataFrame) -> DataFrame:
    """1 + number of other hulls whose best passage stands above the best passage of the query's own."""
    best = scores.groupBy("method", "query_id", "q_hull", "g_hull").agg(F.max("sim").alias("sim"))
    return true_rank(best)


def export_bundle(scores: DataFrame, path: str, key: str, withhold: tuple = ("q_hull", "g_hull")) -> None:
    """Scores written for others: hull identifiers are replaced by keyed digests, one folder a method, sorted by query."""
    out = scores
    for c in withhold:
        out = out.withColumn(c, F.substring(F.sha2(F.concat(F.lit(key + "|"), F.col(c).cast("string")), 256), 1, 16))
    out.repartition("method").sortWithinPartitions("query_id", "gallery_id").write.partitionBy("method").mode("overwrite").parquet(path)
