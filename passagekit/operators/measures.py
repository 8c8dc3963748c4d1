"""Measures over scores and ranks."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..functions.vectors import binomial_two_sided


def rank_measures(ranks: DataFrame) -> DataFrame:
    hit = lambda k: F.avg(F.when(F.col("rank") <= k, 1.0).otherwise(0.0))
    return ranks.groupBy("method").agg(F.count(F.lit(1)).alias("n"), F.round(hit(1), 6).alias("rank1"), F.round(hit(5), 6).alias("hit5"), F.round(hit(10), 6).alias("hit10"), F.round(F.percentile("rank", F.lit(0.5)), 6).alias("medr"), F.round(F.lit(1.0) / F.count(F.lit(1)), 6).alias("one_query"))


def labelled(scores: DataFrame, genuine: str = "best") -> DataFrame:
    """method, sim, same: impostor scores, and the best (or all) genuine ones of each query."""
    own = scores.where("q_hull = g_hull")
    own = own.groupBy("method", "query_id").agg(F.max("sim").alias("sim")) if genuine == "best" else own
    return own.select("method", "sim", F.lit(1).alias("same")).unionByName(scores.where("q_hull <> g_hull").select("method", "sim", F.lit(0).alias("same")))


def roc(points: DataFrame) -> DataFrame:
    """Cumulative genuine and impostor shares at or above each distinct score, with those at the score itself."""
    by = points.groupBy("method", "sim").agg(F.sum("same").alias("g"), F.sum(1 - F.col("same")).alias("i")).withColumn("bin", F.floor(F.col("sim") * 1024))
    # sums of narrow bins of scores run over few rows a method; the scores of a bin are one task's work, not those of a method
    bins = by.groupBy("method", "bin").agg(F.sum("g").alias("bg"), F.sum("i").alias("bi"))
    above, every = W.partitionBy("method").orderBy(F.col("bin").desc()).rowsBetween(W.unboundedPreceding, -1), W.partitionBy("method")
    bins = bins.select("method", "bin", F.coalesce(F.sum("bg").over(above), F.lit(0)).alias("ag"), F.coalesce(F.sum("bi").over(above), F.lit(0)).alias("ai"), F.sum("bg").over(every).alias("tg"), F.sum("bi").over(every).alias("ti"))
    down = W.partitionBy("method", "bin").orderBy(F.col("sim").desc())
    return by.join(bins, ["method", "bin"]).select("method", "sim", "g", "i", (F.col("ag") + F.sum("g").over(down)).alias("cg"), (F.col("ai") + F.sum("i").over(down)).alias("ci"), "tg", "ti")


def curve(points: DataFrame) -> DataFrame:
    """method, auc, eer from one pass over the operating points.

    auc: chance that a genuine score beats an impostor score, ties one half. eer: where false accepts equal false rejects,
    linear between neighbouring thresholds; what stands above a score is the point before it.
    """
    far, frr = F.col("ci") / F.col("ti"), 1 - F.col("cg") / F.col("tg")
    r = roc(points).withColumns({"far": far, "frr": frr, "far0": (F.col("ci") - F.col("i")) / F.col("ti"), "frr0": 1 - (F.col("cg") - F.col("g")) / F.col("tg")})
    a, b = F.col("frr0") - F.col("far0"), F.col("far") - F.col("frr")
    r = r.withColumn("at", F.col("far0") + (F.col("far") - F.col("far0")) * F.coalesce(a / F.nullif(a + b, F.lit(0.0)), F.lit(0.0)))
    won = F.sum(F.col("g") * ((F.col("ti") - F.col("ci")) + F.lit(0.5) * F.col("i")))
    return r.groupBy("method").agg(F.round(won / F.max(F.col("tg").cast("double") * F.col("ti")), 6).alias("auc"), F.expr("round(max_by(at, sim) filter (where far >= frr and far0 < frr0), 6)").alias("eer"))


def auc(points: DataFrame) -> DataFrame:
    return curve(points).select("method", "auc")


def eer(points: DataFrame) -> DataFrame:
    return curve(points).select("method", "eer").where("eer is not null")


def curve_of_points(points: DataFrame) -> DataFrame:
    """curve() from counts at the genuine scores only: method, sim, g, i (genuine and impostor scores there), above (impostors above it), ti (impostors).

    Between two genuine scores the false rejects stay, so where the false accepts pass them there, they are the rate.
    """
    down, every = W.partitionBy("method").orderBy(F.col("sim").desc()), W.partitionBy("method")
    ti, tg = F.nullif(F.col("ti"), F.lit(0).cast("long")), F.col("tg")
    r = points.withColumns({"cg": F.sum("g").over(down), "tg": F.sum("g").over(every), "ci": F.col("above") + F.col("i")})
    r = r.withColumns({"far": F.col("ci") / ti, "frr": 1 - F.col("cg") / tg, "far0": F.col("above") / ti, "frr0": 1 - (F.col("cg") - F.col("g")) / tg})
    a, b = F.col("frr0") - F.col("far0"), F.col("far") - F.col("frr")
    at = F.when(F.col("far0") < F.col("frr0"), F.col("far0") + (F.col("far") - F.col("far0")) * F.coalesce(a / F.nullif(a + b, F.lit(0.0)), F.lit(0.0))).otherwise(F.col("frr0"))
    won = F.sum(F.col("g") * ((F.col("ti") - F.col("ci")) + F.lit(0.5) * F.col("i")))
    return r.withColumn("at", at).groupBy("method").agg(F.round(won / F.nullif(F.max(F.col("tg").cast("double") * F.col("ti")), F.lit(0.0)), 6).alias("auc"), F.expr("round(max_by(at, sim) filter (where far >= frr), 6)").alias("eer"))


def eer_of_points(points: DataFrame) -> DataFrame:
    return curve_of_points(points).select("method", "eer").where("eer is not null")


def evaluate_networks(nets, methods: list | None = None) -> DataFrame:
    """evaluate() of a blocked.Networks."""
    ranks = nets.ranks()
    ranks = ranks.where(F.col("method").isin(*methods)) if methods else ranks
    return rank_measures(ranks).join(curve_of_points(nets.points(methods=methods)).where("eer is not null"), "method")


def evaluate(scores: DataFrame, ranks: DataFrame) -> DataFrame:
    return rank_measures(ranks).join(curve(labelled(scores)).where("eer is not null"), "method")


def mcnemar(ranks: DataFrame, ks: tuple = (1, 5, 10)) -> DataFrame:
    """Exact paired test of all method pairs at each k."""
    a = ranks.select(F.col("method").alias("first"), "query_id", F.col("rank").alias("ra"))
    b = ranks.select(F.col("method").alias("second"), "query_id", F.col("rank").alias("rb"))
    pairs = a.join(b, "query_id").where("first < second").withColumn("k", F.explode(F.array(*(F.lit(k) for k in ks))))
    only = lambda x, y: F.count_if((F.col(x) <= F.col("k")) & (F.col(y) > F.col("k")))
    out = pairs.groupBy("first", "second", "k").agg(only("ra", "rb").alias("only_first"), only("rb", "ra").alias("only_second"))
    return out.withColumn("p", F.round(binomial_two_sided(F.col("only_first"), F.col("only_second")), 6))


def gap(scores: DataFrame) -> DataFrame:
    """Mean same minus mean different over unordered pairs."""
    s = scores.where("query_id < gallery_id")
    mean = lambda same: F.avg(F.when((F.col("q_hull") == F.col("g_hull")) == same, F.col("sim")))
    return s.groupBy("method").agg(F.count_if(F.col("q_hull") == F.col("g_hull")).alias("n_same"), F.count_if(F.col("q_hull") != F.col("g_hull")).alias("n_diff"), F.round(mean(True), 6).alias("same"), F.round(mean(False), 6).alias("diff"), F.round(mean(True) - mean(False), 6).alias("gap"))


def gap_of_passages(p: DataFrame, method: str = "a") -> DataFrame:
    """gap() over all unordered pairs of passages p, without a pair: a group's products sum to half its summed vector's square less its own squares.

    Null or empty vectors take no part; without pairs of a kind its mean and the gap are null.
    """
    p = p.where("size(vec) > 0")
    at = p.select("hull_id", F.posexplode("vec")).groupBy("hull_id", "pos").agg(F.sum("col").alias("s"), F.sum(F.col("col") * F.col("col")).alias("q"), F.count(F.lit(1)).alias("n"))
    hull = at.groupBy("hull_id").agg(F.sum(F.col("s") * F.col("s")).alias("ss"), F.sum("q").alias("q"), F.max("n").alias("n"))
    own = hull.agg(F.sum((F.col("ss") - F.col("q")) / 2).alias("same"), F.coalesce(F.sum(F.expr("n * (n - 1) div 2")), F.lit(0).cast("long")).alias("n_same"), F.sum("q").alias("q"), F.coalesce(F.sum("n"), F.lit(0).cast("long")).alias("n"))
    every = at.groupBy("pos").agg(F.sum("s").alias("s")).agg(F.sum(F.col("s") * F.col("s")).alias("ss"))
    out = own.crossJoin(every).withColumn("n_diff", F.expr("n * (n - 1) div 2 - n_same"))  # one row each
    mean = lambda total, n: total / F.nullif(F.col(n), F.lit(0).cast("long"))
    out = out.withColumns({"a": mean(F.col("same"), "n_same"), "b": mean((F.col("ss") - F.col("q")) / 2 - F.col("same"), "n_diff")})
    return out.select(F.lit(method).alias("method"), "n_same", "n_diff", F.round("a", 6).alias("same"), F.round("b", 6).alias("diff"), F.round(F.col("a") - F.col("b"), 6).alias("gap"))


def chance_level(p: DataFrame) -> DataFrame:
    """n, chance_rank1: share of a query's candidates that are of its hull, meant over queries with a candidate.

    Candidates are the other passages of the query's source; hulls of one passage neither ask nor stand in the gallery. All
    of it follows from counts by hull and source.
    """
    many = p.groupBy("hull_id").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("hull_id")
    cell = p.join(many, "hull_id", "left_semi").groupBy("source", "hull_id").agg(F.count(F.lit(1)).alias("own"))
    cell = cell.join(cell.groupBy("source").agg(F.sum("own").alias("every")), "source").where("every > 1")
    out = cell.agg(F.coalesce(F.sum("own"), F.lit(0).cast("long")).alias("n"), F.sum(F.col("own") * (F.col("own") - 1) / (F.col("every") - 1)).alias("c"))
    return out.select("n", F.round(F.col("c") / F.nullif(F.col("n"), F.lit(0).cast("long")), 6).alias("chance_rank1"))


def win_matrix(scores: DataFrame) -> DataFrame:
    """Per method and pair of query hulls: wins (ties one half) and pairs of genuine against impostor scores. All that a
    hull bootstrap of the AUC needs: a replicate with multiplicities w is sum w w wins / sum w w pairs."""
    g = scores.where("q_hull = g_hull").groupBy("method", "query_id", "q_hull").agg(F.max("sim").alias("sim")).groupBy("method", F.col("q_hull").alias("g_of"), "sim").agg(F.count(F.lit(1)).alias("m"))
    i = scores.where("q_hull <> g_hull").groupBy("method", F.col("q_hull").alias("i_of"), "sim").agg(F.count(F.lit(1)).alias("k"))
    # a genuine score goes to every hull once (as many rows as the result needs) and is ranked among that hull's impostor scores
    hulls = i.select("method", "i_of").distinct()
    every = g.join(hulls, "method").select("method", "i_of", "sim", "g_of", "m", F.lit(0).cast("long").alias("k")).unionByName(i.select("method", "i_of", "sim", F.lit(None).cast("long").alias("g_of"), F.lit(0).cast("long").alias("m"), "k"))
    one = W.partitionBy("method", "i_of")
    upto, same = F.sum("k").over(one.orderBy("sim").rangeBetween(W.unboundedPreceding, 0)), F.sum("k").over(W.partitionBy("method", "i_of", "sim"))
    ranked = every.withColumn("won", upto - 0.5 * same).withColumn("n", F.sum("k").over(one)).where("m > 0")
    return ranked.groupBy("method", "g_of", "i_of").agg(F.sum(F.col("m") * F.col("won")).alias("wins"), F.sum(F.col("m") * F.col("n")).alias("pairs"))


def draws(hulls: DataFrame, b: int, offset: int = 0) -> DataFrame:
    """replicate, hull, w: hulls drawn with replacement, by md5 of replicate (from offset on) and place."""
    n = hulls.count()
    at = hulls.sparkSession.range(b).select(F.col("id").alias("r")).withColumn("place", F.explode(F.sequence(F.lit(0), F.lit(n - 1))))
    pick = F.conv(F.substring(F.md5(F.concat_ws("|", F.col("r") + offset, "place")), 1, 8), 16, 10).cast("long") % n
    rank = hulls.select("hull", (F.row_number().over(W.orderBy("hull")) - 1).cast("long").alias("pick"))
    return at.withColumn("pick", pick).join(F.broadcast(rank), "pick").groupBy("r", "hull").agg(F.count(F.lit(1)).alias("w"))


def bootstrap_auc(wins: DataFrame, b: int = 200) -> DataFrame:
    """method, replicate and AUC."""
    hulls = wins.select(F.col("g_of").alias("hull")).distinct()
    w = draws(hulls, b)
    x = wins.join(w.select(F.col("hull").alias("g_of"), "r", F.col("w").alias("wg")), "g_of").join(w.select(F.col("hull").alias("i_of"), "r", F.col("w").alias("wi")), ["i_of", "r"])
    return x.groupBy("method", "r").agg((F.sum(F.col("wg") * F.col("wi") * F.col("wins")) / F.sum(F.col("wg") * F.col("wi") * F.col("pairs"))).alias("auc"))


def discordance(ranks: DataFrame, first: str, second: str, ks: tuple = (1, 5, 10)) -> DataFrame:
    """k, queries, and how many of them exactly one of two methods answers."""
    of = lambda m: F.max(F.when(F.col("method") == m, F.col("rank")))
    by = ranks.where(F.col("method").isin(first, second)).groupBy("query_id").agg(of(first).alias("a"), of(second).alias("b")).withColumn("k", F.explode(F.array(*(F.lit(k) for k in ks))))
    one = (F.col("a") <= F.col("k")) != (F.col("b") <= F.col("k"))
    return by.groupBy("k").agg(F.count(F.lit(1)).alias("queries"), F.count_if(one).alias("discordant"), F.round(F.avg(F.when(one, 1.0).otherwise(0.0)), 6).alias("share"))


def wrong_top(scores: DataFrame) -> DataFrame:
    """Scores of the top returns that are of another hull: how confident the mistakes are."""
    top = scores.groupBy("method", "query_id").agg(F.max_by(F.struct("q_hull", "g_hull", "sim"), F.struct("sim", -F.col("gallery_id"))).alias("t"))
    bad = top.where("t.q_hull <> t.g_hull")
    return bad.groupBy("method").agg(F.count(F.lit(1)).alias("n"), F.round(F.min("t.sim"), 6).alias("lowest"), F.round(F.avg("t.sim"), 6).alias("mean"), F.round(F.max("t.sim"), 6).alias("highest"))


def wrong_top_of_ranks(ranks: DataFrame) -> DataFrame:
    """wrong_top() from ranks that hold the nearest passage of each query (blocked.network_ranks)."""
    bad = ranks.where("q_hull <> top.hull")
    return bad.groupBy("method").agg(F.count(F.lit(1)).alias("n"), F.round(F.min("top.sim"), 6).alias("lowest"), F.round(F.avg("top.sim"), 6).alias("mean"), F.round(F.max("top.sim"), 6).alias("highest"))


def lift(metrics: DataFrame, base: str, on: str = "set") -> DataFrame:
    """How far each method moves every measure against the base method, by query set."""
    b = metrics.where(F.col("method") == base).select(on, F.col("medr").alias("b_medr"), F.col("auc").alias("b_auc"), F.col("rank1").alias("b_rank1"))
    m = metrics.where(F.col("method") != base).join(b, on)
    return m.select("method", on, F.round(F.col("medr") / F.col("b_medr"), 6).alias("medr_ratio"), F.round(F.col("auc") - F.col("b_auc"), 6).alias("auc_gain"), F.round(F.col("rank1") - F.col("b_rank1"), 6).alias("rank1_gain"))


def classification_metrics(*_, **__) -> None:
    """Accuracy, F1 and the like assume that every hull is known; in an open set most are not, so there is no such measure here."""
    raise NotImplementedError("the task is open-set: use ranks, AUC and EER, not classification measures")


def bootstrap_two_way(wins: DataFrame, b: int = 200) -> DataFrame:
    """method, r, auc where the hulls of genuine and of impostor scores are drawn apart from each other."""
    hulls = wins.select(F.col("g_of").alias("hull")).distinct()
    w, v = draws(hulls, b), draws(hulls, b, offset=b)
    x = wins.join(w.select(F.col("hull").alias("g_of"), "r", F.col("w").alias("wg")), "g_of").join(v.select(F.col("hull").alias("i_of"), "r", F.col("w").alias("wi")), ["i_of", "r"])
    return x.groupBy("method", "r").agg((F.sum(F.col("wg") * F.col("wi") * F.col("wins")) / F.sum(F.col("wg") * F.col("wi") * F.col("pairs"))).alias("auc"))


def query_wins(scores: DataFrame) -> DataFrame:
    """Per query: share of its impostor scores that its best genuine score beats (ties one half), and how many there are."""
    best = F.max(F.when(F.col("q_hull") == F.col("g_hull"), F.col("sim"))).over(W.partitionBy("method", "query_id"))
    s = scores.withColumn("gs", best).where("gs is not null and q_hull <> g_hull")
    won = F.when(F.col("gs") > F.col("sim"), 1.0).when(F.col("gs") == F.col("sim"), 0.5).otherwise(0.0)
    return s.groupBy("method", "query_id", "q_hull").agg(F.sum(won).alias("wins"), F.count(F.lit(1)).alias("pairs"))


def query_wins_of_ranks(ranks: DataFrame) -> DataFrame:
    """query_wins() from ranks that count impostors and ties (blocked.network_ranks)."""
    lost = F.col("rank") - 1 + F.lit(0.5) * F.col("ties")
    return ranks.where("impostors > 0").select("method", "query_id", "q_hull", (F.col("impostors") - lost).alias("wins"), F.col("impostors").alias("pairs"))


def bootstrap_queries(wins: DataFrame, b: int = 200) -> DataFrame:
    """method, r, auc where queries are drawn as if they were independent: too narrow, as queries of a hull are not."""
    w = draws(wins.select(F.col("query_id").alias("hull")).distinct(), b).withColumnRenamed("hull", "query_id")
    return wins.join(w, "query_id").groupBy("method", "r").agg((F.sum(F.col("w") * F.col("wins")) / F.sum(F.col("w") * F.col("pairs"))).alias("auc"))
