"""Temperature mixing of sources, realised as budgeted block permutations. DataFrame expressions only.

A source with token share p gets weight p^a / sum p^a. The exponent a is found by bisection: an entropy target or a
limit on repetition is monotone in a, and each round evaluates a whole grid of exponents in one aggregate over
the sources (so 32 parts instead of 2 are told apart a round), which never brings the sources to the driver.
A source's budget is its weight times the token budget. It is spent in blocks: each block is a permutation of the
source (order by a keyed hash of block and document), whole blocks first; the last one is cut where the budget ends. The
cut is found from sums over hash buckets, so no source, however hot, passes through one task.

A null source is a source of its own. Null and empty texts have no tokens; a source without tokens is passed once. Rows
that are alike in id and text stand at the same place in the order, and are taken or left together. An empty table gives
an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .common import materialise

PARTS, ROUNDS, BUCKET_ROWS = 32, 4, 4096


def tokens(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def shares(docs: DataFrame) -> DataFrame:
    """source, documents and tokens of each source; docs has source and n_tokens."""
    return docs.groupBy("source").agg(F.count(F.lit(1)).alias("n_docs"), F.sum("n_tokens").alias("tokens"))


def exponent(sources: DataFrame, entropy: float | None = None, max_repeats: float | None = None, budget: int | None = None) -> float:
    """The exponent in [0, 1] that meets the target: the largest whose entropy (in nats) is at least `entropy`, or
    the smallest under which no source is passed more than max_repeats times.

    budget: tokens to spend; None: as many as pass every source at least once.
    """
    if (entropy is None) == (max_repeats is None):
        raise ValueError("one of entropy and max_repeats is needed")
    total = sources.agg(F.sum("tokens").cast("double").alias("t")).first()["t"]
    if not total:
        return 1.0
    p = F.col("tokens") / F.lit(total)
    some = sources.where("tokens > 0").withColumn("p", p)
    low, high = 0.0, 1.0
    for _ in range(ROUNDS):
        step = (high - low) / PARTS
        grid = some.select("p", F.explode(F.array(*(F.lit(low + k * step) for k in range(PARTS + 1)))).alias("a"))
        w, r = F.pow("p", F.col("a")), F.pow("p", F.col("a") - 1)
        rows = grid.groupBy("a").agg(F.sum(w).alias("z"), F.sum(w * F.ln(w)).alias("wl"), F.max(r).alias("most"), F.min(r).alias("fewest"))
        scale = F.col("fewest") if budget is None else F.col("z") * F.lit(total) / F.lit(float(budget))
        rows = rows.select("a", (F.ln("z") - F.col("wl") / F.col("z")).alias("h"), (F.col("most") / scale).alias("reps")).orderBy("a").collect()
        if entropy is not None:  # falls as a grows
            met = [x["a"] for x in rows if x["h"] >= entropy]
            if not met:
                return low
            low, high = max(met), min(1.0, max(met) + step)
        else:  # so does the largest repetition
            met = [x["a"] for x in rows if x["reps"] <= max_repeats * (1 + 1e-12)]
            if not met:
                return high
            low, high = max(0.0, min(met) - step), min(met)
    return low if entropy is not None else high


def weights(sources: DataFrame, a: float, budget: int | None = None) -> DataFrame:
    """sources with weight, token budget and passes (whole blocks and the tokens of the last one)."""
    total = sources.agg(F.sum("tokens").cast("double").alias("t"), F.sum(F.when(F.col("tokens") > 0, F.pow(F.col("tokens").cast("double"), F.lit(a)))).alias("z"), F.max(F.when(F.col("tokens") > 0, F.pow(F.col("tokens").cast("double"), F.lit(1 - a)))).alias("least")).first()
    z, all_tokens = total["z"] or 1.0, total["t"] or 0.0
    spend = float(budget) if budget is not None else (total["least"] or 0.0) * z
    w = F.when(F.col("tokens") > 0, F.pow(F.col("tokens").cast("double"), F.lit(a)) / F.lit(z)).otherwise(0.0)
    out = sources.withColumn("weight", w).withColumn("budget", F.when(F.col("tokens") > 0, F.round(F.col("weight") * F.lit(spend)).cast("long")).otherwise(F.lit(0).cast("long")))
    if budget is None:
        out = out.withColumn("budget", F.greatest("budget", "tokens"))
    out = out.withColumn("blocks", F.when(F.col("tokens") > 0, F.expr("budget div tokens")).otherwise(F.lit(1).cast("long")))
    return out.withColumn("rest", F.when(F.col("tokens") > 0, F.col("budget") - F.col("blocks") * F.col("tokens")).otherwise(F.lit(0).cast("long"))).withColumn("share", F.try_divide(F.col("tokens"), F.lit(all_tokens)))


def _order(block: Column, seed: int) -> Column:
    """Place of a document in a block: 63 bits of a keyed hash."""
    return F.shiftrightunsigned(F.xxhash64(F.lit(seed), block, F.col("_key")), 1)


def plan(keyed: DataFrame, a: float, budget: int | None = None, seed: int = 17) -> DataFrame:
    """Per source: weight, budget, whole blocks, and the place where the last block is cut (documents below it belong to it).

    keyed: source, n_tokens and _key (the hash that names a document) of every row.
    """
    sources = weights(shares(keyed), a, budget)
    plan_rows = materialise(sources.withColumn("_buckets", F.greatest(F.lit(1), F.ceil(F.col("n_docs") / BUCKET_ROWS)).cast("long")).withColumn("_s", F.xxhash64("source")))
    at = lambda: F.floor(F.col("_u") / F.lit(2.0**63) * F.col("_buckets")).cast("long")
    part = plan_rows.where("rest > 0").select("_s", "blocks", "rest", "_buckets")
    placed = keyed.select(F.xxhash64("source").alias("_s"), "n_tokens", "_key").join(part, "_s").withColumn("_u", _order(F.col("blocks"), seed)).select("_s", "n_tokens", "_u", "rest", at().alias("_b"))
    placed = materialise(placed)
    sums = placed.groupBy("_s", "_b").agg(F.sum("n_tokens").alias("t"), F.max("rest").alias("rest"))
    before = F.coalesce(F.sum("t").over(W.partitionBy("_s").orderBy("_b").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    cut = sums.withColumn("before", before).where("before <= rest and before + t > rest")
    # ends inside this bucket: the rows of one bucket decide
    inside = placed.join(cut.select("_s", "_b", "before"), ["_s", "_b"])
    run = F.sum("n_tokens").over(W.partitionBy("_s", "_b").orderBy("_u").rangeBetween(W.unboundedPreceding, 0)) + F.col("before")
    first_out = inside.withColumn("upto", run).where("upto > rest").groupBy("_s").agg(F.min("_u").alias("cut"))
    return materialise(plan_rows.join(first_out, "_s", "left").withColumn("cut", F.coalesce("cut", F.lit(0).cast("long"))).drop("_buckets"))


def realise(docs: DataFrame, planned: DataFrame, n_sources: int, seed: int = 17, broadcast_at_most: int = 100_000) -> DataFrame:
    """docs (with source and _key), each row once for every block it belongs to, with block and order.

    The plan is broadcast while it has at most broadcast_at_most sources; beyond that Spark chooses the join.
    """
    side = planned.select("_s", "weight", "blocks", "cut")
    side = F.broadcast(side) if n_sources <= broadcast_at_most else side
    out = docs.withColumn("_s", F.xxhash64("source")).join(side, "_s").withColumn("block", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks"))))
    return out.withColumn("order", _order(F.col("block"), seed)).where("block < blocks or `order` < cut").drop("_s", "blocks", "cut")


def mix(docs: DataFrame, entropy: float | None = None, max_repeats: float | None = 2.0, budget: int | None = None, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", seed: int = 17, keep: list[str] | None = None) -> DataFrame:
    """Rows of docs as often as the mixture takes them: id, source, n_tokens, block, order, weight (and the columns of keep)."""
    # reading twice is cheaper than keeping the texts: the first pass leaves ids and token counts only
    cols = lambda df: df.select(F.col(id_col).alias("_id"), F.col(source_col).alias("source"), tokens(F.col(text_col)).alias("n_tokens"), F.xxhash64(F.col(id_col), F.col(text_col)).alias("_key"), *(F.struct(*(F.col(c) for c in keep)).alias("_row") for _ in [0] if keep))
    keyed = materialise(cols(docs).select("source", "n_tokens", "_key", "_id"))
    sources = materialise(shares(keyed))
    a = exponent(sources, entropy, max_repeats, budget)
    planned = plan(keyed, a, budget, seed)
    out = realise(cols(docs) if keep else keyed, planned, sources.count(), seed)
    return out.select(F.col("_id").alias(id_col), F.col("source").alias(source_col), "n_tokens", "block", "order", "weight", *(["_row"] if keep else []))


def query(spark, sf_dir: str) -> DataFrame:
    from .common import table

    return mix(table(spark, sf_dir, "documents"))
