"""Identity, split, sessions, segments, manifests and schedules."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W


def key_hulls(rec: DataFrame, keys: tuple = ("key_a", "key_b")) -> DataFrame:
    """hull_id from the first identifier that is there, and which one it was."""
    kind = F.coalesce(*(F.when(F.col(k).isNotNull(), F.lit(k)) for k in keys))
    return rec.withColumn("hull_id", F.coalesce(*(F.col(k).cast("string") for k in keys))).withColumn("key_kind", kind)


def identified(rec: DataFrame, col: str = "hull_id") -> tuple[DataFrame, DataFrame]:
    """(recordings with a numeric identifier, the others)."""
    ok = F.coalesce(F.col(col).rlike("^[0-9]+$"), F.lit(False))
    return rec.where(ok), rec.where(~ok)


def key_by_proximity(pings: DataFrame, near: float = 20.0, clear: float = 60.0, width: str = "300 seconds") -> DataFrame:
    """window start, number of vessels near and clear, and the vessel if exactly one is near and no other within clear."""
    by = pings.groupBy(F.window("ts", width)["start"].alias("start"), "vessel_id").agg(F.min("range").alias("r"))
    out = by.groupBy("start").agg(F.count_if(F.col("r") <= near).alias("n_near"), F.count_if(F.col("r") <= clear).alias("n_clear"), F.min_by("vessel_id", "r").alias("nearest"))
    return out.withColumn("vessel_id", F.when((F.col("n_near") == 1) & (F.col("n_clear") == 1), F.col("nearest"))).drop("nearest")


def split_hulls(rec: DataFrame, share: float = 0.1, least: int = 2, seed: str = "7") -> DataFrame:
    """hull_id, n, part: hulls of at least `least` recordings may fall to validation, by md5 of seed and hull."""
    by = rec.groupBy("hull_id").agg(F.count(F.lit(1)).alias("n"))
    u = F.conv(F.substring(F.md5(F.concat(F.lit(seed + "|"), F.col("hull_id").cast("string"))), 1, 8), 16, 10).cast("long")
    return by.withColumn("part", F.when((F.col("n") >= least) & (u % 1000 < int(share * 1000)), "validation").otherwise("train"))


def leakage(a: DataFrame, b: DataFrame, on: str = "hull_id") -> DataFrame:
    """Keys on both sides; a split is sound when this is empty."""
    return a.select(on).distinct().join(b.select(on).distinct(), on, "left_semi")


def census(passages: DataFrame) -> DataFrame:
    """Hulls by number of passages, with the queries they can give."""
    by = passages.groupBy("hull_id").agg(F.count(F.lit(1)).alias("passages"))
    return by.groupBy("passages").agg(F.count(F.lit(1)).alias("hulls"), F.sum(F.when(F.col("passages") > 1, F.col("passages")).otherwise(0)).alias("queries"))


def sessions(ev: DataFrame, gap: str = "24 hours") -> DataFrame:
    return ev.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count(F.lit(1)).alias("n"), F.min("ts").alias("first"), F.max("ts").alias("last")).drop("w")


def segment(rec: DataFrame, width: int, least: int, tail: str = "last", keep: tuple = ()) -> DataFrame:
    """start and is_tail of windows of n samples: whole ones, and for a tail of at least `least` the last `width` samples. keep: columns to carry along."""
    n = F.col("n_samples")
    starts = F.transform(F.sequence(F.lit(0), F.expr(f"n_samples div {width}").cast("int")), lambda i: (i * width).cast("long"))
    starts = F.filter(starts, lambda s: s + width <= n)
    extra = (n >= width) & (n % width >= least) if tail == "last" else F.lit(False)
    every = F.concat(F.transform(starts, lambda s: F.struct(s.alias("start"), F.lit(False).alias("is_tail"))), F.when(extra, F.array(F.struct((n - width).cast("long").alias("start"), F.lit(True).alias("is_tail")))).otherwise(F.array().cast("array<struct<start:bigint,is_tail:boolean>>")))
    return rec.select("recording_id", "n_samples", *keep, F.inline(every))


def lr_schedule(rows: DataFrame, epochs: int = 40, warm: int = 3, low: float = 1e-4, high: float = 1e-3, floor: float = 1e-6) -> DataFrame:
    """rows (epoch, from 1) with their rate lr: linear warm-up, then a cosine to the floor at the last of the epochs."""
    e = F.col("epoch").cast("double") - 1
    up = F.lit(low) + (high - low) * e / F.lit(float(warm))
    down = F.lit(floor) + F.lit(0.5 * (high - floor)) * (1 + F.cos(F.lit(3.141592653589793) * (e - warm) / F.lit(float(epochs - warm))))
    return rows.withColumn("lr", F.when(e < warm, up).otherwise(down))


def select_epoch(history: DataFrame, patience: int = 10) -> DataFrame:
    """Best epoch by gap and where patience alone would stop. history: epoch, gap."""
    best = F.max("gap").over(W.orderBy("epoch").rowsBetween(W.unboundedPreceding, 0))
    h = history.withColumn("running", best)
    h = h.withColumn("since", F.col("epoch") - F.max(F.when(F.col("gap") == F.col("running"), F.col("epoch"))).over(W.orderBy("epoch")))
    stop = F.coalesce(F.min(F.when(F.col("since") >= patience, F.col("epoch"))), F.max("epoch"))
    return h.agg(stop.alias("stop"), F.max_by("epoch", F.struct("gap", -F.col("epoch"))).alias("best"))


def _turns(tensors: DataFrame, quota: int) -> tuple[DataFrame, Callable[[Column], Column]]:
    """tensors with their places in their hulls, and whether the manifest of a number takes a row."""
    hull = W.partitionBy("hull_id")
    t = tensors.withColumn("k", (F.row_number().over(W.partitionBy("hull_id", "is_aug").orderBy("tensor_id")) - 1).cast("long"))
    t = t.withColumn("n_orig", F.count_if(~F.col("is_aug")).over(hull)).withColumn("n_aug", F.count_if(F.col("is_aug")).over(hull))
    o, a, k = F.col("n_orig"), F.col("n_aug"), F.col("k")
    need = F.lit(quota) - o

    def pick(j: Column) -> Column:
        # the divisors are 0 only where the condition before does not hold
        turn = F.pmod(k - j * quota, F.greatest(o, F.lit(1).cast("long")))
        return F.when(o >= quota, ~F.col("is_aug") & (turn < quota)).when(o + a >= quota, ~F.col("is_aug") | (F.pmod(k - j * need, F.greatest(a, F.lit(1).cast("long"))) < need)).otherwise(F.lit(True))

    return t, pick


def _set_numbers(sets: int) -> Column:
    return F.sequence(F.lit(0).cast("long"), F.lit(sets - 1).cast("long"))


def epoch_manifests(tensors: DataFrame, quota: int = 8, sets: int = 25) -> DataFrame:
    """Originals-preferred manifests: set_no, hull_id, tensor_id, is_aug. tensors: hull_id, tensor_id, is_aug."""
    t, pick = _turns(tensors, quota)
    s = t.withColumn("set_no", F.explode(_set_numbers(sets)))
    return s.where(pick(F.col("set_no"))).select("set_no", "hull_id", "tensor_id", "is_aug")


def uncovered(tensors: DataFrame, quota: int = 8, sets: int = 25) -> DataFrame:
    """tensor_id of the originals that no manifest holds, found row by row without the manifests. A tensor_id stands in one hull."""
    t, pick = _turns(tensors, quota)
    return t.where(~F.col("is_aug") & ~F.exists(_set_numbers(sets), pick)).select("tensor_id")


def capped(tensors: DataFrame, cap: int) -> DataFrame:
    """The replaced variant: at most cap tensors a hull, the rest silently lost; here they are counted."""
    k = F.row_number().over(W.partitionBy("hull_id").orderBy("tensor_id"))
    return tensors.withColumn("lost", k > cap)


def split_enrolled(passages: DataFrame, enrolled: int, sequestered: int = 0, singletons: int = 0, seed: str = "7") -> DataFrame:
    """hull_id, n, part: of the hulls with several passages the first by md5 are sequestered, the next enrolled, the others held out;
    so many single-passage hulls join the training side as new identities, the other ones are gallery only."""
    by = passages.groupBy("hull_id").agg(F.count(F.lit(1)).alias("n")).withColumn("u", F.md5(F.concat(F.lit(seed + "|"), F.col("hull_id").cast("string"))))
    # only so many leading hulls of each kind matter, and Spark keeps no more than those while it sorts
    lead = lambda cond, k: by.where(cond).orderBy("u").limit(k).withColumn("k", F.row_number().over(W.orderBy("u")))
    many = lead("n > 1", sequestered + enrolled).select("hull_id", F.when(F.col("k") <= sequestered, "sequestered").otherwise("enrolled").alias("part"))
    one = lead("n = 1", singletons).select("hull_id", F.lit("added").alias("part"))
    rest = F.when(F.col("n") > 1, "held-out").otherwise("gallery")
    return by.join(many.unionByName(one), "hull_id", "left").select("hull_id", "n", F.coalesce("part", rest).alias("part"))


def heldout_uses(log: DataFrame) -> DataFrame:
    """Evaluations spent on each held-out set: log has set, model, selected (whether the model was chosen by that score)."""
    return log.groupBy("set").agg(F.count(F.lit(1)).alias("uses"), F.count_if("selected").alias("selections"))


def split_clips(segments: DataFrame, share: float = 0.1, seed: str = "7") -> DataFrame:
    """The practice that the protocol forbids, as negative control: segments fall to either side one by one."""
    u = F.conv(F.substring(F.md5(F.concat_ws("|", F.lit(seed), "recording_id", "start")), 1, 8), 16, 10).cast("long")
    return segments.withColumn("part", F.when(u % 1000 < int(share * 1000), "validation").otherwise("train"))


def corpus_readiness(passages: DataFrame) -> DataFrame:
    """hulls, those with independent repeat days, those seen by several sensors, passages with a logged speed. passages: hull_id, day, sensor, speed."""
    by = passages.groupBy("hull_id").agg(F.count_distinct("day").alias("days"), F.count_distinct("sensor").alias("sensors"), F.count("speed").alias("speeds"))
    return by.agg(F.count(F.lit(1)).alias("hulls"), F.count_if(F.col("days") > 1).alias("repeat_days"), F.count_if(F.col("sensors") > 1).alias("several_sensors"), F.sum("speeds").alias("with_speed"))


def pair_supply(passages: DataFrame) -> DataFrame:
    """Hulls that give positive pairs, hulls that cannot, and the pairs there are."""
    by = passages.groupBy("hull_id").agg(F.count(F.lit(1)).alias("n"))
    return by.agg(F.count_if(F.col("n") > 1).alias("with_pairs"), F.count_if(F.col("n") == 1).alias("singletons"), F.sum(F.expr("n * (n - 1) div 2")).alias("pairs"))


def weighted_sampler(tensors: DataFrame, k: int, weight: str = "w", seed: str = "7") -> DataFrame:
    """k rows without replacement in proportion to their weights: the smallest keys -ln(u) / w. tensors: tensor_id and a weight."""
    u = (F.conv(F.substring(F.md5(F.concat(F.lit(seed + "|"), F.col("tensor_id").cast("string"))), 1, 8), 16, 10).cast("double") + 0.5) / F.lit(4294967296.0)
    return tensors.withColumn("key", -F.ln(u) / F.col(weight)).orderBy("key", "tensor_id").limit(k)


def selection_gate(history: DataFrame, heldout: DataFrame, allow_leak: bool = False) -> DataFrame:
    """history (model, hull_id, gap) as a basis for choosing a model. Held-out hulls in it stop the plan when it is read;
    with allow_leak they stay, and every row is stamped."""
    seen = history.join(heldout.select("hull_id").distinct().withColumn("leak", F.lit(True)), "hull_id", "left").withColumn("leak", F.coalesce("leak", F.lit(False)))
    if allow_leak:
        marks = seen.groupBy("model").agg(F.bool_or("leak").alias("leaky"))
        return seen.drop("leak").join(marks, "model")
    return seen.where(F.when(F.col("leak"), F.raise_error(F.lit("held-out hulls in a selection"))).otherwise(F.lit(True))).drop("leak").withColumn("leaky", F.lit(False))


def segment_outcomes(rec: DataFrame, width: int, least: int) -> DataFrame:
    """What becomes of each recording: too short for one window (counted, never dropped unseen), no tail, tail kept or tail dropped."""
    n = F.col("n_samples")
    what = F.when(n.isNull() | (n < width), "short").when(n % width == 0, "no tail").when(n % width >= least, "tail kept").otherwise("tail dropped")
    return rec.groupBy(what.alias("outcome")).agg(F.count(F.lit(1)).alias("recordings"), F.sum(F.coalesce(n, F.lit(0)) % width).alias("tail_samples"))


def pad_tail(x, width: int):
    """The last window of an array, with zeros to its full width: the other tail rule."""
    return F.concat(x, F.array_repeat(F.lit(0.0), F.greatest(F.lit(0), F.lit(width) - F.size(x))))
