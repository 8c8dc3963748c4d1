"""Passages and proximity windows from a stream of events; the same rows as the batch forms once a watermark has passed."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.vectors import dot


def stream_passages(events: DataFrame, gap: str = "24 hours", late: str = "1 hour") -> DataFrame:
    e = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)
    return e.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count(F.lit(1)).alias("n"), F.min("ts").alias("first"), F.max("ts").alias("last"))


def stream_proximity(pings: DataFrame, width: str = "5 minutes", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    e = pings.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)
    return e.groupBy(F.window("ts", width, slide or width).alias("w"), "vessel_id").agg(F.min("range").alias("r"))


def stream_enrol(passages: DataFrame, path: str, checkpoint: str):
    """Appends passages to the gallery at path, each id once."""

    def put(batch: DataFrame, _) -> None:
        spark = batch.sparkSession
        new = batch.dropDuplicates(["passage_id"])
        try:
            new = new.join(spark.read.parquet(path).select("passage_id"), "passage_id", "left_anti")
        except Exception as e:  # the gallery does not exist before its first batch
            if "PATH_NOT_FOUND" not in str(e):
                raise
        new.write.mode("append").parquet(path)

    return passages.writeStream.foreachBatch(put).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def stream_identify(queries: DataFrame, gallery: DataFrame, tau: float) -> DataFrame:
    """query_id, gallery_id, hull_id, sim, verdict: arriving passages against a gallery snapshot. queries: query_id, source, vec.

    A stream-static join on source; the nearest is a streaming aggregate, so complete or update mode writes it.
    """
    g = gallery.select(F.col("passage_id").alias("gallery_id"), "hull_id", "source", F.col("vec").alias("gv"))
    s = queries.join(g, "source").select("query_id", F.struct(F.round(dot("vec", "gv"), 9).alias("sim"), (-F.col("gallery_id")).alias("minus"), "hull_id").alias("hit"))
    top = s.groupBy("query_id").agg(F.max("hit").alias("hit"))
    return top.select("query_id", (-F.col("hit.minus")).alias("gallery_id"), "hit.hull_id", "hit.sim", F.when(F.col("hit.sim") >= tau, "accept").otherwise("unknown").alias("verdict"))


def stream_exact_dedup(recordings: DataFrame, late: str = "1 day") -> DataFrame:
    """Each digest once within the watermark; state of older digests is dropped. recordings: ts, payload."""
    r = recordings.withColumn("digest", F.sha2("payload", 256)).withWatermark("ts", late)
    return r.dropDuplicatesWithinWatermark(["digest"])


def stream_key(windows: DataFrame, pings: DataFrame, reach: int = 300, late: str = "1 hour") -> DataFrame:
    """Recordings joined with the pings within `reach` seconds of their start; both sides' state ends with their watermarks.

    A ping's bucket of `reach` seconds is one of the three around the recording's, which gives the join its equality.
    """
    at = lambda c: F.floor(F.unix_seconds(c) / reach)
    w = windows.select("recording_id", F.col("ts").alias("w_ts")).withWatermark("w_ts", late).withColumn("bucket", F.explode(F.array(at("w_ts") - 1, at("w_ts"), at("w_ts") + 1)))
    p = pings.select("vessel_id", "range", F.col("ts").alias("p_ts")).withWatermark("p_ts", late).withColumn("p_bucket", at("p_ts"))
    near = F.expr(f"bucket = p_bucket and p_ts between w_ts - interval {reach} seconds and w_ts + interval {reach} seconds")
    return w.join(p, near).drop("bucket", "p_bucket")


def stream_hull_state(passages: DataFrame, lost_after_ms: int = 86_400_000, late: str = "1 hour") -> DataFrame:
    """hull_id, n, mean, state: running mean vector of each hull, and 'lost' once the watermark is that much past its last passage.

    passages: hull_id, ts, vec. State is one sum vector and one count a hull, whatever the number of its passages.
    """

    def step(key, parts, state):
        if state.hasTimedOut:
            n, total, _ = state.get
            state.remove()
            yield pd.DataFrame({"hull_id": [key[0]], "n": [n], "mean": [[x / n for x in total]], "state": ["lost"]})
            return
        n, total, last = state.get if state.exists else (0, None, 0)
        for part in parts:
            v = np.stack(part["vec"].to_numpy()).astype(float).sum(0)
            n, total = n + len(part), v if total is None else v + np.asarray(total)
            last = max(last, int(part["ts"].max().timestamp() * 1000))
        state.update((n, [float(x) for x in total], last))
        state.setTimeoutTimestamp(max(last, state.getCurrentWatermarkMs()) + lost_after_ms)
        yield pd.DataFrame({"hull_id": [key[0]], "n": [n], "mean": [[float(x) / n for x in total]], "state": ["seen"]})

    return passages.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late).groupBy("hull_id").applyInPandasWithState(step, "hull_id long, n long, mean array<double>, state string", "n long, total array<double>, last long", "update", "EventTimeTimeout")


def late_rows(query) -> int:
    """Rows that a finished or running query has dropped because they came after the watermark."""
    return sum(op.numRowsDroppedByWatermark for p in query.recentProgress for op in p.stateOperators)
