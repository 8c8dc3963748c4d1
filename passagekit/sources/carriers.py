"""How the given tables become recordings and passages."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.batches import whole
from ..functions.vectors import add, unit


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def base_vectors(emb: DataFrame) -> DataFrame:
    return emb.select(F.col("vec_id").cast("long").alias("i"), F.col("embedding").cast("array<double>").alias("v"))


def planted_size(emb: DataFrame) -> tuple[int, int]:
    """(vectors, hulls): forty hulls for every five hundred vectors, numbered from 0 without gaps."""
    n = emb.count()
    return n, 40 * max(1, n // 500)


def _census(h: Column) -> Column:
    """Passages of a hull, by its place among forty."""
    return F.when(h < 3, 1).when(h < 22, 2).when(h < 36, 3).otherwise(4)


def _first(h: Column) -> Column:
    """Passages of the hulls before it, among forty."""
    return F.when(h < 3, h).when(h < 22, 2 * h - 3).when(h < 36, 3 * h - 25).otherwise(4 * h - 61)


def planted(emb: DataFrame, stride_h: int = 11, stride_p: int = 97, lam: float = 2.0, off: float = 0.0) -> DataFrame:
    """Hulls with one to four passages each: a hull's vector plus interference, over the whole table; off adds a per-source offset."""
    spark, base = emb.sparkSession, base_vectors(emb)
    n, hulls = planted_size(emb)
    h, p = F.col("hull_id"), F.col("passage_no")
    grid = spark.range(hulls).select(F.col("id").alias("hull_id")).withColumn("passage_no", F.explode(F.sequence(F.lit(0), _census(h % 40) - 1)))
    grid = grid.withColumn("noise", hulls + (stride_h * h + stride_p * p) % max(1, n - hulls)).withColumn("lift", F.when(h % 2 == 0, n - 1).otherwise(n - 2))
    named = lambda key, as_: base.select(F.col("i").alias(key), F.col("v").alias(as_))
    raw = grid.join(named("hull_id", "own"), "hull_id").join(named("noise", "by"), "noise")
    v = add("own", "by", lam)
    if off:
        raw = raw.join(F.broadcast(named("lift", "at").where(F.col("lift") >= n - 2)), "lift")  # two rows
        v = add(v, F.col("at"), off)
    source = F.when(h % 2 == 0, "A").otherwise("B") if off else F.lit("A")
    number = 99 * F.floor(h / 40) + _first(h % 40) + p
    return raw.select(number.cast("long").alias("passage_id"), "hull_id", p.cast("long").alias("passage_no"), source.alias("source"), unit(v).alias("vec"))


def planted_duplicates(emb: DataFrame, every: int = 6, eps: float = 0.1) -> DataFrame:
    """planted() plus a re-recording of every sixth passage, with ids below 0; dup_of names the passage it copies."""
    own = planted(emb)
    n, hulls = planted_size(emb)
    base = base_vectors(emb).select(F.col("i").alias("noise"), F.col("v").alias("by"))
    k = F.col("passage_id")
    again = own.where(k % every == 0).withColumn("noise", hulls + (7 * k + 3) % max(1, n - hulls)).join(base, "noise")
    again = again.select((-1 - k).alias("passage_id"), "hull_id", "passage_no", "source", unit(add("vec", "by", eps)).alias("vec"), k.alias("dup_of"))
    return own.withColumn("dup_of", F.lit(None).cast("long")).unionByName(again)


def label_passages(emb: DataFrame) -> DataFrame:
    """hull = label, one passage for each vector of the table, source = vec_id modulo 4.

    Labels say nothing about the vectors, so this is the chance slice.
    """
    i = F.col("vec_id").cast("long")
    return emb.select(i.alias("passage_id"), F.col("label").cast("long").alias("hull_id"), (i % 4).cast("string").alias("source"), unit(F.col("embedding").cast("array<double>")).alias("vec"))


def series(rows: DataFrame) -> DataFrame:
    """rid, hull, x (array) of rows (rid, hull, x) whose partitions hold keys whole and sorted. A task holds one batch and one series."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t, ends in whole(batches, "rid", "hull"):
            at = t.select(["rid", "hull"]).take(pa.array(ends[:-1]))
            yield from at.append_column("x", pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.concat_arrays(t.column("x").chunks))).to_batches()

    return rows.mapInArrow(run, "rid long, hull long, x array<double>")


def supplier_years(li: DataFrame, copies: bool = True) -> DataFrame:
    """rid, hull, x: a supplier's prices of one year in time order; copies re-file some recordings with another gain and level."""
    order = ("l_shipdate", "l_orderkey", "l_linenumber", "l_partkey", "l_quantity", "l_extendedprice")  # rows alike up to here have one price
    rid = F.col("l_suppkey") * 10000 + F.year("l_shipdate")
    rows = li.select(rid.cast("long").alias("rid"), F.col("l_suppkey").cast("long").alias("hull"), *order).repartition("rid").sortWithinPartitions("rid", "hull", *order)
    rec = series(rows.select("rid", "hull", F.col("l_extendedprice").cast("double").alias("x")))
    if not copies:
        return rec
    again = rec.where("hull % 5 = 0 and rid % 3 = 0").select((-F.col("rid")).alias("rid"), "hull", F.transform("x", lambda v: F.lit(0.99) * v + 100.0).alias("x"))
    return rec.unionByName(again)


def document_segments(docs: DataFrame, width: int = 256) -> DataFrame:
    """recording_id, hull_id, start, x: codepoints of whole texts in windows, the last one ending at the end of the text.

    The windows are those of operators.supply.segment with a fifth of a window as the least tail; a null text or one below
    one window has none (segment_outcomes counts such). Time is linear in a text, and rows leave a worker in slices.
    """
    least, slices = max(1, width // 5), 512

    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for part in parts:
            for i, hull, text in zip(part["recording_id"], part["hull_id"], part["text"], strict=True):
                x = np.frombuffer(text.encode("utf-32-le"), "<u4")
                starts = list(range(0, len(x) - width + 1, width))
                if starts and len(x) % width >= least:
                    starts.append(len(x) - width)
                for at in range(0, len(starts), slices):
                    some = starts[at : at + slices]
                    yield pd.DataFrame({"recording_id": i, "hull_id": hull, "start": some, "x": [x[k : k + width].astype(float) for k in some]})

    rows = docs.where(F.length("text") >= width).select(F.col("doc_id").cast("long").alias("recording_id"), F.concat_ws("|", "lang", "source").alias("hull_id"), "text")
    cores = docs.sparkSession.sparkContext.defaultParallelism
    if rows.rdd.getNumPartitions() < cores:  # a few files: texts are dealt out before the work, which is in the windows
        rows = rows.repartition(cores, "recording_id")
    return rows.mapInPandas(run, "recording_id long, hull_id string, start long, x array<double>")
