"""Sources, resampling, specifications, guards and exports."""

import struct

import numpy as np
import pytest
from pyspark.errors import PySparkException
from pyspark.sql import functions as F

from passagekit.operators import measures as M
from passagekit.operators import preprocess as Q
from passagekit.operators import protocol as P
from passagekit.operators import supply as S
from passagekit.operators import dedup as D
from passagekit.operators import tonal as T


def wav(x: np.ndarray, rate: int, bits: int) -> bytes:
    """x: samples by channel in -1..1."""
    step = bits // 8
    if bits == 8:
        body = (np.round(x * 127) + 128).astype(np.uint8).tobytes()
    else:
        v = np.round(x * (2 ** (bits - 1) - 1)).astype("<i4")
        body = (v.reshape(-1, 1).view(np.uint8)[:, :step]).tobytes()
    fmt = struct.pack("<HHIIHH", 1, x.shape[1], rate, rate * x.shape[1] * step, x.shape[1] * step, bits)
    note = b"LIST" + struct.pack("<I", 3) + b"abc\0"
    return b"RIFF" + struct.pack("<I", 36 + len(body)) + b"WAVE" + note + b"fmt " + struct.pack("<I", 16) + fmt + b"data" + struct.pack("<I", len(body)) + body


@pytest.mark.parametrize("bits", [8, 16, 24, 32])
def test_wav_of_every_width(bits):
    x = np.stack([np.sin(np.arange(50) / 5), np.cos(np.arange(50) / 7)], 1) * 0.9
    rate, got = Q.read_wav(wav(x, 16000, bits))
    assert rate == 16000 and got.shape == x.shape and np.abs(got - x).max() < 2.0 ** (2 - bits)
    with pytest.raises(ValueError):
        Q.read_wav(b"nothing of the kind")


def test_resampling_keeps_tones_and_removes_what_would_fold():
    t = np.arange(16000) / 16000
    low, high = np.sin(2 * np.pi * 440 * t), np.sin(2 * np.pi * 6000 * t)
    y = Q.resample(low + high, 16000, 8000)
    want = np.sin(2 * np.pi * 440 * np.arange(8000) / 8000)
    assert len(y) == 8000 and np.abs(y - want)[200:-200].max() < 0.02
    assert np.allclose(Q.resample(low, 8000, 8000), low) and len(Q.resample(np.zeros(0), 4, 8)) == 0


def test_recordings_of_files(spark, tmp_path):
    x = np.sin(2 * np.pi * 300 * np.arange(1600) / 16000)[:, None] * [[0.5, 0.5]]
    for k in range(3):
        (tmp_path / f"r{k}.wav").write_bytes(wav(x, 16000, 16))
    got = Q.recordings(spark.read.format("binaryFile").load(str(tmp_path)))
    assert [(r["n_samples"], r["spec"]) for r in got.collect()] == [(800, Q.Spec().fingerprint)] * 3
    assert Q.same_spec(got, Q.Spec()).count() == 3
    with pytest.raises(PySparkException):
        Q.same_spec(got, Q.Spec(seconds=2.0)).count()


def test_great_circle(spark):
    r = spark.range(1).select(Q.great_circle(F.lit(0.0), F.lit(0.0), F.lit(0.0), F.lit(90.0)).alias("km")).first()["km"]
    assert abs(r - 6371 * np.pi / 2) < 1e-6


def test_held_out_hulls_may_not_choose_a_model(spark):
    h = spark.createDataFrame([("a", 1, 0.1), ("b", 1, 0.2), ("b", 9, 0.3)], "model string, hull_id long, gap double")
    out = spark.createDataFrame([(9,)], "hull_id long")
    with pytest.raises(PySparkException):
        S.selection_gate(h, out).collect()
    assert {(r["model"], r["leaky"]) for r in S.selection_gate(h, out, allow_leak=True).collect()} == {("a", False), ("b", True)}
    assert S.selection_gate(h.where("hull_id = 1"), out).count() == 2


def test_first_identifier_and_padding(spark):
    rec = spark.createDataFrame([(None, "x"), (5, "y"), (None, None)], "key_a long, key_b string")
    assert [(r["hull_id"], r["key_kind"]) for r in S.key_hulls(rec).collect()] == [("x", "key_b"), ("5", "key_a"), (None, None)]
    assert spark.createDataFrame([([1.0, 2.0],)], "x array<double>").select(S.pad_tail(F.col("x"), 4).alias("y")).first()["y"] == [1.0, 2.0, 0.0, 0.0]


def test_sampler_follows_the_weights(spark):
    t = spark.range(4000).select(F.col("id").alias("tensor_id"), F.when(F.col("id") % 2 == 0, 3.0).otherwise(1.0).alias("w"))
    n = S.weighted_sampler(t, 400).where("tensor_id % 2 = 0").count()
    assert 260 <= n <= 330


def test_no_classification_measures_and_acceptance(spark):
    with pytest.raises(NotImplementedError):
        M.classification_metrics(None)
    got = spark.createDataFrame([("a", 1), ("b", 2)], "k string, value long")
    want = spark.createDataFrame([("a", 1), ("b", 3), ("c", 1)], "k string, value long")
    assert {r["k"]: r["ok"] for r in D.acceptance(got, want, ["k"]).collect()} == {"a": True, "b": False, "c": False}


def test_findings_and_line_sets(spark):
    p = spark.createDataFrame([(1, 2, "x", "x"), (1, 2, "x", "y"), (1, 50, "x", "z")], "a long, b long, a_digest string, b_digest string")
    assert [r["finding"] for r in D.finding_class(p).collect()] == ["identical file", "neighbouring ids", "shared scene"]
    q = spark.createDataFrame([(0b1010000, 0b0101000)], "a long, b long")
    one, two = q.select(T.fraction(F.col("a"), F.col("b"), 1).alias("x"), T.symmetric(F.col("a"), F.col("b"), 0).alias("y")).first()
    assert one == 1.0 and two == 0.0


def test_export_withholds_hulls(spark, tmp_path):
    sc = spark.createDataFrame([("a", 1, 2, 77, 78, 0.5), ("b", 1, 2, 77, 77, 0.5)], "method string, query_id long, gallery_id long, q_hull long, g_hull long, sim double")
    P.export_bundle(sc, str(tmp_path / "out"), "k")
    rows = spark.read.parquet(str(tmp_path / "out")).collect()
    assert len(rows) == 2 and all(len(r["q_hull"]) == 16 for r in rows) and {r["q_hull"] == r["g_hull"] for r in rows} == {True, False}


def test_top_hits_and_map(spark):
    from passagekit.functions.register import top_hits

    s = spark.createDataFrame([(1, 5, 0.2), (1, 4, 0.9), (1, 3, 0.9), (2, 7, 0.1)], "query_id long, gallery_id long, sim double")
    assert sorted((r["query_id"], r["gallery_id"]) for r in top_hits(s).collect()) == [(1, 3), (2, 7)]
    p = spark.createDataFrame([(1,), (2,), (3,)], "passage_id long")
    moved = spark.createDataFrame([(1, 1), (2, 1), (3, 3)], "passage_id long, transit_id long")
    assert sorted(r[0] for r in P.apply_map(p, moved).collect()) == [1, 3]


def test_text_windows_are_those_of_the_segment_rule(spark):
    from pyspark.sql import functions as F

    from passagekit.sources import carriers as C

    texts = [None, "", "short", "a" * 8, "äbc\U0001f600" * 5, "x" * 17, "y" * 18, "z" * 40_000]
    docs = spark.createDataFrame([(i, t, "l", "s", 7) for i, t in enumerate(texts)], "doc_id long, text string, lang string, source string, x int")
    got = {(r["recording_id"], r["start"]): r["x"] for r in C.document_segments(docs, 8).collect()}
    rec = docs.where("text is not null").select(F.col("doc_id").alias("recording_id"), F.length("text").cast("long").alias("n_samples"))
    want = {(r["recording_id"], r["start"]) for r in S.segment(rec, 8, 1).collect()}
    assert set(got) == want and all(x == [float(ord(c)) for c in texts[i][k : k + 8]] for (i, k), x in got.items())


def test_pooled_vectors_are_the_unit_means_of_the_segments(spark):
    from passagekit.operators import encoder as E
    from passagekit.operators import protocol as P

    rng = np.random.default_rng(12)
    seg = spark.createDataFrame([(i % 3, i, v.tolist()) for i, v in enumerate(rng.normal(size=(20, 64)))], "recording_id long, start long, x array<double>")
    p = E.init(E.SMALL)
    want = {r["passage_id"]: (r["n"], r["vec"]) for r in P.pool_passages(E.embed(seg, p, E.SMALL).withColumnRenamed("recording_id", "passage_id")).collect()}
    for r in E.embed_pooled(seg, p, E.SMALL, batch=7).collect():
        assert r["n"] == want[r["recording_id"]][0] and np.allclose(r["vec"], want[r["recording_id"]][1])
