"""The encoder, augmentation, deduplication and blocked scores against plain numpy, differences and loops."""

import numpy as np
import pytest

from passagekit.operators import augment as A
from passagekit.operators import blocked as B
from passagekit.operators import dedup as D
from passagekit.operators import encoder as E
from passagekit.operators import protocol as P


def _small():
    rng = np.random.default_rng(1)
    p = E.init(E.SMALL)
    p["head"] = rng.normal(0, 1, (3, 16))
    return rng, p, rng.normal(0, 1, (4, 64)), np.array([0, 1, 2, 1])


def test_parameters_of_the_published_network():
    assert abs(E.count_params(E.EncoderSpec()) - 4.62e6) < 0.02e6


def test_bank_is_same_padded_correlation():
    rng = np.random.default_rng(2)
    x, w = rng.normal(size=(2, 40)), rng.normal(size=(3, 7))
    y, _ = E.bank(x, w, np.zeros(3))
    for b in range(2):
        for c in range(3):
            assert np.allclose(y[b, c], np.correlate(np.pad(x[b], 3), w[c], "valid"))


def test_gradients_against_differences():
    rng, p, x, y = _small()
    _, grad = E.loss_and_gradient(x, y, p, E.SMALL)
    for name in sorted(p):
        for _ in range(2):
            at = tuple(rng.integers(s) for s in p[name].shape)
            up, down = {k: v.copy() for k, v in p.items()}, {k: v.copy() for k, v in p.items()}
            up[name][at] += 1e-5
            down[name][at] -= 1e-5
            want = (E.loss_and_gradient(x, y, up, E.SMALL)[0] - E.loss_and_gradient(x, y, down, E.SMALL)[0]) / 2e-5
            assert grad[name][at] == pytest.approx(want, rel=1e-3, abs=2e-4), name


def test_micro_batches_add_up():
    _, p, x, y = _small()
    whole = E.loss_and_gradient(x, y, p, E.SMALL)[1]
    parts = [E.loss_and_gradient(x[i : i + 2], y[i : i + 2], p, E.SMALL)[1] for i in (0, 2)]
    for k in whole:
        assert np.allclose(whole[k], parts[0][k] + parts[1][k])


def test_margin_makes_the_loss_harder():
    _, p, x, y = _small()
    assert E.loss_and_gradient(x, y, p, E.SMALL, m=0.0)[0] < E.loss_and_gradient(x, y, p, E.SMALL, m=0.3)[0]


def test_training_lowers_the_loss_and_weights_survive_a_round_trip(spark, tmp_path):
    t = np.arange(64)
    rng = np.random.default_rng(4)
    rows = [(i, i % 2, (np.sin(2 * np.pi * (3 if i % 2 else 11) * t / 64 + rng.uniform(0, 6)) + 0.1 * rng.normal(size=64)).tolist()) for i in range(16)]
    df = spark.createDataFrame(rows, "tensor_id long, cls long, x array<double>")
    p, history = E.train(spark, df, E.SMALL, [3e-3] * 8, batch=16, micro=8)
    assert history[-1][1] < history[0][1]
    E.save(spark, p, str(tmp_path / "w"))
    q = E.load(spark, str(tmp_path / "w"))
    assert all(np.array_equal(p[k], q[k]) for k in p)
    seg = spark.createDataFrame([(1, 0, [5 * v for v in rows[0][2]]), (2, 0, rows[0][2]), (3, 0, [2.0] * 64)], "recording_id long, start long, x array<double>")
    v = {r["recording_id"]: np.array(r["vec"]) for r in E.embed(seg, p, E.SMALL).collect()}
    assert np.allclose(v[1], v[2]) and np.isclose(np.linalg.norm(v[1]), 1) and np.isfinite(v[3]).all()


def test_epochs_take_manifests_in_turn(spark):
    rng = np.random.default_rng(9)
    x = rng.normal(size=(14, 64))
    rows = [(i, i % 3, None if i > 12 else 4 if i % 2 else 2, v.tolist()) for i, v in enumerate(x)]
    df = spark.createDataFrame(rows, "tensor_id long, cls long, manifest long, x array<double>")
    start = E.init(E.SMALL, 7)
    _, history = E.train(spark, df, E.SMALL, [0.0] * 3, start, batch=100, micro=4)
    start["head"] = np.random.default_rng(7).normal(0, 1, (3, E.SMALL.widths[-1]))
    want = []
    for m in (2, 4, 2):
        own = [i for i, r in enumerate(rows) if r[2] == m]
        want.append(E.loss_and_gradient(E.standardise(x[own]), np.array([i % 3 for i in own]), start, E.SMALL, 30.0, 0.3)[0] / len(own))
    assert [b for _, b in history] == pytest.approx(want)
    assert E.train(spark, df.limit(0), E.SMALL, [1e-3])[1] == []


def test_staged_training_releases_the_longest_branch_last(spark, monkeypatch):
    start = E.gabor_init(E.EncoderSpec(kernels=(127, 511), channels=8))
    crest = E.inspect_kernels(start, E.EncoderSpec(kernels=(127, 511), channels=8))
    assert crest["cycles"].between(4, 11).all()
    rng = np.random.default_rng(13)
    df = spark.createDataFrame([(i, i % 2, v.tolist()) for i, v in enumerate(rng.normal(size=(8, 64)))], "tensor_id long, cls long, x array<double>")
    seen, plain = [], E.train
    monkeypatch.setattr(E, "train", lambda *a, **k: seen.append((a[3], plain(*a, **k))) or seen[-1][1])
    p, history = E.train_staged(spark, df, E.SMALL, (1, 1, 1), batch=8, micro=4)
    a, b, c = (m for _, (m, _) in seen)
    first = E.gabor_init(E.SMALL)
    moved = lambda x, y: [not np.array_equal(x[f"bank{i}.w"], y[f"bank{i}.w"]) for i in range(3)]
    assert (moved(first, a), moved(a, b), moved(b, c)) == ([False] * 3, [True, True, False], [True] * 3)
    assert [r for r, _ in seen] == [[1e-3], [1e-4], [1e-4]] and [s for s, _, _ in history] == [0, 1, 2] and p is c


def test_a_step_reads_its_own_folder(spark):
    """Every tensor takes part once an epoch, in steps beyond one folder's."""
    rng = np.random.default_rng(11)
    df = spark.createDataFrame([(i, 0, v.tolist()) for i, v in enumerate(rng.normal(size=(12, 64)))], "tensor_id long, cls long, x array<double>")
    was, E.STEPS = E.STEPS, 2
    try:
        _, history = E.train(spark, df, E.SMALL, [0.0], batch=2, micro=2)
    finally:
        E.STEPS = was
    assert 2 < len(history) <= 6


def test_copies_depend_on_their_keys_alone(spark):
    x = [(i, 0, np.sin(np.arange(64) * 2 * np.pi * 9 / 64).tolist()) for i in range(6)]
    noise = np.random.default_rng(0).normal(0, 1, (2, 64))
    df = spark.createDataFrame(x, "recording_id long, start long, x array<double>")
    key = lambda r: (r["recording_id"], r["copy"], tuple(r["ops"]), tuple(r["x"]))
    one, two = A.augment(df, noise).collect(), A.augment(df.repartition(3), noise).collect()
    assert sorted(map(key, one)) == sorted(map(key, two)) and len(one) == 24
    assert all(len(r["ops"]) >= 2 for r in one if r["copy"]) and all(r["peak_kept"] for r in one if r["copy"] == 0)


def test_excluded_operations_fail_their_checks():
    x = np.sin(np.arange(512) * 2 * np.pi * 40 / 512)
    peak = lambda v: int(np.abs(np.fft.rfft(v))[1:].argmax()) + 1
    assert abs(peak(A.warp(x, 1.25)) - peak(x)) > 1 and peak(A.tilt(x, 4, 512.0)) == peak(x)
    noise = np.random.default_rng(0).normal(size=512)
    turned = A.phase_scramble(noise, np.random.default_rng(1))
    assert np.allclose(np.abs(np.fft.rfft(turned)), np.abs(np.fft.rfft(noise))) and D.waveform_peak(noise, turned) < 0.5


def test_copies_outside_training_are_refused(spark):
    a = spark.createDataFrame([(1, 7), (2, 8)], "recording_id long, hull_id long")
    m = spark.createDataFrame([(7, "train"), (8, "validation")], "hull_id long, part string")
    assert A.train_only(a.where("hull_id = 7"), m).count() == 1
    with pytest.raises(Exception, match="outside training"):
        A.train_only(a, m).collect()


def test_recaptures_are_found_by_spectrum_and_waveform():
    rng = np.random.default_rng(3)
    x, other = np.convolve(rng.normal(size=600), [1, 0.8, 0.3], "same"), rng.normal(size=600)
    again = 0.7 * np.roll(x, 5) + 3
    assert D.waveform_peak(x, again) > 0.95 > 0.3 > D.waveform_peak(x, other)
    assert D.residual_spectrum(x) @ D.residual_spectrum(again) > 0.8 > abs(D.residual_spectrum(x) @ D.residual_spectrum(other))


def test_chains_close_and_keep_apart(spark):
    n = 40
    rec = spark.createDataFrame([(i, i // n) for i in range(2 * n)], "rid long, hull long")
    edges = spark.createDataFrame([(i, i + 1) for i in range(n - 1)] + [(n + 1, n + 2)], "a long, b long")
    got = {r["rid"]: r["transit_id"] for r in D.transits(edges, rec).collect()}
    assert all(got[i] == 0 for i in range(n)) and got[n + 2] == n + 1 and got[n] == n and len(got) == 2 * n


def test_no_edges_make_every_recording_its_own_transit(spark):
    rec = spark.createDataFrame([(5, 1)], "rid long, hull long")
    assert D.transits(spark.createDataFrame([], "a long, b long"), rec).first()["transit_id"] == 5


def test_thresholds_are_inclusive(spark):
    from pyspark.sql import functions as F

    rows = [(0.40, 0.0), (0.20, 0.15), (0.20, 0.149), (0.0, 0.80), (0.399, 0.149)]
    df = spark.createDataFrame(rows, "t double, w double").select(D.Rule().verdict(F.col("t"), F.col("w")).alias("v"))
    assert [r["v"] for r in df.collect()] == ["same transit", "same transit", "distinct", "same capture", "distinct"]


def test_gate_refuses_an_unapproved_rule(spark):
    m = spark.createDataFrame([(1,)], "n long")
    v = spark.createDataFrame([("joint", True), ("cut10", False)], "rule string, approved boolean")
    assert D.require(m, v, "joint").count() == 1
    for rule in ("cut10", "unheard of"):
        with pytest.raises(Exception, match="no approved transit map"):
            D.require(m, v, rule).collect()


def test_blocked_ranks_equal_the_join(spark):
    rng = np.random.default_rng(6)
    vec = rng.normal(size=(30, 8))
    vec /= np.linalg.norm(vec, axis=1, keepdims=True)
    p = spark.createDataFrame([(i, i // 2 if i < 28 else i, "", v.tolist()) for i, v in enumerate(vec)], "passage_id long, hull_id long, source string, vec array<double>")
    want = {r["query_id"]: (r["rank"], r["candidates"]) for r in P.true_rank(P.leave_one_out(p)).collect()}
    top = {}
    for r in P.shortlist(P.leave_one_out(p), 5).orderBy("query_id", "place").collect():
        top.setdefault(r["query_id"], []).append(r["gallery_id"])
    got = B.ranks(p, k=5, size=7).collect()
    assert {r["query_id"]: (r["rank"], r["candidates"]) for r in got} == want
    assert {r["query_id"]: list(r["top"]) for r in got} == top
