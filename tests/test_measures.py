"""Literals and plain loops for measures, segments and schedules."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from passagekit.operators import measures as M
from passagekit.operators import protocol as P
from passagekit.operators import supply as S


def test_published_p_values(spark):
    from passagekit.plans.retrieval import published_tests

    got = {(r["a"], r["b"]): r["p"] for r in published_tests(spark, "").collect()}
    want = {(11, 1): 0.006, (9, 5): 0.42, (11, 8): 0.65, (9, 10): 1.0, (10, 12): 0.83, (13, 11): 0.84, (13, 4): 0.049, (6, 4): 0.75, (6, 1): 0.13}
    for k, p in want.items():
        assert abs(got[k] - p) < 0.006


def test_auc_and_rank_against_loops(spark):
    rng = random.Random(3)
    rows = [("m", q, g, q % 3, g % 3, round(rng.random(), 1)) for q in range(9) for g in range(9) if q != g]
    s = spark.createDataFrame(rows, "method string, query_id long, gallery_id long, q_hull long, g_hull long, sim double")
    best = {q: max(r[5] for r in rows if r[1] == q and r[3] == r[4]) for q in range(9)}
    imp = [r[5] for r in rows if r[3] != r[4]]
    want = sum((b > i) + 0.5 * (b == i) for b in best.values() for i in imp) / (len(best) * len(imp))
    assert abs(M.auc(M.labelled(s)).first()["auc"] - want) < 1e-6
    ranks = {r["query_id"]: r["rank"] for r in P.true_rank(s).collect()}
    assert ranks == {q: 1 + sum(r[5] > best[q] for r in rows if r[1] == q) for q in range(9)}


def test_constant_row_fuses_to_zero(spark):
    s = spark.createDataFrame([("a", 1, 2, 0, 0, 0.5), ("a", 1, 3, 0, 1, 0.5)], "method string, query_id long, gallery_id long, q_hull long, g_hull long, sim double")
    assert {r["sim"] for r in P.fuse(s).collect()} == {0.0}


def test_tails_of_segments(spark):
    rec = spark.createDataFrame([(1, 100), (2, 76), (3, 77), (4, 63), (5, 64), (6, 0)], "recording_id long, n_samples long")
    got = {}
    for r in S.segment(rec, 64, 13).collect():
        got.setdefault(r["recording_id"], []).append((r["start"], r["is_tail"]))
    assert got == {1: [(0, False), (36, True)], 2: [(0, False)], 3: [(0, False), (13, True)], 5: [(0, False)]}


def test_unidentified_are_kept_apart(spark):
    rec = spark.createDataFrame([("12",), ("x1",), (None,)], "hull_id string")
    ok, rest = S.identified(rec)
    assert ok.count() == 1 and rest.count() == 2


def test_gap_and_chance_by_sums_equal_pairs(spark):
    rng = np.random.default_rng(8)
    vec = rng.normal(size=(40, 6))
    p = spark.createDataFrame([(i, i % 5, str(i % 3), v.tolist()) for i, v in enumerate(vec)], "passage_id long, hull_id long, source string, vec array<double>")
    s = P.leave_one_out(p, pure=False)
    want, got = M.gap(s).first().asDict(), M.gap_of_passages(p).first().asDict()
    assert got == pytest.approx(want, abs=2e-6)
    lone = p.unionByName(spark.createDataFrame([(99, 77, "0", vec[0].tolist()), (98, 78, "9", vec[0].tolist())], p.schema))
    by = P.leave_one_out(lone, keep_singletons=False).groupBy("query_id").agg((F.count_if(F.col("q_hull") == F.col("g_hull")) / F.count(F.lit(1))).alias("c"))
    want = by.agg(F.count(F.lit(1)), F.avg("c")).first()
    assert tuple(M.chance_level(lone).first()) == pytest.approx(tuple(want), abs=1e-6)
    none = M.gap_of_passages(p.limit(0)).first()
    assert (none["n_same"], none["n_diff"], none["gap"]) == (0, 0, None) and tuple(M.chance_level(p.limit(0)).first()) == (0, None)
