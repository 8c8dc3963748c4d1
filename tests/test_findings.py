"""Cases that reviews found, each held to DuckDB on a small table of its own or to a literal."""

import duckdb
import pytest

from passagekit.plans import registry


def same(spark, tmp_path, name, **tables):
    """The query over given SQL tables (files in tmp_path) equals its SQL; returns the rows."""
    con = duckdb.connect()
    for t, sql in tables.items():
        con.sql(f"copy ({sql}) to '{tmp_path}/{t}.parquet' (format parquet)")
        con.sql(f"create view {t} as select * from '{tmp_path}/{t}.parquet'")
    f, sql = registry.ALL[name]
    df, want = f(spark, str(tmp_path)), con.sql(sql)
    cols = sorted(df.columns)
    assert cols == sorted(want.columns)
    got = sorted((tuple(r[c] for c in cols) for r in df.collect()), key=str)
    at = [want.columns.index(c) for c in cols]
    full = sorted((tuple(r[i] for i in at) for r in want.fetchall()), key=str)
    assert len(got) == len(full)
    for a, b in zip(got, full, strict=True):
        assert a == pytest.approx(b, abs=1e-6)
    return got


def test_regular_grid_rounds_times_as_its_sql(spark, tmp_path):
    ev = "select i event_id, ts, 1 user_id, 'view' event_type, i + 0.5::double as value from (values (0, timestamp '2024-01-01 10:00:00'), (1, timestamp '2024-01-02 23:59:59.7'), (2, timestamp '2024-01-04 23:59:59.5'), (3, timestamp '2024-01-06 00:00:00.5')) v(i, ts)"
    assert same(spark, tmp_path, "regular_grid", events=ev) == [(6, 10.0, 1)]


def test_recursion_takes_more_rows_than_the_limit_of_spark(spark, tmp_path):
    got = same(spark, tmp_path, "sql_recursive", customer="select range::bigint - 5 c_custkey from range(200000)")
    assert len(got) == 18 and sum(n for _, n in got) > 1_000_000


def test_coverage_of_manifests_needs_no_manifest(spark, tmp_path):
    got = same(spark, tmp_path, "manifest_coverage", orders="select range::bigint o_orderkey, case when range < 210 then 1 else range end::bigint o_custkey from range(230)")
    assert len(got) == 10  # 25 manifests of 8 of a hull's 210 originals
    plan = registry.ALL["manifest_coverage"][0](spark, str(tmp_path))._jdf.queryExecution().optimizedPlan().toString()
    assert "Join" not in plan


def test_lr_schedule_reads_orders(spark, tmp_path):
    assert same(spark, tmp_path, "lr_schedule", orders="select range::bigint o_orderkey, (range % 7)::bigint o_custkey, timestamp '1995-01-01' + to_days((range * 37 % 2400)::int) o_orderdate, ['F', 'O', 'P'][range % 3 + 1] o_orderstatus, (range % 5)::varchar o_orderpriority from range(3000)") != same(spark, tmp_path, "lr_schedule", orders="select range::bigint o_orderkey, (range % 7)::bigint o_custkey, timestamp '1995-01-01' + to_days((range * 37 % 2400)::int) o_orderdate, ['F', 'O', 'P'][range % 3 + 1] o_orderstatus, (range % 5)::varchar o_orderpriority from range(1000)")


def test_select_epoch_reads_orders(spark, tmp_path):
    assert same(spark, tmp_path, "select_epoch", orders="select range::bigint o_orderkey, (range % 7)::bigint o_custkey, timestamp '1995-01-01' + to_days((range * 37 % 2400)::int) o_orderdate, ['F', 'O', 'P'][range % 3 + 1] o_orderstatus, (range % 5)::varchar o_orderpriority from range(3001)") != same(spark, tmp_path, "select_epoch", orders="select range::bigint o_orderkey, (range % 7)::bigint o_custkey, timestamp '1995-01-01' + to_days((range * 37 % 2400)::int) o_orderdate, ['F', 'O', 'P'][range % 3 + 1] o_orderstatus, (range % 5)::varchar o_orderpriority from range(1000)")


def test_checkpoint_epochs_reads_orders(spark, tmp_path):
    assert same(spark, tmp_path, "checkpoint_epochs", orders="select range::bigint o_orderkey, (range % 7)::bigint o_custkey, timestamp '1995-01-01' + to_days((range * 37 % 2400)::int) o_orderdate, ['F', 'O', 'P'][range % 3 + 1] o_orderstatus, (range % 5)::varchar o_orderpriority from range(3000)") != same(spark, tmp_path, "checkpoint_epochs", orders="select range::bigint o_orderkey, (range % 7)::bigint o_custkey, timestamp '1995-01-01' + to_days((range * 37 % 2400)::int) o_orderdate, ['F', 'O', 'P'][range % 3 + 1] o_orderstatus, (range % 5)::varchar o_orderpriority from range(1000)")


def test_heldout_uses_reads_orders(spark, tmp_path):
    assert same(spark, tmp_path, "heldout_uses", orders="select range::bigint o_orderkey, (range % 7)::bigint o_custkey, timestamp '1995-01-01' + to_days((range * 37 % 2400)::int) o_orderdate, ['F', 'O', 'P'][range % 3 + 1] o_orderstatus, (range % 5)::varchar o_orderpriority from range(3000)") != same(spark, tmp_path, "heldout_uses", orders="select range::bigint o_orderkey, (range % 7)::bigint o_custkey, timestamp '1995-01-01' + to_days((range * 37 % 2400)::int) o_orderdate, ['F', 'O', 'P'][range % 3 + 1] o_orderstatus, (range % 5)::varchar o_orderpriority from range(1000)")


def test_mcnemar_published_reads_orders(spark, tmp_path):
    assert same(spark, tmp_path, "mcnemar_published", orders="select range::bigint o_orderkey, (range % 7)::bigint o_custkey, timestamp '1995-01-01' + to_days((range * 37 % 2400)::int) o_orderdate, ['F', 'O', 'P'][range % 3 + 1] o_orderstatus, (range % 5)::varchar o_orderpriority from range(300)") != same(spark, tmp_path, "mcnemar_published", orders="select range::bigint o_orderkey, (range % 7)::bigint o_custkey, timestamp '1995-01-01' + to_days((range * 37 % 2400)::int) o_orderdate, ['F', 'O', 'P'][range % 3 + 1] o_orderstatus, (range % 5)::varchar o_orderpriority from range(100)")


def test_published_counts_give_their_p_values(spark):
    from passagekit.functions.vectors import binomial_two_sided
    from pyspark.sql import functions as F

    rows = spark.createDataFrame([(11, 1, 0.006348), (9, 5, 0.423950), (13, 4, 0.049042), (6, 1, 0.125)], "a long, b long, want double")
    for r in rows.select(binomial_two_sided(F.col("a"), F.col("b")).alias("p"), "want").collect():
        assert r["p"] == pytest.approx(r["want"], abs=1e-6)


def test_encoder_params_reads_orders(spark, tmp_path):
    assert same(spark, tmp_path, "encoder_params", orders="select range::bigint o_orderkey, (range % 70)::bigint o_custkey, timestamp '1995-01-01' + to_days((range * 37 % 2400)::int) o_orderdate, ['F', 'O', 'P'][range % 3 + 1] o_orderstatus, (range % 5)::varchar o_orderpriority from range(9)") != same(spark, tmp_path, "encoder_params", orders="select range::bigint o_orderkey, (range % 70)::bigint o_custkey, timestamp '1995-01-01' + to_days((range * 37 % 2400)::int) o_orderdate, ['F', 'O', 'P'][range % 3 + 1] o_orderstatus, (range % 5)::varchar o_orderpriority from range(3)")


def test_kernel_crest_reads_every_vector(spark, tmp_path):
    import math

    tone = [math.sin(2 * math.pi * 8 * i / 64) for i in range(64)]
    rows = [(0, tone, 3), (1, [1.0] + [0.0] * 63, 4), (2, None, 4), (3, [0.0] * 64, 4)]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").write.parquet(f"{tmp_path}/embeddings.parquet")
    got = {r["branch"]: r for r in registry.ALL["kernel_crest"][0](spark, str(tmp_path)).collect()}
    assert sorted(got) == [3, 4] and got[3]["cycles"] == pytest.approx(8, abs=0.2) and got[3]["peak_hz"] == pytest.approx(1000, abs=25)
    assert got[4]["median_crest"] == pytest.approx(0.5, abs=1e-6)


def test_ranks_of_networks_by_blocks_equal_those_from_pairs(spark):
    import numpy as np

    from passagekit.operators import blocked as B
    from passagekit.operators import measures as M
    from passagekit.operators import protocol as P

    rng = np.random.default_rng(3)
    v = rng.normal(size=(2, 40, 4))
    v[:, 7], v[:, 9] = v[:, 3], v[:, 3]  # ties
    v[0, 11] = 0.0  # a constant row
    nets = {}
    for m, x in zip("ab", v, strict=True):
        rows = [(i, i % 3 + 100 * (i > 30) * i, "A", (u / max(np.linalg.norm(u), 1e-9)).tolist()) for i, u in enumerate(x) if m == "a" or i != 5]
        nets[m] = spark.createDataFrame(rows, "passage_id long, hull_id long, source string, vec array<double>")
    a, b = (P.leave_one_out(p, method=m) for m, p in nets.items())
    scores = a.unionByName(b).unionByName(P.fuse(a, b))
    got = B.network_ranks(nets, size=7)
    cols = ["method", "query_id", "q_hull", "best", "rank", "candidates"]
    key = lambda df, cs: sorted(tuple(r[c] for c in cs) for r in df.collect())
    for x, y in zip(key(got, cols), key(P.true_rank(scores), cols), strict=True):
        assert x == pytest.approx(y, abs=2e-9)
    wins = ["method", "query_id", "q_hull", "wins", "pairs"]
    assert key(M.query_wins_of_ranks(got), wins) == key(M.query_wins(scores), wins)
    top = ["method", "n", "lowest", "mean", "highest"]
    for x, y in zip(key(M.wrong_top_of_ranks(got), top), key(M.wrong_top(scores), top), strict=True):
        assert x == pytest.approx(y, abs=2e-6)


def test_gallery_ranks_do_not_depend_on_blocks_or_tiles(spark, monkeypatch):
    import numpy as np

    from passagekit.operators import blocked as B

    rng = np.random.default_rng(5)
    p = spark.createDataFrame([(i, i % 9, v.tolist()) for i, v in enumerate(rng.integers(-2, 3, size=(60, 3)).astype(float))], "passage_id long, hull_id long, vec array<double>")
    rows = lambda df: sorted(tuple(r) for r in df.collect())
    want = rows(B.ranks(p, size=100))
    monkeypatch.setattr(B, "TILE", 7)
    monkeypatch.setattr(B, "SIDES", 2)
    assert rows(B.ranks(p, size=20)) == want
    assert [r[:5] for r in rows(B.ranks(p, k=0, size=20))] == [r[:5] for r in want]


def networks_with_ties():
    import numpy as np

    rng = np.random.default_rng(3)
    v = rng.normal(size=(2, 40, 4))
    v[:, 7], v[:, 9] = v[:, 3], v[:, 3]  # ties
    v[0, 11] = 0.0  # a constant row
    return [[(i, i % 3 + 100 * (i > 30) * i, "A", (u / max(np.linalg.norm(u), 1e-9)).tolist()) for i, u in enumerate(x) if m == "a" or i != 5] for m, x in zip("ab", v, strict=True)]


@pytest.mark.parametrize("weights", [None, {"a": 1.0, "b": 3.0}])
def test_measures_of_networks_by_blocks_equal_those_from_pairs(spark, monkeypatch, weights):
    from passagekit.operators import blocked as B
    from passagekit.operators import measures as M
    from passagekit.operators import protocol as P

    nets = {m: spark.createDataFrame(rows, "passage_id long, hull_id long, source string, vec array<double>") for m, rows in zip("ab", networks_with_ties(), strict=True)}
    a, b = (P.leave_one_out(p, method=m) for m, p in nets.items())
    fused = P.fuse_weighted(weights, a.unionByName(b), "fused") if weights else P.fuse(a, b)
    scores = a.unionByName(b).unionByName(fused).cache()
    key = lambda df: sorted(tuple(r[c] for c in sorted(df.columns)) for r in df.collect())
    for most in (32768, 16):  # a gallery of one and of several blocks
        monkeypatch.setattr(B, "MOST", most)
        got = B.Networks(nets, size=7, weights=weights)
        for which in ("best", "all"):
            for x, y in zip(key(M.curve_of_points(got.points(which))), key(M.curve(M.labelled(scores, which))), strict=True):
                assert x == pytest.approx(y, abs=1e-9)
        for x, y in zip(key(got.win_matrix()), key(M.win_matrix(scores)), strict=True):
            assert x == pytest.approx(y, abs=1e-9)
        one, two = got.bootstrap(lambda h: (M.draws(h, 7), None), 7), got.bootstrap(lambda h: (M.draws(h, 7), M.draws(h, 7, offset=7)), 7)
        for x, y in zip(key(one) + key(two), key(M.bootstrap_auc(M.win_matrix(scores), 7)) + key(M.bootstrap_two_way(M.win_matrix(scores), 7)), strict=True):
            assert x == pytest.approx(y, abs=1e-9)


@pytest.mark.parametrize("name", ["eer", "auc_all_genuine", "fused_weighted", "difficulty_sweep", "boot_auc_diff_ci", "boot_auc_ci", "boot_win_matrix", "boot_two_way"])
def test_measures_need_no_row_for_each_pair(spark, monkeypatch, name):
    from passagekit.operators import protocol as P

    def refuse(*_, **__):
        raise AssertionError("a row for each pair")

    monkeypatch.setattr(P, "leave_one_out", refuse)
    registry.ALL[name][0](spark, "/root/testdata/sf0.001").schema


def test_line_measures_count_alike_passages_once_a_line_set(spark):
    import numpy as np
    from pyspark.sql import functions as F

    from passagekit.operators import measures as M
    from passagekit.operators import protocol as P
    from passagekit.operators import tonal as T

    rng = np.random.default_rng(7)
    p = spark.createDataFrame([(i, i // 3 if i < 50 else i, int(b) << 1) for i, b in enumerate(rng.integers(1, 40, size=60))], "passage_id long, hull_id long, bits long")
    q, g = (p.select(F.col("passage_id").alias(f"{a}_id"), F.col("hull_id").alias(f"{b}_hull"), F.col("bits").alias(f"{b}b")) for a, b in (("query", "q"), ("gallery", "g")))
    many = p.groupBy("hull_id").count().where("count > 1").select(F.col("hull_id").alias("q_hull"))
    s = q.join(many, "q_hull", "left_semi").join(g, F.col("query_id") != F.col("gallery_id")).select("query_id", "gallery_id", "q_hull", "g_hull", T._sims(F.col("qb"), F.col("gb"))).cache()
    ranks, points = T.line_measures(p)
    key = lambda df: sorted(tuple(r[c] for c in sorted(df.columns)) for r in df.collect())
    assert key(ranks) == key(P.true_rank(s).select("method", "query_id", "rank"))
    for x, y in zip(key(M.curve_of_points(points)), key(M.curve(M.labelled(s))), strict=True):
        assert x == pytest.approx(y, abs=1e-9)


def test_steps_of_a_small_network_share_a_job(spark):
    """F8: one task takes the steps of a folder in turn, with the weights and losses of a job for each step."""
    import numpy as np

    from passagekit.operators import encoder as E

    rng = np.random.default_rng(17)
    df = spark.createDataFrame([(i, i % 3, v.tolist()) for i, v in enumerate(rng.normal(size=(40, 64)))], "tensor_id long, cls long, x array<double>").cache()
    sc = spark.sparkContext
    sc.setJobGroup("F8", "steps")
    try:
        p, history = E.train(spark, df, E.SMALL, [1e-3, 5e-4], batch=2, micro=2)
        jobs = len(sc.statusTracker().getJobIdsForGroup("F8"))
    finally:
        sc.setLocalProperty("spark.jobGroup.id", None)
    assert jobs < len(history)
    want, again = E.train(spark, df, E.SMALL, [1e-3, 5e-4], batch=2, micro=2, alone=False)
    assert [t for t, _ in history] == [t for t, _ in again]
    assert [x for _, x in history] == pytest.approx([x for _, x in again], abs=1e-6)
    for k in want:
        assert np.allclose(p[k], want[k], atol=1e-6)


def test_ranks_without_nearest_shuffle_no_blocks(spark, monkeypatch):
    """counts above the best genuine score, part after part of the gallery, equal those of crossed blocks."""
    import numpy as np

    from passagekit.operators import blocked as B

    rng = np.random.default_rng(11)
    v = np.round(rng.normal(size=(90, 3)) + 2, 1)  # with ties
    v = v / np.linalg.norm(v, axis=1, keepdims=True)
    v[5] = 0.0
    p = spark.createDataFrame([(7 * i - 50, i % 20, u.tolist()) for i, u in enumerate(v)], "passage_id long, hull_id long, vec array<double>")
    cols = ["query_id", "q_hull", "best", "rank", "candidates"]
    rows = lambda df: sorted(tuple(r[c] for c in cols) for r in df.collect())
    want = rows(B.ranks(p))

    def refuse(*_):
        raise AssertionError("blocks are shuffled")

    monkeypatch.setattr(B, "_crossed", refuse)
    assert len(want) == 90 and rows(B.ranks(p, k=0)) == want
    monkeypatch.setattr(B, "HELD", 30 * 24)  # a gallery of three parts
    monkeypatch.setattr(B, "TALL", 7)
    monkeypatch.setattr(B, "LONG", 11)
    assert rows(B.ranks(p, k=0)) == want
    x = v[v.any(1)]
    best = np.round((x[:40] * x[40:80]).sum(1), 9)
    assert (B.above(x[:40], x, best) == (np.round(x[:40] @ x.T, 9) > best[:, None]).sum(1)).all()


def test_chance_slice_needs_no_row_for_each_pair(spark, tmp_path, monkeypatch):
    """ties, hulls of one passage and sources without a genuine pair, over several parts and ranges."""
    from passagekit.operators import blocked as B
    from passagekit.operators import protocol as P

    def refuse(*_, **__):
        raise AssertionError("a row for each pair")

    monkeypatch.setattr(P, "leave_one_out", refuse)
    rows = "select i::bigint vec_id, [((i // 2) * 37 % 11 - 5)::float, (i * 53 % 7 - 3 + 0.5)::float, (i * 29 % 13 - 6)::float] embedding, case when i < 6 then 100 + i when i < 12 then 50 + i // 4 else i * 7 % 5 end::int label from range(150) t(i)"
    want = same(spark, tmp_path, "null_metrics", embeddings=rows)
    monkeypatch.setattr(B, "HELD", 40 * 24)
    monkeypatch.setattr(B, "COLS", 16)
    for few, wide in ((0, 1 << 25), (300, 1 << 17)):  # tables by unit, and lists of scores beside them
        monkeypatch.setattr(B, "FEW", few)
        monkeypatch.setattr(B, "RANGE", wide)
        assert same(spark, tmp_path, "null_metrics", embeddings=rows) == want


def test_a_step_works_on_parts_of_the_head_in_place(spark, monkeypatch, tmp_path):
    """parts of classes by threads and windows instead of transforms give the gradients of one table; input is read once."""
    import numpy as np

    from passagekit.operators import encoder as E

    rng = np.random.default_rng(19)
    x, y = E.standardise(rng.normal(size=(12, 64))), np.array([0, 9, 9, 3, 4, 7, 12, 12, 12, 1, 8, 5])
    p = E.init(E.SMALL) | {"head": rng.normal(size=(13, 16))}
    want = E.loss_and_gradient(x, y, p, E.SMALL)
    e = E.forward(x, p, E.SMALL)[0]
    u = p["head"] / np.linalg.norm(p["head"], axis=1, keepdims=True)
    z = 30 * e @ u.T
    z[range(12), y] = 30 * np.cos(np.arccos((e * u[y]).sum(1)) + 0.3)
    assert want[0] == pytest.approx((np.log(np.exp(z).sum(1)) - z[range(12), y]).sum())
    monkeypatch.setattr(E, "CLASSES", 4)
    monkeypatch.setattr(E, "CHUNK", 7)
    monkeypatch.setattr(E, "DIRECT", 0)
    monkeypatch.setattr(E, "KEPT", 0)
    got = E.loss_and_gradient(x, y, p, E.SMALL)
    assert got[0] == pytest.approx(want[0]) and all(np.allclose(got[1][k], want[1][k], atol=1e-10) for k in p)
    for s in (30.0, 900.0):
        loss, _, grad = E.margin_head(e, y, p["head"], s)
        assert np.isfinite(loss) and np.isfinite(grad).all()
    mean, var = ({k: np.full(v.shape, c) for k, v in p.items()} for c in (0.2, 0.3))
    q, before, d = {k: v.copy() for k, v in p.items()}, {k: v.copy() for k, v in p.items()}, {k: v / 12 for k, v in want[1].items() if k != "bank0.w"}
    d = {k: v * min(1.0, 0.5 / np.sqrt(sum((w * w).sum() for w in d.values()))) for k, v in d.items()}
    E._adamw(q, mean, var, 3, want[1], 12, 1e-2, 1e-4, 0.5, ("bank0.w",))
    for k, v in before.items():
        a, b = (0.18 + 0.1 * d[k], 0.2997 + 0.001 * d[k] ** 2) if k in d else (0.2, 0.3)
        assert np.allclose(mean[k], a) and np.allclose(var[k], b)
        assert np.allclose(q[k], v * (1 - 1e-6) - 1e-2 * (a / (1 - 0.9**3)) / (np.sqrt(b / (1 - 0.999**3)) + 1e-8) if k in d else v)

    def once(parts):
        for part in parts:
            with open(tmp_path / "read", "a") as f:
                f.write("x" * len(part))
            yield part

    rows = spark.createDataFrame([(i, int(c), v.tolist()) for i, (c, v) in enumerate(zip(y, x, strict=True))], "tensor_id long, cls long, x array<double>")
    _, history = E.train(spark, rows.mapInPandas(once, rows.schema), E.SMALL, [1e-3, 1e-3], batch=4)
    assert len(history) > 2 and len((tmp_path / "read").read_text()) == 12


def test_alike_vectors_are_scored_once(spark, monkeypatch, tmp_path):
    """counts between distinct vectors equal those of pairs of passages, with ties, rounding at half a digit, and vectors that are no numbers."""
    import numpy as np

    from passagekit.operators import blocked as B

    rng = np.random.default_rng(23)
    v = np.round(rng.integers(-2, 3, size=(240, 3)) / 3, 6)  # products end in a digit beyond the ninth
    v[100:], v[7], v[9, 1] = v[rng.integers(0, 40, size=140)], 0.0, np.nan
    v[200:] = np.round(rng.normal(size=(40, 3)), 6)
    hull = [i if i > 230 else i % 31 for i in range(240)]
    p = spark.createDataFrame([(3 * i - 90, h, u.tolist()) for i, (h, u) in enumerate(zip(hull, v, strict=True))], "passage_id long, hull_id long, vec array<double>")
    cut = lambda s: np.trunc(s * 1e9 + np.copysign(0.5, s)) / 1e9
    s = cut((v[:, 0, None] * v[:, 0] + v[:, 1, None] * v[:, 1]) + v[:, 2, None] * v[:, 2])
    want = []
    for i in range(240):
        others = [j for j in range(240) if j != i]
        own = [s[i, j] for j in others if hull[j] == hull[i]]
        if own and not np.isnan(max(own, key=lambda z: (np.isnan(z), z))):
            want.append((3 * i - 90, hull[i], max(own), 1 + sum(s[i, j] > max(own) for j in others), sum(np.isfinite(s[i, j]) for j in others)))
    rows = lambda: sorted(tuple(r)[:5] for r in B.ranks(p, k=0).collect() if not np.isnan(r["best"]))
    assert rows() == want
    for held, tall, long in ((40 * 24, 7, 11), (1 << 20, 5, 64)):
        monkeypatch.setattr(B, "HELD", held)
        monkeypatch.setattr(B, "TALL", tall)
        monkeypatch.setattr(B, "LONG", long)
        assert rows() == want


def test_event_days_are_ranked_between_histograms(spark, tmp_path, monkeypatch):
    """days of many users with alike histograms need no product for each pair of days, and the series is not gathered."""
    from passagekit.operators import blocked as B

    scored, plain = [], B._counted
    monkeypatch.setattr(B, "_counted", lambda p: scored.append(p.select("vec").distinct().count()) or plain(p))
    events = "select i::bigint event_id, timestamp '2024-01-01' + to_hours(((i * 7) % 96)::int) ts, (i % 50)::bigint user_id, 'view' event_type, case when i % 101 = 0 then null else (i * 37 % 4) * 60.0 end::double as value from range(300) t(i)"
    assert same(spark, tmp_path, "event_reid", events=events)[0][4] > 100
    assert scored[0] < 40


def test_groups_stay_whole_over_batches():
    import pyarrow as pa

    from passagekit.functions.batches import whole

    keys = [None, None, 1, 1, 1, 2, 5, 5, 5, 5, 5, 6]
    for size in (1, 2, 3, 12):
        cut = [pa.record_batch({"k": pa.array(keys[a : a + size], pa.int64()), "x": list(range(a, min(a + size, 12)))}) for a in range(0, 12, size)]
        got = [(set(t["k"].to_pylist()[a:b]), t["x"].to_pylist()[a:b]) for t, ends in whole(iter([cut[0].slice(0, 0), *cut]), "k") for a, b in zip(ends[:-1], ends[1:], strict=True)]
        assert got == [({None}, [0, 1]), ({1}, [2, 3, 4]), ({2}, [5]), ({5}, [6, 7, 8, 9, 10]), ({6}, [11])]
