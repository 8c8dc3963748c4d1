"""The word process: base counts by brute force, seatings against enumeration, probabilities that sum to one, odd inputs."""

import itertools
import math
import zlib
from collections import Counter

import numpy as np
import pytest

from passagekit.llm import lm_scoring as L

SCHEMA = "doc_id long, text string, lang string, score double, held_out boolean, piece long"


def frame(spark, rows):
    return spark.createDataFrame([(i, t, "en", 1.5, None, 7) for i, t in rows], SCHEMA)


@pytest.fixture(scope="module")
def texts():
    rng = np.random.default_rng(1)
    words, out = [f"w{i}" for i in range(150)], [(0, None), (1, ""), (2, "  \t "), (3, "One two"), (4, "one TWO"), (5, "é漢 \x85 x")]
    nxt = {w: rng.choice(words, 3) for w in words}
    for i in range(6, 80):
        w = [str(rng.choice(words))]
        while len(w) < 50:
            w.append(str(rng.choice(nxt[w[-1]] if rng.random() < 0.8 else words)))
        out.append((i, " ".join(w)))
    return [*out, out[7], (90, "never seen words only"), (100, "w1 " * 30_000 + "w2")]


def test_base_counts_and_other_pieces(spark, texts):
    held = L.F.col("doc_id") % 10 == 0
    one = {r["doc_id"]: r for r in L.score(frame(spark, texts), held).collect()}
    c = Counter()
    for i, t in texts:
        if i % 10:
            c.update([*(t or "").encode().lower().split(), b"\n"])
    n, v = sum(c.values()), len(c)
    for i, t in texts:
        w = [*(t or "").encode().lower().split(), b"\n"]
        assert one[i]["base_score"] == pytest.approx(sum(math.log10((c[x] + 0.1) / (n + 0.1 * (v + 1))) for x in w))
        assert (one[i]["n_tokens"], one[i]["n_known"], one[i]["train_tokens"], one[i]["held_out"]) == (len(w), sum(c[x] > 0 for x in w), n, i % 10 == 0)
        assert -1e6 < one[i]["score"] < 0
    # where texts are cut into pieces changes nothing
    other = {r["doc_id"]: r for r in L.score(frame(spark, texts).repartition(7), held, piece=300).collect()}
    assert all(other[i]["score"] == pytest.approx(one[i]["score"], rel=1e-5) for i in one)
    # more parts and dealt contexts draw other numbers from the same process
    many = {r["doc_id"]: r for r in L.score(frame(spark, texts), held, piece=500, word_bytes=4000, pair_bytes=2000, hot=40).collect()}
    assert all(many[i]["base_score"] == pytest.approx(one[i]["base_score"]) for i in one)
    a, b = (sum(x[i]["score"] for i in x if i % 10 == 0 and i < 90) for x in (one, many))
    assert abs(a / b - 1) < 0.03 and a > sum(one[i]["base_score"] for i in one if i % 10 == 0 and i < 90)


def test_odd_tables(spark):
    held = L.F.col("doc_id") % 10 == 0
    assert L.score(frame(spark, []), held).count() == 0
    nothing = L.score(frame(spark, [(10, "a b"), (20, None)]), held).collect()  # nothing to learn from
    assert {(r["doc_id"], r["n_tokens"], r["n_known"], r["train_tokens"]) for r in nothing} == {(10, 3, 0, 0), (20, 1, 0, 0)}
    assert all(math.isfinite(r["score"]) for r in nothing)
    assert all(r["held_out"] is False for r in L.score(frame(spark, [(1, "a b"), (2, "a")]), L.F.lit(None).cast("boolean")).collect())


def _process(counts: dict, word_parts=2):
    """A part that holds all of some pair counts."""
    keys = sorted(counts)
    u, w = (np.array([k[i] for k in keys]) for i in range(2))
    return L.Part(L.put_pairs(u, w, 2 * np.array([counts[k] for k in keys])), word_parts)


def _replies(part, t, word_parts):
    """What the vocabulary would answer if this part were all."""
    out = {}
    for p, blob in part.message(t, word_parts):
        _, m, _, c, k = L.get(blob)
        out[p] = L.put(m, c, k)
    return out


def test_seatings_follow_the_exact_posterior():
    counts = {(1, 1): 3, (1, 2): 2, (2, 1): 2, (2, 3): 1, (3, 2): 4}
    d, d0, theta, theta0 = 0.6, 0.5, 0.8, 1.3
    part = _process(counts)
    keys = sorted(counts)
    s = lambda c, t: math.exp(L.log_stirling(d, 8)[c, t])
    want, total = np.zeros(len(keys)), 0.0
    for ts in itertools.product(*(range(1, counts[k] + 1) for k in keys)):
        p = 1.0
        for u in {k[0] for k in keys}:
            n = sum(t for k, t in zip(keys, ts) if k[0] == u)
            p *= math.prod(theta + i * d for i in range(n))
        m = Counter()
        for k, t in zip(keys, ts):
            p *= s(counts[k], t)
            m[k[1]] += t
        for x in m.values():
            p *= math.gamma(x - d0) / math.gamma(1 - d0)
        n = sum(m.values())
        p *= math.gamma(theta0) / math.gamma(theta0 + n)
        want += p * np.array(ts)
        total += p
    want /= total
    heard, told, got, rng = [], [], [], np.random.default_rng(3)
    t = np.minimum(part.c, 1)
    for r in range(3000):
        m = np.bincount(part.iw, t)
        z = L.keyed_gamma(m - d0, part.words, 11 * 1000 + 2 * r + 1).sum() if r else 0
        told = [{"theta": theta, "theta0": theta0, "d": d, "d0": d0, "m": int(m.sum()), "v": 3, "z": float(z + rng.gamma(theta0 + 3 * d0))}]
        # one round at a time: the same draws as replay, without doing the earlier ones again
        x = L.keyed_gamma(theta / d + np.bincount(part.iu, t), part.ids, 11 * 1000 + 2 * r)
        beta = L.parent(m.astype(float), part.words, told[0], r, 11)
        t = L.draw_tables(part.c, d * x[part.iu] * beta[part.iw], d, rng)
        if r >= 50:
            got.append(t)
    assert np.allclose(np.mean(got, 0), want, atol=0.06)
    steps = list(part.replay([_replies(part, np.minimum(part.c, 1), 2)], told[:1], 0, 5))
    assert len(steps) == 2 and all((1 <= x) & (x <= c) for x, c in zip(steps[1][0], part.c))


def test_predictions_sum_to_one():
    counts = {(1, 1): 3, (1, 2): 2, (2, 1): 2, (2, 3): 1, (3, 2): 600}
    part = _process(counts | {(1, 3): 0, (1, 0): 0, (9, 1): 0, (9, 2): 0, (9, 3): 0, (9, 0): 0})
    t = np.minimum(part.c, 1)
    d, d0, theta, theta0, v = 0.6, 0.5, 0.8, 1.3, 3
    for t in (t, L.draw_tables(part.c, np.full(len(t), 2.0), d, np.random.default_rng(0))):
        m, c, k = part.replies(_replies(part, t, 2))
        k = part.tables_of(t, k)
        mean = np.where(part.words > 0, np.maximum(m - d0, 0), theta0 + d0 * v) / (theta0 + m.sum())
        back = np.where(c > 0, (theta + d * k) / (theta + np.maximum(c, 1)), 1.0)
        p = np.where(part.c > 0, part.c - d * t, 0) / (theta + np.maximum(c, 1))[part.iu] + back[part.iu] * mean[part.iw]
        of = np.bincount(part.iu, p)
        assert of[0] == pytest.approx(1) and of[3] == pytest.approx(1)  # contexts 1 and 9 ask for all words


def test_tables_of_large_restaurants_agree_with_small_ones():
    c = np.full(4000, 400)
    rng = np.random.default_rng(1)
    for z, d in ((0.3, 0.7), (3.0, 0.7), (40.0, 0.7), (3.0, 0.3), (30.0, 0.3)):
        exact = L.draw_tables(c, np.full(4000, z), d, rng)
        t = L.draw_tables(c, np.full(4000, z), d, rng, exact=150)
        assert abs(exact.mean() / t.mean() - 1) < 0.06 and abs(exact.std() / t.std() - 1) < 0.2
    many = L.draw_tables(np.full(500, 10**7), np.full(500, 1e5), 0.5, rng)
    assert 1 < many.min() and many.max() < 10**6 and abs(L.log_factorial(np.array([0.0, 1, 10]))[2] - math.lgamma(11)) < 1e-6


def test_spelling_sums_to_one():
    words = [b"abra", b"cad", b"abba", "é".encode()]
    gram, at = L.triples(words)
    assert len(gram) == sum(len(w) + 1 for w in words) and at.tolist().count(0) == 5
    u, n = np.unique(gram, return_counts=True)
    s = L.Spelling(u, n * (1 << 20))
    for k in range(3):
        assert np.allclose((10.0 ** s.__dict__[f"level{k}"][1].astype(float)).sum(1), 1, atol=1e-4)
    assert np.isfinite(s.log10([b"zzz", b"abra"])).all() and s.log10([b"abra"])[0] > s.log10([b"zzzz"])[0]


def test_draws_and_arrays():
    ids = np.arange(200_000)
    for a in (0.2, 1.0, 7.5):
        g = L.keyed_gamma(a, ids, 3)
        assert abs(g.mean() / a - 1) < 0.02 and abs(g.var() / a - 1) < 0.05
        assert np.array_equal(L.keyed_gamma(a, ids[5:9], 3), g[5:9])
    x = [np.array([], np.int64), np.array([0, 5, 1 << 40]), np.arange(300)]
    assert all(np.array_equal(a, b) for a, b in zip(L.get(L.put(*x)), x, strict=True))
    u, w = np.array([1, 1, 1, 4, 4, 9]), np.array([0, 3, 8, 2, 1 << 40, 0])
    for got, want in zip(L.get_pairs(L.put_pairs(u, w, u)), (u, w, u), strict=True):
        assert np.array_equal(got, want)


def test_held_out_texts_are_likelier_than_under_the_base(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    got = L.score(docs, L.crc(L.F.col("doc_id")) % 10 == 0).where("held_out").toPandas()
    assert all(zlib.crc32(str(i).encode()) % 10 == 0 for i in got.doc_id)
    assert got.score.sum() / got.n_tokens.sum() > got.base_score.sum() / got.n_tokens.sum() + 0.4
