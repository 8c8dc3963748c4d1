"""Each operator against brute force, with nulls, empty texts, repeated rows, clashing columns and empty tables."""

import math
import re
from collections import Counter, defaultdict

import numpy as np
import pytest

from passagekit.llm import ann_graph, importance, jaccard_join, language_id, license_scan, lm_scoring, mixing, packing, quality_rules, surrogates

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, kept boolean"
WORD = re.compile(r"[^\x20\x09-\x0D]+")


def frame(spark, rows):
    return spark.createDataFrame([(i, t, "en", s, len(t or ""), True) for i, t, s in rows], SCHEMA)


@pytest.fixture(scope="module")
def texts():
    rng = np.random.default_rng(1)
    words = [f"w{i}" for i in range(400)]
    out = [(0, None, "a"), (1, "", "a"), (2, "  \t ", None), (3, "One two", "a"), (4, "one TWO", "b")]
    for i in range(5, 60):
        out.append((i, " ".join(rng.choice(words, 60)), "a" if i % 3 else "b"))
    for i in range(60, 90):  # near copies of earlier texts
        w = out[5 + (i - 60) % 6][1].split()
        w[int(rng.integers(len(w)))] = f"n{i}"
        out.append((i, " ".join(w), "c"))
    return [*out, out[7], (91, out[8][1], "c"), (92, "the mit license " * 3 + "x " * 5000, "c")]


def brute_components(rows, k, percent):
    low = str.maketrans({chr(65 + i): chr(97 + i) for i in range(26)})
    sets = {}
    for i, t, _ in rows:
        w = WORD.findall((t or "").translate(low))
        sets[i] = frozenset(zip(*(w[j:] for j in range(k)), strict=False)) if len(w) >= k else frozenset([tuple(w)] if w else [])
    up = {i: i for i in sets}

    def find(a):
        while up[a] != a:
            a = up[a]
        return a

    for a in sets:
        for b in sets:
            c = len(sets[a] & sets[b])
            if a < b and c and 100 * c >= percent * len(sets[a] | sets[b]):
                x, y = find(a), find(b)
                up[max(x, y)] = min(x, y)
    return {i: (len(sets[i]), find(i)) for i in sets}


@pytest.mark.parametrize(("k", "percent", "weight", "small"), [(4, 85, 2_000_000, 400), (5, 80, 300, 400), (4, 85, 2_000_000, 3), (5, 80, 500, 2)])
def test_jaccard_join(spark, texts, k, percent, weight, small):
    got = jaccard_join.join(frame(spark, texts), k=k, percent=percent, weight=weight, small=small).collect()
    assert len(got) == len(texts)
    want = brute_components(texts, k, percent)
    assert {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in got} == want


def test_shingle_sets_hash_every_word_once_and_not_one_by_one():
    import sys

    import pyarrow as pa

    rng = np.random.default_rng(11)
    letters = list("abcXYZ\u00e9\u4e2d\U0001f600\x00\x1e\x1f\x85\u00a0")
    gaps = list(" \t\n\x0b\x0c\r")
    words = ["".join(rng.choice(letters, n)) for n in range(1, 40) for _ in range(8)] + ["q" * n for n in (63, 64, 65, 66, 200)] + ["abcdefg", "abcdefg\x1e", "abcdefg\x00", "ABCDEFGH"]
    texts = [None, "", " \n", "a", "A b", "a b c", "a\x0bB\x0cc\rd", *("".join(w + rng.choice(gaps) for w in rng.choice(words, n)) + end for n in (2, 3, 4, 5, 300) for end in ("", "end") for _ in range(6))]
    held = pa.array(["left out", *texts, *texts], pa.string()).slice(1)
    for at_once in (1, 50, 1 << 20):
        jaccard_join.AT_ONCE, was = at_once, jaccard_join.AT_ONCE
        try:
            for kind in (pa.string(), pa.large_string()):
                got, names = list(jaccard_join.shingle_sets(held.cast(kind), 4)), {}
                assert len(got) == 2 * len(texts)
                for t, s in zip([*texts, *texts], got, strict=True):
                    w = WORD.findall("".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or ""))
                    want = {tuple(w[i : i + 4]) for i in range(len(w) - 3)} if len(w) > 3 else {tuple(w)} - {()}
                    assert len(s) == len(want) and (s[1:] > s[:-1]).all()
                    assert names.setdefault(frozenset(want), s.tobytes()) == s.tobytes()
                assert len(set(names.values())) == len(names)
        finally:
            jaccard_join.AT_ONCE = was
    # CPU seconds: calls are counted for texts, not for words
    calls, many = [], pa.array([" ".join(f"w{i}" for i in range(50_000))])
    sys.setprofile(lambda frame, event, arg: calls.append(event))
    try:
        list(jaccard_join.shingle_sets(many, 4))
    finally:
        sys.setprofile(None)
    assert len(calls) < 2_000


def test_region_join_is_exact():
    rng = np.random.default_rng(5)
    base = [np.unique(rng.integers(0, 1 << 62, 80).astype(np.uint64)) for _ in range(4)]
    points = []
    for i in range(120):
        p = base[i % 4].copy()
        p[rng.integers(0, len(p), int(rng.integers(0, 16)))] = rng.integers(0, 1 << 62, 1).astype(np.uint64)
        points.append(np.unique(p))
    seen = jaccard_join.Classes(len(points))
    for a, b in jaccard_join.join_region(points, 85):
        seen.join(a, b)
    want = jaccard_join.Classes(len(points))
    for a in range(len(points)):
        for b in range(a):
            c = len(np.intersect1d(points[a], points[b]))
            if jaccard_join.linked(c, len(points[a]), len(points[b]), 85):
                want.join(a, b)
    assert [seen.find(i) for i in range(120)] == [want.find(i) for i in range(120)]


def test_license_scan(spark, texts):
    rows = [*texts, (200, "under the Apache License, and CC-BY apache license", "a"), (201, "Licensed under CC BY-NC 4.0.", "a")]
    got = {r["doc_id"]: r for r in license_scan.scan(frame(spark, rows)).collect()}
    assert (got[0]["n_words"], got[0]["n_base"], got[0]["first_word"], got[0]["labels"]) == (0, 0, None, "")
    assert got[92]["n_base"] == 3 and got[92]["base_labels"] == "mit" and (got[92]["first_word"], got[92]["last_word"]) == (1, 7)
    assert got[200]["n_base"] == 3 and got[200]["base_labels"] == "apache,cc-by"
    assert "cc-by-nc" in got[201]["labels"] and got[201]["base_labels"] == "cc-by" and got[201]["score"] == 1.0


def test_packing_round_trip(spark, texts):
    import public_tokenizers as P
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(P.path("byte_bpe_50k.json"))
    rows = [*texts, (300, "end <|endoftext|> é 漢字", "a")]
    got = packing.pack(frame(spark, rows), size=256, with_ids=True).collect()
    docs, seqs = defaultdict(list), defaultdict(list)
    for r in got:
        docs[r["doc_id"]].append(r)
        seqs[r["sequence_id"]].append((r["offset"], r["length"]))
    for i, t, _ in rows:
        ids = tok.encode(t or "", add_special_tokens=False).ids + [0]
        pieces = sorted(docs[i], key=lambda r: (r["piece"], r["sequence_id"], r["offset"]))
        times = sum(j == i for j, _, _ in rows)
        assert sorted([x for r in pieces for x in r["ids"]]) == sorted(ids * times)
        if times == 1:
            assert [x for r in pieces for x in r["ids"]] == ids and all(r["length"] == 256 for r in pieces[1:])
    for own in seqs.values():
        at = 0
        for offset, n in sorted(own):
            assert offset == at
            at += n
        assert at <= 256


def test_quality_statistics(spark, texts):
    rows = [*texts, (400, "a b c a b c x\na b\n\na b # <", "a")]
    got = {r["doc_id"]: r for r in quality_rules.statistics(frame(spark, rows)).collect()}
    for i, t, _ in rows:
        w = WORD.findall(t or "")
        grams = Counter(zip(w, w[1:], w[2:], strict=False))
        hit = {k + j for k in range(len(w) - 2) if grams[tuple(w[k : k + 3])] > 1 for j in range(3)}
        lines = [x for x in (t or "").split("\n") if WORD.search(x)]
        assert (got[i]["n_words"], got[i]["word_chars"], got[i]["n_repeat_words"], got[i]["n_dup_lines"]) == (len(w), sum(map(len, w)), len(hit), len(lines) - len(set(lines)))


def test_rules_separate(spark):
    rows = [(i, "junk### " * 60 if i % 4 == 0 else " ".join(f"word{(i * 7 + k) % 97}" for k in range(80)), "a") for i in range(200)]
    stats = quality_rules.statistics(frame(spark, rows))
    labelled = stats.withColumn("bad", quality_rules.F.col("doc_id") % 4 == 0)
    rules = quality_rules.learn(labelled, "bad")
    assert rules
    assert all((r["rule"] > 0) == (r["doc_id"] % 4 == 0) for r in quality_rules.judge(stats, rules).collect())
    assert quality_rules.learn(labelled.limit(0), "bad") == []


def test_mixing_budgets(spark, texts):
    docs = frame(spark, [(i, t, s) for i, t, s in texts] + [(1000 + i, f"many words here {i} " * 20, "hot") for i in range(300)])
    out = mixing.mix(docs, max_repeats=2.0).collect()
    by = Counter((r["doc_id"], r["source"]) for r in out)
    assert all(by[i, s] >= 1 for i, _, s in texts) and max(by[i, s] for i, _, s in texts if i != 7) <= 2
    assert all(by[1000 + i, "hot"] == 1 for i in range(300))
    assert mixing.mix(docs.limit(0)).count() == 0


def test_entropy_target(spark):
    rows = [(i, "w " * n, s) for i, (s, n) in enumerate([("a", 1000), ("b", 100), ("c", 10)])]
    src = mixing.shares(frame(spark, rows).withColumn("n_tokens", mixing.tokens(mixing.F.col("text"))))
    a = mixing.exponent(src, entropy=0.9)
    w = [(x / 1110) ** a for x in (1000, 100, 10)]
    p = [x / sum(w) for x in w]
    assert abs(-sum(x * math.log(x) for x in p) - 0.9) < 1e-3


def test_surrogates():
    s = surrogates.Surrogates()
    text = "mail ann.12@mail3.example.com or +1 (407) 555-7710, card 4539578763621486, at 10.2.3.4; Mrs Jones met Mr Smith and Mrs Jones. token = \"908b038b7daaf91e730d2f64001c52934d43d9336\" ann.12@mail3.example.com"
    new, found = s.replace(text)
    assert Counter(k for k, _, _ in found) == Counter(email=2, phone=1, card=1, ip=1, person=3, secret=1)
    for _, a, b in found:
        assert text[a:b] not in new
    mails = re.findall(r"\S+@\S+", new)
    assert len(mails) == 2 and mails[0] == mails[1]
    names = re.findall(r"(?:Mrs|Mr) (\w+)", new)
    assert names[0] == names[2] != names[1]
    card = re.search(r"\d{16}", new)[0]
    assert surrogates.luhn(card[:-1]) == int(card[-1])
    assert s.replace(None) == (None, []) and s.replace("plain words only") == ("plain words only", [])


def test_permutation_is_one_to_one():
    assert sorted(surrogates.permute(x, 300, b"k", "t") for x in range(300)) == list(range(300))


def test_language_model_sums_to_one(spark):
    keys, counts = language_id.count_grams(["abracadabra", "banana band"])
    m = language_id.Model({"x": (keys, counts)})
    assert np.allclose((2.0 ** -m.bits[:, 1:, 0]).sum(1) + (256 - m.a + 1) * 2.0 ** -m.bits[:, 0, 0], 1, atol=1e-3)
    assert m.predict(None) == ("und", 0.0) and m.predict("123")[0] == "und"


def test_importance(spark):
    rows = [(i, "good plain text about things " * 5 if i % 5 else "!!! $$$ ### " * 20, "a") for i in range(100)] + [(500, None, "a"), (501, "", "a")]
    docs = frame(spark, rows)
    labels = spark.createDataFrame([(i, i % 5 != 0) for i in range(0, 100, 2)], "doc_id long, target boolean")
    out = {r["doc_id"]: r["kept"] for r in importance.resample(docs, labels).collect()}
    assert len(out) == 102 and all(out[i] == (i % 5 != 0) for i in range(100))
    assert importance.keep(docs, labels).columns == docs.columns


def test_graph_recall_and_ties(spark):
    rng = np.random.default_rng(2)
    x = rng.normal(size=(600, 16))
    x[100:140] = x[7]
    rows = [(i, [float(c) for c in v]) for i, v in enumerate(x)] + [(900, None), (901, [0.0] * 16), (902, [float("nan")] * 16)]
    pts = ann_graph.usable(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), "vec_id", "embedding")
    assert pts.count() == 600
    got = ann_graph.search(ann_graph.build(pts, 5, shard=200), pts.where("id % 50 = 0"), 5).collect()
    u = x / np.linalg.norm(x, axis=1, keepdims=True)
    hit = 0
    for q in range(0, 600, 50):
        s = u @ u[q]
        s[q] = -9
        top = {int(i) for i in sorted(range(600), key=lambda i: (-round(s[i], 12), i))[:5]}
        hit += len(top & {r["vec_id"] for r in got if r["query_id"] == q})
    assert hit >= 0.9 * 60 and [r["vec_id"] for r in sorted(got, key=lambda r: r["rank"]) if r["query_id"] == 100] == [7, 101, 102, 103, 104]


def test_empty_tables(spark):
    d = spark.createDataFrame([], SCHEMA)
    labels = spark.createDataFrame([], "doc_id long, target boolean")
    for out in (jaccard_join.join(d), license_scan.scan(d), packing.pack(d), surrogates.replace(d), quality_rules.statistics(d), importance.resample(d, labels), language_id.predict(d, language_id.fit(d)), lm_scoring.score(d, lm_scoring.F.col("doc_id") % 10 == 0)):
        assert out.count() == 0


def test_wide_regions_are_cut_exactly(spark, monkeypatch):
    monkeypatch.setattr(jaccard_join, "SHARE", 10)
    rng = np.random.default_rng(9)
    base = [[f"b{g}_{i}" for i in range(60)] for g in range(3)]
    common = "this very rare passage is shared by all of them and makes one region".split()
    rows = []
    for i in range(150):  # drifting copies: neighbours link, the ends of a chain do not
        w = list(base[i % 3])
        for j in range(i // 3):
            if j % 2:
                w[j % 60] = f"x{j}"
        rows.append((i, " ".join([*common, *w]), "a"))
    for i in range(150, 230):
        rows.append((i, " ".join([*common, *rng.choice([f"r{k}" for k in range(2000)], 50)]), "b"))
    got = jaccard_join.join(frame(spark, rows), small=8).collect()
    want = brute_components(rows, 4, 85)
    assert {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in got} == want and len({c for _, c in want.values()}) > 80
