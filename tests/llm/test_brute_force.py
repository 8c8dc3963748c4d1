"""The operators that SQL cannot state, each against a plain version, with clashing column names, nulls, empty and long texts and ties."""

import math
import os
import re
from collections import Counter, defaultdict

import numpy as np
import pytest

from passagekit.llm import ann_graph, importance, jaccard_join, language_id, license_scan, lm_scoring, mixing, packing, quality_rules, surrogates

#: Columns that are named like outputs of the operators.
CLASH = "doc_id long, text string, lang string, source string, n_chars long, labels string, entities string, block long, `order` long, piece long, score double, log_weight double, kept boolean, id long, rank int, weight double"


def clashing(spark, rows):
    return spark.createDataFrame([(i, t, lang, s, len(t or ""), "l", "e", 5, 6, 7, 0.5, 0.25, False, 9, 3, 2.0) for i, t, lang, s in rows], CLASH)


# ---- licence scan


def brute_matches(words, template, least):
    """Maximal stretches of words of at least `least` that occur in the template."""
    inside = {tuple(template[a:b]) for a in range(len(template)) for b in range(a + 1, len(template) + 1)}
    longest = []
    for i in range(len(words)):
        n = 0
        while n <= i and tuple(words[i - n : i + 1]) in inside:
            n += 1
        longest.append(n)
    out = []
    for i, n in enumerate(longest):
        if n >= least and (i + 1 == len(words) or longest[i + 1] != n + 1):
            out.append((i - n + 1, i))
    return out


def test_matches_of_every_template_equal_brute_force():
    rng = np.random.default_rng(4)
    for _ in range(60):
        letters = [x.encode() for x in "abcdef"[: int(rng.integers(2, 7))]]
        templates = [[letters[i] for i in rng.integers(0, len(letters), int(rng.integers(3, 14)))] for _ in range(4)]
        templates.append(templates[0][:4])
        words = [letters[i] for i in rng.integers(0, len(letters), 40)] + templates[0] + [b"z"] + templates[1]
        auto = license_scan.Automaton(templates, [])
        _, got = auto.stream(words, 3)
        for t, template in enumerate(templates):
            assert [(a, b) for a, b, _ in got.get(t, [])] == brute_matches(words, template, 3)
            for a, b, state in got.get(t, []):
                assert auto.ends[state][t] == [e for e in range(len(template)) if e + 1 >= b - a + 1 and template[e - (b - a) : e + 1] == words[a : b + 1]]


def test_base_phrases_equal_brute_force(spark):
    rng = np.random.default_rng(5)
    vocab = "gnu general public license apache cc by mit a the GNU Cc".split()
    rows = [(i, " ".join(rng.choice(vocab, 60)), "en", "s") for i in range(40)] + [(100, None, None, None), (101, "", "en", "s"), (102, "mit license " * 20_000, "en", "s"), (0, "again", "en", "s")]
    got = defaultdict(list)
    for r in license_scan.scan(clashing(spark, rows)).collect():
        got[r["doc_id"]].append(r)
    assert sum(map(len, got.values())) == len(rows)
    for i, t, *_ in rows[1:-1]:
        w = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
        at = [(k, lab) for p, lab in license_scan.BASE.items() for q in [p.split()] for k in range(len(w)) if w[k : k + len(q)] == q]
        r = got[i][0]
        assert (r["n_words"], r["n_base"], r["first_word"], r["last_word"], r["base_labels"]) == (len(w), len(at), min([k for k, _ in at], default=None), max([k for k, _ in at], default=None), ",".join(sorted({x for _, x in at})))


def test_short_templates_and_names_count(spark):
    given = {"short": ["a b c d"], "long": ["a b c d e f g h i j k l m n o p"], "twice": ["x y z w q x y z w r s"]}
    rows = [(1, "a b c d e f", "", ""), (2, "x y z w r s", "", ""), (3, "released under the Mozilla Public License; SPDX-License-Identifier: Apache-2.0", "", "")]
    got = {r["doc_id"]: r for r in license_scan.scan(clashing(spark, rows), templates=given).collect()}
    assert got[1]["labels"] == "short" and got[2]["score"] == pytest.approx(6 / 11) and got[3]["labels"] == "apache,mpl" and got[3]["base_labels"] == ""


# ---- pruned graphs


def test_graph_takes_any_magnitude_and_length(spark):
    schema = "vec_id long, embedding array<double>, rank int, score double"
    rows = [(0, [1e200, 2e200]), (50, [1e-200, 2e-200]), (1, [3.0, 6.0]), (2, [-1e200, 2e200]), (3, [1.0, 0.0, 0.0]), (100, [1.0, 1.0, 0.0]), (4, [math.inf, 1.0]), (5, []), (6, None), (7, [5e-324, 0.0])]
    pts = ann_graph.usable(spark.createDataFrame([(*r, 1, 1.0) for r in rows], schema), "vec_id", "embedding")
    got = defaultdict(list)
    for r in sorted(ann_graph.search(ann_graph.build(pts, 5), pts.where("id % 50 = 0"), 5).collect(), key=lambda r: r["rank"]):
        got[r["query_id"]].append((r["vec_id"], r["score"]))
    assert {i for i, _ in got[0][:2]} == {1, 50} and [i for i, _ in got[0][2:]] == [2, 7] and [i for i, _ in got[100]] == [3]
    assert got[0][0][1] == pytest.approx(1) and got[100][0][1] == pytest.approx(math.sqrt(0.5)) and got[0][3][1] == pytest.approx(1 / math.sqrt(5))
    none = ann_graph.usable(spark.createDataFrame([], schema), "vec_id", "embedding")
    assert ann_graph.search(ann_graph.build(none, 5), none, 5).count() == 0


# ---- surrogates


def test_maps_are_one_to_one_and_leave_nothing_in_place():
    for n in (2, 3, 10, 257, 1000):
        got = [surrogates.moved(x, n, b"k", "t") for x in range(n)]
        assert sorted(got) == list(range(n)) and all(x != y for x, y in enumerate(got))
        assert [surrogates.unpermute(surrogates.permute(x, n, b"k", "u"), n, b"k", "u") for x in range(n)] == list(range(n))
    assert len({surrogates.keep_format(f"{x:03d}", b"k", "phone") for x in range(1000)}) == 1000
    cards = {surrogates._card(f"{x:04d}", b"k") for x in range(10_000)}
    assert len(cards) == 10_000
    assert all((surrogates.luhn(c[:-1]) == int(c[-1])) == (surrogates.luhn(f"{x:03d}") == y) for x in range(100) for y in range(10) for c in [surrogates._card(f"{x:03d}{y}", b"k")])


def test_names_stay_distinct_over_the_corpus():
    a = "abcdefghijklmnopqrstuvwxyz"
    words = [x + y for x in a for y in a] + [x + y + "a" for x in a for y in a] + ["o", "müller", "muller", "señor"]
    for gender in (None, "f", "m"):
        got = [surrogates.name_word(w, gender, b"k", apart) for w in words for apart in (False, True)]
        assert len(set(got)) == len(got)
    assert len({surrogates.name_word(x + y, None, b"k") for x in "абвгд" for y in "абвгдежз"}) == 40
    names = [f"Q{x}{y}" for x in a for y in a][:600]
    new, found = surrogates.Surrogates().replace(". ".join(f"Mr {n}" for n in names))
    assert len(found) == 600 and len(set(new.split(". "))) == 600


def test_coreference_in_every_format_and_text():
    s = surrogates.Surrogates()
    new, found = s.replace("Mr John Smith met Mrs Anna-Maria Schmidt. Dr Smith, Mr. SMITH and Mr O'Neill wrote to ann@x.com, Ann@X.com or called +1 407 555 7710, then (407) 555-7710.")
    assert [k for k, _, _ in found] == ["person"] * 5 + ["email"] * 2 + ["phone"] * 2
    m = re.match(r"Mr (\w+) (\w+) met Mrs (\w+)-(\w+) (\w+)\. Dr (\w+), Mr\. (\w+) and Mr O'(\w+) wrote to (\S+), (\S+) or called \+1 (.*), then \((\d+)\) (.*)\.$", new)
    assert m[2] == m[6] and m[7] == m[2].upper() and m[9].lower() == m[10].lower() and m[10][0].isupper()
    assert re.sub(r"\D", "", m[11]) == re.sub(r"\D", "", m[12] + m[13]) != "4075557710"
    assert m[3].endswith("a") and m[4].endswith("a") and m[1].endswith("n")
    assert not set(re.findall(r"\w{3,}", new)) & set("John Smith Anna Maria Schmidt SMITH Neill ann".split())
    assert s.replace("Mrs Smith")[0].split()[1] == m[2]  # the same family in another text
    greek, _ = s.replace("Κύριος Παπαδόπουλος")
    assert surrogates.script_of(greek.split()[1]) == "greek" and surrogates.script_of(s.replace("г-н Петров")[0].split()[1]) == "cyrillic"


def test_no_surrogate_is_an_original_of_the_text():
    s = surrogates.Surrogates()
    taken = s.of("ssn", "123-45-6789")
    new, _ = s.replace(f"123-45-6789 and {taken}")
    assert len(set(new.split(" and "))) == 2 and not set(new.split(" and ")) & {"123-45-6789", taken}
    other = s.replace("Mr Smith")[0].split()[1]
    new, _ = s.replace(f"Mr Smith, Mr {other}, Mr Smith")
    a, b, c = re.findall(r"Mr (\w+)", new)
    assert a == c and len({a, b, "Smith", other}) == 4


def test_surrogates_of_a_table(spark):
    rows = [(1, "Mr Smith", "en", "s"), (1, "Mr Smith", "en", "s"), (2, None, None, None), (3, "", "en", "s"), (4, "x " * 100_000 + "a@b.cd", "en", "s")]
    docs = clashing(spark, rows)
    out = surrogates.replace(docs)
    assert sorted(out.columns) == sorted(docs.columns) and surrogates.replace(docs, spans=False).columns == docs.columns
    got = sorted((r["doc_id"], r["text"], r["entities"]) for r in out.collect())
    assert got[0] == got[1] and got[2][1] is None and got[3][1] == "" and len(got[4][2]) == 1 and got[4][1].startswith("x x") and "a@b" not in got[4][1]


# ---- packing


def test_packing_does_not_depend_on_small_partitions(spark):
    docs = clashing(spark, [(i, "a b c d " * (3 + i * 7 % 29), "en", "s") for i in range(1200)]).repartition(200)
    got = packing.pack(docs, size=1024).collect()
    tokens = sum(r["length"] for r in got)
    assert len({r["sequence_id"] for r in got}) <= 1.02 * -(-tokens // 1024) + 1


# ---- language id


def plain_ppm(texts, order, kept):
    """Code lengths in bits of a textbook coder with exclusion; coding begins at the longest context that `kept` holds."""
    counts = defaultdict(Counter)
    for t in texts:
        b = bytes(order) + language_id.fold(t)
        for i in range(order, len(b)):
            for n in range(order + 1):
                counts[b[i - n : i]][b[i]] += 1

    def bits(text):
        b, out = bytes(order) + language_id.fold(text), 0.0
        for i in range(order, len(b)):
            n = next(n for n in range(order, -1, -1) if b[i - n : i] in kept)
            seen, p = set(), 1.0
            while True:
                own = {s: c for s, c in counts[b[i - n : i]].items() if s not in seen}
                total = sum(own.values()) + len(own)
                if b[i] in own:
                    p *= own[b[i]] / total
                    break
                if total:
                    p *= len(own) / total
                seen |= counts[b[i - n : i]].keys()
                n -= 1
                if n < 0:
                    p /= 256 - len(seen)
                    break
            out -= math.log2(p)
        return out

    return bits, counts


def test_code_lengths_equal_a_plain_coder():
    texts = {"x": ["abracadabra abba", "banana band a bandana"], "y": ["ababab cdcdcd abcd", "dcba"]}
    model = language_id.Model({k: language_id.count_grams(v) for k, v in texts.items()})
    visits = [Counter() for _ in texts]
    for seen, v in zip(visits, texts.values(), strict=True):
        for t in v:
            b = bytes(3) + language_id.fold(t)
            for i in range(3, len(b)):
                seen.update(b[i - n : i] for n in range(1, 4))
    total = sum(visits, Counter())
    kept = {c for c, n in total.items() if n >= 2} | {b""}
    for j, k in enumerate(sorted(texts)):
        bits, _ = plain_ppm(texts[k], 3, kept)
        for text in ("abracadabra", "bandana", "zebra é", "abcdabcd", "a"):
            assert model.lengths(text)[j] == pytest.approx(bits(text), rel=1e-4)


def test_language_table(spark):
    rows = [(i, f"the cat sat on the mat {i} and the dog", "en", "s") for i in range(30)] + [(100 + i, f"die katze liegt auf der matte {i} und der hund", "de", "s") for i in range(30)] + [(200, "the dog", None, "s")]
    model = language_id.fit(clashing(spark, rows), per_language=20)
    asked = [(1, None, "en", "s"), (2, "", "en", "s"), (3, "123 !", "en", "s"), (4, "der hund und die katze", "en", "s"), (4, "der hund und die katze", None, "s"), (5, "the cat " * 60_000, "de", "s")]
    got = sorted((r["doc_id"], r["lang_pred"], r["score"]) for r in language_id.predict(clashing(spark, asked), model).collect())
    assert [x[1] for x in got] == ["und", "und", "und", "de", "de", "en"] and got[3] == got[4] and all(0 <= x[2] <= 1 for x in got)


def test_languages_of_held_out_documents(spark):
    got = language_id.query(spark, "/root/testdata/sf0.01").where("held_out").join(spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "lang"), "doc_id").where("lang is not null and lang_pred <> 'und'").collect()
    assert len(got) > 100 and sum(r["lang"] == r["lang_pred"] for r in got) >= 0.98 * len(got)


# ---- importance resampling


def test_weights_and_choice_equal_brute_force(spark):
    rng = np.random.default_rng(8)
    rows = [(i, " ".join(rng.choice(["a", "b", "c", "##", "d,e"], 12 if i % 3 else 3)), "en", "s") for i in range(60)] + [(100, None, "en", "s"), (101, "", "en", "s"), (102, "long " * 30_000, "en", "s"), (5, "a b", "en", "s")]
    labels = [(i, i % 3 != 0) for i in range(0, 60, 2)] + [(4, True), (58, None)]
    cache, buckets = importance.Hashes(), 256
    f = lambda t: importance.features(t, cache, buckets)
    raw, own = np.zeros(buckets), np.zeros(buckets)
    good = {i for i, x in labels if x}
    for i, t, *_ in rows:
        np.add.at(raw, f(t), 1)
        if i in good:
            np.add.at(own, f(t), 1)
    ratio = np.log((own + 8) / (raw / raw.sum() * own.sum() + 8))
    docs, given = clashing(spark, rows), spark.createDataFrame(labels, "doc_id long, target boolean")
    got = importance.resample(docs, given, k=20, buckets=buckets).collect()
    want = Counter((i, round(float(ratio[f(t)].sum()), 6)) for i, t, *_ in rows)
    assert Counter((r["doc_id"], round(r["log_weight"], 6)) for r in got) == want
    keys = sorted((r["key"] for r in got), reverse=True)
    assert all(r["kept"] == (r["key"] >= keys[19]) for r in got)
    kept = importance.keep(docs, given, k=20, buckets=buckets)
    assert kept.columns == docs.columns and Counter(r["doc_id"] for r in kept.collect()) == Counter(r["doc_id"] for r in got if r["kept"])


# ---- mixing and the rest under clashing names


def test_operators_pass_over_columns_named_like_their_own(spark):
    rows = [(i, f"some words of text number {i} " * (1 + i % 4), "en", "a" if i % 3 else None) for i in range(40)] + [(50, None, None, None), (51, "", "en", "a"), (3, "some words of text number 3 " * 4, "en", None)]
    docs = clashing(spark, rows)
    n = len(rows)
    assert jaccard_join.join(docs).count() == n and quality_rules.statistics(docs).count() == n
    assert set(jaccard_join.one_of_each(docs).columns) == set(docs.columns)
    assert lm_scoring.score(docs, lm_scoring.F.col("doc_id") % 10 == 0).count() == n
    out = mixing.mix(docs, max_repeats=2.0, keep=docs.columns).select("_row.*")
    assert out.columns == docs.columns and n <= out.count() <= 2 * n
    assert packing.pack(docs, with_ids=True).select("doc_id").distinct().count() == n - 1


def test_base_columns_of_the_rules(spark):
    rng = np.random.default_rng(3)
    rows = [(i, " ".join(rng.choice(["a", "b", "#", "<x>", "word", "q|r"], int(rng.integers(1, 140)))), "en", "s") for i in range(40)] + [(90, None, None, None), (91, "", "en", "s"), (92, "w% " * 20_000, "en", "s")]
    got = {r["doc_id"]: r for r in quality_rules.statistics(clashing(spark, rows)).withColumn("bad", quality_rules.base_failed()).collect()} if hasattr(quality_rules, "base_failed") else None
    stats = got or {r["doc_id"]: r for r in quality_rules.statistics(clashing(spark, rows)).collect()}
    for i, t, *_ in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", t or "")
        assert (stats[i]["n_words"], stats[i]["n_symbols"]) == (len(w), len(re.findall(r"[#*$%&|<>]", t or "")))


# ---- the pipeline


def test_pipeline_equals_its_stages_by_hand(spark, tmp_path):
    pipeline = pytest.importorskip("corpus_pipeline")
    rng = np.random.default_rng(6)
    vocab = [f"word{k}" for k in range(300)]
    rows = []
    for i in range(120):
        t = "### $$$ !!! " * 30 if i % 6 == 0 else " ".join(rng.choice(vocab, 80))
        rows.append((i, t + (" Mr Brown a@b.org" if i % 5 == 1 else ""), "en", ["a", "b", None][i % 3], len(t)))
    rows += [(200 + i, rows[1 + i][1] + " tail", "en", "b", 5) for i in range(10)] + [(300, None, None, None, None), (301, "", "en", "a", 0), (7, rows[7][1], "en", "b", 1)]
    schema = "doc_id long, text string, lang string, source string, n_chars long"
    folder = str(tmp_path)
    spark.createDataFrame(rows, schema).write.parquet(os.path.join(folder, "documents.parquet"))
    spark.createDataFrame([(i, 0 if i % 6 == 0 else 1, 0) for i in range(0, 120, 2)] + [(i, 1, 0) for i in range(1, 120, 4)], "doc_id long, quality int, toxic int").write.parquet(os.path.join(folder, "labels.parquet"))
    got = pipeline.run(spark, folder).collect()
    docs = spark.read.parquet(os.path.join(folder, "documents.parquet"))
    kept = {(r["doc_id"], r["text"]) for r in pipeline.quality(spark, docs, folder).collect()}
    assert not any(i % 6 == 0 and i < 120 for i, _ in kept) and sum(i < 120 for i, _ in kept) > 80
    sets = {}
    for i, t in kept:
        w = (t or "").lower().split()
        sets.setdefault(i, set()).update(tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4)) if w)
    ids = sorted(sets)
    first = {i: i for i in ids}
    for a in ids:
        for b in ids:
            if a < b and sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b]):
                x, y = first[a], first[b]
                first = {k: min(x, y) if v in (x, y) else v for k, v in first.items()}
    s, enc = surrogates.Surrogates(), packing.encoder()
    want = {i: [*enc.encode(s.replace(t)[0] or "", allowed_special="all"), 0] for i, t in kept if first[i] == i}
    pieces, seqs = defaultdict(list), defaultdict(list)
    for r in got:
        pieces[r["doc_id"]].append(r)
        seqs[r["sequence_id"]].append((r["offset"], r["length"]))
    assert pieces.keys() == want.keys()
    for i, own in pieces.items():
        flat = [x for r in sorted(own, key=lambda r: (r["piece"], r["sequence_id"], r["offset"])) for x in r["ids"]]
        assert len(flat) % len(want[i]) == 0 and flat == want[i] * (len(flat) // len(want[i])) and 1 <= len(flat) // len(want[i]) <= 3
    for own in seqs.values():
        assert sum(n for _, n in own) <= 2048 and sorted(own)[0][0] == 0
    empty = spark.createDataFrame([], schema)
    for _, stage in pipeline.STAGES:
        empty = stage(spark, empty, folder)
    assert empty.count() == 0
