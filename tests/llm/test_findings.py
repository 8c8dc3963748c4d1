"""Cases that reviews found in the operators."""

import pytest

from passagekit.llm import surrogates as P


@pytest.mark.parametrize("text, gone", [("Dr Smith came", "Smith"), ("says Sir John Barker", "Barker"), ("Lady Jane Grey", "Grey"), ("Prof. Weber", "Weber"), ("Don Quijote", "Quijote"), ("Mr J. Barker", "Barker"), ("Mrs J.R. Barker", "Barker"), ("Herr von Braun", "Braun"), ("Herr Dr. Weber", "Weber"), ("ring +12345", "+12345"), ("to GB29NWBKABCDEFGH now", "GB29NWBKABCDEFGH")])
def test_entities_that_stand_alone_in_a_text_are_replaced(text, gone):
    out, found = P.Surrogates().replace(text)
    assert gone not in out and len(found) == 1


def test_every_pattern_passes_the_first_look():
    """The first look may let more through, and stops no text that holds an entity."""
    titles = [*P._FEMALE, *P._MALE, *P._NEUTRAL]
    some = ["a@b.c", "password: abcdef", "AKIA" + "A" * 16, "ghp_" + "a" * 36, "1.2.3.4", "+1 23 45", "(123) 456-7890", "123.456.7890", "123-45-6789", "4111111111111111", "AB12CDEFGHIJ", *(f"{t} Abel" for t in titles), *(f"{t}. Abel" for t in titles)]
    assert all(P._ALL.search(t) and P.may_hold(t) for t in some)


def test_private_data_of_the_pipeline_covers_texts_with_one_titled_name(spark):
    import corpus_pipeline

    docs = spark.createDataFrame([(1, "Dr Smith came", "en", "s", 13), (2, "nothing here", "en", "s", 12), (3, None, "en", "s", None)], "doc_id long, text string, lang string, source string, n_chars long")
    got = {r["doc_id"]: r for r in corpus_pipeline.private_data(spark, docs, "").collect()}
    assert "Smith" not in got[1]["text"] and got[1]["n_chars"] == len(got[1]["text"])
    assert got[2]["text"] == "nothing here" and got[3]["text"] is None


def test_every_labelled_target_document_is_counted(spark):
    import numpy as np
    from pyspark.sql import functions as F

    from passagekit.llm import importance

    n = 24_000
    docs = spark.range(n).select(F.col("id").alias("doc_id"), F.concat(F.lit("w"), F.col("id") % 7).alias("text"))
    labels = docs.select("doc_id", (F.col("doc_id") % 7 != 0).alias("target"))
    ratio, share = importance.fit(docs, labels, buckets=64)
    raw, own, cache = np.zeros(64), np.zeros(64), importance.Hashes()
    for w in range(7):
        at = importance.features(f"w{w}", cache, 64)
        raw[at] += len(range(w, n, 7))
        own[at] += len(range(w, n, 7)) * (w > 0)
    want = np.log((own + 8.0) / (raw / raw.sum() * own.sum() + 8.0))
    assert np.allclose(ratio, want, atol=1e-12) and abs(share - own.sum() / n) < 1e-12
