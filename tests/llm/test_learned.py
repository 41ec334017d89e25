import random

import numpy as np
from pyspark.sql import functions as F

from gsample.llm import language_codes, toxicity_pu
from gsample.llm.folds import held_out, learns
from tests.llm.conftest import sentence


def test_pu_scores_held_out_rows(spark):
    rng = random.Random(1)
    rows = []
    for k in range(1200):
        toxic = k % 6 == 0
        w = sentence(rng, rng.randint(20, 200)).split()
        if toxic:
            for _ in range(4):
                w.insert(rng.randrange(len(w)), rng.choice(["vilescum", "dreckling", "grimoaf"]))
        rows.append((k, " ".join(w), int(toxic)))
    docs = spark.createDataFrame([(k, t) for k, t, _ in rows], "doc_id bigint, text string")
    labels = spark.createDataFrame([(k, y) for k, _, y in rows if k % 3 == 0], "doc_id bigint, toxic int")
    model = toxicity_pu.fit(docs, labels, learns("doc_id"))
    got = {r["doc_id"]: r["score"] for r in toxicity_pu.score(docs, model).collect()}
    held = {r["doc_id"] for r in docs.where(held_out("doc_id")).collect()}
    right = sum((got[k] >= 0.5) == bool(y) for k, _, y in rows if k in held)
    assert right / len(held) > 0.97 and all(0 <= s <= 1 for s in got.values())
    again = toxicity_pu.fit(docs.repartition(9), labels, learns("doc_id"))
    assert np.allclose(model.w, again.w)


def test_pu_of_odd_rows(odd, no_docs, spark):
    labels = spark.createDataFrame([(0, 1), (3, 1), (6, 0), (9, None), (None, 1)], "doc_id bigint, toxic int")
    for model in (toxicity_pu.fit(odd, labels, learns("doc_id")), toxicity_pu.fit(odd, labels.where("false"), learns("doc_id")), toxicity_pu.fit(no_docs, labels, learns("doc_id"))):
        out = toxicity_pu.score(odd, model).collect()
        assert len(out) == odd.count() and all(0 <= r["score"] <= 1 for r in out)
        assert toxicity_pu.drop_toxic(odd, model).columns == odd.columns
        assert toxicity_pu.score(no_docs, model).isEmpty()


def test_codewords_tell_languages_apart():
    for n in (2, 3, 4, 7, 12):
        m = language_codes.codewords(n)
        assert m.shape[0] == n and len({tuple(r) for r in m.tolist()}) == n
    assert language_codes.codewords(4).shape[1] == 7


def test_languages_of_held_out_rows(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    found = language_codes.predict(docs, language_codes.fit(docs, learns("doc_id")))
    joined = found.join(docs.select("doc_id", "lang"), "doc_id").where(held_out("doc_id"))
    share = joined.agg(F.avg((F.col("lang") == F.col("lang_pred")).cast("double"))).first()[0]
    assert share > 0.9


def test_languages_of_odd_rows(odd, no_docs):
    for model in (language_codes.fit(odd, learns("doc_id")), language_codes.fit(no_docs, learns("doc_id"))):
        out = {r["doc_id"]: r for r in language_codes.predict(odd, model).collect()}
        text = {r["doc_id"]: r["text"] for r in odd.collect()}
        for i, r in out.items():
            if i is not None:
                letters = any(c.isalpha() for c in text[i] or "")
                assert (r["lang_pred"] == "und") == (not letters or model is None)
                assert 0 <= r["score"] <= 1
        kept = language_codes.drop_undetermined(odd, model)
        assert kept.columns == odd.columns
        assert not any(r["text"] is None or r["text"].strip() == "" for r in kept.collect())
    assert language_codes.predict(no_docs, model).isEmpty()
