import numpy as np
import pytest

from cutfold.llm import language_id, toxicity


def test_language_on_held_out_rows(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    from pyspark.sql import functions as F

    from cutfold.llm._common import held_out

    out = language_id.predict_language(docs, language_id.fit(docs, per_language=60), F.col("lang"), held_out().alias("h")).where("h")
    right, n = out.agg(F.avg((F.col("lang") == F.col("lang_pred")).cast("double")), F.count(F.lit(1))).first()
    assert n > 150 and right > 0.97


def test_language_edges(spark, docs, none, rows):
    model = language_id.fit(docs)
    out = language_id.predict_language(docs, model, docs["doc_id"]).collect()
    assert len(out) == len(rows)
    und = {r.doc_id for r in out if r.lang_pred == "und"}
    assert und == {3, 4, 5, 6}
    assert all(0 <= r.score <= 1 for r in out) and all(r.score == 0 for r in out if r.doc_id in und)
    assert language_id.fit(none) is None
    assert language_id.predict_language(none, None, none["doc_id"]).count() == 0
    kept = language_id.reject_unknown(docs)
    assert kept.dtypes == docs.dtypes and kept.count() == len(rows) - 4


def test_families_and_pairs():
    x, ok = language_id.features(["hello there", "guten tag", "bonjour le monde", "hola el mundo"] * 3)
    assert ok.all() and np.allclose(np.linalg.norm(x, axis=1), 1)
    h = language_id.Hierarchy(x, ["en", "de", "fr", "es"] * 3)
    assert h.families == ["germanic", "romance"] and set(h.pairs) == {("de", "en"), ("es", "fr")}
    assert h.predict(x)[0] == ["en", "de", "fr", "es"] * 3


def test_same_text_same_answer(docs):
    out = [(r.lang_pred, r.score) for r in language_id.predict_language(docs, language_id.fit(docs), docs["doc_id"]).where("doc_id = 0").collect()]
    assert len(out) == 2 and out[0] == out[1]


@pytest.fixture(scope="module")
def biased():
    """Toxic rows name a group more often than others, and hold a slur word."""
    rng = np.random.default_rng(0)
    sets, y = [], []
    for i in range(600):
        toxic = i % 4 == 0
        words = {f"w{j}" for j in rng.integers(0, 80, 20)}
        if rng.random() < (0.7 if toxic else 0.1):
            words.add("muslims")
        if toxic and rng.random() < 0.9:
            words.add("rotten")
        sets.append(words)
        y.append(float(toxic))
    return sets, np.array(y)


def test_swaps_flatten_identity_terms(biased):
    sets, y = biased
    share = np.ones(len(y))
    free = toxicity.train(sets, y, share, swap=0.0)
    held = toxicity.train(sets, y, share, swap=2.0)
    gap = lambda m: abs(m.weights["muslims"] - m.weights.get("christians", 0.0))
    assert gap(held) < 0.3 * gap(free)
    assert abs(held.weights["muslims"]) < 0.5 * abs(free.weights["muslims"])
    assert held.weights["rotten"] > 1


def test_toxicity_on_held_out_rows(spark):
    base = "/root/testdata/sf0.1"
    docs, labels = spark.read.parquet(f"{base}/documents.parquet"), spark.read.parquet(f"{base}/labels.parquet")
    out = toxicity.score_toxicity(docs, toxicity.fit(docs, labels)).join(labels, "doc_id").where("held_out").toPandas()
    hit = out.predicted == 1
    assert out.toxic[hit].mean() > 0.9 and out.predicted[out.toxic == 1].mean() > 0.85


def test_toxicity_with_few_labels():
    rng = np.random.default_rng(3)
    sets = [{f"w{j}" for j in rng.integers(0, 3000, 200)} | ({f"bad{rng.integers(0, 2)}"} if i % 10 == 0 else set()) for i in range(300)]
    y = np.array([float(i % 10 == 0) for i in range(300)])
    model = toxicity.train(sets[:200], y[:200], np.ones(200))
    found = np.array([model.score(" ".join(s)) >= 0.3 for s in sets[200:]])
    assert found[y[200:] == 1].all() and found[y[200:] == 0].mean() < 0.05


def test_toxicity_edges(spark, docs, none, rows):
    labels = spark.createDataFrame([(0, 0), (1, 1), (1, 1), (None, 1), (7, None), (9, 1), (10, 0)], "doc_id long, toxic int")
    model = toxicity.fit(docs, labels)
    out = toxicity.score_toxicity(docs, model).collect()
    assert len(out) == len(rows) and all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.3) for r in out)
    empty = toxicity.fit(docs, labels.limit(0))
    assert all(r.score < 1e-9 for r in toxicity.score_toxicity(docs, empty).collect())
    assert toxicity.score_toxicity(none, model).count() == 0
