import math

from rangecut.llm import toxicity

CALM = [f"This is sentence {i} about gardens. It goes on for a while, as they do." for i in range(60)]
RUDE = [f"This is sentence {i} about blorgish{'abcdef'[i % 6]} gardens. It goes on for a while, as they do." for i in range(60)]


def model():
    return toxicity.train([(t, 0) for t in CALM] + [(t, 1) for t in RUDE])


def test_learns_from_document_labels_and_finds_the_sentence():
    m = model()
    assert max(m.score(t) for t in CALM) < 0.5 < min(m.score(t) for t in RUDE)
    # A form that training never saw.
    text = "This goes on. What a blorgishly thing. It is about gardens."
    assert m.score(text) > m.score(text.replace("blorgishly", "lovely")) + 0.2
    assert [s for s, _ in m.locate(RUDE[0])] == ["This is sentence 0 about blorgisha gardens"]


def test_score_is_the_noisy_or_of_all_sentences():
    m = model()
    for text in (*CALM[:3], *RUDE[:3], "", "one", "a. b. c.\nd"):
        logits = m.sentence_logits(toxicity.SENTENCE.split(text))
        brute = 1 - math.prod(1 - 1 / (1 + math.exp(-x)) for x in logits)
        assert math.isclose(m.score(text), brute, abs_tol=1e-9)


def test_harmless_sentences_dont_add_up():
    assert model().score("Nothing to see here. " * 3000) < 0.5


def test_frames(spark):
    docs = spark.createDataFrame([(1, RUDE[0], "k"), (2, CALM[0], "k"), (None, None, None), (4, "", "k"), (1, RUDE[0], "k")], "doc_id long, text string, score string")
    m = model()
    assert sorted((r.doc_id or 0, r.score > 0.5) for r in toxicity.score(docs, m).collect()) == [(0, False), (1, True), (1, True), (2, False), (4, False)]
    kept = toxicity.keep(docs, m)
    assert kept.columns == docs.columns and kept.count() == 3
    assert toxicity.locate(docs, m).count() == 2
    assert toxicity.keep(docs.where("false"), m).count() == 0
    assert toxicity.fit(docs, spark.createDataFrame([(1, 1)], "doc_id long, toxic int")) is None


def test_fit_on_executors_equals_training_in_memory(spark):
    texts = [*CALM, *RUDE, "", RUDE[0] * 50]
    labels = [0] * 60 + [1] * 60 + [0, 1]
    docs = spark.createDataFrame(list(enumerate(texts)) + [(None, "x"), (500, None)], "doc_id long, text string")
    known = spark.createDataFrame(list(enumerate(labels)) + [(None, 1)], "doc_id long, toxic int")
    whole = toxicity.train(list(zip(texts, labels, strict=True)))
    found = toxicity.fit(docs, known)
    assert found.weights.keys() == whole.weights.keys() and len(whole.weights) > 0
    assert all(math.isclose(w, whole.weights[t], abs_tol=1e-9) for t, w in found.weights.items())


def test_very_long_texts_and_ties(spark):
    m = model()
    long = "Calm words here. " * 40_000 + RUDE[0]
    docs = spark.createDataFrame([(1, long, 0), (1, long, 0), (2, long[:-len(RUDE[0])], 0)], "doc_id long, text string, score int")
    assert [(r.doc_id, r.score > 0.5) for r in toxicity.score(docs, m).orderBy("doc_id").collect()] == [(1, True), (1, True), (2, False)]
