import itertools
import re
import zlib
from collections import Counter

import numpy as np
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from rangecut.llm import line_quality, linechain, quality_rules
from rangecut.llm.catalog import quality_queries


def random_parts(seed):
    rng = np.random.default_rng(seed)
    return [rng.normal(size=(n, 2)) for n in (1, 4, 2, 6, 1)], rng.normal(size=(2, 2))


def path_score(e, tr, path):
    return sum(e[t, k] for t, k in enumerate(path)) + sum(tr[a, b] for a, b in zip(path, path[1:]))


def test_viterbi_and_marginals_match_all_paths():
    for seed in range(5):
        parts, tr = random_parts(seed)
        decoded, (good, log_z, expected) = linechain.viterbi(parts, tr), linechain.marginals(parts, tr)
        total = np.zeros((2, 2))
        for e, d, g, z in zip(parts, decoded, good, log_z):
            paths = list(itertools.product((0, 1), repeat=len(e)))
            scores = np.array([path_score(e, tr, p) for p in paths])
            assert tuple(d) == paths[int(scores.argmax())]
            weight = np.exp(scores - np.logaddexp.reduce(scores))
            assert np.isclose(z, np.logaddexp.reduce(scores))
            assert np.allclose(g, [sum(w for w, p in zip(weight, paths) if p[t]) for t in range(len(e))])
            for w, p in zip(weight, paths):
                for a, b in zip(p, p[1:]):
                    total[a, b] += w
        assert np.allclose(total, expected)


WORD = re.compile("[^\x20\x09-\x0d]+")


def brute_counts(text):
    words = WORD.findall(text)
    windows = Counter(tuple(words[i : i + 3]) for i in range(len(words) - 2))
    inside = {j for i in range(len(words) - 2) if windows[tuple(words[i : i + 3])] > 1 for j in (i, i + 1, i + 2)}
    lines = text.split("\n")
    dup = sum(1 for i, x in enumerate(lines) if WORD.search(x) and x in lines[:i])
    return len(words), sum(map(len, words)), sum(c in "#*$%&|<>" for c in text), dup, len(inside)


@settings(max_examples=200, deadline=None)
@given(st.text(alphabet="ab# \n\t\x0b\x0c\r\x1c\x85\u00a0é|", max_size=60))
def test_base_counts(text):
    assert quality_rules.base_counts(text) == brute_counts(text)


GOOD = "The quick brown fox went over the hills and saw what there was to see, then it came home again.\n" * 1
DOCS = [(" ".join(f"word{i}x{j}" for j in range(60)) + ".\nMore prose follows here, as it should.", 1) for i in range(30)] + [(" ".join(f"BUY{i}{j}!!" for j in range(60)) + "\n$$$ ### %%% ***", 0) for i in range(30)]


def fixture(spark):
    docs = spark.createDataFrame([(i, t, "x") for i, (t, _) in enumerate(DOCS)] + [(900, None, "x"), (901, "", "x"), (None, "no id", "x"), (902, "w " * 30_000, "x")], "doc_id long, text string, kept string")
    labels = spark.createDataFrame([(i, y) for i, (_, y) in enumerate(DOCS)] + [(None, 1), (7, None)], "doc_id long, quality int")
    return docs, labels


def test_rules_keep_prose_and_drop_junk(spark):
    docs, labels = fixture(spark)
    chain = quality_rules.fit(docs, labels)
    out = {r.doc_id: r for r in quality_rules.judge(docs, chain).collect()}
    assert len(out) == docs.count()
    assert all(out[i].kept == bool(y) for i, (_, y) in enumerate(DOCS))
    assert out[900].n_words == 0 and out[900].base_failed and not out[900].kept
    assert out[902].n_repeat_words == 30_000 and out[902].base_failed
    kept = quality_rules.keep(docs, chain)
    assert kept.columns == docs.columns and kept.count() == 30


def test_classifier_separates_and_scores_everything(spark):
    docs, labels = fixture(spark)
    out = {r.doc_id: r.score for r in line_quality.score(docs, line_quality.fit(docs, labels)).collect()}
    assert min(out[i] for i, (_, y) in enumerate(DOCS) if y) > 0.5 > max(out[i] for i, (_, y) in enumerate(DOCS) if not y)
    assert all(0 <= s <= 1 for s in out.values()) and len(out) == docs.count()


def test_without_labels_or_rows(spark):
    docs, labels = fixture(spark)
    assert quality_rules.fit(docs, labels.where("false")) is None
    assert line_quality.score(docs, None).where("score != 0.5").count() == 0
    assert quality_rules.judge(docs.where("false"), None).count() == 0


def test_training_sees_the_end_of_long_texts():
    clean = [f"The river number {i} ran past the old mill and out to the sea, as it always had." for i in range(220)]
    junk = [f"$$$ ### {i} %%% ***" for i in range(220)]
    sample = [("\n".join(clean), 1)] * 5 + [("\n".join(clean + junk), 0)] * 5
    chain = linechain.train(sample, neighbours=False)
    labels = linechain.viterbi([chain.scores("\n".join(clean + junk))], chain.transition)[0]
    assert labels[:200].mean() > 0.9 and labels[-200:].mean() < 0.1


def test_gradient_of_the_likelihood():
    rng = np.random.default_rng(3)
    lengths = np.array([3, 1, 5, 2])
    learned = linechain.Sequences(rng.normal(size=(11, 4)), rng.integers(0, 2, 11), lengths, rng.uniform(0.5, 2, 4))
    theta = rng.normal(size=12)
    value, gradient = learned.likelihood(theta, 0.1)
    for i in range(len(theta)):
        step = np.zeros(12)
        step[i] = 1e-5
        slope = (learned.likelihood(theta + step, 0.1)[0] - learned.likelihood(theta - step, 0.1)[0]) / 2e-5
        assert np.isclose(slope, gradient[i], atol=1e-6)
    # The value itself, over all label sequences.
    e, tr, at, total = theta[:8].reshape(4, 2), theta[8:].reshape(2, 2), 0, -0.05 * theta @ theta
    for n, w in zip(lengths, learned.weight):
        part, y = learned.rows[at : at + n] @ e, learned.labels[at : at + n]
        every = [path_score(part, tr, p) for p in itertools.product((0, 1), repeat=int(n))]
        total += w * (path_score(part, tr, tuple(y)) - np.logaddexp.reduce(every))
        at += n
    assert np.isclose(value, total)


def prose(k):
    return f"The river number {k} ran past the old mill and out to the sea, as it always had."


def junk(k):
    return f"$$$ {k} ### BUY %%% NOW*** {k}!!"


def mixed_sample():
    """Bad documents hold good lines too; nothing says which."""
    good = [("\n".join(prose(10 * d + k) for k in range(8)), 1) for d in range(40)]
    bad = [("\n".join([prose(d)] * (d % 4) + [junk(10 * d + k) for k in range(6)] + [prose(d + 7)]), 0) for d in range(40)]
    return good + bad


def test_lines_of_mixed_texts_are_told_apart():
    for neighbours in (False, True):
        chain = linechain.train(mixed_sample(), neighbours)
        text = "\n".join([prose(1), prose(2), prose(3), junk(1), junk(2), junk(3), prose(4), prose(5)])
        assert linechain.viterbi([chain.scores(text)], chain.transition)[0].tolist() == [1, 1, 1, 0, 0, 0, 1, 1]
        p = linechain.marginals([chain.scores(text)], chain.transition)[0][0]
        assert p[:3].min() > 0.5 > p[3:6].max()


def test_transitions_change_labels():
    chain = linechain.train(mixed_sample(), False)
    assert chain.transition[0, 0] + chain.transition[1, 1] > chain.transition[0, 1] + chain.transition[1, 0]
    # A line that says nothing takes its neighbours' side, and only through the transitions.
    clear = np.log(np.array([[0.02, 0.98]]))
    vague = np.array([[0.05, 0.0]])
    e = np.concatenate([clear, vague, clear])
    assert linechain.viterbi([e], chain.transition)[0].tolist() == [1, 1, 1]
    assert linechain.viterbi([e], np.zeros((2, 2)))[0].tolist() == [1, 0, 1]


def test_worst_line_of_a_bad_document_stays_bad():
    rows = np.array([[1.0, 0.0], [1.0, 0.1], [1.0, 0.0], [1.0, 0.0]])
    labels = linechain.line_labels(rows, np.array([0, 0, 1, 1]), np.array([1, 0]), 1e-3)
    assert labels[:2].tolist() == [1, 1] and labels[2:].min() == 0


def test_scores_never_fall_with_more_good_text():
    model = line_quality.train(mixed_sample())
    scores = line_quality.score_texts(["\n".join([prose(k) for k in range(n)] + [junk(k) for k in range(8 - n)]) for n in range(9)], model)
    assert scores == sorted(scores) and scores[0] < 0.5 < scores[-1]


def test_registered_queries(spark, tmp_path):
    """The contract's columns over nulls, empties, long texts, repeated rows and clashing names."""
    docs, labels = fixture(spark)
    odd = docs.withColumn("score", F.lit("x")).withColumn("n_words", F.lit(-1)).withColumn("found", F.lit(0))
    odd.unionByName(odd.where("doc_id = 3")).write.parquet(str(tmp_path / "documents.parquet"))
    labels.withColumn("toxic", F.lit(0)).write.parquet(str(tmp_path / "labels.parquet"))
    rules = quality_queries.op7_quality_rules(spark, str(tmp_path))
    assert {"doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept"} <= set(rules.columns)
    texts = {r.doc_id: r.text for r in docs.collect()}
    rows = rules.collect()
    assert len(rows) == docs.count() + 1
    for r in rows:
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == brute_counts(texts[r.doc_id] or "") if r.doc_id != 902 else r.n_words == 30_000
        assert r.base_failed == (r.n_words < 50 or 100 * r.n_repeat_words > 50 * r.n_words)
        assert not (r.kept and r.base_failed)
    scored = quality_queries.op9_quality_classifier(spark, str(tmp_path))
    assert dict(scored.dtypes) == {"doc_id": "bigint", "held_out": "boolean", "score": "double", "predicted": "int"}
    for r in scored.collect():
        assert r.held_out == (r.doc_id is None or zlib.crc32(str(r.doc_id).encode()) % 3 == 1)
        assert 0 <= r.score <= 1 and r.predicted == (r.score >= 0.5)
        if r.doc_id is not None and r.doc_id < len(DOCS):
            assert r.predicted == DOCS[r.doc_id][1]
    spark.createDataFrame([], odd.schema).write.parquet(str(tmp_path / "none" / "documents.parquet"))
    labels.where("false").write.parquet(str(tmp_path / "none" / "labels.parquet"))
    for query in quality_queries.QUERIES.values():
        assert query(spark, str(tmp_path / "none")).count() == 0
