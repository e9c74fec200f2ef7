import random

import numpy as np
import pyarrow as pa

from rangecut.llm import jaccard_join


def texts():
    rng = random.Random(3)
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(5))
    out = []
    shared = " ".join(word() for _ in range(60))
    for g in range(12):
        base = [word() for _ in range(150)]
        for _ in range(rng.choice([1, 2, 6])):
            copy = list(base)
            for _ in range(rng.choice([0, 1, 3, 6])):
                copy[rng.randrange(150)] = word()
            out.append(" ".join(copy))
        out.append(" ".join(word() for _ in range(100)) + " " + shared)
    chain = [word() for _ in range(200)]
    for _ in range(6):  # each near the last, the ends far apart
        chain = chain[6:] + [word() for _ in range(6)]
        out.append(" ".join(chain))
    return [*out, out[0], out[0], "", None, "  \n", "one two", "one  two", "x"]


def brute(rows, least=0.8):
    sets = []
    for _, t in rows:
        w = (t or "").split()
        sets.append({tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set())
    n = len(rows)
    near = lambda a, b: (not a and not b) or (a | b and len(a & b) >= least * len(a | b))
    linked = [[j for j in range(n) if j != i and near(sets[i], sets[j])] for i in range(n)]
    label = list(range(n))
    for _ in range(n):
        for i in range(n):
            for j in linked[i]:
                label[i] = label[j] = min(label[i], label[j])
    return linked, label


def test_links_and_classes_match_brute_force(spark):
    rows = list(enumerate(texts()))
    docs = spark.createDataFrame([(*r, "z") for r in rows], "doc_id long, text string, node string")
    linked, label = brute(rows)
    got = {r.doc_id: r for r in jaccard_join.links(docs).collect()}
    assert {i: r.n_links for i, r in got.items()} == {i: len(x) for i, x in enumerate(linked)}
    assert {i: r.class_id for i, r in got.items()} == dict(enumerate(label))
    kept = jaccard_join.keep_one(docs)
    assert kept.columns == docs.columns
    assert sorted(r.doc_id for r in kept.collect()) == sorted(set(label))


def test_small_buckets_split_and_large_ones_go_in_blocks(spark, monkeypatch):
    rows = list(enumerate(texts()))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    monkeypatch.setattr(jaccard_join, "BUCKET", 4)
    monkeypatch.setattr(jaccard_join, "LEVELS", 1)
    linked, label = brute(rows)
    got = {r.doc_id: (r.n_links, r.class_id) for r in jaccard_join.links(docs).collect()}
    assert got == {i: (len(linked[i]), label[i]) for i in range(len(rows))}
    monkeypatch.setattr(jaccard_join, "LEVELS", 3)
    split = {r.doc_id: r.n_links for r in jaccard_join.links(docs).collect()}
    total = sum(map(len, linked))
    assert 0.9 * total <= sum(split.values()) <= total


def test_repeated_rows_and_null_ids_leave_one(spark):
    text = " ".join(f"w{i}" for i in range(30))
    docs = spark.createDataFrame([(1, text), (1, text), (None, text), (None, "other words that nobody else has said"), (2, text + " end")], "doc_id long, text string")
    kept = jaccard_join.keep_one(docs).collect()
    assert sorted((r.doc_id is None, r.doc_id or 0) for r in kept) == [(False, 1), (True, 0)]
    assert jaccard_join.keep_one(docs.where("false")).count() == 0


def test_intersections_and_forest():
    rng = np.random.default_rng(1)
    sets = [np.unique(rng.integers(0, 40, n)) for n in (5, 20, 0, 30, 12)]
    tokens = pa.array([s.tolist() for s in sets], pa.list_(pa.int64()))
    a, b = np.array([0, 0, 1, 1, 2]), np.array([1, 3, 3, 4, 3])
    assert jaccard_join.intersections(tokens, a, b).tolist() == [len(np.intersect1d(sets[i], sets[j])) for i, j in zip(a, b)]
    assert jaccard_join.forest(7, np.array([5, 2, 3]), np.array([3, 6, 4])).tolist() == [0, 1, 2, 3, 3, 3, 2]


def test_components(spark):
    edges = [(i, i + 1) for i in range(1, 40)] + [(100, 103), (103, 101)]
    got = {r.node: r.root for r in jaccard_join.components(spark.createDataFrame(edges, "node long, root long")).collect()}
    assert got == {**{i: 1 for i in range(2, 41)}, 101: 100, 103: 100}


def test_below_its_recall_the_join_is_done_exactly(spark, monkeypatch):
    """With a recall that no run reaches, the pairs come from shared prefixes; none may be missing."""
    monkeypatch.setattr(jaccard_join, "RUNS", 1)
    monkeypatch.setattr(jaccard_join, "DOUBLINGS", 0)
    monkeypatch.setattr(jaccard_join, "BUCKET", 4)  # prefixes' buckets are dealt into blocks, too
    rows = list(enumerate(texts()))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    linked, label = brute(rows)
    got = {r.doc_id: (r.n_links, r.class_id) for r in jaccard_join.links(docs, recall=1.1).collect()}
    assert got == {i: (len(linked[i]), label[i]) for i in range(len(rows))}
