import numpy as np
from hypothesis import given, settings
from hypothesis import strategies as st

from rangecut.llm import mixing


@settings(max_examples=100, deadline=None)
@given(st.lists(st.integers(0, 500), min_size=1, max_size=12))
def test_targets(sizes):
    weights = [(5, 2, 1)[i % 3] for i in range(len(sizes))]
    target = mixing.targets_of(sizes, weights, 1.5 * sum(sizes), 2)
    assert all(t <= 2 * s + 1e-6 for t, s in zip(target, sizes))
    assert abs(sum(target) - 1.5 * sum(sizes)) < 1e-6 * max(1, sum(sizes))
    free = [t / w for t, w, s in zip(target, weights, sizes) if t < 2 * s - 1e-6]
    assert not free or max(free) - min(free) < 1e-6 * max(1, max(free))
    # A source at its limit would get more, were there none.
    assert all(t / w <= max(free) + 1e-6 for t, w in zip(target, weights) if free)


def test_permutation():
    for n in (1, 2, 3, 7, 64, 1000):
        for key in (0, 5):
            out = mixing.permuted(np.arange(n), np.full(n, n), np.full(n, key))
            assert sorted(out) == list(range(n))
            assert mixing.unpermuted(out, np.full(n, n), np.full(n, key)).tolist() == list(range(n))


def test_draws_end_at_the_slots():
    slots = [1000, 0, 37, 512]
    drawn = list(mixing.draw_shards(slots, 100, 3))
    assert sum(drawn).tolist() == slots and all(d.sum() == 100 for d in drawn[:-1])


def documents(spark):
    rows = [(i, f"s{i % 4}" if i % 9 else None, " ".join(f"w{i}_{j}" for j in range(i % 50))) for i in range(400)]
    rows += [(None, "s1", "no id at all"), (7, "s1", "twice the same words"), (7, "s1", "twice the same words"), (8, "s2", None)]
    return spark.createDataFrame([(*r, 1) for r in rows], "doc_id long, source string, text string, n_chars long")


def test_taken_words(spark):
    docs = documents(spark)
    rows = mixing.taken_words(docs, (5, 2, 1), 1.5, 2).collect()
    assert len(rows) == docs.count()
    assert all(0 <= r.taken <= 2 * r.size for r in rows)
    by = {}
    for r in rows:
        by.setdefault((r.source_size, r.target), []).append(r.taken)
    for (size, target), taken in by.items():
        assert abs(sum(taken) - target) < 1 + 1e-6  # the target's whole words
    again = mixing.taken_words(docs.repartition(7), (5, 2, 1), 1.5, 2).collect()
    key = lambda r: (r.doc_id is None, r.doc_id or 0, r.size, r.taken)
    assert sorted(map(key, rows)) == sorted(map(key, again))


def test_documents_of_the_mix_hold_the_taken_words(spark):
    docs = documents(spark)
    taken = {}
    for r in mixing.taken_words(docs, (5, 2, 1), 1.5, 2).collect():
        taken[r.doc_id] = taken.get(r.doc_id, 0) + r.taken
    out = mixing.mixed_documents(docs, (5, 2, 1), 1.5, 2)
    assert out.columns == docs.columns
    got = {}
    for r in out.collect():
        assert r.n_chars == len(r.text)
        got[r.doc_id] = got.get(r.doc_id, 0) + len(r.text.split())
    assert got == {k: v for k, v in taken.items() if v}


def test_cut_out():
    text = " a  b\nc d\te "
    assert mixing.cut_out(text, [(0, 2), (2, 3)]) == [text]
    assert mixing.cut_out(text, [(3, 1), (0, 2)]) == ["a  b", "d"]


def test_empty(spark):
    assert mixing.taken_words(documents(spark).where("false"), (5, 2, 1), 1.5, 2).count() == 0


@settings(max_examples=200, deadline=None)
@given(st.integers(1, 5000), st.floats(0, 2), st.integers(0, 50))
def test_slots_take_the_whole_words_of_the_target(size, share, number):
    target = share * size
    slots, last = mixing.slots_for(number, size, target, 7)
    blocks = -(-size // mixing.BLOCK)
    drawn = mixing.permuted(np.arange(slots) % blocks, np.full(slots, blocks), np.full(slots, number + 7_000_021)) if slots else np.empty(0, int)
    lengths = np.where(drawn == blocks - 1, size - (blocks - 1) * mixing.BLOCK, mixing.BLOCK)
    if slots:
        lengths[-1] = min(lengths[-1], last)
    assert lengths.sum() == int(target)
    assert slots <= 2 * blocks


def test_rows_of_one_id_and_text_keep_their_columns(spark):
    text = " ".join(f"word{i}" for i in range(60))
    rows = [(1, text, "a", lang) for lang in ("en", "fr", "de")] + [(1, text, "b", "es"), (2, text, None, "it")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string, lang string")
    out = mixing.mixed_documents(docs, (1,), 2.0, 2).collect()
    words = {}
    for r in out:
        words[r.source, r.lang] = words.get((r.source, r.lang), 0) + len(r.text.split())
    assert words == {("a", "en"): 120, ("a", "fr"): 120, ("a", "de"): 120, ("b", "es"): 120, (None, "it"): 120}
