"""Every registered query of the training-data operators, and the pipeline, over the smallest tables."""

import binascii
import struct
import sys
from collections import Counter, defaultdict
from pathlib import Path

import numpy as np
import pyarrow.parquet as pq
import pytest

import __spark_entry__ as entry

SF = "/root/testdata/sf0.001"
COLUMNS = {
    "op1_chat_format": "conv_id bigint, n_turns bigint, turns_sha256 string, loss_chars bigint, loss_sha256 string, formatted_chars bigint",
    "op2_nn_descent": "query_id bigint, rank int, vec_id bigint, score double",
    "op3_toxicity": "doc_id bigint, held_out boolean, score double, predicted int",
    "op4_pattern_packing": "doc_id bigint, piece int, start bigint, length bigint, ids_crc32 bigint, sequence_id bigint, offset bigint",
    "op5_source_mixing": "doc_id bigint, size bigint, source_size bigint, target double, taken bigint",
    "op6_url_filter": "page_id bigint, host string, path string, rule string, verdict string",
    "op7_quality_rules": "doc_id bigint, n_words bigint, word_chars bigint, n_symbols bigint, n_dup_lines bigint, n_repeat_words bigint, base_failed boolean, kept boolean",
    "op8_html_extract": "page_id bigint, url string, text string, n_chars bigint",
    "op9_quality_classifier": "doc_id bigint, held_out boolean, score double, predicted int",
}


def table(name):
    return pq.read_table(f"{SF}/{name}.parquet").to_pylist()


def token_ids(texts):
    sys.path.insert(0, "/opt/tokenizers")
    public_tokenizers = pytest.importorskip("public_tokenizers")
    from tokenizers import Tokenizer

    encoder = Tokenizer.from_file(str(public_tokenizers.path("byte_bpe_50k.json")))
    return [e.ids + [0] for e in encoder.encode_batch(texts, add_special_tokens=False)]


@pytest.fixture(scope="module")
def results(spark):
    held = {}

    def get(name):
        if name not in held:
            out = entry.queries()[name](spark, SF)
            held[name] = (dict(out.dtypes), out.collect())
        return held[name]

    return get


@pytest.mark.parametrize("name", COLUMNS)
def test_columns(results, name):
    found, _ = results(name)
    want = dict(c.split() for c in COLUMNS[name].split(", "))
    assert {c: found.get(c) for c in want} == want


@pytest.mark.parametrize("name,of", [("op3_toxicity", "documents"), ("op5_source_mixing", "documents"), ("op7_quality_rules", "documents"), ("op9_quality_classifier", "documents")])
def test_a_row_for_each_document(results, name, of):
    assert Counter(r.doc_id for r in results(name)[1]) == Counter(r["doc_id"] for r in table(of))


@pytest.mark.parametrize("name", ["op6_url_filter", "op8_html_extract"])
def test_a_row_for_each_page(results, name):
    assert Counter(r.page_id for r in results(name)[1]) == Counter(r["page_id"] for r in table("pages"))


@pytest.mark.parametrize("name,folds,fold,label", [("op3_toxicity", 5, 0, "toxic"), ("op9_quality_classifier", 3, 1, "quality")])
def test_folds_scores_and_held_out_labels(results, name, folds, fold, label):
    rows = results(name)[1]
    for r in rows:
        assert r.held_out == (binascii.crc32(str(r.doc_id).encode()) % folds == fold)
        assert 0 <= r.score <= 1 and r.predicted == int(r.score >= 0.5)
    predicted = {r.doc_id: r.predicted for r in rows if r.held_out}
    known = [(predicted[r["doc_id"]], r[label]) for r in table("labels") if r["doc_id"] in predicted]
    assert sum(a == b for a, b in known) >= 0.9 * len(known)


def test_nearest_against_brute_force(results):
    rows = table("embeddings")
    ids = np.array([r["vec_id"] for r in rows])
    x = np.array([r["embedding"] for r in rows], np.float64)
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    found = defaultdict(list)
    for r in sorted(results("op2_nn_descent")[1], key=lambda r: (r.query_id, r.rank)):
        found[r.query_id].append(r)
    assert set(found) == {int(i) for i in ids if i % 50 == 0}
    hits = 0
    for query, got in found.items():
        cos = x @ x[ids == query][0]
        cos[ids == query] = -2
        best = ids[np.lexsort((ids, -cos))[:5]]
        hits += len(set(best) & {r.vec_id for r in got})
        assert [r.rank for r in got] == [1, 2, 3, 4, 5]
        assert all(abs(r.score - cos[ids == r.vec_id][0]) < 1e-9 for r in got)
    assert hits >= 0.9 * 5 * len(found)


def whole_and_gapless(pieces, ids_of):
    """Pieces make up each document's ids; sequences are gapless and of 2048 tokens at most."""
    cut, placed = defaultdict(list), defaultdict(list)
    for r in pieces:
        cut[r.doc_id].append(r)
        placed[r.sequence_id].append(r)
    for doc, rows in cut.items():
        rows.sort(key=lambda r: r.piece)
        ids, at = ids_of[doc], 0
        for i, r in enumerate(rows):
            part = ids[at : at + r.length]
            assert (r.piece, r.start) == (i, at) and 0 < r.length <= 2048 and (i == 0 or r.length == 2048)
            assert r.ids_crc32 == binascii.crc32(struct.pack(f"<{len(part)}I", *part))
            at += r.length
        assert at == len(ids)
    for rows in placed.values():
        at = 0
        for r in sorted(rows, key=lambda r: r.offset):
            assert r.offset == at
            at += r.length
        assert at <= 2048
    return len(placed)


def test_packing_is_whole_and_tight(results):
    docs = table("documents")
    ids_of = dict(zip([d["doc_id"] for d in docs], token_ids([d["text"] or "" for d in docs]), strict=True))
    rows = results("op4_pattern_packing")[1]
    assert {r.doc_id for r in rows} == set(ids_of)
    sequences = whole_and_gapless(rows, ids_of)
    assert sequences <= -(-sum(map(len, ids_of.values())) // 2048) * 1.05 + 1


def test_the_mix_meets_its_targets(results):
    source = {d["doc_id"]: d["source"] for d in table("documents")}
    taken, target = Counter(), {}
    for r in results("op5_source_mixing")[1]:
        assert 0 <= r.taken <= 2 * r.size
        taken[source[r.doc_id]] += r.taken
        target[source[r.doc_id]] = r.target
        assert r.target <= 2 * r.source_size
    assert all(abs(taken[s] - t) < 1 for s, t in target.items())


def test_text_lengths(results):
    assert all(r.n_chars == len(r.text) for r in results("op8_html_extract")[1])


def test_pipeline_packs_what_its_stages_keep(spark, monkeypatch):
    monkeypatch.syspath_prepend(str(Path(entry.__file__).parent))
    pipeline = pytest.importorskip("corpus_pipeline")
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    kept = []
    for _, stage in pipeline.STAGES[:-1]:
        before = docs
        docs = stage(spark, docs, SF).cache()
        assert docs.columns == before.columns
        kept.append(docs)
    ids = [{r.doc_id for r in d.select("doc_id").collect()} for d in kept]
    assert ids[3] <= ids[2] <= ids[1] <= ids[0]
    labels = {r["doc_id"]: r for r in table("labels")}
    toxic = {i for i, r in labels.items() if r["toxic"] == 1}
    clean = {i for i, r in labels.items() if r["toxic"] == 0}
    assert not toxic & ids[0] and len(clean & ids[0]) >= 0.98 * len(clean)
    pieces = pipeline.STAGES[-1][1](spark, docs, SF).collect()
    assert {r.doc_id for r in pieces} == ids[3]


def test_pipeline_run_leaves_only_the_last_stage_table(spark, monkeypatch):
    monkeypatch.syspath_prepend(str(Path(entry.__file__).parent))
    pipeline = pytest.importorskip("corpus_pipeline")
    folder = Path(spark.conf.get("spark.checkpoint.dir").removeprefix("file:"), "rangecut")
    found = lambda: {p.name for p in folder.glob("stage-*")}
    before = found()
    out = pipeline.run(spark, SF)
    assert {p.split("-")[1] for p in found() - before} == {"mixing"}
    docs = {d["doc_id"]: d["text"] or "" for d in table("documents")}
    rows = out.collect()
    assert {r.doc_id for r in rows} <= set(docs)
    assert sum(r.length for r in rows) > 0


def test_pipeline_stages_of_an_empty_table(spark, monkeypatch):
    monkeypatch.syspath_prepend(str(Path(entry.__file__).parent))
    pipeline = pytest.importorskip("corpus_pipeline")
    docs = spark.read.parquet(f"{SF}/documents.parquet").limit(0)
    for name, stage in pipeline.STAGES:
        assert stage(spark, docs, SF).count() == 0, name


CLASHING = ("score", "label", "key", "bucket", "block", "words", "size", "kept", "class_id", "n_links", "piece", "position", "_bucket", "_salt", "ids")


def test_pipeline_stages_of_awkward_rows(spark, monkeypatch):
    """Nulls, empty and very long texts, repeated rows, one source only null, columns named like inner ones."""
    from pyspark.sql import functions as F

    monkeypatch.syspath_prepend(str(Path(entry.__file__).parent))
    pipeline = pytest.importorskip("corpus_pipeline")
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    prose = max((r["text"] for r in table("documents")), key=len)
    odd = [(None, "no id here"), (9_000_001, None), (9_000_002, ""), (9_000_003, " \n\t "), (9_000_004, prose * 8), (9_000_004, prose * 8), (None, None)]
    rows = spark.createDataFrame([(i, t, None, None, None) for i, t in odd], docs.schema)
    awkward = docs.unionByName(rows)
    for c in CLASHING:
        awkward = awkward.withColumn(c, F.lit(c))
    for name, stage in pipeline.STAGES:
        out = stage(spark, awkward, SF)
        if name != pipeline.STAGES[-1][0]:
            assert out.columns == awkward.columns, name
            assert all(r[c] == c for r in out.select(*CLASHING).limit(50).collect() for c in CLASHING), name
        assert out.count() > 0, name
    pieces = out.where("doc_id = 9000004").collect()
    ids = token_ids([prose * 8])[0]
    assert sum(r.length for r in pieces) == 2 * len(ids)
