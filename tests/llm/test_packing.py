import zlib

import numpy as np
import public_tokenizers
from hypothesis import given, settings
from hypothesis import strategies as st
from tokenizers import Tokenizer

from rangecut.llm import packing


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(1, 64), max_size=80))
def test_plan_places_every_piece_once_and_fits(lengths):
    counts = np.bincount(np.array(lengths, int), minlength=65)
    groups = packing.plan(counts, 64)
    used = np.zeros(65, int)
    for content, n in groups:
        assert sum(content) <= 64 and n > 0
        for v in content:
            used[v] += n
    assert (used[1:] == counts[1:]).all()
    # Never worse than half as many again as the bound from volume and long pieces.
    bound = max(-(-int((counts * np.arange(65)).sum()) // 64), int(counts[33:].sum()))
    assert sum(n for _, n in groups) <= 1.5 * bound + 1


def test_least_squares_uses_up_a_histogram_of_patterns():
    counts = np.zeros(65, int)
    counts[[40, 24, 30, 20, 14]] = [500, 500, 300, 300, 300]
    table = packing.patterns(64, counts)
    x = packing.least_squares(64, counts, table, rounds=2000)
    made = sum(np.bincount(t, x, 65) for t in table)
    assert (x >= 0).all() and np.abs(made[1:] - counts[1:]).max() < 5
    assert sum(n for _, n in packing.plan(counts, 64)) <= 803


def test_encoder_equals_the_tokenizer():
    whole = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    whole.encode_special_tokens = True
    ours = packing.Encoder(public_tokenizers.path("byte_bpe_50k.tiktoken"))
    texts = ["", " ", "a", " a", "a  b", "x \n y", "\n\n a", "a\n b", "a \nb", "it's 'll  ", "<|endoftext|> x", "a\x1f b\u00a0c", "é ß 日本語 🙂", "tab\t x\ty", "a b\n\nc d", "12 345,67", " \t "]
    for _ in range(2):
        assert [ours(t) for t in texts] == [np.array(e.ids, "<u4").tobytes() for e in whole.encode_batch(texts, add_special_tokens=False)]


def test_pack(spark):
    whole = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    texts = ["short text", None, "", "long " * 3000, "word " * 500, "same same", "same same", "x " * 1023, "y" * 9]
    docs = spark.createDataFrame([(i if i != 4 else None, t, 0) for i, t in enumerate(texts)], "doc_id long, text string, length int")
    rows = packing.pack(docs, 256).collect()
    for i, t in enumerate(texts):
        ids = np.array([*whole.encode(t or "", add_special_tokens=False).ids, 0], "<u4")
        mine = sorted((r for r in rows if r.doc_id == (i if i != 4 else None)), key=lambda r: r.piece)
        assert sum(r.length for r in mine) == len(ids) and [r.piece for r in mine] == list(range(len(mine)))
        for r in mine:
            assert zlib.crc32(ids[r.start : r.start + r.length].tobytes()) == r.ids_crc32
        assert all(r.length == 256 for r in mine[1:])
    by = {}
    for r in rows:
        by.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for parts in by.values():
        parts.sort()
        assert parts[0][0] == 0 and all(a + n == b for (a, n), (b, _) in zip(parts, parts[1:])) and sum(n for _, n in parts) <= 256
    assert packing.pack(docs.where("false"), 256).count() == 0


def test_added_tokens_are_single_ids(spark):
    whole = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    texts = ["<|endoftext|> x", "a <|endoftext|>", "a<|endoftext|><|endoftext|>  b", "<|endoftext", "a b\n<|endoftext|>\n c", " <|endoftext|> ", "<|endoftext|>"]
    assert whole.encode(texts[0], add_special_tokens=False).ids == [50256, 2124]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    for r in packing.pieces(docs, 256).collect():
        ids = np.array([*whole.encode(texts[r.doc_id], add_special_tokens=False).ids, 0], "<u4")
        assert r.length == len(ids) and r.ids_crc32 == zlib.crc32(ids.tobytes())
