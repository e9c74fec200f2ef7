"""Best-fit packing from a histogram of lengths, by patterns of few documents.

1. Documents become token ids plus a closing id and are cut, where longer than a
   sequence, into pieces of the sequence's length; the first piece is the rest.
2. The plan needs only how many pieces have each length. Patterns of one, two
   and three lengths that fill a sequence are enumerated; non-negative least
   squares finds how often to use each so that the histogram is used up; the
   counts are rounded along their running sum and cut to what the histogram
   still holds. What remains is packed best fit first, longest first, first
   into gaps that exist already. All of this is on one machine, and bounded by
   the sequence's length, not by the data.
3. A piece's rank among those of its length finds its place in the plan. Ranks
   come from counts of (length, salt) and ranks inside these, so a length that
   a third of all pieces have is spread over many tasks.

Cases: a null text is an empty one, a single closing id; a null id stays null;
repeated rows are packed as often as they occur; an empty table gives no rows;
other columns are left out. Texts are tokenized whole.
"""

from __future__ import annotations

import base64
import json
import re
import zlib
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rangecut.llm.shared import written

CLOSING_ID = 0
#: Encoded words that a worker remembers; then it starts anew.
REMEMBERED = 300_000
#: Pieces of one length and salt that one task ranks, about.
RANKED_AT_ONCE = 10_000

PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"


class Encoder:
    """Ids of a byte-level BPE vocabulary as little-endian unsigned 32-bit bytes.

    A text is cut where single spaces lead a word; the tokenizer's own rule
    never joins anything across these places, so words can be encoded one by
    one and remembered. Texts with other runs of white space go through the
    tokenizer whole. ``added`` tokens (text to id) are taken out of a text
    first; what stands between them is encoded by itself.
    """

    def __init__(self, ranks_path: str, added: dict[str, int] | None = None):
        import public_tokenizers
        import tiktoken

        with open(ranks_path, "rb") as lines:
            ranks = {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, lines)}
        self.encoding = tiktoken.Encoding("bytes", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
        self.known = _Known(self.whole)
        self.added = {token: np.array([i], "<u4").tobytes() for token, i in (added or {}).items()}
        longest_first = sorted(self.added, key=len, reverse=True)
        self.cut = re.compile(f"({'|'.join(map(re.escape, longest_first))})") if self.added else None

    def whole(self, text: str) -> bytes:
        return np.array(self.encoding.encode_ordinary(text), "<u4").tobytes()

    def __call__(self, text: str) -> bytes:
        if self.cut is None:
            return self.words(text)
        # Every second part is an added token.
        parts = self.cut.split(text)
        return b"".join(self.added[part] if k % 2 else self.words(part) for k, part in enumerate(parts))

    def words(self, text: str) -> bytes:
        first, *rest = text.split(" ")
        if not first or first[-1].isspace():
            return self.whole(text)
        try:
            ids = b"".join(map(self.known.__getitem__, rest))
        except _Unusual:
            return self.whole(text)
        if len(self.known) > REMEMBERED:
            self.known.clear()
        return self.whole(first) + ids


class _Unusual(Exception):
    pass


class _Known(dict):
    def __init__(self, whole):
        self.whole = whole

    def __missing__(self, word: str) -> bytes:
        if not word or word[0].isspace() or word[-1].isspace():
            raise _Unusual
        found = self[word] = self.whole(" " + word)
        return found


def added_tokens(tokenizer_path: str) -> dict[str, int]:
    """The vocabulary's added tokens, as the tokenizer's file lists them."""
    with open(tokenizer_path, encoding="utf-8") as file:
        listed = json.load(file).get("added_tokens") or []
    for token in listed:
        if token.get("single_word") or token.get("lstrip") or token.get("rstrip") or token.get("normalized"):
            raise ValueError(f"added token {token['content']!r} isn't matched as it stands")
    return {token["content"]: token["id"] for token in listed}


def cut_lengths(total: int, size: int) -> list[int]:
    """Lengths of a document's pieces: all of ``size`` but the first, which may be shorter."""
    first = total % size
    return ([first] if first else []) + [size] * (total // size)


def pieces(docs: DataFrame, size: int, vocabulary: str = "byte_bpe_50k.tiktoken") -> DataFrame:
    """A row for each piece of each document: doc_id, piece, start, length, ids_crc32."""

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import public_tokenizers

        added = added_tokens(public_tokenizers.path(vocabulary.replace(".tiktoken", ".json")))
        encode = Encoder(public_tokenizers.path(vocabulary), added)
        closing = np.array([CLOSING_ID], "<u4").tobytes()
        for batch in batches:
            out: tuple[list, ...] = ([], [], [], [], [])
            for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                ids = encode(text.as_py() or "") + closing
                start = 0
                for k, length in enumerate(cut_lengths(len(ids) // 4, size)):
                    for column, value in zip(out, (doc_id, k, start, length, zlib.crc32(memoryview(ids)[4 * start : 4 * (start + length)])), strict=True):
                        column.append(value)
                    start += length
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(out, (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()), strict=True)], names=["doc_id", "piece", "start", "length", "ids_crc32"])

    return docs.select("doc_id", "text").mapInArrow(cut, PIECES)


# The plan: a list of (lengths, repeats); repeats sequences hold one piece of each of these lengths.


def patterns(size: int, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """All (a, b, c), a >= b >= c, of lengths that occur and fill a sequence: sum ``size``, b and c may be 0."""
    have = counts > 0
    present = np.flatnonzero(have)
    rows = []
    if len(have) > size and have[size]:
        rows.append(np.array([[size, 0, 0]]))
    two = present[(present * 2 >= size) & (present < size)]
    two = two[have[size - two]]
    rows.append(np.stack([two, size - two, np.zeros_like(two)], 1))
    for c in present[present * 3 <= size]:
        b = present[(present >= c) & (present * 2 <= size - c)]
        b = b[have[size - c - b]]
        rows.append(np.stack([size - c - b, b, np.full_like(b, c)], 1))
    table = np.concatenate(rows).astype(np.int64)
    return table[:, 0], table[:, 1], table[:, 2]


def least_squares(size: int, counts: np.ndarray, table: tuple[np.ndarray, ...], rounds: int = 150) -> np.ndarray:
    """Non-negative repeats whose pieces come closest to the histogram, by accelerated projected gradients.

    A residual of a long length weighs more: short pieces find a gap anyway.
    """
    weight = np.clip(np.arange(size + 1) / size * 4, 0.1, 1.0)
    weight[0] = 0.0  # length 0 stands for nothing
    target = counts.astype(np.float64)

    def demand(x: np.ndarray) -> np.ndarray:
        return sum(np.bincount(t, x, size + 1) for t in table)

    x = np.zeros(len(table[0]))
    # Gershgorin: what a column meets in the rows that it touches bounds the step.
    degree = demand(np.ones_like(x))
    lipschitz = max(1.0, max(float(sum(weight[t] * degree[t] for t in table).max()), 1.0))
    y, momentum = x.copy(), 1.0
    for _ in range(rounds):
        residual = weight * (demand(y) - target)
        gradient = sum(residual[t] for t in table)
        new = np.maximum(y - gradient / lipschitz, 0.0)
        ahead = (1 + np.sqrt(1 + 4 * momentum**2)) / 2
        y = new + (momentum - 1) / ahead * (new - x)
        x, momentum = new, ahead
    return x


def plan(counts: np.ndarray, size: int) -> list[tuple[tuple[int, ...], int]]:
    """Sequences for ``counts[length]`` pieces of each length up to ``size``."""
    left = counts.astype(np.int64).copy()
    chosen: list[tuple[tuple[int, ...], int]] = []
    table = patterns(size, left)
    if len(table[0]):
        repeats = least_squares(size, left, table)
        total = np.cumsum(repeats)
        whole = np.floor(total + 0.5).astype(np.int64)
        whole = np.diff(whole, prepend=0)
        order = np.argsort(-repeats, kind="stable")
        for j in order[whole[order] > 0]:
            lengths = tuple(int(t[j]) for t in table if t[j])
            n = int(min(whole[j], min(left[v] // lengths.count(v) for v in set(lengths))))
            if n > 0:
                chosen.append((lengths, n))
                for v in lengths:
                    left[v] -= n
    return chosen + best_fit(left, size)


def best_fit(counts: np.ndarray, size: int) -> list[tuple[tuple[int, ...], int]]:
    """Best fit, longest first, for many equal pieces at once: groups of equal sequences by what they have left."""
    groups: dict[int, list[tuple[tuple[int, ...], int]]] = defaultdict(list)
    room = np.zeros(size + 1, bool)
    for length in range(size, 0, -1):
        n = int(counts[length])
        while n:
            fits = np.flatnonzero(room[length:])
            if len(fits):
                gap = length + int(fits[0])
                content, k = groups[gap].pop()
                used = min(n, k)
                if used < k:
                    groups[gap].append((content, k - used))
                room[gap] = bool(groups[gap])
                groups[gap - length].append((content + (length,), used))
                room[gap - length] = gap > length
                n -= used
                continue
            each = size // length
            k, rest = divmod(n, each)
            for content, k in (((length,) * each, k), ((length,) * rest, 1)):
                if k and content:
                    gap = size - length * len(content)
                    groups[gap].append((content, k))
                    room[gap] = gap > 0
            n = 0
    return [g for gap in sorted(groups) for g in groups[gap]]


def places(groups: list[tuple[tuple[int, ...], int]]) -> dict[int, tuple[np.ndarray, ...]]:
    """For each length, by rank: where a run of ranks begins, its first sequence, its place in the sequence."""
    runs: dict[int, list[tuple[int, int, int]]] = defaultdict(list)
    used: dict[int, int] = defaultdict(int)
    sequence = 0
    for content, n in groups:
        at = 0
        for length in content:
            runs[length].append((used[length], sequence, at))
            used[length] += n
            at += length
        sequence += n
    return {length: tuple(np.array(c, np.int64) for c in zip(*rows, strict=True)) for length, rows in runs.items()}


def ranked(found: DataFrame) -> DataFrame:
    """Adds ``rank``, from 0 within each length, in an order that reruns repeat."""
    total = found.count()
    salts = max(1, -(-total // RANKED_AT_ONCE))
    salted = found.withColumn("_salt", F.pmod(F.xxhash64("doc_id", "piece"), F.lit(salts)))
    counts = salted.groupBy("length", "_salt").count()
    before = counts.select("length", "_salt", (F.sum("count").over(Window.partitionBy("length").orderBy("_salt")) - F.col("count")).alias("_before"))
    inside = F.row_number().over(Window.partitionBy("length", "_salt").orderBy("doc_id", "piece", "ids_crc32"))
    return salted.withColumn("_row", inside).join(before, ["length", "_salt"]).withColumn("rank", F.col("_row") + F.col("_before") - 1).drop("_salt", "_row", "_before")


def pack(docs: DataFrame, size: int) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset for every piece of every document."""
    found = written(pieces(docs, size), "pieces")
    counts = np.zeros(size + 1, np.int64)
    for row in found.groupBy("length").count().collect():  # at most ``size`` rows
        counts[row.length] = row["count"]
    where = found.sparkSession.sparkContext.broadcast(places(plan(counts, size)))  # bounded by the patterns of ``size``

    @F.pandas_udf("sequence_id long, offset long")
    def placed(length: pd.Series, rank: pd.Series) -> pd.DataFrame:
        n, r = length.to_numpy(), rank.to_numpy()
        sequence, offset = np.empty(len(n), np.int64), np.empty(len(n), np.int64)
        for v in np.unique(n):
            mine = np.flatnonzero(n == v)
            begins, first, at = where.value[v]
            run = np.searchsorted(begins, r[mine], side="right") - 1
            sequence[mine] = first[run] + r[mine] - begins[run]
            offset[mine] = at[run]
        return pd.DataFrame({"sequence_id": sequence, "offset": offset})

    return ranked(found).withColumn("_at", placed("length", "rank")).select("doc_id", "piece", "start", "length", "ids_crc32", "_at.sequence_id", "_at.offset")
