"""Quality rules: counts of a text, and a line labelling whose share of content decides.

The lines of a text are labelled content or boilerplate by Viterbi decoding of
a linear-chain random field (``linechain``). A text that passes the base rules
is kept where lines of content hold at least ``CONTENT_SHARE`` of its
characters.

Cases: a null text is an empty one, which fails the base rules; a null id stays
null; texts of any length are read whole; repeated rows give a row each, judged
alike; a share of exactly ``CONTENT_SHARE`` is kept, and of two equally good
labellings the one with content counts; an empty table gives no rows; columns
beyond doc_id and text are left out by ``judge``, whatever their names, and
kept by ``keep``. Where no labelled document of either class exists, no field
can be trained and the base rules decide alone.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rangecut.llm import linechain
from rangecut.llm.shared import labelled_sample

#: Training takes at most this many labelled documents.
TRAINING_DOCUMENTS = 1000
CONTENT_SHARE = 0.5
#: Texts decoded at once.
AT_ONCE = 256

SCHEMA = "n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, content_share double, kept boolean"


def base_counts(text: str) -> tuple[int, int, int, int, int]:
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words."""
    raw = text.encode("utf-8", "surrogatepass")
    words = raw.split()  # of bytes: at ASCII white space only
    n_spaces = sum(map(text.count, " \t\n\x0b\x0c\r"))
    n_symbols = sum(map(text.count, "#*$%&|<>"))
    lines = Counter(raw.split(b"\n"))
    n_dup = sum(n - 1 for line, n in lines.items() if n > 1 and line.split())
    return len(words), len(text) - n_spaces, n_symbols, n_dup, _repeated(words)


def _repeated(words: list[bytes]) -> int:
    """Words that stand in a window of three words which occurs at least twice."""
    windows = list(zip(words, words[1:], words[2:]))
    if len(set(windows)) == len(windows):
        return 0
    count = Counter(windows)
    covered, end = 0, 0
    for i, window in enumerate(windows):
        if count[window] > 1:
            covered += i + 3 - max(i, end)
            end = i + 3
    return covered


def fit(docs: DataFrame, labels: DataFrame) -> linechain.Chain | None:
    """The field, from at most ``TRAINING_DOCUMENTS`` labelled documents: lines that good ones are made of are content."""
    return linechain.train(labelled_sample(docs, labels, "quality", TRAINING_DOCUMENTS), neighbours=False)


def _judged(texts: list[str], chain: linechain.Chain | None) -> list[tuple]:
    shares = [1.0] * len(texts)
    if chain is not None:
        decoded = linechain.viterbi([chain.scores(t) for t in texts], chain.transition)
        for i, (text, label) in enumerate(zip(texts, decoded, strict=True)):
            size = linechain.line_lengths(text)
            shares[i] = float((size * label).sum() / size.sum())
    out = []
    for text, share in zip(texts, shares, strict=True):
        counts = base_counts(text)
        failed = counts[0] < 50 or 100 * counts[4] > 50 * counts[0]
        out.append((*counts, failed, share, not failed and share >= CONTENT_SHARE))
    return out


def judging(chain: linechain.Chain | None):
    names = [x.split()[0] for x in SCHEMA.split(", ")]

    @F.pandas_udf(SCHEMA)
    def judged(parts: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        for part in parts:
            texts = [t or "" for t in part]
            rows = [r for i in range(0, len(texts), AT_ONCE) for r in _judged(texts[i : i + AT_ONCE], chain)]
            yield pd.DataFrame(rows, columns=names)

    return judged


def judge(docs: DataFrame, chain: linechain.Chain | None) -> DataFrame:
    """doc_id, the counts, content_share and kept."""
    return docs.select("doc_id", judging(chain)("text").alias("found")).select("doc_id", "found.*")


def keep(docs: DataFrame, chain: linechain.Chain | None) -> DataFrame:
    """The rows of ``docs`` that are kept, with all their columns."""
    return docs.where(judging(chain)(docs["text"])["kept"])
