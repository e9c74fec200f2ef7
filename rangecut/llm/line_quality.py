"""A quality classifier: every line is good or bad, a document is judged by the length-weighted mean of its lines.

The linear-chain random field of ``linechain`` also sees the features of the
lines before and after. Forward-backward gives each line's probability of being
good; weighted by the lines' characters they make the document's good share,
and a logistic curve fitted on the training documents turns it into the
probability that the document is labelled good. The curve never falls, so more
good text never lowers a score.

Cases: a null or empty text is one empty line and gets that line's probability;
a text of any length is read whole, one long line is one line; a null id is held
out; repeated rows give a row each, with equal scores; a score of exactly 0.5
predicts good; an empty table gives no rows; columns beyond doc_id and text are
left out, so none can clash. Without labelled documents of both classes the
score is 0.5 for all.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rangecut.llm import linechain
from rangecut.llm.shared import labelled_sample

#: Training takes at most this many labelled documents.
TRAINING_DOCUMENTS = 1000
AT_ONCE = 256


@dataclass
class Model:
    """The chain, and the curve from good shares to probabilities: slope, offset."""

    chain: linechain.Chain
    slope: float
    offset: float


def fit(docs: DataFrame, labels: DataFrame, where: Column | None = None) -> Model | None:
    return train(labelled_sample(docs, labels, "quality", TRAINING_DOCUMENTS, where))


def train(sample: list[tuple[str, int]]) -> Model | None:
    chain = linechain.train(sample, neighbours=True)
    if chain is None:
        return None
    x = np.array([s for i in range(0, len(sample), AT_ONCE) for s in good_shares([t for t, _ in sample[i : i + AT_ONCE]], chain)]) - 0.5
    y = np.array([q for _, q in sample], np.float64)
    design = np.stack([x, np.ones_like(x)], axis=1)
    each = np.where(y == 1, 0.5 / y.sum(), 0.5 / (1 - y).sum())  # a corpus with few bad documents doesn't tilt it

    def gradient(theta: np.ndarray) -> np.ndarray:
        return design.T @ (each * (y - 1 / (1 + np.exp(-np.clip(design @ theta, -30, 30))))) - 1e-4 * theta

    slope, offset = linechain.ascend(gradient, np.array([4.0, 0.0]), 300)
    return Model(chain, max(0.0, float(slope)), float(offset))


def good_shares(texts: list[str], chain: linechain.Chain) -> list[float]:
    """Expected share of each text's characters that stand in good lines."""
    good, _, _ = linechain.marginals([chain.scores(t) for t in texts], chain.transition)
    out = []
    for text, p in zip(texts, good, strict=True):
        size = linechain.line_lengths(text)
        out.append(float((size * p).sum() / size.sum()))
    return out


def score_texts(texts: list[str], model: Model | None) -> list[float]:
    if model is None or not texts:
        return [0.5] * len(texts)
    z = model.slope * (np.array(good_shares(texts, model.chain)) - 0.5) + model.offset
    return (1 / (1 + np.exp(-z))).tolist()


def scoring(model: Model | None):
    @F.pandas_udf("double")
    def scored(parts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for part in parts:
            texts = [t or "" for t in part]
            yield pd.Series([s for i in range(0, len(texts), AT_ONCE) for s in score_texts(texts[i : i + AT_ONCE], model)], dtype="float64")

    return scored


def score(docs: DataFrame, model: Model | None) -> DataFrame:
    """doc_id and score."""
    return docs.select("doc_id", scoring(model)("text").alias("score"))
