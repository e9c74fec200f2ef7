"""Toxicity by multiple-instance learning: sentences have scores, documents have labels.

A bias plus the weights of a sentence's words make a logit, and what its
probability has beyond that of the bias alone, as a share of what is left, is
the sentence's. A document is toxic unless all its sentences are harmless: with
p the sentences' probabilities, its own is 1 - (1 - p1)(1 - p2)... (noisy-or). Only documents are labelled; the
gradient through the noisy-or puts the blame on the sentences that explain the
label, so the trained model also locates the offending sentences.

A sentence's features are its words (runs of letters, digits and what is not
ASCII, in lower case) and their first four and five letters, which catch
inflected forms that training never saw. Features seen in fewer than
``LEAST_DOCUMENTS`` training documents get no weight; of the others an L1
penalty leaves a few hundred. A sentence without any of them has a probability
of 0, so however many there are, they don't add up. The bias is fixed and low;
labels that no sentence explains fall to a leak of the document.

Cases: a null or empty text is one sentence without words; a text of any length
is read whole; a null id is held out; repeated rows give a row each, scored
alike; a score of exactly ``TOXIC`` rejects; an empty table gives no rows; other
columns, whatever their names, are left out by ``score`` and kept by ``keep``.
Without labelled documents of both classes every score is 0.
"""

from __future__ import annotations

import math
import re
from array import array
from collections import Counter
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rangecut.llm.shared import forget, labelled_rows, written

#: Training takes at most this many labelled documents.
TRAINING_DOCUMENTS = 4000
LEAST_DOCUMENTS = 3
#: A document is rejected from here on.
TOXIC = 0.5

#: Logit without the words, and the share of labels that sentences don't explain.
BIAS, LEAK = -10.0, 0.02

SENTENCE = re.compile(r"[.!?]+\s+|\n")
TERM = re.compile(r"[0-9a-z\u0080-\U0010ffff]+")


def features(sentence: str) -> set[str]:
    """Words, and as ``abcd*`` the beginnings of longer ones; the sentence is in lower case."""
    terms = set(TERM.findall(sentence))
    return terms.union((t[:4] + "*" for t in terms if len(t) > 4), (t[:5] + "*" for t in terms if len(t) > 5))


@dataclass
class Model:
    weights: dict[str, float]
    bias: float = BIAS

    def sentence_logits(self, sentences: list[str]) -> list[float]:
        known, base = self.weights, self.bias - softplus(self.bias)
        added = (math.fsum(known[t] for t in features(s.lower()) if t in known) for s in sentences)
        return [base + w + math.log(-math.expm1(-w)) if w else -math.inf for w in added]

    def score(self, text: str) -> float:
        """Only texts with words that have weights are looked at sentence by sentence."""
        lower = text.lower()
        known, plain, harmless = self.weights.keys(), softplus(self.bias), 0.0
        if not known.isdisjoint(features(lower)):
            for sentence in SENTENCE.split(lower):
                found = known & features(sentence)
                if found:
                    harmless += plain - softplus(self.bias + math.fsum(self.weights[t] for t in found))
        return min(1.0, max(0.0, -math.expm1(harmless)))

    def locate(self, text: str, least: float = TOXIC) -> list[tuple[str, float]]:
        """The sentences whose own probability is at least ``least``."""
        parts = SENTENCE.split(text)
        scored = ((s, 1 / (1 + math.exp(-x))) for s, x in zip(parts, self.sentence_logits(parts), strict=True))
        return [(s, p) for s, p in scored if p >= least]


def softplus(x: float) -> float:
    return max(x, 0.0) + math.log1p(math.exp(-abs(x)))


def vocabulary_of(n_docs: dict[str, int], n_toxic: dict[str, int], share: float) -> list[str]:
    """Features that get weights: one that is no commoner among toxic documents than among all can't explain a label."""
    return sorted(t for t, n in n_docs.items() if n >= LEAST_DOCUMENTS and n_toxic.get(t, 0) > max(1, 1.3 * share * n))


def numbered(text: str, number: dict[str, int]) -> tuple[int, list[int], list[int]]:
    """How many sentences there are, and pairs of a sentence's place and the number of a known feature."""
    parts = SENTENCE.split(text.lower())
    places, terms = [], []
    for i, sentence in enumerate(parts):
        for t in sorted(number[f] for f in features(sentence) if f in number):
            places.append(i)
            terms.append(t)
    return len(parts), places, terms


def train(sample: list[tuple[str, int]], rounds: int = 200, l1: float = 1.5e-4) -> Model | None:
    """``descend`` on texts in memory."""
    n_docs, n_toxic = Counter(), Counter()
    for text, y in sample:
        found = set().union(*map(features, SENTENCE.split(text.lower())))
        n_docs.update(found)
        if y:
            n_toxic.update(found)
    labels = [y for _, y in sample]
    vocabulary = vocabulary_of(n_docs, n_toxic, sum(labels) / max(1, len(labels)))
    number = {t: i for i, t in enumerate(vocabulary)}
    return descend(labels, (numbered(text, number) for text, _ in sample), vocabulary, rounds, l1)


def descend(classes: list[int], documents: Iterable[tuple[int, list[int], list[int]]], vocabulary: list[str], rounds: int = 200, l1: float = 1.5e-4) -> Model | None:
    """Adam with a proximal L1 step on the mean log loss of the noisy-or, both classes weighing the same.

    ``documents`` come as ``numbered`` has them, one for each of ``classes``.
    """
    labels = np.array(classes, np.float64)
    if len(set(labels.tolist())) < 2:
        return None
    counts, terms, sentences, begun = [], array("i"), array("q"), 0
    for n_sentences, places, found in documents:
        counts.append(n_sentences)
        terms.extend(found)
        sentences.extend(begun + i for i in places)
        begun += n_sentences
    doc = np.repeat(np.arange(len(counts)), counts)
    term, sentence = np.array(terms, np.int64), np.array(sentences, np.int64)
    weight = np.where(labels == 1, 0.5 / labels.sum(), 0.5 / (1 - labels).sum())
    theta, rate = np.zeros(len(vocabulary)), 0.15
    m, v = np.zeros_like(theta), np.zeros_like(theta)
    for step in range(1, rounds + 1):
        bias = max(BIAS, -4.0 - 12.0 * step / rounds)  # comes down while the weights grow
        z = bias + np.bincount(sentence, theta[term], len(doc))
        p = 1 / (1 + np.exp(-z))
        harmless = np.log1p(-LEAK) - np.bincount(doc, np.logaddexp(0, z) - np.logaddexp(0, bias), len(labels))
        toxic = np.clip(-np.expm1(harmless), 1e-6, 1.0)
        # d loss / d z of a sentence: p times (1 - y / P(document)).
        g = weight[doc] * p * (1 - labels[doc] / toxic[doc])
        grad = np.bincount(term, g[sentence], len(vocabulary))
        m, v = 0.9 * m + 0.1 * grad, 0.99 * v + 0.01 * grad**2
        scale = rate / (np.sqrt(v / (1 - 0.99**step)) + 1e-4)
        theta = np.maximum(theta - scale * (m / (1 - 0.9**step) + l1), 0.0)
    return Model({t: float(w) for t, w in zip(vocabulary, theta, strict=True) if w > 0.01})


def fit(docs: DataFrame, labels: DataFrame, where: Column | None = None) -> Model | None:
    """Executors count the sample's features and look up those that get weights; the driver sees counts and numbers, no texts."""
    rows = written(labelled_rows(docs, labels, "toxic", TRAINING_DOCUMENTS, where), "toxic-sample")
    try:
        sizes = {r.label: r["count"] for r in rows.groupBy("label").count().collect()}
        if len(sizes) < 2:
            return None
        total = sum(sizes.values())
        share = sum(y * n for y, n in sizes.items()) / total
        counted = (
            rows.select("label", F.explode(distinct_features()("text")).alias("term"))
            .groupBy("term")
            .agg(F.count(F.lit(1)).alias("n"), F.sum("label").alias("toxic"))
            .where((F.col("n") >= LEAST_DOCUMENTS) & (F.col("toxic") > F.greatest(F.lit(1.0), 1.3 * share * F.col("n"))))
        )
        found = counted.collect()
        vocabulary = vocabulary_of({r.term: r.n for r in found}, {r.term: r.toxic for r in found}, share)
        number = {t: i for i, t in enumerate(vocabulary)}

        @F.pandas_udf("struct<sentences:int,places:array<int>,terms:array<int>>")
        def looked_up(parts: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
            for part in parts:
                yield pd.DataFrame([numbered(t, number) for t in part], columns=["sentences", "places", "terms"])

        sample = rows.select("doc_id", "label", looked_up("text").alias("x")).select("doc_id", "label", "x.*").collect()
        sample.sort(key=lambda r: r.doc_id)
        return descend([r.label for r in sample], ((r.sentences, r.places, r.terms) for r in sample), vocabulary)
    finally:
        forget(rows, steps=False)


def distinct_features():
    @F.pandas_udf("array<string>")
    def found(parts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for part in parts:
            yield pd.Series([sorted(set().union(*map(features, SENTENCE.split(t.lower())))) for t in part])

    return found


def scoring(model: Model | None):
    @F.pandas_udf("double")
    def scored(parts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for part in parts:
            yield pd.Series([model.score(t or "") if model else 0.0 for t in part], dtype="float64")

    return scored


def score(docs: DataFrame, model: Model | None) -> DataFrame:
    """doc_id and score."""
    return docs.select("doc_id", scoring(model)("text").alias("score"))


def locate(docs: DataFrame, model: Model | None) -> DataFrame:
    """doc_id, sentence and its probability, for the offending sentences."""

    @F.pandas_udf("array<struct<sentence:string,probability:double>>")
    def found(parts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for part in parts:
            yield pd.Series([[{"sentence": s, "probability": p} for s, p in (model.locate(t or "") if model else [])] for t in part])

    return docs.select("doc_id", F.inline(found("text")))


def keep(docs: DataFrame, model: Model | None) -> DataFrame:
    """The rows of ``docs`` that aren't toxic, with all their columns."""
    return docs.where(scoring(model)(docs["text"]) < TOXIC)
