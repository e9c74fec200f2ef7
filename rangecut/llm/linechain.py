"""A linear-chain conditional random field over the lines of a text, in numpy.

Lines (what stands between newlines) get a vector of plain features; a line's
label also depends on its neighbour's label, and optionally on the neighbours'
features. Only documents have labels, so training finds those of lines first:

1. All lines of a good document are good, those of a bad one bad. Weights
   without transitions are fitted, lines of bad documents that look good are
   relabelled, and so on, a few times. At least one line of a bad document stays
   bad: the one that looks worst.
2. The sequences of the chain are the documents with these labels, and joins of
   a good and a bad document's lines in either order, so that changes of the
   label occur and transitions mean something.
3. One conditional likelihood of those label sequences, weighted by sequence,
   is maximised for emissions and transitions together.

Many texts are handled at once: they are ordered by their number of lines, so
step t of the recursions works on the first so many of them, and a text of
many thousand lines costs just its own steps.
"""

from __future__ import annotations

import re
from dataclasses import dataclass
from operator import eq

import numpy as np

N_FEATURES = 16
_UPPER = bytes(range(65, 91))
_LOWER = bytes(range(97, 123))
_DIGIT = bytes(range(48, 58))
_SYMBOL = b"#*$%&|<>"
_HIGH = bytes(range(128, 256))
_ADDRESS = re.compile(rb"https?:|www\.|\S@\S|\d{3}[-.]\d{3,4}|[=;{}\\]")


def line_features(text: str) -> np.ndarray:
    """A row of features in about [0, 1] for each line of the text."""
    lines = text.encode("utf-8", "replace").split(b"\n")
    out = np.zeros((len(lines), N_FEATURES), np.float32)
    seen: set[bytes] = set()
    for row, line in zip(out, lines, strict=True):
        words = line.split()
        if not words:
            row[0] = row[1] = 1
            continue
        n, n_words = len(line), len(words)
        upper = n - len(line.translate(None, _UPPER))
        lower = n - len(line.translate(None, _LOWER))
        symbols = n - len(line.translate(None, _SYMBOL))
        row[0] = 1
        row[2] = upper / (upper + lower + 1)
        row[3] = min(1.0, symbols / n_words)
        row[4] = min(1.0, line.count(b"!") / n_words)
        row[5] = min(1.0, 2 * line.count(b"|") / n_words)
        row[6] = (n - len(line.translate(None, _DIGIT))) / n
        row[7] = 1 - len(set(words)) / n_words
        row[8] = min(1.0, np.log1p(n_words) / 6)
        row[9] = min(1.0, n / n_words / 12)
        row[10] = words[-1][-1:] in b".!?:"
        row[11] = line in seen
        row[12] = (n - len(line.translate(None, _HIGH))) / n
        row[13] = min(1.0, 5 * len(_ADDRESS.findall(line)) / n_words)
        row[14] = n_words < 5
        row[15] = sum(map(eq, words, words[1:])) / n_words
        seen.add(line)
    return out


def line_lengths(text: str) -> np.ndarray:
    """Characters of each line, its newline included."""
    return np.array([len(x) + 1 for x in text.split("\n")], np.float64)


def with_neighbours(x: np.ndarray) -> np.ndarray:
    """Each line's features, then those of the line before and of the line after."""
    before, after = np.zeros_like(x), np.zeros_like(x)
    before[1:], after[:-1] = x[:-1], x[1:]
    return np.hstack([x, before, after])


@dataclass
class Chain:
    """Weights: emission (features, 2), transition (2, 2); state 1 is content or good."""

    emission: np.ndarray
    transition: np.ndarray
    neighbours: bool

    def scores(self, text: str) -> np.ndarray:
        x = line_features(text)
        return (with_neighbours(x) if self.neighbours else x) @ self.emission


class _Ragged:
    """Texts of different lengths, longest first: at step t those that still have a line are the first ``active[t]``."""

    def __init__(self, parts: list[np.ndarray]):
        lengths = np.array([len(p) for p in parts], np.int64)
        self.order = np.argsort(-lengths, kind="stable")
        starts = np.concatenate([[0], np.cumsum(lengths)])[:-1]
        self.start, self.length = starts[self.order], lengths[self.order]
        steps = int(lengths.max())
        self.active = np.searchsorted(-self.length, -np.arange(steps), side="left")
        self.all = np.concatenate(parts)


def marginals(parts: list[np.ndarray], transition: np.ndarray, weight: np.ndarray | None = None) -> tuple[list[np.ndarray], np.ndarray, np.ndarray]:
    """Forward-backward: for each text the probability of state 1 of its lines; log partition; expected transitions (2, 2), ``weight`` a text."""
    r = _Ragged(parts)
    each = np.ones(len(parts)) if weight is None else weight[r.order]
    e, tr = r.all.astype(np.float64), transition.astype(np.float64)
    alpha, beta = np.empty_like(e), np.zeros_like(e)
    steps = len(r.active)
    alpha[r.start] = e[r.start]
    for t in range(1, steps):
        at = r.start[: r.active[t]] + t
        prev = alpha[at - 1]
        for k in (0, 1):
            alpha[at, k] = np.logaddexp(prev[:, 0] + tr[0, k], prev[:, 1] + tr[1, k]) + e[at, k]
    last = r.start + r.length - 1
    log_z = np.logaddexp(alpha[last, 0], alpha[last, 1])
    expected = np.zeros((2, 2))
    for t in range(steps - 2, -1, -1):
        n = r.active[t + 1]
        at = r.start[:n] + t
        ahead = e[at + 1] + beta[at + 1]
        for j in (0, 1):
            beta[at, j] = np.logaddexp(tr[j, 0] + ahead[:, 0], tr[j, 1] + ahead[:, 1])
            for k in (0, 1):
                expected[j, k] += each[:n] @ np.exp(alpha[at, j] + tr[j, k] + ahead[:, k] - log_z[:n])
    lines_z = np.empty(len(e))
    for s, n, z in zip(r.start, r.length, log_z, strict=True):
        lines_z[s : s + n] = z
    good = np.exp(alpha[:, 1] + beta[:, 1] - lines_z)
    out: list[np.ndarray] = [good[:0]] * len(parts)
    for i, s, n in zip(r.order, r.start, r.length, strict=True):
        out[i] = good[s : s + n]
    z = np.empty(len(parts))
    z[r.order] = log_z
    return out, z, expected


def viterbi(parts: list[np.ndarray], transition: np.ndarray) -> list[np.ndarray]:
    """The likeliest labels of each text's lines; at equal scores state 1."""
    r = _Ragged(parts)
    e, tr = r.all.astype(np.float64), transition.astype(np.float64)
    best, back = e.copy(), np.zeros(e.shape, np.int8)
    for t in range(1, len(r.active)):
        at = r.start[: r.active[t]] + t
        prev = best[at - 1]
        for k in (0, 1):
            from_0, from_1 = prev[:, 0] + tr[0, k], prev[:, 1] + tr[1, k]
            back[at, k] = from_1 >= from_0
            best[at, k] = np.maximum(from_0, from_1) + e[at, k]
    label = np.zeros(len(e), np.int8)
    last = r.start + r.length - 1
    label[last] = best[last, 1] >= best[last, 0]
    for t in range(len(r.active) - 2, -1, -1):
        at = r.start[: r.active[t + 1]] + t
        label[at] = back[at + 1, label[at + 1]]
    out: list[np.ndarray] = [label[:0]] * len(parts)
    for i, s, n in zip(r.order, r.start, r.length, strict=True):
        out[i] = label[s : s + n]
    return out


#: Training cuts texts into pieces of so many lines, which bounds the steps of its recursions; no line is left out.
PIECE = 64
#: Times that the lines of bad documents are labelled anew.
RELABELLED = 4


@dataclass
class Sequences:
    """Label sequences to learn from: features and labels of all lines, where sequences end, and their weights."""

    rows: np.ndarray
    labels: np.ndarray
    lengths: np.ndarray
    weight: np.ndarray

    def likelihood(self, theta: np.ndarray, ridge: float) -> tuple[float, np.ndarray]:
        """The weighted conditional log likelihood of all sequences less the ridge, and its gradient."""
        emission, transition = theta[:-4].reshape(-1, 2), theta[-4:].reshape(2, 2)
        scores = self.rows @ emission
        parts = np.split(scores, np.cumsum(self.lengths)[:-1])
        good, log_z, expected = marginals(parts, transition, self.weight)
        each = np.repeat(self.weight, self.lengths)
        inner = np.ones(len(self.labels), bool)
        inner[np.cumsum(self.lengths)[:-1]] = False  # a sequence's first line follows no other
        before, after = self.labels[:-1][inner[1:]], self.labels[1:][inner[1:]]
        observed = np.zeros((2, 2))
        np.add.at(observed, (before, after), each[1:][inner[1:]])
        value = each @ scores[np.arange(len(scores)), self.labels] + (observed * transition).sum() - self.weight @ log_z
        miss = each * (self.labels - np.concatenate(good))
        gradient = np.concatenate([np.stack([-self.rows.T @ miss, self.rows.T @ miss], axis=1).ravel(), (observed - expected).ravel()])
        return value - 0.5 * ridge * theta @ theta, gradient - ridge * theta


def ascend(gradient, theta: np.ndarray, steps: int) -> np.ndarray:
    """Adam on whole gradients."""
    theta, m, v = theta.copy(), np.zeros_like(theta), np.zeros_like(theta)
    for step in range(1, steps + 1):
        g = gradient(theta)
        m, v = 0.9 * m + 0.1 * g, 0.99 * v + 0.01 * g**2
        theta += 0.15 * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-8)
    return theta


def line_labels(rows: np.ndarray, doc: np.ndarray, quality: np.ndarray, ridge: float) -> np.ndarray:
    """Labels of lines (rows of document ``doc``) from documents' labels, without the chain."""
    bad = quality[doc] == 0
    label = np.where(bad, 0, 1)
    n_lines = np.bincount(doc, minlength=len(quality))
    weights = np.zeros(rows.shape[1])
    for _ in range(RELABELLED):
        w = np.empty(len(rows))
        for c in (0, 1):
            each = 1.0 / n_lines[doc[label == c]]
            w[label == c] = 0.5 * each / each.sum()
        weights = ascend(lambda t: rows.T @ (w * (label - 1 / (1 + np.exp(-np.clip(rows @ t, -30, 30))))) - ridge * t, weights, 60)  # noqa: B023
        looks = rows @ weights
        worst = np.full(len(quality), np.inf)
        np.minimum.at(worst, doc, looks)
        relabelled = np.where(bad, (looks > 0) & (looks > worst[doc]), 1).astype(np.int64)
        if (relabelled == label).all():
            break
        label = relabelled
    return label


def sequences(sample: list[tuple[str, int]], neighbours: bool, ridge: float) -> Sequences:
    """Pieces of the documents with their lines' labels, and joins of good and bad pieces; both classes weigh the same."""
    features = [line_features(text) for text, _ in sample]
    quality = np.array([y for _, y in sample], np.int64)
    doc = np.repeat(np.arange(len(features)), [len(x) for x in features])
    rows = np.concatenate(features).astype(np.float64)
    labels = line_labels(rows, doc, quality, ridge)
    by_class: tuple[list, list] = ([], [])
    at = 0
    for x, y in zip(features, quality, strict=True):
        for i in range(0, len(x), PIECE):
            piece = x[i : i + PIECE]
            by_class[y].append((piece, labels[at + i : at + i + len(piece)], 1.0 / len(x)))
        at += len(x)
    found = []
    for pieces in by_class:
        total = sum(w * len(x) for x, _, w in pieces)
        found += [(x, z, 0.5 * w / total) for x, z, w in pieces]
    good, bad = by_class[1], by_class[0]
    n = max(len(good), len(bad))
    for k in range(n):
        a, b = good[k % len(good)], bad[k % len(bad)]
        a, b = (a, b) if k % 2 else (b, a)
        x = np.concatenate([a[0], b[0]])
        found.append((x, np.concatenate([a[1], b[1]]), 1.0 / n / len(x)))
    xs = [with_neighbours(x) if neighbours else x for x, _, _ in found]
    return Sequences(np.concatenate(xs).astype(np.float64), np.concatenate([z for _, z, _ in found]), np.array([len(x) for x in xs]), np.array([w for _, _, w in found]))


def train(sample: list[tuple[str, int]], neighbours: bool, rounds: int = 100, ridge: float = 1e-3) -> Chain | None:
    """The chain of greatest likelihood over the sample; None where a class is missing.

    All lines of all sampled texts count; the number of texts bounds memory.
    """
    if len({y for _, y in sample}) < 2:
        return None
    learned = sequences(sample, neighbours, ridge)
    theta = ascend(lambda t: learned.likelihood(t, ridge)[1], np.zeros(learned.rows.shape[1] * 2 + 4), rounds)
    return Chain(theta[:-4].reshape(-1, 2), theta[-4:].reshape(2, 2), neighbours)
