"""Quality by a linear-chain conditional random field over the lines of a document.

Each line is good (1) or bad (0). Unary scores are linear in features of the line and of its neighbours; a transition
score ties neighbouring labels. Only documents are labelled, so the lines' labels are latent: all lines of a good document
are good, and of a bad one at least one is bad. Which ones is guessed first by a model of single lines, then by the field
itself, which is fitted again (hard expectation maximisation). Forward-backward gives each line's marginal; a document's
score is their mean, weighted by line length.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DoubleType

from .common import held_out, release, training_rows

#: Features of a line itself; the model sees them for the line, the one before and the one after, plus a constant.
OWN = 14
#: Documents that score less are rejected.
CUT = 0.3
#: Lines of a training document that are looked at: a run of them that begins at a place given by a hash of the text.
TRAIN_LINES = 200
MARKS = str.maketrans(dict.fromkeys("#$%&*|{}<>=+^~\\@_[]!"))


def line_features(line: str) -> list[float]:
    words = line.split()
    n, chars = len(words), len(line)
    if not n:
        return [1.0] + [0.0] * (OWN - 1)
    letters = line.replace(" ", "")
    m = len(letters) or 1
    plain = letters.translate(MARKS)
    marks = len(letters) - len(plain)
    lower = letters.lower()
    upper = sum(map(str.__ne__, letters, lower)) if len(lower) == len(letters) else 0
    distinct = len(set(words))
    repeats = sum(map(str.__eq__, words, words[1:]))
    digits = sum(map(letters.count, "0123456789"))
    mean = m / n
    return [
        0.0,
        min(chars, 400) / 400,
        min(n, 60) / 60,
        upper / m,
        float(upper / m > 0.5),
        marks / m,
        float(marks / m > 0.08),
        digits / m,
        distinct / n if n > 3 else 1.0,
        repeats / n,
        min(mean, 20.0) / 20,
        line.count("|") / n,
        float(letters[-1] in ".!?…。"),
        float(n < 4),
    ]


def own_features(lines: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """(lines x OWN features, weights: characters of each line + 1)."""
    return np.array([line_features(x) for x in lines], dtype=np.float32).reshape(len(lines), OWN), np.array([len(x) + 1 for x in lines], dtype=np.float64)


def with_neighbours(own: np.ndarray) -> np.ndarray:
    """(lines x (3 OWN + 1)): a line's features, those of the line before and of the line after, and a constant."""
    zero = np.zeros((1, OWN), dtype=np.float32)
    return np.hstack([own, np.vstack([zero, own[:-1]]), np.vstack([own[1:], zero]), np.ones((len(own), 1), dtype=np.float32)])


def document_features(text: str | None) -> tuple[np.ndarray, np.ndarray]:
    """(features, weights) of the lines of a text. No text: one empty line."""
    own, weight = own_features((text or "").split("\n"))
    return with_neighbours(own), weight


@dataclass
class ChainField:
    """unary: weights of label good (bad is the reference). pull[a, b]: score of label a followed by b.

    power: documents' mean marginals are raised to it, so that the best cut of the training documents becomes CUT.
    """

    unary: np.ndarray
    pull: np.ndarray
    power: float = 1.0

    def marginals(self, features: np.ndarray) -> np.ndarray:
        """P(line is good) for each line, by scaled forward-backward."""
        good = np.clip(features @ self.unary, -30, 30)
        n = len(good)
        (p00, p01), (p10, p11) = np.exp(self.pull).tolist()
        weight = np.exp(good).tolist()
        fore = [0.0] * n
        a, b = 1.0, weight[0]
        for k in range(n):
            if k:
                a, b = a * p00 + b * p10, (a * p01 + b * p11) * weight[k]
            s = a + b
            a, b = a / s, b / s
            fore[k] = b
        out = np.empty(n)
        a = b = 1.0
        for k in range(n - 1, -1, -1):
            f = fore[k]
            out[k] = f * b / ((1 - f) * a + f * b)
            w = weight[k] * b
            a, b = p00 * a + p01 * w, p10 * a + p11 * w
            s = a + b
            a, b = a / s, b / s
        return out

    def score(self, text: str | None) -> float:
        """Length-weighted mean of the marginals, calibrated: 0 to 1, higher is better."""
        features, weight = document_features(text)
        return self.mean(features, weight) ** self.power

    def raised(self, marginals: np.ndarray, weight: np.ndarray) -> float:
        return min(1.0, float(marginals @ weight / weight.sum())) ** self.power

    def mean(self, features: np.ndarray, weight: np.ndarray) -> float:
        return min(1.0, float(self.marginals(features) @ weight / weight.sum()))


class Chains:
    """Documents' lines packed for fitting: all chains advance one line at a time, the longest first."""

    def __init__(self, features: list[np.ndarray]):
        self.size = np.array([len(x) for x in features])
        self.order = np.argsort(-self.size, kind="stable")
        self.size = self.size[self.order]
        self.flat = np.concatenate([features[k] for k in self.order]).astype(np.float64)
        self.start = np.cumsum(self.size) - self.size
        self.live = [int((self.size > k).sum()) for k in range(int(self.size[0]))]  # chains still running at line k
        self.weight = np.full(len(features), 1.0 / len(features)) / self.size  # each document counts alike

    def pack(self, labels: list[np.ndarray]) -> np.ndarray:
        return np.concatenate([labels[k] for k in self.order]).astype(np.int64)

    def gradient(self, theta: np.ndarray, pull: np.ndarray, truth: np.ndarray) -> tuple[float, np.ndarray, np.ndarray]:
        """(weighted log-likelihood of the line labels, its gradients by theta and by pull)."""
        n, longest, start, live = len(self.size), len(self.live), self.start, self.live
        score = np.clip(self.flat @ theta, -30, 30)
        node, pull_e = np.ones((n, longest, 2)), np.exp(pull)
        for k in range(longest):
            node[: live[k], k, 1] = np.exp(score[start[: live[k]] + k])
        fore, value = np.zeros((n, longest, 2)), 0.0
        for k in range(longest):
            c = live[k]
            x = node[:c, 0] if not k else fore[:c, k - 1] @ pull_e * node[:c, k]
            total = x.sum(1, keepdims=True)
            fore[:c, k] = x / total
            at, w = start[:c] + k, self.weight[:c]
            value += float(w @ (score[at] * truth[at] - np.log(total[:, 0])))
            if k:
                value += float(w @ pull[truth[at - 1], truth[at]])
        back, miss, pull_grad = np.ones((n, 2)), np.empty(len(self.flat)), np.zeros((2, 2))
        for k in range(longest - 1, -1, -1):
            c = live[k]
            at, w = start[:c] + k, self.weight[:c]
            p = fore[:c, k] * back[:c]
            p /= p.sum(1, keepdims=True)
            miss[at] = (truth[at] - p[:, 1]) * w
            if k:
                right = node[:c, k] * back[:c]
                pair = fore[:c, k - 1][:, :, None] * pull_e[None] * right[:, None, :]
                pair /= pair.sum((1, 2), keepdims=True)
                pull_grad -= (pair * w[:, None, None]).sum(0)
                np.add.at(pull_grad, (truth[at - 1], truth[at]), w)
                new = right @ pull_e.T
                back[:c] = new / new.sum(1, keepdims=True)
        return value, self.flat.T @ miss, pull_grad


def _ascend(chains: Chains, truth: np.ndarray, rounds: int, rate: float, decay: float) -> ChainField:
    """Gradient ascent (Adam) on the log-likelihood of line labels, less a ridge."""
    state = [np.zeros(chains.flat.shape[1]), np.zeros((2, 2))]
    m, v = [np.zeros_like(x) for x in state], [np.zeros_like(x) for x in state]
    for step in range(1, rounds + 1):
        _, *grads = chains.gradient(*state, truth)
        for i, (g, ridge) in enumerate(zip(grads, (decay, 20 * decay), strict=True)):
            g = g - ridge * state[i]
            m[i] = 0.9 * m[i] + 0.1 * g
            v[i] = 0.99 * v[i] + 0.01 * g * g
            state[i] = state[i] + rate * (m[i] / (1 - 0.9**step)) / (np.sqrt(v[i] / (1 - 0.99**step)) + 1e-8)
    return ChainField(*state)


def _single_lines(documents: list[tuple[np.ndarray, int]], rounds: int = 200) -> list[np.ndarray]:
    """Chance that each line is good by its own features alone: logistic regression on the documents' labels.

    Documents count alike within a label, and both labels alike, so a kind of line that bad documents have no more often
    than good ones comes out at a half or more.
    """
    x = np.concatenate([f[:, :OWN] for f, _ in documents]).astype(np.float64)
    x = np.hstack([x, np.ones((len(x), 1))])
    y = np.concatenate([np.full(len(f), float(label)) for f, label in documents])
    w = np.concatenate([np.full(len(f), 1.0 / len(f)) for f, _ in documents])
    for label in (0.0, 1.0):
        w[y == label] /= max(w[y == label].sum(), 1e-12)
    theta = np.zeros(x.shape[1])
    for _ in range(rounds // 10):  # Newton steps
        p = 1 / (1 + np.exp(-np.clip(x @ theta, -30, 30)))
        h = (x * (w * p * (1 - p))[:, None]).T @ x + 1e-3 * np.eye(len(theta))
        theta = theta + np.linalg.solve(h, x.T @ (w * (y - p)) - 1e-3 * theta)
    p = 1 / (1 + np.exp(-np.clip(x @ theta, -30, 30)))
    return np.split(p, np.cumsum([len(f) for f, _ in documents])[:-1])


def _line_labels(documents: list[tuple[np.ndarray, int]], good: list[np.ndarray]) -> list[np.ndarray]:
    """All lines of good documents are good; of a bad one those of a chance under a half are bad, or else the least likely."""
    out = []
    for (_, label), p in zip(documents, good, strict=True):
        y = np.ones(len(p), dtype=np.int64) if label else (p >= 0.5).astype(np.int64)
        if not label and y.all():
            y[int(np.argmin(p))] = 0
        out.append(y)
    return out


def fit(documents: list[tuple[np.ndarray, int]], rounds: int = 80, relabel: int = 2, rate: float = 0.15, decay: float = 1e-3) -> ChainField:
    """documents: (features of the lines, label). None: all weights zero. One label only: lines all have it."""
    if not documents:
        return ChainField(np.zeros(3 * OWN + 1), np.zeros((2, 2)))
    chains = Chains([x for x, _ in documents])
    if len({y for _, y in documents}) < 2:
        return _ascend(chains, chains.pack([np.full(len(x), y, dtype=np.int64) for x, y in documents]), rounds, rate, decay)
    good = _single_lines(documents)
    for _ in range(relabel):
        field = _ascend(chains, chains.pack(_line_labels(documents, good)), rounds, rate, decay)
        good = [field.marginals(x) for x, _ in documents]
    return field


def train(docs: DataFrame, labelled: DataFrame, most: int = 3000) -> ChainField:
    """Fit on at most `most` labelled rows that are not held out, TRAIN_LINES lines of each: what comes to the driver is bounded."""

    def features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        release()
        for batch in batches:
            own, weights = [], []
            for t in batch.column("text").to_pylist():
                lines = t.split("\n")
                begin = zlib.crc32(t.encode()) % max(1, len(lines) - TRAIN_LINES + 1)
                x, w = own_features(lines[begin : begin + TRAIN_LINES])
                own.append(x.tobytes())
                weights.append(w.tobytes())
            yield pa.RecordBatch.from_arrays([batch.column("label"), pa.array(own, pa.binary()), pa.array(weights, pa.binary())], ["label", "own", "weights"])

    rows = training_rows(docs, labelled, "quality", most).select("label", "text").mapInArrow(features, "label int, own binary, weights binary").collect()
    rows.sort(key=lambda r: (r["label"], bytes(r["own"]), bytes(r["weights"])))
    samples = [(with_neighbours(np.frombuffer(r["own"], np.float32).reshape(-1, OWN)), int(r["label"] > 0), np.frombuffer(r["weights"], np.float64)) for r in rows]
    return calibrate(fit([(x, y) for x, y, _ in samples]), samples)


def calibrate(field: ChainField, samples: list[tuple[np.ndarray, int, np.ndarray]]) -> ChainField:
    """Set the power. The best cut has the fewest errors, a lost good document counting five times; of equal ones the middle."""
    if len({y for _, y, _ in samples}) < 2:
        return field
    means = np.array([field.mean(x, w) for x, _, w in samples])
    good = np.array([y for _, y, _ in samples]) == 1
    cuts = np.linspace(0.05, 0.995, 190)
    cost = np.array([5 * (means[good] < c).sum() + (means[~good] >= c).sum() for c in cuts])
    best = float(np.median(cuts[cost == cost.min()]))
    return ChainField(field.unary, field.pull, float(np.log(CUT) / np.log(best)))


def line_scores(docs: DataFrame, field: ChainField, text: str = "text", out: str = "lines") -> DataFrame:
    """Add an array with the chance of each line of the text that it is good, in order. Null: one empty line. Narrow: no shuffle."""

    @F.pandas_udf(ArrayType(DoubleType()))
    def of(texts: pd.Series) -> pd.Series:
        release()
        return pd.Series([field.marginals(document_features(t)[0]) for t in texts], dtype=object)

    return docs.withColumn(out, of(F.col(text)))


def score(docs: DataFrame, field: ChainField, text: str = "text", out: str = "score") -> DataFrame:
    """Add the score of each whole text. Null and empty texts score as one empty line. Narrow: no shuffle."""

    @F.pandas_udf(DoubleType())
    def of(texts: pd.Series) -> pd.Series:
        release()
        return pd.Series([field.score(t) for t in texts], dtype="float64")

    return docs.withColumn(out, of(F.col(text)))


def keeps(column: str = "score", least: float = CUT) -> Column:
    return F.col(column) >= least


def document_quality(docs: DataFrame, labelled: DataFrame, most: int = 3000) -> DataFrame:
    """(doc_id, held_out, score, predicted, n_lines, n_bad_lines) of each row; a bad line's chance to be good is under a half."""
    field = train(docs, labelled, most)

    @F.pandas_udf("score double, n_lines int, n_bad_lines int")
    def of(texts: pd.Series) -> pd.DataFrame:
        release()
        rows = []
        for t in texts:
            features, weight = document_features(t)
            p = field.marginals(features)
            rows.append((field.raised(p, weight), len(p), int((p < 0.5).sum())))
        return pd.DataFrame(rows, columns=["score", "n_lines", "n_bad_lines"])

    scored = docs.select("doc_id", of(F.col("text")).alias("found"))
    return scored.select("doc_id", held_out().alias("held_out"), "found.score", keeps("found.score").cast("int").alias("predicted"), "found.n_lines", "found.n_bad_lines")
