"""Toxicity by a counterfactually regularised linear classifier.

A text's features are which words and word prefixes it has (lower case, outer punctuation off). The loss is the log loss of
the labels plus a penalty on the squared change of the logit when a labelled sentence's identity term is swapped for
another of its group, or taken out, with all features of both (the bare words and their prefixes): terms are pulled
together and to no effect, so neutral mentions aren't marked. Terms that no labelled sentence has are swapped on their own.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType

from .common import held_out, training_rows

#: Identity terms by group, in the corpus's languages; terms of a group stand for each other in a counterfactual.
IDENTITY_TERMS = (
    ("women", "men", "girls", "boys"),
    ("woman", "man", "girl", "boy"),
    ("gay", "straight", "lesbian", "transgender", "bisexual"),
    ("muslim", "christian", "jewish", "hindu", "buddhist", "atheist"),
    ("muslims", "christians", "jews", "hindus", "buddhists", "atheists"),
    ("black", "white", "asian", "latino"),
    ("immigrants", "refugees", "foreigners", "natives"),
    ("deaf", "blind", "disabled", "autistic"),
    ("old", "young", "elderly"),
    ("femmes", "hommes", "filles", "garçons"),
    ("musulman", "chrétien", "juif", "hindou", "bouddhiste", "athée"),
    ("musulmans", "chrétiens", "juifs", "hindous", "bouddhistes", "athées"),
    ("noirs", "blancs", "asiatiques", "arabes"),
    ("immigrés", "réfugiés", "étrangers"),
    ("homosexuel", "hétérosexuel", "lesbienne", "transgenre"),
    ("sourd", "aveugle", "handicapé", "autiste"),
    ("frauen", "männer", "mädchen", "jungen"),
    ("muslimisch", "christlich", "jüdisch", "hinduistisch", "buddhistisch", "atheistisch"),
    ("muslime", "christen", "juden", "buddhisten", "atheisten"),
    ("schwarze", "weiße", "asiaten", "araber"),
    ("einwanderer", "flüchtlinge", "ausländer", "einheimische"),
    ("schwul", "lesbisch", "heterosexuell", "bisexuell"),
    ("gehörlos", "behindert", "autistisch"),
    ("mujeres", "hombres", "chicas", "chicos"),
    ("musulmán", "cristiano", "judío", "budista", "ateo"),
    ("musulmanes", "cristianos", "judíos", "budistas", "ateos"),
    ("negros", "blancos", "asiáticos", "árabes"),
    ("inmigrantes", "refugiados", "extranjeros"),
    ("gais", "lesbianas", "bisexuales", "transexuales"),
    ("sordo", "ciego", "discapacitado", "autista"),
)
OUTER = ".,;:!?\"'()[]{}<>*#&%$|+=~^_-…«»“”‘’/\\@"


#: Lengths of the prefixes that count as features beside whole words (inflected forms share them).
PREFIXES = (4, 5, 6)


def features_of(word: str) -> list[str]:
    """Of a lower-case word as it stands between spaces: the bare word, and its prefixes marked by a dash."""
    bare = word.strip(OUTER)
    return [bare, *(bare[:n] + "-" for n in PREFIXES if len(bare) > n)] if bare else []


def words_of(text: str | None) -> set[str]:
    """The distinct features of a text."""
    return {f for w in set((text or "").lower().split()) for f in features_of(w)}


def swapped(words: set[str], term: str, other: str | None) -> tuple[set[str], set[str]]:
    """(features that go, features that come) when a text with these features has `other`, or nothing, in the place of `term`.

    A prefix that another word of the text has too stays.
    """
    rest = [w for w in words if w != term and not w.endswith("-")]
    shared = lambda f: f.endswith("-") and any(len(w) >= len(f) and w.startswith(f[:-1]) for w in rest)
    out = {f for f in features_of(term) if f in words and not shared(f)}
    new = set(features_of(other)) if other else set()
    return out - new, new - words


class Active(dict):
    """Word to its features that have weights; filled on demand, emptied beyond a bound."""

    def __init__(self, weights: dict[str, float], most: int = 300_000):
        super().__init__()
        self.weights, self.most = weights, most

    def __missing__(self, word: str) -> tuple[str, ...]:
        if len(self) >= self.most:
            self.clear()
        found = tuple(f for f in features_of(word) if f in self.weights)
        if len(word) <= 64:
            self[word] = found
        return found


@dataclass
class Linear:
    weights: dict[str, float]
    bias: float

    def __post_init__(self) -> None:
        self.active = Active(self.weights)

    def score(self, text: str | None) -> float:
        found: set[str] = set()
        for features in map(self.active.__getitem__, set((text or "").lower().split())):
            if features:
                found.update(features)
        z = self.bias + sum(map(self.weights.__getitem__, sorted(found)))
        return float(1 / (1 + np.exp(-max(-30.0, min(30.0, z)))))


def _select(samples: list[tuple[set[str], int]], most: int) -> list[str]:
    """Words whose presence tells about the label (G statistic over 12), the strongest first, and all identity terms."""
    count = [Counter(), Counter()]
    total = [0, 0]
    for words, y in samples:
        count[y].update(words)
        total[y] += 1
    n = sum(total)
    if not n or not all(total):
        return []
    found = []
    for w in count[1].keys() | count[0].keys():
        a, b = count[1][w], count[0][w]
        if a + b < 3:
            continue
        g = 0.0
        for k, t in ((a, total[1]), (b, total[0])):
            for seen, of in ((k, a + b), (t - k, n - a - b)):
                if seen:
                    g += 2 * seen * np.log(seen * n / (t * of))
        if g > 12:
            found.append((-g, w))
    return [w for _, w in sorted(found)[:most]]


def counterfactuals(samples: list[tuple[set[str], int]]) -> list[list[tuple[set[str], set[str]]]]:
    """What goes and what comes in each counterfactual, in two sets: of the labelled texts, and of the terms on their own."""
    group = {w: ws for ws in IDENTITY_TERMS for w in ws}
    labelled = [swapped(words, w, v) for words, _ in samples for w in sorted(words & group.keys()) for v in (*group[w], None) if v != w]
    alone = [swapped(set(features_of(w)), w, v) for ws in IDENTITY_TERMS for w in ws for v in (*ws, None) if v != w]
    return [c for c in (labelled, alone) if c]


def fit(samples: list[tuple[set[str], int]], most_words: int = 4000, swap: float = 20.0, rounds: int = 300, rate: float = 0.1, decay: float = 2e-3) -> Linear:
    """Full-batch Adam on log loss + swap * mean squared change of the logit over each set of counterfactuals + decay.

    samples: (words, label 0 or 1). One label only, or none: the prior alone scores.
    """
    positive = sum(y for _, y in samples)
    prior = float(np.log((positive + 0.5) / (len(samples) - positive + 0.5)))
    chosen = _select(samples, most_words)
    if not chosen:
        return Linear({}, prior)
    index = {w: k for k, w in enumerate(dict.fromkeys([*chosen, *sorted(w for ws in IDENTITY_TERMS for w in ws)]))}
    at_text, feature, y = [], [], np.array([y for _, y in samples], dtype=np.float64)
    for k, (words, _) in enumerate(samples):
        own = [index[w] for w in words if w in index]
        at_text += [k] * len(own)
        feature += own
    at_text, feature = np.array(at_text, dtype=np.int64), np.array(feature, dtype=np.int64)
    # Each set of counterfactuals as a sparse matrix: a row each, -1 where a feature goes and 1 where one comes.
    changes = []
    for one in counterfactuals(samples):
        entries = [(k, index[f], sign) for k, sides in enumerate(one) for side, sign in zip(sides, (-1.0, 1.0), strict=True) for f in sorted(side) if f in index]
        changes.append((len(one), *(np.array(c) for c in zip(*entries, strict=True))))
    w, bias = np.zeros(len(index)), prior
    m, v = np.zeros(len(w) + 1), np.zeros(len(w) + 1)
    for step in range(1, rounds + 1):
        z = bias + np.bincount(at_text, w[feature], minlength=len(y))
        miss = (1 / (1 + np.exp(-np.clip(z, -30, 30))) - y) / len(y)
        g = np.bincount(feature, miss[at_text], minlength=len(w)) + decay * w / 10
        for n, row, of, sign in changes:
            change = 2 * swap * np.bincount(row, sign * w[of], minlength=n) / n
            g += np.bincount(of, sign * change[row], minlength=len(w))
        g = np.append(g, miss.sum())
        m, v = 0.9 * m + 0.1 * g, 0.99 * v + 0.01 * g * g
        move = rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-8)
        w -= move[:-1]
        bias -= move[-1]
    return Linear({t: float(x) for t, x in zip(index, w, strict=True) if abs(x) > 1e-4}, float(bias))


def train(docs: DataFrame, labelled: DataFrame, most: int = 6000, **options) -> Linear:
    """Fit on at most `most` labelled rows that are not held out. Only their distinct words come to the driver."""

    def reduce(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data = [" ".join(sorted(words_of(t))) for t in batch.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("label"), pa.array(data, pa.string())], ["label", "words"])

    rows = training_rows(docs, labelled, "toxic", most).select("label", "text").mapInArrow(reduce, "label int, words string").collect()
    return fit(sorted(((set(r["words"].split()), int(r["label"] > 0)) for r in rows), key=lambda x: (x[1], sorted(x[0]))), **options)


def score(docs: DataFrame, model: Linear, text: str = "text", out: str = "score") -> DataFrame:
    """Add the score of each whole text: 0 to 1, higher is more toxic. Null or empty: the prior. Narrow: no shuffle."""

    @F.pandas_udf(DoubleType())
    def of(texts: pd.Series) -> pd.Series:
        return pd.Series([model.score(t) for t in texts], dtype="float64")

    return docs.withColumn(out, of(F.col(text)))


def document_toxicity(docs: DataFrame, labelled: DataFrame, most: int = 6000) -> DataFrame:
    scored = score(docs.select("doc_id", "text"), train(docs, labelled, most))
    return scored.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
