"""Mixing sources to target weights by soft membership.

A naive Bayes classifier, fitted on a labelled sample, gives each document its posterior over domains. Its evidence is the
mean over the text's known words, times a scale that a held-back part of the sample calibrates, so that long texts don't
saturate and a text in two languages belongs to both. Document rates r >= 0 are then sought whose expected domain tokens,
sum of r * tokens * posterior, equal the targets: least squares by projected gradient from r = 1, so the rates stay as
near to 1 as the targets allow. A round is one aggregation to a vector of the domains' size; a document's rate follows
from the gradients so far, so no state is kept between rounds.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import fresh, held_out, materialise, release, without_gc


#: Scales of the evidence that calibration tries, from soft to sharp, and the loss (nats) it gives up for a softer one.
SCALES, SOFTER = tuple(2 ** (k / 2) for k in range(-6, 9)), 0.02
#: One in so many labelled rows is held back for calibration.
HELD_BACK = 4


@dataclass
class Domains:
    names: list[str]
    prior: np.ndarray
    index: dict[str, int]  # word: its row of weights
    weights: np.ndarray  # log-likelihood of each domain, less the mean
    scale: float = 1.0

    def evidence(self, text: str | None) -> tuple[np.ndarray, int]:
        """(mean weights of the text's known words, each counted once; words of the text)."""
        words = (text or "").split()
        rows = set(map(self.index.get, words))
        rows.discard(None)
        return (self.weights[sorted(rows)].mean(axis=0) if rows else np.zeros(len(self.names))), len(words)

    def posterior(self, text: str | None) -> tuple[np.ndarray, int]:
        """(posterior over the domains, words of the text). No known words: the prior."""
        found, n = self.evidence(text)
        z = self.prior + self.scale * found
        z = np.exp(z - z.max())
        return z / z.sum(), n


def calibrate(model: Domains, samples: list[tuple[np.ndarray, str]]) -> Domains:
    """The model with the softest scale whose log loss on held-back (evidence, domain) is within SOFTER of the best."""
    known = [(e, model.names.index(d)) for e, d in samples if d in model.names]
    if not known:
        return model
    evidence, truth = np.array([e for e, _ in known]), np.array([d for _, d in known])
    loss = []
    for scale in SCALES:
        z = model.prior + scale * evidence
        z -= z.max(axis=1, keepdims=True)
        loss.append(float(np.mean(np.log(np.exp(z).sum(axis=1)) - z[np.arange(len(truth)), truth])))
    model.scale = next(s for s, x in zip(SCALES, loss, strict=True) if x <= min(loss) + SOFTER)
    return model


def fit(samples: list[tuple[Counter, str]], most_words: int = 20_000) -> Domains:
    """Bernoulli-like naive Bayes on which words a text has, smoothed by a half. samples: (document counts of words, domain)."""
    names = sorted({d for _, d in samples}) or ["all"]
    index = {d: k for k, d in enumerate(names)}
    size = np.zeros(len(names))
    count: dict[str, np.ndarray] = {}
    for words, d in samples:
        size[index[d]] += words.pop("", 0)
        for w, n in words.items():
            if w not in count:
                count[w] = np.zeros(len(names))
            count[w][index[d]] += n
    words = sorted(count, key=lambda w: (-count[w].sum(), w))[:most_words]
    weights = np.log((np.array([count[w] for w in words]).reshape(len(words), len(names)) + 0.5) / (size + 1.0))
    weights -= weights.mean(axis=1, keepdims=True)
    prior = np.log((size + 1) / (size + 1).sum())
    return Domains(names, prior, {w: i for i, w in enumerate(words)}, weights)


def train(docs: DataFrame, labelled: DataFrame, domain: str = "lang", most: int = 4000, seed: int = 11) -> Domains:
    """Fit on at most `most` labelled rows. Their domain is the column `domain`; word counts come to the driver in sums.

    Rows count as labelled if the label table has their id and they aren't held out. Rows without domain are left out.
    One in HELD_BACK of them calibrates the scale and is not fitted on.
    """
    chosen = labelled.where(F.col("doc_id").isNotNull() & ~held_out()).select("doc_id").distinct().orderBy(F.xxhash64(F.lit(seed), "doc_id"), "doc_id").limit(most)
    rows = docs.where(F.col(domain).isNotNull() & F.col("text").isNotNull()).select("doc_id", "text", F.col(domain).cast("string").alias("domain")).join(F.broadcast(chosen), "doc_id")
    back = F.pmod(F.xxhash64(F.lit(seed + 1), "doc_id"), F.lit(HELD_BACK)) == 0

    def words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[str, Counter] = {}
        for batch in batches:
            for d, t in zip(batch.column("domain").to_pylist(), batch.column("text").to_pylist(), strict=True):
                sums.setdefault(d, Counter()).update({*t.split(), ""})
        flat = [(d, w, n) for d, c in sums.items() for w, n in c.items()]
        yield pa.RecordBatch.from_arrays([pa.array([x[k] for x in flat], t) for k, t in enumerate((pa.string(), pa.string(), pa.int64()))], ["domain", "word", "n"])

    sums = rows.where(~back).select("domain", "text").mapInArrow(words, "domain string, word string, n long").groupBy("domain", "word").agg(F.sum("n").alias("n")).where("n >= 3")
    by: dict[str, Counter] = {}
    for r in sums.collect():  # words that three of the `most` texts share
        by.setdefault(r["domain"], Counter())[r["word"]] = r["n"]
    model = fit([(by[d], d) for d in sorted(by)])

    def evidence(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [model.evidence(t)[0] for t in batch.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("domain"), pa.array(found, pa.list_(pa.float64()))], ["domain", "evidence"])

    held = rows.where(back).select("domain", "text").mapInArrow(evidence, "domain string, evidence array<double>")
    return calibrate(model, [(np.array(r["evidence"]), r["domain"]) for r in held.collect()])  # a vector for each of most / HELD_BACK rows


def memberships(docs: DataFrame, model: Domains, tokens: str = "tokens", posterior: str = "posterior") -> DataFrame:
    """docs with the columns `tokens` (words) and `posterior`. Narrow: no shuffle. Columns of these names are replaced."""
    keep = [c for c in docs.columns if c not in (tokens, posterior)]
    schema = ", ".join([*(f"`{n}` {t}" for n, t in docs.select(*(f"`{c}`" for c in keep)).dtypes), f"`{tokens}` long, `{posterior}` array<double>"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        release()
        for batch in batches:
            found = [model.posterior(t) for t in batch.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in keep), pa.array([n for _, n in found], pa.int64()), pa.array([p for p, _ in found], pa.list_(pa.float64()))], [*keep, tokens, posterior])

    return docs.mapInArrow(without_gc(run), schema)


def moments(members: DataFrame, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(expected tokens of each domain at rate 1, k x k matrix of the preconditioned least squares). k + k*k sums."""
    p = [F.col("posterior")[i] for i in range(k)]
    row = members.agg(*(F.coalesce(F.sum(F.col("tokens") * p[i]), F.lit(0.0)).alias(f"s{i}") for i in range(k)), *(F.coalesce(F.sum(F.col("tokens") * p[i] * p[j]), F.lit(0.0)).alias(f"m{i}_{j}") for i in range(k) for j in range(k))).first()
    return np.array(row[:k], dtype=float), np.array(row[k:], dtype=float).reshape(k, k)


def rate_after(gradients: list[np.ndarray], least: float = 0.0, posterior: str = "posterior") -> Column:
    """The rate of a document after steps along the gradients, each projected to [least, infinity)."""
    if not gradients:
        return F.lit(1.0)
    steps = F.array(*(F.array(*(F.lit(float(x)) for x in g)) for g in gradients))
    dot = lambda g: F.aggregate(F.zip_with(F.col(f"`{posterior}`"), g, lambda a, b: a * b), F.lit(0.0), lambda a, b: a + b)
    return F.aggregate(steps, F.lit(1.0), lambda r, g: F.greatest(r - dot(g), F.lit(float(least))))


def solve(members: DataFrame, targets: np.ndarray, least: float = 0.0, rounds: int = 100, tolerance: float = 1e-3) -> tuple[list[np.ndarray], np.ndarray]:
    """(gradients, domain tokens they give). Ends when no domain is off by more than `tolerance` of the total target.

    The gradient is preconditioned: by the document's tokens, so that rates of long and short documents move alike, and
    by the domains' k x k curvature. While no rate meets its bound one step is exact; a step that makes the error larger
    is taken back and halved, and after one that helps the next is half as long again. Where that gains nothing more, plain steps (by the largest curvature alone) go on; where
    these gain nothing more either, the bounds keep the targets out of reach and what is left is the least squares
    residual. Rounds that run out before are an error, unless what is left is small (20 times the tolerance).
    """
    k = len(targets)
    now, matrix = moments(members, k)
    total, gradients = max(float(targets.sum()), 1.0), []
    curved = np.linalg.pinv(matrix + 1e-9 * np.trace(matrix) * np.eye(k) / k) if matrix.any() else np.zeros((k, k))
    plain = np.eye(k) / max(float(np.linalg.eigvalsh(matrix).max()), 1e-300) if matrix.any() else np.zeros((k, k))
    ways, step, idle = [curved, plain], 1.0, 0
    for _ in range(rounds):
        if np.abs(now - targets).max() <= tolerance * total:
            return gradients, now
        if step < 1e-3 or idle >= 3:
            ways, step, idle = ways[1:], 1.0, 0
            if not ways:
                return gradients, now
        tried = [*gradients, step * ways[0] @ (now - targets)]
        rate = rate_after(tried, least)
        row = members.select("tokens", "posterior", rate.alias("rate")).agg(*(F.coalesce(F.sum(F.col("rate") * F.col("tokens") * F.col("posterior")[i]), F.lit(0.0)).alias(f"s{i}") for i in range(k))).first()
        got = np.array(row, dtype=float)
        was, error = np.linalg.norm(now - targets), np.linalg.norm(got - targets)
        if error < was:
            idle = idle + 1 if error > 0.99 * was else 0
            now, gradients, step = got, tried, step * (1.5 if len(ways) == 1 else 1.0)
        else:
            step /= 2
    if np.abs(now - targets).max() <= 20 * tolerance * total:
        return gradients, now
    raise RuntimeError(f"rates didn't settle in {rounds} rounds: {now.tolist()} for {targets.tolist()}")


def smoothed_targets(now: np.ndarray, power: float = 0.7) -> np.ndarray:
    """Target tokens whose shares are the present ones to the power, scaled so that no domain has to shrink."""
    share = np.where(now > 0, now, 0) ** power
    if not share.any():
        return now
    share = share / share.sum()
    return share * max(n / s for n, s in zip(now, share, strict=True) if s > 0)


@dataclass
class Plan:
    model: Domains
    gradients: list[np.ndarray]
    least: float
    targets: np.ndarray
    reached: np.ndarray
    seed: int
    members: DataFrame  # doc_id, tokens, posterior and chance of each row

    @property
    def residual(self) -> float:
        """How far the domain that is furthest off misses its target, as a share of all target tokens."""
        return float(np.abs(self.reached - self.targets).max() / max(self.targets.sum(), 1.0))

    def rate(self, posterior: str = "posterior") -> Column:
        return rate_after(self.gradients, self.least, posterior)

    def rated(self) -> DataFrame:
        """(doc_id, tokens, posterior, rate, copies) of the rows that were planned for, from their written scores."""
        return self.members.withColumn("rate", self.rate()).withColumn("copies", copies(F.col("rate"), F.col("chance"))).drop("chance")


def copies(rate: Column, chance: Column) -> Column:
    """The rate rounded up or down by a number from [0, 1), so that its mean is the rate."""
    return (F.floor(rate) + (chance < rate - F.floor(rate)).cast("long")).cast("long")


def chance(seed: int) -> Column:
    """A number from [0, 1) by id and text."""
    return F.pmod(F.xxhash64(F.lit(seed), "doc_id", "text"), F.lit(1 << 30)) / float(1 << 30)


def plan(docs: DataFrame, labelled: DataFrame, domain: str = "lang", weights: dict[str, float] | None = None, seed: int = 5) -> Plan:
    """Fit the classifier and the rates over all of docs (doc_id, text, domain).

    weights: target share of each domain, with as many tokens in all as there are, rates from 0 on; none:
    smoothed_targets() and rates from 1 on, which repeats documents of small domains and drops none. copies: the rate
    rounded up or down by a seeded hash of id and text, so that its mean is the rate. Null and empty texts have no
    tokens and the prior as posterior. An empty table, or one without labelled rows, gives rates of 1 or, where weights
    name none of its domains, too.
    """
    model = train(docs, labelled, domain)
    members = materialise(memberships(docs.select("doc_id", "text"), model).withColumn("chance", chance(seed)).drop("text"), "members")
    now, _ = moments(members, len(model.names))
    if weights is None:
        targets = smoothed_targets(now)
    else:
        share = np.array([max(0.0, weights.get(n, 0.0)) for n in model.names])
        targets = now.sum() * share / share.sum() if share.any() else now
    least = 1.0 if weights is None else 0.0
    gradients, reached = solve(members, targets, least)
    return Plan(model, gradients, least, targets, reached, seed, members)


def rates(docs: DataFrame, labelled: DataFrame, domain: str = "lang", weights: dict[str, float] | None = None) -> DataFrame:
    """(doc_id, tokens, domain, posterior, rate, copies, residual) of each row; domain: the likeliest; residual: Plan.residual."""
    found = plan(docs, labelled, domain, weights)
    likeliest = F.get(F.array(*(F.lit(n) for n in found.model.names)), F.array_position("posterior", F.array_max("posterior")).cast("int") - 1)
    return found.rated().select("doc_id", "tokens", likeliest.alias("domain"), "posterior", "rate", "copies", F.lit(found.residual).alias("residual"))


def mix(docs: DataFrame, labelled: DataFrame, domain: str = "lang", weights: dict[str, float] | None = None) -> DataFrame:
    """docs, each row as often as its copies say. No shuffle: documents are scored again where they are. Columns of any name pass through."""
    found = plan(docs, labelled, domain, weights)
    tokens, posterior, times, copy = fresh(docs.columns, "tokens", "posterior", "times", "copy")
    scored = memberships(docs, found.model, tokens, posterior)
    timed = scored.withColumn(times, copies(found.rate(posterior), chance(found.seed)).cast("int"))
    names = [F.col(f"`{c}`") for c in docs.columns]
    return timed.where(F.col(times) > 0).select(*names, F.explode(F.sequence(F.lit(1), F.col(times))).alias(copy)).select(*names)
