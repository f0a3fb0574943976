"""Mixing to target weights with soft membership.

A labelled table teaches a classifier: softmax regression over the presence of
hashed words, of which those that tell a domain from the others best are used,
with a temperature that labelled rows it hasn't seen choose.  It gives every
document a posterior over the domains.  Then each document gets a rate, a number
from 0 to ``max_rate`` by which it is to be drawn, so that the expected words of
each domain, summed over all documents by rate, words and posterior, match the
targets.

The rates minimise the squared misfit of the totals plus a ridge on their distance
from 1, and the ridge shrinks to nothing.  The projection is lazy: the gradient
steps add up in one small vector, and a document's rate is 1 less its posterior's
product with that vector, brought into its bounds.  So a pass needs no state beside
the vector: one sum over all documents for several lengths of step, and small sums
back.  Steps are scaled by the second moments of the documents inside their bounds;
a plain gradient step that can't overshoot is always among those tried.

All of it is DataFrame functions; the driver sees tables whose size depends on
the numbers of word buckets and domains, and the chosen buckets of the bounded
sample of labelled documents.

Defined results: rows that repeat a doc_id are one document, as long as its
longest row, and each row has its rate; rows without doc_id count as one document as well; a null
or wordless text has the domains' shares as posterior and the rate that these
give; labels without a document, null labels and repeated labels (the least
holds) do no harm; without any labels the posterior is even, and without words
every rate is 1; targets out of reach give the nearest totals, and ``misfit`` says
how far off they are; an empty table gives an empty table; very long texts give
one row for each distinct word; other columns are not read.
"""

from __future__ import annotations

import json
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from nearfield.llm.common import keep, temporaries

#: Word buckets of the classifier, those used for each domain, and the most labelled documents it learns from.
BUCKETS, USED, LABELLED = 4096, 256, 10_000
#: What parts words: ASCII white space, control characters and punctuation.
BREAKS = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"
#: Temperatures that are tried; the labelled rows of every fifth hash choose.
TEMPERATURES = (2.0, 1.0, 0.5, 0.25, 0.1)
#: Domains of the labels table and the share of words that each is to have.
TARGETS = {"high": 0.96, "low": 0.035, "toxic": 0.005}
MAX_RATE, CLOSE = 2.0, 1e-6
#: Lengths of steps that a pass tries; when a ridge counts as solved, the least gain of a step, alone and as a share of
#: the ridge's first, and the most passes at one ridge; the least ridge.
STEPS, SOLVED, LEAST_GAIN, LEAST_SHARE, PASSES, LEAST_RIDGE = (1.0, 0.5, 0.2, 0.05, 0.01), 0.05, 1e-9, 1e-4, 8, 1.1e-8


def domains_of_labels(labels: DataFrame) -> DataFrame:
    """``doc_id, domain`` from quality and toxic marks; rows without either mark go."""
    domain = F.when(F.col("toxic") == 1, "toxic").when(F.col("quality") == 1, "high").when(F.col("quality") == 0, "low")
    return labels.select("doc_id", domain.alias("domain")).where(F.col("doc_id").isNotNull() & F.col("domain").isNotNull())


def _bounded(labelled: DataFrame, most: int) -> DataFrame:
    """At most about ``most`` labelled rows, taken by the hash of their id, one for each id."""
    single = labelled.groupBy("doc_id").agg(F.min("domain").alias("domain"))
    n = single.count()
    place = F.pmod(F.xxhash64(F.col("doc_id"), F.lit("labelled")), F.lit(1 << 30)) / float(1 << 30)
    taken = single.where(place < most / n) if n > most else single
    return taken.withColumn("unseen", F.pmod(F.xxhash64(F.col("doc_id"), F.lit("unseen")), F.lit(5)) == 0)


def _words(docs: DataFrame, *others: str) -> DataFrame:
    """One row for each distinct word of each text: its bucket, and the words of the text in all."""
    listed = docs.where(F.col("text").isNotNull()).select("doc_id", *others, F.split(F.lower("text"), BREAKS).alias("words"))
    # A break at either end leaves an empty word there.
    ends = (F.element_at("words", 1) == "").cast("int") + ((F.size("words") > 1) & (F.element_at("words", -1) == "")).cast("int")
    each = listed.select("doc_id", *others, (F.size("words") - ends).alias("n_words"), F.explode(F.array_distinct("words")).alias("word"))
    return each.where(F.col("word") != "").select("doc_id", *others, "n_words", F.pmod(F.xxhash64("word"), F.lit(BUCKETS)).cast("int").alias("bucket"))


@dataclass
class Classifier:
    """Domains, their biases, the weights of the buckets (domains by buckets), and the temperature."""

    domains: list[str]
    biases: np.ndarray
    weights: np.ndarray
    temperature: float = 1.0

    def sums(self, words: DataFrame) -> DataFrame:
        """``doc_id, n_words, s0, s1, ...``: each document's summed weights."""
        tables = [F.from_json(F.lit(json.dumps([round(float(x), 6) for x in row])), "array<double>") for row in self.weights]
        return words.groupBy("doc_id").agg(F.max("n_words").cast("long").alias("n_words"), *[F.sum(t[F.col("bucket")]).alias(f"s{k}") for k, t in enumerate(tables)])

    def posterior(self) -> list[Column]:
        logits = [(F.lit(round(float(b), 6)) + F.coalesce(F.col(f"s{k}"), F.lit(0.0))) * F.lit(self.temperature) for k, b in enumerate(self.biases)]
        top = F.greatest(*logits) if len(logits) > 1 else logits[0]
        parts = [F.exp(x - top) for x in logits]
        total = sum(parts[1:], parts[0])
        return [p / total for p in parts]


def softmax_fit(x: np.ndarray, y: np.ndarray, classes: int, rounds: int = 200, rate: float = 0.05, ridge: float = 1e-4) -> np.ndarray:
    """Weights (features plus bias, by classes) by full-batch adaptive gradient steps."""
    x = np.hstack([x, np.ones((len(x), 1), np.float32)])
    target = np.eye(classes, dtype=np.float32)[y]
    w = np.zeros((x.shape[1], classes), np.float32)
    first, second = np.zeros_like(w), np.zeros_like(w)
    for t in range(1, rounds + 1):
        logits = x @ w
        p = np.exp(logits - logits.max(axis=1, keepdims=True))
        p /= p.sum(axis=1, keepdims=True)
        g = x.T @ (p - target) / len(x) + ridge * w
        first, second = 0.9 * first + 0.1 * g, 0.99 * second + 0.01 * g * g
        w -= rate * (first / (1 - 0.9**t)) / (np.sqrt(second / (1 - 0.99**t)) + 1e-8)
    return w


def learn(docs: DataFrame, labelled: DataFrame, most: int = LABELLED, used: int = USED) -> Classifier | None:
    """The classifier from a bounded sample of the labelled documents; None without any."""
    sample = keep(_bounded(labelled, most))
    # At most ``most`` ids and labels, give or take the spread of a hash.
    known = docs.select("doc_id", "text").join(F.broadcast(sample), "doc_id")
    words = keep(_words(known, "domain", "unseen").select("doc_id", "domain", "unseen", "bucket").distinct())
    seen = words.where(~F.col("unseen"))
    counts = seen.groupBy("domain", "bucket").agg(F.count(F.lit(1)).alias("n")).collect()
    if not counts:
        return None
    domains = sorted({r.domain for r in counts})
    own = np.zeros((len(domains), BUCKETS))
    for r in counts:
        own[domains.index(r.domain), r.bucket] = r.n
    sizes = {r["domain"]: r["n"] for r in seen.groupBy("domain").agg(F.count_distinct("doc_id").alias("n")).collect()}
    n = np.array([sizes[d] for d in domains], float)
    share, other = own / n[:, None], (own.sum(axis=0) - own) / np.maximum(n.sum() - n, 1)[:, None]
    pooled = np.clip(own.sum(axis=0) / n.sum(), 1e-9, 1 - 1e-9)
    deviation = np.abs(share - other) / np.sqrt(pooled * (1 - pooled) * (1 / n + 1 / np.maximum(n.sum() - n, 1))[:, None])
    chosen = np.unique(np.argsort(-deviation, axis=1, kind="stable")[:, :used])
    rows = words.where(F.from_json(F.lit(json.dumps(_marks(chosen))), "array<int>")[F.col("bucket")] == 1).groupBy("doc_id", "domain", "unseen").agg(F.collect_set("bucket").alias("buckets")).orderBy("doc_id").collect()
    place = {int(b): i for i, b in enumerate(chosen)}
    x, y = np.zeros((len(rows), len(chosen)), np.float32), np.array([domains.index(r.domain) if r.domain in domains else -1 for r in rows])
    for i, r in enumerate(rows):
        x[i, [place[b] for b in r.buckets]] = 1
    fresh = np.array([r.unseen for r in rows], bool)
    fitted = softmax_fit(x[~fresh], y[~fresh], len(domains))
    weights = np.zeros((len(domains), BUCKETS))
    weights[:, chosen] = fitted[:-1].T
    model = Classifier(domains, fitted[-1], weights)
    test = fresh & (y >= 0)
    if test.any():
        logits = x[test] @ fitted[:-1] + fitted[-1]

        def loss(t: float) -> float:
            z = t * (logits - logits.max(axis=1, keepdims=True))
            return round(float((np.log(np.exp(z).sum(axis=1)) - z[np.arange(len(z)), y[test]]).mean()), 9)

        model.temperature = min(TEMPERATURES, key=loss)
    return model


def _marks(chosen: np.ndarray) -> list[int]:
    marks = np.zeros(BUCKETS, int)
    marks[chosen] = 1
    return marks.tolist()


def memberships(docs: DataFrame, model: Classifier | None, domains: list[str]) -> DataFrame:
    """``doc_id, n_words, p0, p1, ...`` over ``domains``: one row for each document."""
    ids = docs.select("doc_id").distinct()
    if model is None:
        n = _words(docs).groupBy("doc_id").agg(F.max("n_words").cast("long").alias("n_words"))
        even = [F.lit(1.0 / len(domains)).alias(f"p{k}") for k in range(len(domains))]
        return _met(ids, n).select("doc_id", F.coalesce("n_words", F.lit(0)).alias("n_words"), *even)
    given = dict(zip(model.domains, model.posterior(), strict=True))
    found = [F.round(given[d], 9).alias(f"p{k}") if d in given else F.lit(0.0).alias(f"p{k}") for k, d in enumerate(domains)]
    return _met(ids, model.sums(_words(docs))).select("doc_id", F.coalesce("n_words", F.lit(0)).alias("n_words"), *found)


def _met(ids: DataFrame, found: DataFrame) -> DataFrame:
    """Ids with what was found for them; a null id meets a null id."""
    return ids.join(found.withColumnRenamed("doc_id", "_id"), F.col("doc_id").eqNullSafe(F.col("_id")), "left").drop("_id")


def _rate(state: list[Column], max_rate: Column) -> Column:
    """All gradient steps so far, taken from rate 1 and projected to the bounds at once."""
    slope = sum((F.col(f"p{k}") * state[k] for k in range(1, len(state))), F.col("p0") * state[0])
    return F.greatest(F.lit(0.0), F.least(max_rate, F.lit(1.0) - slope))


@dataclass
class Trial:
    """What one sum over all documents tells of a state: totals by domain, moments of the free documents, and the value."""

    state: np.ndarray
    totals: np.ndarray
    moments: np.ndarray
    value: float


def _tried(members: DataFrame, states: list[np.ndarray], wanted: np.ndarray, words: float, max_rate: float) -> list[Trial]:
    """One pass over the documents for all of these states; a document is free if its rate is inside its bounds.

    The states are a literal array, so every pass runs the same compiled code.
    """
    size = len(wanted)
    listed = F.from_json(F.lit(json.dumps([{"t": t, "z": [float(x) for x in z]} for t, z in enumerate(states)])), "array<struct<t:int,z:array<double>>>")
    met = members.select(F.col("n_words").cast("double").alias("n"), *[f"p{k}" for k in range(size)], F.explode(listed).alias("s"))
    given = met.select("n", *[f"p{k}" for k in range(size)], F.col("s.t").alias("t"), _rate([F.col("s.z")[k] for k in range(size)], F.lit(float(max_rate))).alias("r"))
    pairs = [(i, j) for i in range(size) for j in range(i, size)]
    r = F.col("r")
    free = F.when((r > 0) & (r < max_rate), F.col("n")).otherwise(0.0)
    sums = [F.sum(F.col("n") * r * F.col(f"p{k}")) for k in range(size)] + [F.sum(free * F.col(f"p{i}") * F.col(f"p{j}")) for i, j in pairs] + [F.sum(F.col("n") * (r - 1) * (r - 1))]
    rows = given.groupBy("t").agg(*[x.alias(f"x{i}") for i, x in enumerate(sums)]).collect()
    flat = np.array([list(x)[1:] for x in sorted(rows, key=lambda x: x.t)]) / words
    out = []
    for z, row in zip(states, flat, strict=True):
        moments = np.zeros((size, size))
        for (i, j), x in zip(pairs, row[size:-1], strict=True):
            moments[i, j] = moments[j, i] = x
        out.append(Trial(z, row[:size], moments, float(z @ (wanted - row[:size]) - row[-1] / 2)))
    return out


def fitted(members: DataFrame, weights: list[float], max_rate: float = MAX_RATE, close: float = CLOSE) -> tuple[Column, list[float]]:
    """The rate as an expression over ``members``, and the misfit (the worst domain's, as a share of all words) before each step and at the end.

    Steps end when the targets are met to within ``close``, or when the least
    ridge is done: then the bounds stand in the way, the nearest totals that were
    seen hold, and the last misfit says how far off the targets they are.
    """
    size = len(weights)
    words = members.agg(F.sum(F.col("n_words").cast("double"))).first()[0] or 0.0
    if not words:
        return F.lit(1.0), []
    wanted, ridge, misfits = np.array(weights) / sum(weights), 1.0, []
    (at,) = _tried(members, [np.zeros(size)], wanted, words, max_rate)
    # At the start every document is free, so these are the moments of all.
    steepest, eye, gains, nearest = np.linalg.eigvalsh(at.moments)[-1], np.eye(size), [], (np.inf, at)
    while True:
        off = at.totals - wanted
        misfits.append(float(np.abs(off).max()))
        nearest = min(nearest, (float(off @ off), at), key=lambda x: x[0])
        solved = np.linalg.norm(off - ridge * at.state) <= SOLVED * np.linalg.norm(off)
        if misfits[-1] < close or (done := solved or len(gains) == PASSES or bool(gains) and gains[-1] < max(LEAST_GAIN, LEAST_SHARE * gains[0])) and ridge <= LEAST_RIDGE:
            break
        if done:
            ridge, gains = ridge / 10, []
        slope = off - ridge * at.state
        scaled = np.linalg.solve(at.moments + ridge * eye, slope)
        # The last is the plain gradient at a length that never overshoots.
        found = _tried(members, [at.state + s * scaled for s in STEPS] + [at.state + slope / (steepest + ridge)], wanted, words, max_rate)
        worth = [x.value + ridge / 2 * float(x.state @ x.state) for x in found]
        best = int(np.argmin(worth))
        gains.append(at.value + ridge / 2 * float(at.state @ at.state) - worth[best])
        at = found[best]
    misfits.append(float(np.abs(nearest[1].totals - wanted).max()))
    return _rate([F.lit(float(x)) for x in nearest[1].state], F.lit(float(max_rate))), misfits


def mix(docs: DataFrame, labelled: DataFrame, targets: dict[str, float] | None = None, max_rate: float = MAX_RATE) -> DataFrame:
    """``doc_id, n_words, p_<domain>..., rate, misfit``: one row for each document."""
    targets = targets or TARGETS
    domains = sorted(targets)
    slim = docs.select("doc_id", "text")
    with temporaries() as spared:
        members = keep(memberships(slim, learn(slim, labelled), domains))
        spared.append(members)
    rate, misfits = fitted(members, [targets[d] for d in domains], max_rate)
    return members.select("doc_id", F.col("n_words").cast("long").alias("n_words"), *[F.col(f"p{k}").alias(f"p_{d}") for k, d in enumerate(domains)], F.round(rate, 6).alias("rate"), F.lit(round(misfits[-1] if misfits else 0.0, 9)).alias("misfit"))


def drawn(docs: DataFrame, rated: DataFrame) -> DataFrame:
    """``docs`` with each row as often as its rate says: the whole part, and once more by the chance of the rest.

    Chance is the hash of the id, so the same document is drawn alike every time.
    """
    chance = F.pmod(F.xxhash64(F.col("doc_id"), F.lit("drawn")), F.lit(1 << 30)) / float(1 << 30)
    times = rated.select(F.col("doc_id").alias("_id"), F.floor(F.col("rate") + chance).cast("int").alias("_times"))
    met = docs.join(times, F.col("doc_id").eqNullSafe(F.col("_id")), "left").withColumn("_times", F.coalesce("_times", F.lit(1)))
    return met.where(F.col("_times") > 0).withColumn("_copy", F.explode(F.sequence(F.lit(1), F.col("_times")))).select(docs.columns)
