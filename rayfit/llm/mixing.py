"""Rates of documents that bring soft domains to target token totals.

A softmax classifier, learned from a table of labelled documents, gives every document a posterior over the domains. With
t tokens, posterior p and rate r of each document, sum r t p_d is the expected token total of domain d. Nonnegative
rates that make these totals meet the targets in least squares are found by accelerated projected gradient in the metric of
the tokens, starting from r = 1; see fit for the metric of the totals. A step changes r by a function of p and of one residual for each domain, so the state of the
whole fit is the list of past residuals: every iteration is one pass that folds that list for each document and sums a number
for each domain, and nothing is written."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import stats
from .common import ship, slices, staged
from .quality import matrix
from .textkit import Words

WORD_BUCKETS = 1 << 16
#: The classifier is fitted on at most about so many labelled rows, chosen by a hash of the key.
TRAIN_ROWS = 20_000
ITERATIONS, TOLERANCE = 40, 1e-4


class Domains:
    """Words' log odds by domain, and a softmax on statistics and on the mean and the highest log odds of a text's words."""

    def __init__(self, names, odds, mean=None, scale=None, beta=None):
        self.names, self.odds, self.mean, self.scale, self.beta = names, odds, mean, scale, beta

    def features(self, w: Words) -> np.ndarray:
        k = len(self.names)
        bucket = (w.hashes() >> np.uint64(48)).astype(np.int64)
        x = np.zeros((w.rows, len(stats.NAMES) + 2 * k))
        x[:, : len(stats.NAMES)] = stats.of(w)
        o = self.odds[bucket]
        n = np.maximum(1, np.diff(w.first))
        for d in range(k):
            x[:, len(stats.NAMES) + d] = np.bincount(w.row, weights=o[:, d], minlength=w.rows) / n
        full = np.flatnonzero(np.diff(w.first))
        if len(full):
            x[full, len(stats.NAMES) + k :] = np.maximum.reduceat(o, w.first[full], axis=0)
        return x

    def posterior(self, x: np.ndarray) -> np.ndarray:
        z = np.concatenate([np.ones((len(x), 1)), np.clip((x - self.mean) / self.scale, -8, 8)], 1) @ self.beta
        z = np.exp(z - z.max(1, keepdims=True))
        return z / z.sum(1, keepdims=True)


def softmax_fit(x: np.ndarray, y: np.ndarray, k: int, ridge: float = 1e-3, steps: int = 400) -> np.ndarray:
    """Coefficients by accelerated gradient descent with the step that the Gram matrix allows."""
    one = np.eye(k)[y]
    beta = before = np.zeros((x.shape[1], k))
    rate = 1 / (0.5 * np.linalg.eigvalsh(x.T @ x / len(x))[-1] + ridge)
    for s in range(steps):
        ahead = beta + s / (s + 3) * (beta - before)
        z = np.exp((z := x @ ahead) - z.max(1, keepdims=True))
        before, beta = beta, ahead - rate * (x.T @ (z / z.sum(1, keepdims=True) - one) / len(x) + ridge * ahead)
    return beta


def learn(docs: DataFrame, labels: DataFrame, key: str = "doc_id", text: str = "text", rows: int = TRAIN_ROWS) -> Domains:
    """labels: (key, domain string); nulls and further rows of a key do not count. Posteriors are uniform with one domain or none."""
    ship(docs.sparkSession)
    known = labels.filter(F.col("domain").isNotNull() & F.col(key).isNotNull()).groupBy(F.col(key).alias("key")).agg(F.min("domain").alias("domain"))
    total = known.count()
    if total > rows:
        known = known.filter(F.pmod(F.xxhash64("key"), F.lit(total)) < rows)
    labelled = staged(docs.select(F.col(key).alias("key"), F.coalesce(F.col(text), F.lit("")).alias("text")).join(known, "key").select("text", "domain"), "labelled")
    names = sorted(r[0] for r in labelled.select("domain").distinct().collect())

    def words(batches):
        for batch in batches:
            y, sums = np.array(batch.column(1).to_pylist(), object), {}
            for low, high in slices(batch.column(0)):
                w = Words(batch.column(0), low, high)
                # of each text, a word counts once
                code = np.unique(w.row.astype(np.int64) * WORD_BUCKETS + (w.hashes() >> np.uint64(48)).astype(np.int64))
                for name in set(y[low:high]):
                    own = code[(y[low:high] == name)[code // WORD_BUCKETS]] % WORD_BUCKETS
                    sums[name] = sums.get(name, 0) + np.bincount(own, minlength=WORD_BUCKETS)
            for name, c in sums.items():
                at = np.flatnonzero(c)
                yield pa.record_batch([pa.array([name] * len(at), pa.string()), pa.array(at), pa.array(c[at])], ["domain", "bucket", "n"])

    odds = np.zeros((WORD_BUCKETS, max(1, len(names))), np.float32)
    if len(names) < 2:
        model = Domains(names or ["all"], odds)
        model.mean, model.scale = np.zeros(len(stats.NAMES) + 2 * len(model.names)), np.ones(len(stats.NAMES) + 2 * len(model.names))
        model.beta = np.zeros((len(model.mean) + 1, len(model.names)))
        return model
    got = labelled.select("text", "domain").mapInArrow(words, "domain string, bucket long, n long").groupBy("domain", "bucket").agg(F.sum("n").alias("n")).toArrow()
    count = np.zeros((WORD_BUCKETS, len(names)))
    count[got["bucket"].to_numpy(), [names.index(x) for x in got["domain"].to_pylist()]] = got["n"].to_numpy()
    size = np.array([labelled.filter(F.col("domain") == n).count() for n in names], float)
    share, other = (count + 0.1) / (size + 1), (count.sum(1, keepdims=True) - count + 0.1) / (size.sum() - size + 1)
    model = Domains(names, np.clip(np.log(share / other) * (count.sum(1, keepdims=True) > 2), -6, 6).astype(np.float32))

    def features(batches):
        for batch in batches:
            for low, high in slices(batch.column(0)):
                x = model.features(Words(batch.column(0), low, high))
                yield pa.record_batch([pa.ListArray.from_arrays(pa.array(np.arange(0, x.size + 1, x.shape[1], dtype=np.int32)), pa.array(x.ravel())), batch.column(1).slice(low, high - low)], ["x", "domain"])

    held = labelled.select("text", "domain").mapInArrow(features, "x array<double>, domain string").toArrow()
    x, y = matrix(held["x"].combine_chunks()), np.array([names.index(d) for d in held["domain"].to_pylist()])
    model.mean, model.scale = x.mean(0), np.where(x.std(0) > 1e-9, x.std(0), 1.0)
    z = np.concatenate([np.ones((len(x), 1)), np.clip((x - model.mean) / model.scale, -8, 8)], 1)
    model.beta = softmax_fit(z, y, len(names))
    return model


def posteriors(docs: DataFrame, model: Domains, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, tokens, p array) of every row; tokens are the text's words, 0 for null and empty texts."""
    ship(docs.sparkSession)
    sent = docs.sparkSession.sparkContext.broadcast(model)  # WORD_BUCKETS x domains, whatever the corpus

    def run(batches):
        for batch in batches:
            for low, high in slices(batch.column(1)):
                w = Words(batch.column(1), low, high)
                p = sent.value.posterior(sent.value.features(w))
                yield pa.record_batch([batch.column(0).slice(low, high - low), pa.array(np.diff(w.first).astype(np.int64)), pa.ListArray.from_arrays(pa.array(np.arange(0, p.size + 1, p.shape[1], dtype=np.int32)), pa.array(p.ravel()))], ["key", "tokens", "p"])

    out = docs.select(F.col(key).alias("key"), F.coalesce(F.col(text), F.lit("")).alias("text")).mapInArrow(run, f"key {dict(docs.dtypes)[key]}, tokens long, p array<double>")
    return out.withColumnRenamed("key", key)


def fold(p: np.ndarray, past: list[np.ndarray]) -> np.ndarray:
    """The rates from the residuals so far, at which the next residual is due."""
    r = y = np.ones(len(p))
    for s, residual in enumerate(past):
        r, before = np.maximum(0, y - p @ residual), r
        y = np.maximum(0, r + s / (s + 3) * (r - before))
    return y


def fit(held: DataFrame, targets: np.ndarray, iterations: int = ITERATIONS, tolerance: float = TOLERANCE) -> tuple[list, np.ndarray]:
    """Residuals that give the rates of (tokens, p) rows, and the totals reached; see fold.

    Totals are compared in the metric of the inverse of sum t p p', the products at rates of 1: there a step of 1 would meet the
    targets at once if no rate had to stay nonnegative, so that only this bound needs further steps. Targets that no
    nonnegative rates give, like 0 for a domain that every document belongs to a little, are approached from step to step."""
    k = len(targets)

    def total(of):
        names = [f"s{i}" for i in range((1 + k) * k)]

        def run(batches):
            t = np.zeros((1 + k, k))
            for batch in batches:
                if batch.num_rows:
                    t += of(batch.column(0).to_numpy().astype(float), matrix(batch.column(1)))
            yield pa.record_batch([pa.array([x]) for x in t.ravel()], names)

        row = held.select("tokens", "p").mapInArrow(run, ", ".join(f"{n} double" for n in names)).agg(*(F.sum(n) for n in names)).first()
        return np.array([x or 0.0 for x in row]).reshape(1 + k, k)

    first = total(lambda t, p: np.concatenate([t @ p[None] if p.ndim == 1 else (t[None] @ p), (p * t[:, None]).T @ p]))
    now, gram = first[0], first[1:]
    unit = max(1.0, float(now.sum()))
    metric = np.linalg.pinv(gram / unit, rcond=1e-9, hermitian=True)
    past: list[np.ndarray] = []
    for _ in range(iterations):
        residual = (now - targets) / unit
        if np.abs(residual).max() <= tolerance:
            break
        past.append(metric @ residual)
        now = total(lambda t, p: np.concatenate([(t * fold(p, past))[None] @ p, np.zeros((k, k))]))[0]
    return past, now


def mix(docs: DataFrame, labels: DataFrame, shares: dict[str, float], full: str, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, tokens, domain probabilities, rate, copies) of every row.

    shares: the target share of tokens of each domain; those not named get 0. The total is chosen so that the domain full
    keeps its expected tokens. copies: rate rounded up or down by a hash of the key, so that its expectation is the rate.
    A row without words counts for nothing and keeps the rate of its posterior."""
    model = learn(docs, labels, key, text)
    held = staged(posteriors(docs, model, key, text), "posteriors")
    size = held.select(*(F.sum(F.col("tokens") * F.col("p")[i]).alias(f"d{i}") for i in range(len(model.names)))).first()
    size = np.array([x or 0.0 for x in size])
    want = np.array([shares.get(n, 0.0) for n in model.names])
    anchor = model.names.index(full) if full in model.names else int(np.argmax(want))
    targets = want / want[anchor] * size[anchor] if want[anchor] > 0 else want * size.sum()
    past, _ = fit(held, targets)

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                p = matrix(batch.column(2))
                yield pa.record_batch([batch.column(0), batch.column(1), batch.column(2), pa.array(fold(p, past))], ["key", "tokens", "p", "rate"])

    out = held.select(F.col(key).alias("key"), "tokens", "p").mapInArrow(run, f"key {dict(held.dtypes)[key]}, tokens long, p array<double>, rate double")
    spread = F.shiftrightunsigned(F.xxhash64("key", F.lit(29)), 11) / F.lit(float(1 << 53))
    return out.select(F.col("key").alias(key), "tokens", *(F.col("p")[i].alias(f"p_{n}") for i, n in enumerate(model.names)), "rate", F.floor(F.col("rate") + spread).cast("int").alias("copies"))
