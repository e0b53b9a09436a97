"""Quality classifier by positive-unlabelled learning with the non-negative risk.

Trusted positives (labels.quality = 1, training fold only) and unlabelled texts train a small network; labelled negatives
are never looked at. The class prior among the unlabelled is estimated first: for any set A of scores, the unlabelled
share of A is at least prior * the positives' share of A, with equality where A has no negatives, so the smallest ratio of
the two (with a confidence term, over the sets "score at least t") estimates it. The network then minimises
prior * E_p[loss(+)] + max(0, E_u[loss(-)] - prior * E_p[loss(-)]) with the logistic loss; where the second term falls
below zero, the step goes the other way, as the non-negative estimator asks.

Fitting uses a bounded sample (`max_positive`, `max_unlabelled` rows, chosen by a hash of doc_id, gathered as features on
the driver); scoring runs over every whole text in the workers, one Arrow batch at a time.

Defined cases: null and empty texts are scored like any other (features of no words); without positives or unlabelled
rows all scores are 0.5; a null label never counts, and a doc_id with both labels is a trusted positive; texts that tie
get equal scores, and so do repeated rows; very long texts are read whole, in memory linear in them; a score of exactly the
threshold is accepted; an empty table gives an empty result; extra columns are ignored, and lang, source and doc_id are
never inputs.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sparkverdict.llm.common import ship_package

PUNCTUATION = [i for i in range(33, 127) if not chr(i).isalnum()]
N_FEATURES = len(PUNCTUATION) + 14
FOLDS = 5
THRESHOLD = 0.3


@dataclass(frozen=True)
class Fit:
    max_positive: int = 4000
    max_unlabelled: int = 6000
    hidden: int = 24
    steps: int = 400
    rate: float = 0.01
    decay: float = 1e-4
    seed: int = 11


def features(text: str | None) -> np.ndarray:
    """Shares of byte classes and punctuation, word and line measures; all of the whole text."""
    text = text or ""
    raw = np.frombuffer(text.encode("utf-8", "replace"), "u1")
    hist = np.bincount(raw, minlength=256).astype("f8")
    n = max(1, len(raw))
    words = text.split()
    m = max(1, len(words))
    lines = [x for x in text.split("\n") if x.strip()]
    upper, lower = hist[65:91].sum(), hist[97:123].sum()
    same = sum(a == b for a, b in zip(words, words[1:]))
    shares = [
        upper / max(1.0, upper + lower), hist[48:58].sum() / n, hist[10] / n, hist[128:].sum() / n, same / m, len(set(words)) / m ** 0.9,
        1 - len(set(lines)) / max(1, len(lines)), sum(map(str.isupper, words)) / m, sum(map(str.isalpha, words)) / m, hist[33:48].sum() / n,
    ]
    sizes = [math.log1p(len(words)), math.log1p(len(lines)), len(text) / m / 10, math.log1p(m / max(1, len(lines)))]
    return np.asarray([*np.log1p(100 * hist[PUNCTUATION] / m), *np.log1p(20 * np.asarray(shares)), *sizes], "f4")


@dataclass(frozen=True)
class Model:
    mean: np.ndarray
    scale: np.ndarray
    weights: tuple[np.ndarray, ...]
    prior: float

    def score(self, x: np.ndarray) -> np.ndarray:
        w1, b1, w2, b2 = self.weights
        z = np.clip((x - self.mean) / self.scale, -6, 6)
        g = np.tanh(z @ w1 + b1) @ w2 + b2
        return 1 / (1 + np.exp(-np.clip(g, -30, 30)))


def _softplus(x: np.ndarray) -> np.ndarray:
    return np.logaddexp(0, x)


def _train(p: np.ndarray, u: np.ndarray, prior: float | None, fit: Fit) -> tuple[np.ndarray, ...]:
    """Adam on the non-negative risk; without a prior, on plain logistic loss of positives against unlabelled."""
    rng = np.random.default_rng(fit.seed)
    d = p.shape[1]
    params = [rng.normal(0, 1 / math.sqrt(d), (d, fit.hidden)), np.zeros(fit.hidden), rng.normal(0, 1 / math.sqrt(fit.hidden), fit.hidden), np.zeros(1)]
    m, v = [np.zeros_like(x) for x in params], [np.zeros_like(x) for x in params]
    x = np.concatenate([p, u])
    n_p, n_u = len(p), len(u)
    for step in range(1, fit.steps + 1):
        h = np.tanh(x @ params[0] + params[1])
        g = h @ params[2] + params[3]
        s = 1 / (1 + np.exp(-np.clip(g, -30, 30)))
        s_p, s_u = s[:n_p], s[n_p:]
        if prior is None:
            dg = np.concatenate([(s_p - 1) / n_p, s_u / n_u])
        else:
            negative = _softplus(g[n_p:]).mean() - prior * _softplus(g[:n_p]).mean()
            if negative >= 0:
                dg = np.concatenate([prior * (s_p - 1) / n_p - prior * s_p / n_p, s_u / n_u])
            else:
                dg = np.concatenate([prior * s_p / n_p, -s_u / n_u])
        dh = np.outer(dg, params[2]) * (1 - h * h)
        grads = [x.T @ dh, dh.sum(0), h.T @ dg, np.asarray([dg.sum()])]
        rate = fit.rate * (0.1 if step > 0.8 * fit.steps else 1)
        for i, grad in enumerate(grads):
            grad = grad + fit.decay * params[i]
            m[i] = 0.9 * m[i] + 0.1 * grad
            v[i] = 0.999 * v[i] + 0.001 * grad * grad
            params[i] = params[i] - rate * (m[i] / (1 - 0.9**step)) / (np.sqrt(v[i] / (1 - 0.999**step)) + 1e-8)
    return tuple(params)


def estimate_prior(p: np.ndarray, u: np.ndarray) -> float:
    """From the scores of positives and unlabelled that were not trained on."""
    cuts = np.quantile(p, np.linspace(0, 0.8, 81))
    share_p = (p[:, None] >= cuts).mean(0)
    share_u = (u[:, None] >= cuts).mean(0)
    slack = np.sqrt(np.log(20) / 2) * (1 / math.sqrt(len(p)) + 1 / math.sqrt(len(u)))
    best = np.argmin((share_u + slack) / np.maximum(share_p, 1e-9))
    return float(np.clip(share_u[best] / max(share_p[best], 1e-9), 0.05, 0.99))


def fit_model(p: np.ndarray, u: np.ndarray, fit: Fit = Fit()) -> Model:
    if not len(p) or not len(u):
        zero = np.zeros(N_FEATURES)
        return Model(zero, zero + 1, (np.zeros((N_FEATURES, 1)), np.zeros(1), np.zeros(1), np.zeros(1)), 0.5)
    p, u = p.astype("f8"), u.astype("f8")
    mean, scale = u.mean(0), u.std(0) + 1e-3
    p, u = np.clip((p - mean) / scale, -6, 6), np.clip((u - mean) / scale, -6, 6)
    first = Model(np.zeros_like(mean), np.ones_like(scale), _train(p[::2], u[::2], None, fit), 0.5)
    prior = estimate_prior(first.score(p[1::2]), first.score(u[1::2])) if min(len(p), len(u)) > 20 else 0.5
    return Model(mean, scale, _train(p, u, prior, fit), prior)


def _feature_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    from sparkverdict.llm.pu_quality import features

    for batch in batches:
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([features(x.as_py()).tolist() for x in batch.column(1)], pa.list_(pa.float32()))], names=["positive", "x"])


def held_out(doc_id: Column) -> Column:
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit(""))) % FOLDS == 0


def sample(docs: DataFrame, labels: DataFrame, fit: Fit) -> tuple[np.ndarray, np.ndarray]:
    """Features of bounded samples: trusted positives of the training folds, and unlabelled texts."""
    ship_package(docs.sparkSession)
    training = labels.filter(~held_out(F.col("doc_id")))
    ids = docs.select("doc_id").filter(F.col("doc_id").isNotNull())
    turn = F.xxhash64("doc_id")
    positive = ids.join(training.filter(F.col("quality") == 1).select("doc_id"), "doc_id", "left_semi").orderBy(turn, "doc_id").limit(fit.max_positive)
    unlabelled = ids.filter(~held_out(F.col("doc_id"))).join(labels.select("doc_id"), "doc_id", "left_anti").orderBy(turn, "doc_id").limit(fit.max_unlabelled)
    chosen = positive.select("doc_id", F.lit(True).alias("positive")).union(unlabelled.select("doc_id", F.lit(False))).dropDuplicates(["doc_id"])
    # chosen has at most max_positive + max_unlabelled rows of 9 bytes
    rows = docs.select("doc_id", F.col("text").cast("string").alias("text")).join(F.broadcast(chosen), "doc_id").select("doc_id", "positive", "text")
    # a doc_id that occurs many times counts once
    rows = rows.groupBy("doc_id").agg(F.first("positive").alias("positive"), F.max("text").alias("text")).select("positive", "text")
    found = rows.mapInArrow(_feature_batches, "positive boolean, x array<float>").toArrow()
    x = np.asarray(found.column("x").combine_chunks().flatten()).reshape(-1, N_FEATURES) if found.num_rows else np.zeros((0, N_FEATURES))
    flag = np.asarray(found.column("positive").to_pylist(), bool)
    order = np.lexsort(np.round(x.T, 4)) if len(x) else []  # the same order in every run
    x, flag = x[order], flag[order]
    return x[flag], x[~flag]


def _score_batches(model: Model, text: str = "_text"):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from sparkverdict.llm.common import slices
        from sparkverdict.llm.pu_quality import features

        for batch in slices(batches):
            x = np.stack([features(t.as_py()) for t in batch.column(text)])
            kept = [i for i, name in enumerate(batch.schema.names) if name != "_text"]
            yield pa.RecordBatch.from_arrays([*[batch.column(i) for i in kept], pa.array(model.score(x.astype("f8")))], names=[*[batch.schema.names[i] for i in kept], "score"])

    return run


def train(docs: DataFrame, labels: DataFrame, fit: Fit = Fit()) -> Model:
    return fit_model(*sample(docs, labels, fit), fit)


def score(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id and score, one row per document."""
    ship_package(docs.sparkSession)
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("_text")).mapInArrow(_score_batches(model), "doc_id long, score double")


def classify(docs: DataFrame, labels: DataFrame, fit: Fit = Fit()) -> DataFrame:
    scored = score(docs, train(docs, labels, fit))
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))


def accepted(docs: DataFrame, labels: DataFrame, fit: Fit = Fit()) -> DataFrame:
    """The documents, with all their columns, that score at least the threshold."""
    model = train(docs, labels, fit)
    ship_package(docs.sparkSession)
    names = [f"_c{i}" for i in range(len(docs.columns))]
    renamed = docs.toDF(*names)
    schema = ", ".join(f"{n} {f.dataType.simpleString()}" for n, f in zip(names, docs.schema.fields, strict=True))
    at = [c.lower() for c in docs.columns].index("text")
    # a text goes to the workers once
    text = names[at] if docs.dtypes[at][1] == "string" else "_text"
    rows = (renamed if text != "_text" else renamed.withColumn("_text", F.col(names[at]).cast("string"))).mapInArrow(_score_batches(model, text), f"{schema}, score double")
    return rows.filter(F.col("score") >= THRESHOLD).drop("score").toDF(*docs.columns)
