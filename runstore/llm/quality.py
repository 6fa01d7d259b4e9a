"""Operator 10: a quality classifier learned from positive and unlabelled documents.

Trusted positives are labelled rows of quality 1; all other text counts as
unlabelled.  A small network on text statistics is fitted by minimising the
*non-negative* unbiased risk: with class prior q, the risk of positives plus
the risk of unlabelled text less what positives contribute to it, where the
latter difference is not let below zero (a step that would push it there is
taken backwards).  The prior is estimated from the scores of a first plain
positive-versus-unlabelled fit: the least ratio, over thresholds, of the
unlabelled share above a threshold to the positives' share above it.

Two networks are fitted on the two halves of the samples and their logits
averaged.  Each scores the other half's positives, and all logits are shifted so
that CUT keeps all but LOST of those: the shift is a calibration.  The estimated
prior shapes the networks, hence the order of the scores, but where the cut
falls in that order is set by the held-back positives and not by the prior.

Fitting uses bounded samples (`sample` positives and as many unlabelled rows,
chosen by a hash of the id); features and scores cover whole texts of all rows.

Features are counts of character classes, line and word shapes and repetition,
computed from bytes.  A null or empty text has the features of no text and gets
a score like any other.  Labels of null quality are ignored; without a positive
every score is 0.5.  Ids may be null or repeated.  Texts of equal features tie;
a score at the cut is accepted.  A very long text is one array of its bytes.  An
empty table gives no rows.  Other columns are kept, a column of the score's name
is replaced.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from runstore.llm import base
from runstore.llm.language_id import fold

#: Byte classes: control, blank, newline, digit, lower, upper, stop, comma, other mark, bytes of wider characters, the mark '|'.
_CLASS = np.full(256, 8, np.uint8)
_CLASS[:32], _CLASS[32], _CLASS[10] = 0, 1, 2
_CLASS[48:58], _CLASS[97:123], _CLASS[65:91] = 3, 4, 5
_CLASS[[ord(c) for c in ".?!"]], _CLASS[[ord(c) for c in ",;:"]], _CLASS[ord("|")] = 6, 7, 10
_CLASS[128:] = 9
CLASSES = 11
CUT, LOST = 0.3, 0.002
FEATURES = CLASSES + 13


def features(text: str | None) -> np.ndarray:
    """FEATURES numbers of one whole text, each of moderate size."""
    raw = np.frombuffer((text or "").encode(), np.uint8)
    n = len(raw)
    out = np.zeros(FEATURES)
    if not n:
        out[-1] = 1.0
        return out
    kind = _CLASS[raw]
    counts = np.bincount(kind, minlength=CLASSES)
    out[:CLASSES] = np.sqrt(counts / n)
    words = text.split()
    m = len(words)
    lines = text.split("\n")
    mark = (kind == 8) | (kind == 10)
    f = out[CLASSES:]
    f[0] = np.log1p(m) / 10
    if m:
        distinct = len(set(words))
        f[1] = distinct / m
        f[2] = np.log1p(sum(map(len, words)) / m)
        f[3] = np.log1p(m / distinct) / 3
        pairs = set(zip(words, words[1:]))
        f[4] = len(pairs) / max(1, m - 1)
        f[5] = sum(map(str.__eq__, words, words[1:])) / m
    f[6] = len(set(lines)) / len(lines)
    f[7] = np.log1p(n / len(lines)) / 10
    f[8] = np.sqrt((mark[1:] & mark[:-1]).sum() / n)  # marks in runs
    f[9] = np.sqrt(((kind[1:] == 6) & (kind[:-1] == 6)).sum() / n)
    f[10] = np.sqrt((raw[1:] == raw[:-1]).sum() / n)
    f[11] = np.sqrt(((kind[1:] == 5) & (kind[:-1] == 5)).sum() / n)
    return out


@dataclass
class Model:
    """A one-hidden-layer network over standardised features."""

    mean: np.ndarray
    scale: np.ndarray
    networks: list[list[np.ndarray]]
    prior: float
    shift: float = 0.0

    def scores(self, x: np.ndarray) -> np.ndarray:
        if not self.networks:
            return np.full(len(x), 0.5)
        z = np.clip((x - self.mean) / self.scale, -6, 6)
        return _sigmoid(np.mean([_forward(w, z)[0] for w in self.networks], axis=0) + self.shift)


def _sigmoid(z: np.ndarray) -> np.ndarray:
    return 1.0 / (1.0 + np.exp(-np.clip(z, -40, 40)))


def _forward(w: list[np.ndarray], x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    h = np.tanh(x @ w[0] + w[1])
    return h @ w[2] + w[3], h


def negative_risk(z: np.ndarray, is_p: np.ndarray, prior: float) -> float:
    """Estimated risk of negatives: that of unlabelled text taken as negative, less what positives contribute to it."""
    return float(np.logaddexp(0, z[~is_p]).mean() - prior * np.logaddexp(0, z[is_p]).mean())


def slopes(z: np.ndarray, is_p: np.ndarray, prior: float | None) -> np.ndarray:
    """Step direction for each logit: the derivative of the risk, or away from overfitting where its negative part is below zero.

    Losses are logistic: of +1, log(1 + e^-z), slope s - 1; of -1, log(1 + e^z), slope s.
    """
    s, n_p, n_u = _sigmoid(z), is_p.sum(), (~is_p).sum()
    if prior is None:
        return np.where(is_p, (s - 1) / n_p, s / n_u)
    pull = np.where(is_p, -prior * s / n_p, s / n_u)
    if negative_risk(z, is_p, prior) < 0:
        return -pull
    return np.where(is_p, prior * (s - 1) / n_p, 0) + pull


def _fit(xp: np.ndarray, xu: np.ndarray, prior: float | None, steps: int, hidden: int, seed: int) -> list[np.ndarray]:
    """Minimise the non-negative PU risk; with prior None, the plain risk of P versus U."""
    rng = np.random.default_rng(seed)
    d = xp.shape[1]
    w = [rng.normal(0, 1 / np.sqrt(d), (d, hidden)), np.zeros(hidden), rng.normal(0, 0.3, hidden), np.zeros(1)]
    m1, m2 = [np.zeros_like(a) for a in w], [np.zeros_like(a) for a in w]
    size = 512
    for t in range(1, steps + 1):
        p, u = xp[rng.integers(0, len(xp), size)], xu[rng.integers(0, len(xu), size)]
        x = np.concatenate([p, u])
        x = x + rng.normal(0, 0.2, x.shape)  # small samples are not to be learned by heart
        z, h = _forward(w, x)
        g = slopes(z, np.arange(2 * size) < size, prior)
        dh = np.outer(g, w[2]) * (1 - h * h)
        grads = [x.T @ dh + 1e-4 * w[0], dh.sum(0), h.T @ g + 1e-4 * w[2], np.array([g.sum()])]
        rate = 0.01 * (1 - 0.9 * t / steps)
        for k, gr in enumerate(grads):
            m1[k] = 0.9 * m1[k] + 0.1 * gr
            m2[k] = 0.999 * m2[k] + 0.001 * gr * gr
            w[k] = w[k] - rate * (m1[k] / (1 - 0.9**t)) / (np.sqrt(m2[k] / (1 - 0.999**t)) + 1e-8)
    return w


def class_prior(positive: np.ndarray, unlabelled: np.ndarray) -> float:
    """Share of positives in unlabelled rows, from both groups' scores (higher: more like positives)."""
    p, u = np.sort(positive), np.sort(unlabelled)
    cuts = np.quantile(p, np.linspace(0.0, 0.9, 91))
    above_p = 1 - np.searchsorted(p, cuts) / len(p)
    above_u = 1 - np.searchsorted(u, cuts) / len(u)
    slack = 0.5 / np.sqrt(len(u)) + 0.5 / np.sqrt(len(p))
    ratio = (above_u + slack * np.sqrt(above_p)) / np.maximum(above_p, 1e-9)
    return float(np.clip(ratio.min(), 0.05, 0.95))


def train(docs: DataFrame, labels: DataFrame, text_col: str = "text", id_col: str = "doc_id", sample: int = 6000, steps: int = 1500, hidden: int = 16, seed: int = 11) -> Model:
    """Fit on about `sample` positives and `sample` unlabelled documents of docs.

    labels: (doc_id, quality) of trusted rows; only quality 1 is learned from.
    """
    good = labels.where(F.col("quality") == 1).select(F.col("doc_id").alias("__id")).distinct()
    unit = (F.xxhash64(F.lit(seed), F.col(id_col).cast("string")) % 1_000_000 + 1_000_000) % 1_000_000
    n_good, n_docs = good.count(), docs.count()
    some = good.where((F.xxhash64(F.lit(seed + 1), F.col("__id").cast("string")) % 1_000_000 + 1_000_000) % 1_000_000 < 1_000_000 * min(1.0, sample / max(1, n_good)))
    rows = docs.select(F.col(id_col).alias("d"), F.col(text_col).alias("t"), (unit < 1_000_000 * min(1.0, sample / max(1, n_docs))).alias("u"))
    rows = rows.join(F.broadcast(some.withColumn("p", F.lit(True))), F.col("d") == F.col("__id"), "left").where("p or u")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = [features(t.as_py()).tobytes() for t in batch.column(0)]
            yield pa.RecordBatch.from_arrays([batch.column(1), batch.column(2), pa.array(x, pa.binary())], names=["p", "u", "x"])

    got = rows.select("t", F.coalesce("p", F.lit(False)).alias("p"), F.coalesce("u", F.lit(False)).alias("u")).mapInArrow(run, "p boolean, u boolean, x binary").toPandas()
    got["x"] = got["x"].map(bytes)
    got = got.sort_values(["x", "p", "u"])  # rows arrive in any order
    x = np.frombuffer(b"".join(got["x"]), np.float64).reshape(len(got), FEATURES)
    p, u = got["p"].to_numpy(bool), got["u"].to_numpy(bool)
    if not p.any() or not u.any():
        return Model(np.zeros(FEATURES), np.ones(FEATURES), [], 0.5)
    mean, scale = x[u].mean(0), x[u].std(0) + 1e-3
    z = np.clip((x - mean) / scale, -6, 6)
    half = np.arange(len(z)) % 2 == 0
    if not (p & half).any() or not (p & ~half).any() or not (u & half).any() or not (u & ~half).any():
        half = np.ones(len(z), bool)
    parts = [half, ~half] if not half.all() else [half, half]
    plain = [_fit(z[p & a], z[u & a], None, steps // 2, hidden, seed) for a in parts]
    other = parts[::-1]
    prior = class_prior(*(np.concatenate([_forward(w, z[k & b])[0] for w, b in zip(plain, other)]) for k in (p, u)))
    nets = [_fit(z[p & a], z[u & a], prior, steps, hidden, seed + 1) for a in parts]
    kept = np.quantile(np.concatenate([_forward(w, z[p & b])[0] for w, b in zip(nets, other)]), LOST)
    return Model(mean, scale, nets, prior, float(np.log(CUT / (1 - CUT)) - kept))


def score(docs: DataFrame, model: Model, text_col: str = "text", out: str = "score") -> DataFrame:
    """docs with the probability of good quality (replacing a column of that name); no shuffle."""
    keep = [c for c in docs.columns if c != out]
    rows = docs.select(*[F.col(f"`{c}`") for c in keep], F.col(f"`{text_col}`").alias("__text"))
    schema = docs.select(*[F.col(f"`{c}`") for c in keep]).schema.add(out, "double")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = np.array([features(t.as_py()) for t in batch.column(batch.num_columns - 1)]).reshape(-1, FEATURES)
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(model.scores(x))], names=[*batch.schema.names[:-1], out])

    return rows.mapInArrow(run, schema)


def fit_on_tables(docs: DataFrame, labels: DataFrame) -> Model:
    """The model of the query: neither documents nor labels of the held-out fold are used."""
    return train(docs.where(fold("doc_id", 5) != 0), labels.where(fold("doc_id", 5) != 0))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = base.table(spark, sf_dir, "documents").select("doc_id", "text")
    out = score(docs, fit_on_tables(docs, base.table(spark, sf_dir, "labels")))
    return out.select("doc_id", (fold("doc_id", 5) == 0).alias("held_out"), "score", (F.col("score") >= CUT).cast("int").alias("predicted"))
