"""Quality classifier: a regularised quadratic discriminant over document statistics.

Every text becomes a short vector of transformed statistics, counted by numpy over its UTF-8 bytes and
its words. Each class gets a mean and a covariance that is shrunk towards the pooled covariance and then
towards its own diagonal level; the score is the logistic of the difference of the two Gaussian log
densities (Mahalanobis distances by cached Cholesky factors) plus the log prior ratio.

Defined results: a null text counts as empty; every text, empty ones included, gets a finite score; with
no usable label at all the score is 0.5, with labels of one class only it is that class's share (0 or 1);
repeated rows are scored one by one; an empty table gives no rows; further columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fedgrid.llm.common import crc_mod, hash_share, table

#: Bound on the labelled rows that the discriminant is fitted on (a hashed share of the labels).
MAX_LABELLED = 20_000

# Byte classes of the statistics.
_CLASS = np.zeros(256, np.int64)
_GROUPS = [
    b"abcdefghijklmnopqrstuvwxyz",
    b"ABCDEFGHIJKLMNOPQRSTUVWXYZ",
    b"0123456789",
    b" \t\r\x0b\x0c",
    b"\n",
    b".,;:'\"()-",
    b"!?",
    b"#$%&*+/<=>@[\\]^_`{|}~",
]
for _k, _group in enumerate(_GROUPS, start=1):
    _CLASS[list(_group)] = _k
_CLASS[128:] = len(_GROUPS) + 1
_N_CLASSES = len(_GROUPS) + 2
_CLASS = _CLASS.astype(np.uint8)
N_FEATURES = _N_CLASSES - 1 + 7


def statistics(text: str | None) -> np.ndarray:
    """The transformed statistics of one whole text."""
    text = text or ""
    data = text.encode("utf-8", "surrogatepass")
    n = max(len(data), 1)
    counts = np.zeros(_N_CLASSES)
    raw = np.frombuffer(data, np.uint8)
    for at in range(0, len(raw), 1 << 20):
        counts += np.bincount(_CLASS[raw[at : at + (1 << 20)]], minlength=_N_CLASSES)
    shares = np.sqrt(counts[1:] / n)
    words = text.split()
    lines = [x for x in text.split("\n") if x]
    n_words, n_lines = max(len(words), 1), max(len(lines), 1)
    rest = [
        np.log1p(len(text)),
        np.log1p(len(text) / n_words),
        np.log1p(len(words) / n_lines),
        np.sqrt(len(set(words)) / n_words),
        np.sqrt(len(set(lines)) / n_lines),
        np.sqrt(sum(map(str.isupper, words)) / n_words),
        np.sqrt(sum(map(str.isalpha, words)) / n_words),
    ]
    return np.concatenate([shares, rest])


@dataclass
class Discriminant:
    """Means, inverse Cholesky factors, log determinants and log priors of the two classes."""

    means: np.ndarray
    factors: np.ndarray
    log_dets: np.ndarray
    log_priors: np.ndarray
    constant: float | None = None

    def score(self, x: np.ndarray) -> np.ndarray:
        if self.constant is not None:
            return np.full(len(x), self.constant)
        logs = []
        for c in (0, 1):
            z = (x - self.means[c]) @ self.factors[c].T
            logs.append(self.log_priors[c] - self.log_dets[c] - 0.5 * np.einsum("ij,ij->i", z, z))
        return 1.0 / (1.0 + np.exp(np.clip(logs[0] - logs[1], -500, 500)))


def fit(x: np.ndarray, y: np.ndarray, pooling: float = 0.3, levelling: float = 0.05) -> Discriminant:
    """Class covariances S_c, shrunk as (1-l)((1-p)S_c + p S) + l mean(diag S) I."""
    shares = [float(np.mean(y == c)) if len(y) else 0.5 for c in (0, 1)]
    if min(np.sum(y == 0), np.sum(y == 1)) < 2:
        return Discriminant(*[np.zeros(0)] * 4, constant=shares[1])
    scale = x.std(axis=0)
    scale[scale < 1e-6] = 1.0
    z = x / scale
    groups = [z[y == c] for c in (0, 1)]
    covs = [np.cov(g, rowvar=False) for g in groups]
    pooled = sum(s * c for s, c in zip(shares, covs, strict=True))
    level = max(float(np.trace(pooled)) / len(pooled), 1e-3)
    means, factors, log_dets = [], [], []
    for g, cov in zip(groups, covs, strict=True):
        shrunk = (1 - pooling) * cov + pooling * pooled
        shrunk = (1 - levelling) * shrunk + levelling * level * np.eye(len(shrunk))
        chol = np.linalg.cholesky(shrunk)
        means.append(g.mean(axis=0) * scale)
        factors.append(np.linalg.inv(chol) / scale)
        log_dets.append(float(np.log(np.diag(chol)).sum()))
    return Discriminant(np.array(means), np.array(factors), np.array(log_dets), np.log(shares))


def train(documents: DataFrame, labels: DataFrame, bound: int = MAX_LABELLED) -> Discriminant:
    """Fitted on a hashed share of the labels, about ``bound`` rows at most; labels are 0 or 1."""
    labels = labels.where(F.col("quality").isin(0, 1) & F.col("doc_id").isNotNull())
    labels = labels.groupBy("doc_id").agg(F.max("quality").alias("y"))
    total = max(labels.count(), 1)
    picked = labels.where(hash_share("doc_id", min(1.0, bound / total)))
    stats = F.pandas_udf(lambda s: pd.Series([statistics(t) for t in s]), "array<double>")
    rows = documents.select("doc_id", "text").join(F.broadcast(picked), "doc_id").select(stats("text").alias("x"), "y")
    got = rows.toPandas()
    x = np.array(got["x"].tolist()).reshape(len(got), N_FEATURES)
    return fit(x, got["y"].to_numpy())


def scorer(model: Discriminant):
    """A Column function: text to score."""

    def score(texts: pd.Series) -> pd.Series:
        if not len(texts):
            return pd.Series([], dtype="float64")
        return pd.Series(model.score(np.array([statistics(t) for t in texts])))

    return F.pandas_udf(score, "double")


def query(spark: SparkSession, sf_dir: str, threshold: float = 0.3) -> DataFrame:
    documents = table(spark, sf_dir, "documents").select("doc_id", "text")
    labels = table(spark, sf_dir, "labels").select("doc_id", "quality")
    model = train(documents.where(crc_mod("doc_id", 5) != 0), labels.where(crc_mod("doc_id", 5) != 0))
    scored = documents.select(
        "doc_id", (crc_mod("doc_id", 5) == 0).alias("held_out"), scorer(model)("text").alias("score")
    )
    return scored.withColumn("predicted", (F.col("score") >= threshold).cast("int"))
