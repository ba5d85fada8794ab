"""Quality of documents by hierarchical empirical Bayes.

A logistic classifier over the shape of a text gives the evidence of the document.  Its probabilities, summed by host
and by path, are a beta-binomial sample of each site's rate of good documents: hosts are shrunk towards the global
rate and paths towards their host, by prior strengths that the spread between sites implies (method of moments).  The
document's likelihood ratio and its path's posterior rate give the posterior odds.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import looked_up, saved
from .toxicity import labelled_sample

#: Labelled rows used for training at most, and the least posterior of a document that stays.
MAX_LABELLED, KEEP = 20_000, 0.5
FEATURES = ("upper", "symbol", "exclaim", "bar", "digit", "other", "distinct", "echo", "marked", "word_length", "lines", "size")
_CLASS = np.zeros(256, np.int64)
_CLASS[[*range(65, 91)]] = 1
_CLASS[[*b"#$%&*+/<=>@\\^_`~{}[]"]] = 2
_CLASS[ord("!")] = 3
_CLASS[ord("|")] = 4
_CLASS[[*range(48, 58)]] = 5
_CLASS[[*range(97, 123), *range(128, 256)]] = 6


def shape(text: str) -> list[float]:
    """Shares of characters, words and lines that tell junk from prose, in the order of FEATURES; zeros for an empty text."""
    data = text.encode("utf-8", "surrogatepass")
    words = data.split()
    if not words:
        return [0.0] * len(FEATURES)
    count = np.bincount(_CLASS[np.frombuffer(data, np.uint8)], minlength=7)
    letters, n, size = max(1, count[1] + count[6]), len(words), len(data)
    distinct, lines = len(set(words)), data.split(b"\n")
    echo = sum(a == b for a, b in zip(words, words[1:])) / n
    marked = sum(w[-1] in b"!#$%&*@~^" for w in words) / n
    return [
        count[1] / letters, count[2] / size * 5, count[3] / size * 5, count[4] / n * 3, count[5] / size * 5, count[0] / size,
        distinct / min(n, 50 + 4 * n**0.7), echo, marked, min(size / n / 10, 3.0), 1 - len(set(lines)) / len(lines), np.log1p(n) / 10,
    ]


@dataclass
class QualityModel:
    mean: np.ndarray
    scale: np.ndarray
    weights: np.ndarray
    bias: float
    base_rate: float

    def log_odds(self, x: np.ndarray) -> np.ndarray:
        return _expanded((x - self.mean) / self.scale) @ self.weights + self.bias


def _expanded(z: np.ndarray) -> np.ndarray:
    """Each standardised feature, and how far it lies out on either side."""
    z = np.clip(z, -6, 6)
    return np.concatenate((z, np.maximum(z - 1, 0), np.maximum(-z - 1, 0)), axis=1)


def fit(docs: DataFrame, labels: DataFrame, label: str = "quality", most: int = MAX_LABELLED, ridge: float = 1.0) -> QualityModel:
    """Newton's method on a bounded sample of labelled documents.  Without labels of both kinds the evidence is nil."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(1), pa.array([shape(t) for t in batch.column(0).to_pylist()], pa.list_(pa.float64()))], names=["y", "x"])

    rows = labelled_sample(docs, labels, label, most).select("text", "y").mapInArrow(run, "y int, x array<double>").collect()
    k = len(FEATURES)
    y = np.array([r["y"] for r in rows], np.float64)
    if not len(y) or y.min() == y.max():
        rate = min(max(float(y.mean()), 0.01), 0.99) if len(y) else 0.5
        return QualityModel(np.zeros(k), np.ones(k), np.zeros(3 * k), float(np.log(rate / (1 - rate))), rate)
    x = np.array([r["x"] for r in rows])
    mean, scale = x.mean(axis=0), np.maximum(x.std(axis=0), 1e-3)
    z = np.concatenate((_expanded((x - mean) / scale), np.ones((len(x), 1))), axis=1)
    w, penalty = np.zeros(3 * k + 1), np.full(3 * k + 1, ridge)
    penalty[-1] = 1e-6
    for _ in range(30):
        p = 1 / (1 + np.exp(-np.clip(z @ w, -30, 30)))
        step = np.linalg.solve((z * (p * (1 - p))[:, None]).T @ z + np.diag(penalty + 1e-9), z.T @ (y - p) - penalty * w)
        w = w + step
        if np.abs(step).max() < 1e-6:
            break
    return QualityModel(mean, scale, w[:-1], float(w[-1]), float(y.mean()))


def evidence(rows: DataFrame, model: QualityModel) -> DataFrame:
    """``rows`` with the log odds of each document alone in place of its _text.  Only texts go to Python, and one number comes back."""
    shared = rows.sparkSession.sparkContext.broadcast(model)

    def log_odds(texts: pd.Series) -> pd.Series:
        return pd.Series(shared.value.log_odds(np.array([shape(t) for t in texts]).reshape(-1, len(FEATURES))))

    return rows.withColumn("_log_odds", F.pandas_udf(log_odds, "double")("_text")).drop("_text")


def _strength(sites: DataFrame, rate: str, prior: str) -> float:
    """Prior strength (pseudo-documents) from the spread of site rates about their priors beyond binomial noise."""
    r = sites.agg(
        F.sum(F.col("n") * (F.col(rate) - F.col(prior)) ** 2).alias("spread"), F.sum(F.col(prior) * (1 - F.col(prior))).alias("noise"),
        F.sum("n").alias("n"), F.sum(F.col("n") * F.col(prior) * (1 - F.col(prior))).alias("room"),
    ).first()
    if not r["n"] or not r["room"]:
        return 1.0
    between = max((r["spread"] - r["noise"]) / r["n"], 1e-6)
    return min(max(r["room"] / r["n"] / between - 1, 1.0), 1e6)


def logit(p: Column) -> Column:
    q = F.least(F.greatest(p, F.lit(1e-6)), F.lit(1 - 1e-6))
    return F.log(q / (1 - q))


def posterior(scored: DataFrame, base_rate: float, keep: float = KEEP) -> DataFrame:
    """Adds _p_document, _p_host, _p_path, _score and _kept to a saved table with _host, _path and _log_odds.

    Sums are grouped with partial aggregation, so a host with a third of all rows costs a row per task.  Sites with a
    large share of the rows are broadcast, the others join by site.
    """
    p = 1 / (1 + F.exp(-F.col("_log_odds")))
    paths = saved(scored.groupBy("_host", "_path").agg(F.count("*").alias("n"), F.sum(p).alias("good")), "paths")
    total = paths.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"), F.sum("good").alias("good")).first()
    overall = total["good"] / total["n"] if total["n"] else base_rate
    hosts = paths.groupBy("_host").agg(F.sum("n").alias("n"), F.sum("good").alias("good"), F.count("*").alias("paths")).withColumn("rate", F.col("good") / F.col("n")).withColumn("prior", F.lit(float(overall)))
    k = _strength(hosts, "rate", "prior")
    hosts = hosts.select("_host", "paths", ((F.col("good") + k * F.col("prior")) / (F.col("n") + k)).alias("p_host"))
    sites = looked_up(paths, hosts, ["_host"], ["p_host"], "paths", paths.count(), nulls=True).withColumn("rate", F.col("good") / F.col("n"))
    k = _strength(sites, "rate", "p_host")
    sites = sites.withColumn("p_path", (F.col("good") + k * F.col("p_host")) / (F.col("n") + k))
    both = looked_up(scored, sites, ["_host", "_path"], ["p_host", "p_path"], "n", total["n"], nulls=True)
    odds = F.col("_log_odds") - float(np.log(base_rate / (1 - base_rate))) + logit(F.col("p_path"))
    both = both.withColumn("_score", 1 / (1 + F.exp(-odds)))
    return both.withColumnsRenamed({"p_host": "_p_host", "p_path": "_p_path"}).withColumn("_p_document", p).withColumn("_kept", F.col("_score") >= keep)


def url_levels(url: Column) -> tuple[Column, Column]:
    """Host and host with the first path segment of an address."""
    host = F.lower(F.regexp_extract(url, r"^[a-z]+://([^/?#:]+)", 1))
    return host, F.concat_ws("/", host, F.regexp_extract(url, r"^[a-z]+://[^/?#]+/([^/?#]*)", 1))


def _levels(host: Column | None, path: Column | None) -> list[Column]:
    host = F.col("source") if host is None else host
    path = F.concat_ws("/", F.coalesce(F.col("source"), F.lit("?")), F.coalesce(F.col("lang"), F.lit("?"))) if path is None else path
    return [F.coalesce("text", F.lit("")).alias("_text"), host.cast("string").alias("_host"), path.cast("string").alias("_path")]


def quality_posteriors(docs: DataFrame, labels: DataFrame, host: Column | None = None, path: Column | None = None, keep: float = KEEP) -> DataFrame:
    """doc_id, host, path, p_document, p_host, p_path, score and kept, one row per row of ``docs``.

    Default levels: the source as host, source and language as path.  A null host or path is a site of its own.  Null
    and empty texts have the shape of nothing and are judged by that; long texts are read whole.  Repeated rows are
    judged each and count each in their site.  An empty table gives no rows; other columns are ignored.
    """
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), *_levels(host, path))
    model = fit(rows.select("doc_id", F.col("_text").alias("text")), labels)
    found = posterior(saved(evidence(rows, model), "evidence"), model.base_rate, keep)
    return found.select("doc_id", *[F.col(f"_{c}").alias(c) for c in ("host", "path", "p_document", "p_host", "p_path", "score", "kept")])


def keep_good(docs: DataFrame, labels: DataFrame, host: Column | None = None, path: Column | None = None, keep: float = KEEP) -> DataFrame:
    """The rows of ``docs`` whose posterior quality isn't low, all columns as they were.

    Decided by row, so rows without an id and rows that repeat one are judged each by their own text and site.
    """
    rows = docs.select("*", *_levels(host, path))
    model = fit(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text")), labels)
    found = posterior(saved(evidence(rows, model), "evidence"), model.base_rate, keep)
    return found.where("_kept").select(*docs.columns)
