"""Toxicity: a linear classifier on character n-grams scaled by naive Bayes log-count ratios.

Texts are lower-cased; the n-grams of 3 to 5 characters are hashed. A feature is
the presence of an n-gram, times the log ratio of its smoothed shares in toxic
and other training texts; a ratio within ``SURE`` standard errors of zero is taken
as zero, as it tells nothing of the label. Executors count the n-grams and make the ratios; a
logistic regression is trained on all features whose ratio isn't zero. Scoring a
text looks at those alone, after one gather for each character and order.

Null and empty texts have no feature and get the score of the bias. Texts of any
length count whole. Repeated rows are scored each for itself, other columns stay
unless ``keep`` names some. A column named like the score is replaced. An empty table gives an empty result; without training rows every score is
0.5.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F

from ..runtime import durable, ship
from . import _hashing as H
from .quality import training_rows

BITS = 20
ORDERS = (3, 4, 5)
BATCH_BYTES = 1 << 15
#: At most so many labelled rows are used for training; the rows of smallest hashed key.
TRAIN_ROWS = 6_000
#: Standard errors that a log-count ratio is away from zero to be more than chance.
SURE = 2.0

_CODES = H.symbol_codes(1 << 12, 11)


def grams(texts: list[str]) -> tuple[list[np.ndarray], np.ndarray]:
    """For each order the hashed n-gram that starts at each character, -1 where it would leave its text; the n + 1 character offsets."""
    texts = [t.lower() for t in texts]
    at = np.zeros(len(texts) + 1, np.int64)
    np.cumsum([len(t) for t in texts], out=at[1:])
    points = np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), np.uint32)
    n = len(points)
    codes = _CODES[points & 0xFFF] + (points >> 12).astype(np.uint64) * H.ODD
    left = np.repeat(at[1:], np.diff(at)) - np.arange(n)
    out, h = [], codes.copy()
    for k in range(2, max(ORDERS) + 1):
        h = h * np.uint64(0x9E3779B185EBCA87)
        h[: n - k + 1] += codes[k - 1 :] if n >= k else 0
        if k in ORDERS:
            g = ((h ^ (h >> np.uint64(29))) * H.MIX >> np.uint64(64 - BITS)).astype(np.int32)
            g[left < k] = -1
            out.append(g)
    return out, at


def _present(texts: list[str], useful: np.ndarray | None = None) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(text, feature) pairs, each once, sorted; with ``useful`` only features marked there."""
    orders, at = grams(texts)
    n = len(at) - 1
    pairs = []
    for g in orders:
        hit = np.flatnonzero(g >= 0 if useful is None else useful[g])
        pairs.append(np.searchsorted(at, hit, side="right").astype(np.int64) - 1 << BITS | g[hit])
    both = np.unique(np.concatenate(pairs)) if n else np.zeros(0, np.int64)
    return both >> BITS, both & (1 << BITS) - 1


def _slices(column: pa.Array, most: int = BATCH_BYTES) -> Iterator[tuple[int, list[str]]]:
    texts = column.to_pylist()
    i = 0
    while i < len(texts):
        j, size = i, 0
        while j < len(texts) and (j == i or size + len(texts[j] or "") <= most):
            size += len(texts[j] or "")
            j += 1
        yield i, [t or "" for t in texts[i:j]]
        i = j


def log_ratio(yes: Column, n: Column, toxic: float, others: float, smoothing: float = 1.0) -> tuple[Column, Column]:
    """The log ratio of smoothed shares of an n-gram that ``n`` training texts have, ``yes`` toxic ones of them, and its standard error.

    Smoothing follows the sizes of both classes, so that an n-gram never seen has the ratio zero.
    """
    share = toxic / (toxic + others)
    one, two = yes + F.lit(smoothing * share), n - yes + F.lit(smoothing * (1 - share))
    return F.log(one / F.lit(toxic + smoothing)) - F.log(two / F.lit(others + smoothing)), F.sqrt(1 / one + 1 / two)


def train(rows: list[tuple[np.ndarray, int]], ratio: np.ndarray, rounds: int = 120, l2: float = 5e-2) -> tuple[np.ndarray, float]:
    """Weights of the hashed features (log-count ratio times regression weight) and the bias, from sets of features with a ratio."""
    size = 1 << BITS
    y = np.array([y for _, y in rows], np.float64)
    if not len(y) or y.min() == y.max():
        return np.zeros(size + 1, np.float32), 0.0 if not len(y) else float(np.clip((2 * y[0] - 1) * 3, -3, 3))
    few = np.flatnonzero(ratio)
    name = np.full(size, -1, np.int32)
    name[few] = np.arange(len(few))
    f = name[np.concatenate([np.zeros(0, np.int64), *(k for k, _ in rows)])]
    doc = np.repeat(np.arange(len(rows), dtype=np.int32), [len(k) for k, _ in rows])
    x = ratio[few].astype(np.float32)[f]
    w, b = np.zeros(len(few)), 0.0
    gw, gb = np.full(len(few), 1e-8), 1e-8
    weigh = np.where(y == 1, 0.5 / y.sum(), 0.5 / (1 - y).sum())  # both classes count alike
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(np.bincount(doc, x * w[f], len(y)) + b, -35, 35)))
        e = (p - y) * weigh
        d = np.bincount(f, x * e[doc], len(few)) + l2 * w
        gw += d * d
        gb += e.sum() ** 2
        w -= 0.1 * d / np.sqrt(gw)
        b -= 0.1 * e.sum() / np.sqrt(gb)
    out = np.zeros(size + 1, np.float32)  # the last one stands for -1: no n-gram
    out[few] = w * ratio[few]
    return out, float(b)


def score_texts(column: pa.Array, weights: np.ndarray, bias: float) -> np.ndarray:
    useful = weights != 0
    out = np.empty(len(column))
    for i, texts in _slices(column):
        doc, f = _present(texts, useful)
        out[i : i + len(texts)] = 1 / (1 + np.exp(-np.clip(np.bincount(doc, weights[f], len(texts)) + bias, -35, 35)))
    return out


def ratios(sets: DataFrame) -> np.ndarray:
    """The log-count ratio of each hashed n-gram of (f, y), zero where it may be chance; executors count, at most 2**BITS numbers come back."""
    out = np.zeros(1 << BITS)
    all_ = sets.agg(F.count("*").alias("n"), F.sum("y").alias("yes")).first()
    if not all_.n or all_.yes in (0, all_.n):
        return out
    counted = sets.select("y", F.explode("f").alias("f")).groupBy("f").agg(F.sum("y").alias("yes"), F.count("*").alias("n"))
    r, error = log_ratio(F.col("yes"), F.col("n"), float(all_.yes), float(all_.n - all_.yes))
    got = counted.select("f", r.alias("r"), error.alias("error")).filter(F.abs("r") > SURE * F.col("error")).select("f", "r").toArrow()
    out[got["f"].to_numpy()] = got["r"].to_numpy()
    return out


def feature_sets(rows: DataFrame) -> DataFrame:
    """(f, y): the distinct hashed n-grams of every training text, and its label."""

    def sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i, texts in _slices(b.column(0)):
                doc, f = _present(texts)
                at = np.searchsorted(doc, np.arange(len(texts) + 1))
                made = pa.ListArray.from_arrays(pa.array(at, pa.int32()), pa.array(f.astype(np.int32)))
                yield pa.RecordBatch.from_arrays([made, b.column(1).slice(i, len(texts))], names=["f", "y"])

    return rows.mapInArrow(sets, "f array<int>, y int")


def fit(docs: DataFrame, labels: DataFrame, label: str = "toxic", key: str = "doc_id", text: str = "text", limit: int = TRAIN_ROWS) -> tuple[np.ndarray, float]:
    """Count in the executors, then train on the driver from the features of ``limit`` texts whose ratio isn't zero."""
    spark = docs.sparkSession
    ship(spark)
    sets = durable(feature_sets(training_rows(docs, labels, label, key, text, limit)), "ngrams")
    ratio = ratios(sets)
    shared = spark.sparkContext.broadcast(ratio != 0)

    def useful(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            f = [x[shared.value[x]] for x in (v.values.to_numpy() for v in b.column(0))]
            yield pa.RecordBatch.from_arrays([pa.array(f, pa.list_(pa.int32())), b.column(1)], names=["f", "y"])

    got = sets.mapInArrow(useful, "f array<int>, y int").toArrow()
    rows = [(f.values.to_numpy(), y.as_py()) for b in got.to_batches() for f, y in zip(b.column(0), b.column(1), strict=True)]
    return train(sorted(rows, key=lambda r: (len(r[0]), zlib.crc32(r[0]), r[1])), ratio)  # the same order on every run


def score(docs: DataFrame, model: tuple[np.ndarray, float], text: str = "text", column: str = "score", keep: list[str] | None = None) -> DataFrame:
    """``docs`` (or its columns in ``keep``) with a score from 0 to 1 for every row."""
    spark = docs.sparkSession
    ship(spark)
    keep = [c for c in docs.columns if c != column] if keep is None else keep
    shared = spark.sparkContext.broadcast(model)
    spot, names = docs.columns.index(text), [docs.columns.index(c) for c in keep]

    def scored(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        weights, bias = shared.value
        for b in batches:
            yield pa.RecordBatch.from_arrays([*(b.column(i) for i in names), pa.array(score_texts(b.column(spot).cast(pa.string()), weights, bias))], names=[*keep, column])

    return docs.mapInArrow(scored, docs.select(*keep).schema.add(column, "double"))
