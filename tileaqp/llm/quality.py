"""Quality classifier: hashed word n-grams, logistic regression by follow-the-regularised-leader, sparse dot products.

A token is a run of word characters, a run of one other visible character class, or
a line end; features are hashed single tokens and pairs, weighted by their share in
the text. Texts are scored whole, in Arrow batches cut to bounded bytes.

Null and empty texts have no feature and get the score of the bias alone. A text of
any length counts whole. Repeated rows are scored each for itself; columns besides
the key and the text stay unless ``keep`` names others. A column named like the score is replaced. An empty table gives an empty result, and
a training set without rows gives the score 0.5 to every text.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from ..runtime import durable, ship
from . import _hashing as H

BITS = 20
BASE = 0x5851F42D4C957F2D
BATCH_BYTES = 1 << 19
#: At most so many labelled rows are used for training; the rows of smallest hashed key.
TRAIN_ROWS = 4_000
#: And at most so many bytes of their texts.
TRAIN_BYTES = 32 << 20

_CLASS = np.full(256, 3, np.uint8)  # 3: other visible bytes
for _lo, _hi, _k in ((0, 33, 0), (48, 58, 2), (65, 91, 1), (97, 123, 1), (128, 256, 1)):
    _CLASS[_lo:_hi] = _k
_CLASS[10] = 4
_CODES = H.symbol_codes(256, 7)
#: A token and itself again is one feature, whichever token it is.
_AGAIN = np.uint64(0x2545F4914F6CDD1D)


def features(raw: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hashed features of all texts of a batch, in order, and n + 1 offsets into them."""
    n = len(raw)
    if not n:
        return np.zeros(0, np.int64), np.zeros(len(at), np.int64)
    kind = _CLASS[raw]
    edge = np.ones(n + 1, bool)
    edge[1:n] = kind[1:] != kind[:-1]
    odd = np.flatnonzero(kind[1:] == 3) + 1
    edge[odd] |= raw[odd] != raw[odd - 1]
    edge[at] = True
    cut = np.flatnonzero(edge)
    start, end = cut[:-1], cut[1:]
    real = kind[start] > 0
    start, end = start[real], end[real]
    pw, inv = H.powers(n, BASE), H.powers(n, H.inverse_of(BASE))
    one = H.mix(H.span_hash(H.prefix_sums(_CODES[raw], pw), inv, start, end))
    doc = np.searchsorted(at, start, side="right") - 1
    two = np.where(one[:-1] == one[1:], _AGAIN, H.mix(one[:-1] * H.ODD + one[1:]))
    same = doc[1:] == doc[:-1]
    mask = np.uint64((1 << BITS) - 1)
    both = np.empty(2 * len(one), np.int64)
    both[0::2] = (one & mask).astype(np.int64)
    both[1::2] = -1
    both[1:-1:2][same] = (two[same] & mask).astype(np.int64)
    use = both >= 0
    where = np.repeat(doc, 2)[use]
    return both[use], np.searchsorted(where, np.arange(len(at)))


def _batches(column: pa.Array) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Slices of a column of bounded bytes, at least one text each."""
    raw, at = H.utf8(column)
    i = 0
    while i < len(at) - 1:
        j = max(i + 1, int(np.searchsorted(at, at[i] + BATCH_BYTES, side="right")) - 1)
        yield i, j, raw[at[i] : at[j]], at[i : j + 1] - at[i]
        i = j


def score_texts(column: pa.Array, weights: np.ndarray, bias: float) -> np.ndarray:
    out = np.empty(len(column))
    for i, j, raw, at in _batches(column):
        f, o = features(raw, at)
        n = np.diff(o)
        total = np.diff(np.concatenate([[0.0], np.cumsum(weights[f], dtype=np.float64)])[o])
        out[i:j] = 1 / (1 + np.exp(-np.clip(bias + total / np.maximum(np.sqrt(n), 1), -35, 35)))
    return out


def train(rows: Iterator[tuple[np.ndarray, int]], epochs: int = 4, alpha: float = 1.0, beta: float = 1.0, l1: float = 0.1, l2: float = 0.1) -> tuple[np.ndarray, float]:
    """Per-coordinate follow-the-regularised-leader over (hashed features, label) rows; the last coordinate is the bias."""
    data = []
    for f, y in rows:
        ids, count = np.unique(f, return_counts=True)
        data.append((np.append(ids, 1 << BITS), np.append(count / max(1.0, np.sqrt(count.sum())), 1.0), y))
    z, n = np.zeros((1 << BITS) + 1), np.zeros((1 << BITS) + 1)
    order = np.random.default_rng(5)
    for _ in range(epochs):
        for k in order.permutation(len(data)):
            ids, x, y = data[k]
            zi, ni = z[ids], n[ids]
            root = np.sqrt(ni)
            w = np.where(np.abs(zi) <= l1, 0.0, -(zi - np.sign(zi) * l1) / ((beta + root) / alpha + l2))
            p = 1 / (1 + np.exp(-np.clip(w @ x, -35, 35)))
            g = (p - y) * x
            z[ids] = zi + g - (np.sqrt(ni + g * g) - root) / alpha * w
            n[ids] = ni + g * g
    root = np.sqrt(n)
    w = np.where(np.abs(z) <= l1, 0.0, -(z - np.sign(z) * l1) / ((beta + root) / alpha + l2))
    return w[:-1].astype(np.float32), float(w[-1])


def held_out(key) -> F.Column:
    return F.coalesce(F.crc32(key.cast("string").cast("binary")) % 5 == 0, F.lit(False))


def training_rows(docs: DataFrame, labels: DataFrame, label: str, key: str, text: str, limit: int, most_bytes: int = TRAIN_BYTES) -> DataFrame:
    """(_t, _y): a durable table of at most ``limit`` labelled texts outside the held-out fold, the same on every run.

    Keys are taken by their hash. Of rows that repeat a key the smallest text counts; of
    labels that repeat one, the largest. Texts count in the same order until
    all together hold ``most_bytes``, each of at most a sixteenth of that, so that
    what training gathers is bounded whatever the rows hold.
    """
    chosen = (
        labels.filter(F.col(key).isNotNull() & F.col(label).isNotNull() & ~held_out(F.col(key)))
        .groupBy(F.col(key).alias("_k")).agg(F.max(F.col(label).cast("int")).alias("_y"))
        .orderBy(F.xxhash64("_k"), "_k").limit(limit)
    )
    body = F.coalesce(F.col(text).cast("string"), F.lit(""))
    met = docs.select(F.col(key).alias("_k"), body.alias("_t")).join(F.broadcast(chosen), "_k").filter(F.octet_length("_t") <= most_bytes // 16)
    rows = durable(met.groupBy("_k", "_y").agg(F.min("_t").alias("_t")), "training").withColumn("_h", F.xxhash64("_k"))
    sizes = sorted(map(tuple, rows.select("_h", F.octet_length("_t")).collect()))  # two numbers for each of the ``limit`` rows
    held = np.cumsum([n for _, n in sizes])
    last = int(np.searchsorted(held, most_bytes, side="right"))
    return (rows if last == len(sizes) else rows.filter(F.col("_h") < sizes[last][0])).select("_t", "_y")


def fit(docs: DataFrame, labels: DataFrame, label: str = "quality", key: str = "doc_id", text: str = "text", limit: int = TRAIN_ROWS) -> tuple[np.ndarray, float]:
    """Train on the driver from hashed features that the executors make; ``limit`` rows and ``TRAIN_BYTES`` bound what it gathers."""
    ship(docs.sparkSession)

    def hashed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i, j, raw, at in _batches(b.column(0)):
                f, o = features(raw, at)
                rows = pa.LargeListArray.from_arrays(pa.array(o), pa.array(f.astype(np.int32))).cast(pa.list_(pa.int32()))
                yield pa.RecordBatch.from_arrays([rows, b.column(1).slice(i, j - i)], names=["f", "y"])

    got = training_rows(docs, labels, label, key, text, limit).mapInArrow(hashed, "f array<int>, y int").toArrow()
    f, y = got.column(0).combine_chunks(), got.column(1).to_numpy()
    if not len(y):
        return np.zeros(1 << BITS, np.float32), 0.0
    rows = [(f[i].values.to_numpy(), int(y[i])) for i in range(len(y))]
    return train(iter(sorted(rows, key=lambda r: (len(r[0]), r[0].tobytes(), r[1]))))


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
            yield pa.RecordBatch.from_arrays([*(b.column(i) for i in names), pa.array(score_texts(b.column(spot), weights, bias))], names=[*keep, column])

    schema = docs.select(*keep).schema.add(column, "double")
    return docs.mapInArrow(scored, schema)
