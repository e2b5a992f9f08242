"""Repeated byte strings: bytes of every string of ``length`` bytes that starts at two places are removed.

All suffixes of a corpus don't fit the disk that its text takes, so only sampled ones
are named and compared. The sample is chosen by content instead of by residues: of
the 100-byte strings inside every window of ``length`` bytes, the one with the smallest
hash (the rightmost of equals) is an anchor, which makes about seven anchors for a
thousand bytes. Two equal windows hold the same anchor at the same place, so a window
repeats only if its anchor's string does.

An anchor has two names: that of its own string, and that of its whole context, all
bytes of windows that may hold it. Anchors whose string is nowhere else are dropped.
Those that share their context with another have all windows repeated. For the others the
contexts of equal strings are brought together, one for each name, and their windows
are compared with each other, found by hashes and decided by bytes; if too many contexts share a string, their windows are
counted one by one instead. The repeated windows of a text are merged and cut out.

Texts are told apart by a 128-bit digest, so copies are looked at once. Null texts
are empty. Texts of any length count whole, the longest in overlapping pieces.
Repeated rows are copies. Columns besides key and text don't matter. An empty table
gives an empty result.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from ..runtime import durable, ship
from . import _hashing as H
from ._marks import is_marked, mark

LENGTH = 400
#: Bytes of an anchor's string.
GRAM = 100
#: Window starts that are hashed at a time.
PIECE = 1 << 17
#: Contexts of one string that are compared in one task; windows of larger groups are counted.
MOST_CONTEXTS = 16_384
#: Windows of contexts that are hashed and compared at a time.
MOST_WINDOWS = 600_000
BASE = 0x5851F42D4C957F2D
_CODES = H.symbol_codes(256, 3)
_INVERSE = H.inverse_of(BASE)


def _sliding_min(a: np.ndarray, w: int) -> np.ndarray:
    """Minimum of every w following values: those before and after the next multiple of w."""
    m = -(-len(a) // w) * w
    full = np.full(m, np.uint64(2**64 - 1))
    full[: len(a)] = a
    rows = full.reshape(-1, w)
    before = np.minimum.accumulate(rows, axis=1).ravel()
    after = np.minimum.accumulate(rows[:, ::-1], axis=1)[:, ::-1].ravel()
    n = len(a) - w + 1
    return np.minimum(after[:n], before[w - 1 : w - 1 + n])


def _hashes(raw: np.ndarray, pw: np.ndarray, inv: np.ndarray):
    sums = H.prefix_sums(_CODES[raw], pw)
    return lambda start, end: H.mix((sums[end] - sums[start]) * inv[start])


def anchors(raw: np.ndarray, length: int = LENGTH, gram: int = GRAM) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Places of a text's anchors, and names of their strings and contexts."""
    n, reach = len(raw), length - gram
    found: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
    for first in range(0, n - length + 1, PIECE):
        lo, hi = max(0, first - reach), min(n, first + PIECE + 2 * length)
        part = raw[lo:hi]
        pw, inv = H.powers(len(part), BASE), H.powers(len(part), _INVERSE)
        span = _hashes(part, pw, inv)
        starts = np.arange(first - lo, min(first + PIECE, n - length + 1) - lo)
        at = np.arange(starts[0], starts[-1] + reach + 1)
        g = span(at, at + gram)
        low = _sliding_min((g & ~np.uint64(0xFFFFFF)) | (np.uint64(0xFFFFFF) - at.astype(np.uint64)), reach + 1)
        p = np.unique((np.uint64(0xFFFFFF) - (low & np.uint64(0xFFFFFF))).astype(np.int64))
        a, b = np.maximum(p - reach, 0 if lo == 0 else p - reach), np.minimum(p + length, len(part))
        shape = ((p - a) * (length + reach + 1) + (b - p)).astype(np.uint64)
        found.append((p + lo, g[p - at[0]], H.mix(span(a, b) + shape * H.ODD)))
    if not found:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64), np.zeros(0, np.uint64)
    p, g, x = (np.concatenate(c) for c in zip(*found, strict=True))
    p, once = np.unique(p, return_index=True)
    return p, g[once], x[once]


def _digest(data: bytes) -> tuple[int, int]:
    d = hashlib.md5(data, usedforsecurity=False).digest()
    return int.from_bytes(d[:8], "little", signed=True), int.from_bytes(d[8:], "little", signed=True)


def _rows(column: pa.Array) -> Iterator[bytes]:
    raw, at = H.utf8(column)
    view = raw.tobytes()
    for i in range(len(at) - 1):
        yield view[at[i] : at[i + 1]]


def scan(docs: DataFrame, key: str, text: str, length: int, gram: int) -> DataFrame:
    """A row per text: key, c1, c2 (digest), n_bytes, sha256, pos, g, x (anchors)."""

    def scanned(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            c1, c2, size, sha, ends, parts = [], [], [], [], [0], ([], [], [])
            for data in _rows(b.column(1)):
                x, y = _digest(data)
                c1.append(x)
                c2.append(y)
                size.append(len(data))
                sha.append(hashlib.sha256(data).hexdigest())
                got = anchors(np.frombuffer(data, np.uint8), length, gram)
                ends.append(ends[-1] + len(got[0]))
                for kept, part in zip(parts, got, strict=True):
                    kept.append(part.view(np.int64))
            lists = [pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(np.concatenate(k) if k else np.zeros(0, np.int64))) for k in parts]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(c1, pa.int64()), pa.array(c2, pa.int64()), pa.array(size, pa.int64()), pa.array(sha, pa.string()), *lists], names=[key, "c1", "c2", "n_bytes", "sha256", "pos", "g", "x"])

    rows = docs.select(F.col(key), F.col(text).cast("string").alias("_text"))
    return rows.mapInArrow(scanned, f"`{key}` {docs.schema[key].dataType.simpleString()}, c1 long, c2 long, n_bytes long, sha256 string, pos array<long>, g array<long>, x array<long>")


def _needed_texts(docs: DataFrame, text: str, wanted: DataFrame) -> DataFrame:
    """(c1, c2, data) of at least the texts whose digests are in ``wanted``: a table of fixed size sorts out most others in the scan."""
    shared = mark(wanted, "c1")

    def picked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = [(*_digest(data), data) for data in _rows(b.column(0))]
            keep = is_marked(shared.value, np.array([r[0] for r in rows], np.int64))
            out = [r for r, k in zip(rows, keep, strict=True) if k]
            c1, c2, datas = map(list, zip(*out, strict=True)) if out else ([], [], [])
            yield pa.RecordBatch.from_arrays([pa.array(c1, pa.int64()), pa.array(c2, pa.int64()), pa.array(datas, pa.binary())], names=["c1", "c2", "data"])

    return docs.select(F.col(text).cast("string").alias("_text")).mapInArrow(picked, "c1 long, c2 long, data binary")


def _windows(contexts: list[bytes], before: np.ndarray, group: np.ndarray, length: int, reach: int, most: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Windows of contexts: the context, the start in it, a hash that is equal for equal windows at one place of one group.

    Windows at different places can't be equal by the same anchor, so about ``most`` of
    them at a time, those of following places, are given out.
    """
    size = np.array([len(c) for c in contexts], np.int64)
    begin = np.cumsum(size) - size
    raw = np.frombuffer(b"".join(contexts), np.uint8)
    span = _hashes(raw, H.powers(len(raw), BASE), H.powers(len(raw), _INVERSE))
    step = max(1, most // max(1, len(contexts)))
    for place in range(0, reach + 1, step):
        low, high = np.maximum(0, before - place - step + 1), np.minimum(size - length, before - place)
        many = np.maximum(high - low + 1, 0)
        which = np.repeat(np.arange(len(contexts)), many)
        start = np.arange(len(which)) - np.repeat(np.cumsum(many) - many - low, many)
        at = begin[which] + start
        name = H.mix((before[which] - start).astype(np.uint64) * H.ODD + group[which].astype(np.uint64))
        yield which, start, H.mix(span(at, at + length) ^ name)


def _equal_windows(contexts: list[bytes], which: np.ndarray, start: np.ndarray, h: np.ndarray, lone: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray]:
    """Windows of contexts marked ``lone`` whose bytes are those of another window: hashes find them, bytes decide.

    A window is compared with the first of its hash, and that one with the second. Windows that follow one
    another in both contexts are compared as one stretch.
    """
    _, first, back, count = np.unique(h, return_index=True, return_inverse=True, return_counts=True)
    order = np.argsort(back, kind="stable")
    second = order[np.minimum(np.cumsum(count) - count + 1, len(order) - 1)]
    i = np.flatnonzero((count[back] > 1) & lone[which])
    other = np.where(first[back[i]] == i, second[back[i]], first[back[i]])
    i, other = (x[np.lexsort((start[i], which[i]))] for x in (i, other))
    follows = (np.diff(which[i]) == 0) & (np.diff(start[i]) == 1) & (np.diff(which[other]) == 0) & (np.diff(start[other]) == 1)
    ends = np.flatnonzero(np.concatenate([~follows, [True]])) if len(i) else np.zeros(0, np.int64)
    good, a = np.zeros(len(i), bool), 0
    for z in ends.tolist():
        c, d, m, n = contexts[which[i[a]]], contexts[which[other[a]]], int(start[i[a]]), int(start[other[a]])
        size = z - a + length
        if c[m : m + size] == d[n : n + size]:
            good[a : z + 1] = True
        else:  # hashes of unequal windows met: every window against all of its hash
            for k in range(a, z + 1):
                text = c[m + k - a : m + k - a + length]
                same = np.flatnonzero(back == back[i[k]])
                good[k] = sum(contexts[which[j]][start[j] : start[j] + length] == text for j in same.tolist()) > 1
        a = z + 1
    return which[i[good]], start[i[good]]


def _runs(which: np.ndarray, start: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Windows (sorted by context and start) as covered stretches: context, from, to."""
    if not len(which):
        return which, start, start
    new = np.concatenate([[True], (which[1:] != which[:-1]) | (start[1:] > start[:-1] + length)])
    i = np.flatnonzero(new)
    last = np.concatenate([i[1:], [len(which)]]) - 1
    return which[i], start[i], start[last] + length


def stretches(docs: DataFrame, scanned: DataFrame, text: str, length: int, gram: int) -> DataFrame:
    """(c1, c2, from, to): covered bytes of texts, overlapping ones not merged."""
    reach = length - gram
    each = scanned.select("c1", "c2", "n_bytes", F.inline(F.arrays_zip("pos", "g", "x")))
    names = each.groupBy("g", "x").agg(F.count("*").alias("n"), F.min(F.struct("c1", "c2", "pos")).alias("one"))
    names = durable(names, "names")
    strings = names.groupBy("g").agg(F.count("*").alias("d")).filter("d > 1")
    shared = names.filter("n > 1").select("g", "x")
    whole = each.join(shared, ["g", "x"], "left_semi").select("c1", "c2", F.greatest(F.col("pos") - reach, F.lit(0)).alias("from"), F.least(F.col("pos") + length, F.col("n_bytes")).alias("to"))
    whole = whole.filter(F.col("to") - F.col("from") >= length).distinct()
    # contexts that differ around the same string
    open_names = durable(names.join(strings, "g").select("g", "x", "n", "d", "one.*"), "open")
    wanted = open_names.groupBy("c1", "c2").agg(F.collect_list(F.struct("pos", "g", "x", "n", "d")).alias("at"))
    texts = _needed_texts(docs, text, open_names.select("c1")).dropDuplicates(["c1", "c2"])

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(b.num_rows):
                data, at = b.column(2)[i].as_py(), b.column(3)[i].values
                pos = at.field("pos").to_pylist()
                # contexts are cut a thousand at a time, as a long text may have many
                for k in range(0, len(pos), 1000):
                    some = pos[k : k + 1000]
                    part = at.slice(k, len(some))
                    ctx = [data[max(0, p - reach) : p + length] for p in some]
                    ids = [pa.array([b.column(c)[i].as_py()] * len(some), pa.int64()) for c in (0, 1)]
                    yield pa.RecordBatch.from_arrays([*ids, *(part.field(f) for f in ("pos", "g", "x", "n", "d")), pa.array(ctx, pa.binary())], names=["c1", "c2", "pos", "g", "x", "n", "d", "context"])

    contexts = durable(texts.join(wanted, ["c1", "c2"]).select("c1", "c2", "data", "at").mapInArrow(cut, "c1 long, c2 long, pos long, g long, x long, n long, d long, context binary"), "contexts")
    few = contexts.filter(F.col("d") <= MOST_CONTEXTS).groupBy("g").agg(F.collect_list(F.struct("c1", "c2", "pos", "n", "context")).alias("m"))
    kind = "c1 long, c2 long, `from` long, `to` long"

    def compared(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            lists = b.column(0)
            ends = np.concatenate([[0], np.cumsum(lists.value_lengths().to_numpy(zero_copy_only=False))])
            m = lists.flatten()
            k = 0
            while k < len(lists):
                stop = max(k + 1, int(np.searchsorted(ends, ends[k] + MOST_WINDOWS // 300, side="right")) - 1)
                part = m.slice(ends[k], ends[stop] - ends[k])
                group = np.repeat(np.arange(stop - k), np.diff(ends[k : stop + 1]))
                pos = part.field("pos").to_numpy(zero_copy_only=False)
                lone = part.field("n").to_numpy(zero_copy_only=False) == 1
                hits: list[tuple[np.ndarray, np.ndarray]] = []
                held = part.field("context").to_pylist()
                for which, start, h in _windows(held, np.minimum(pos, reach), group, length, reach, MOST_WINDOWS):
                    hits.append(_equal_windows(held, which, start, h, lone, length))
                which, start = (np.concatenate(c) for c in zip(*hits, strict=True))
                order = np.lexsort((start, which))
                at, a, z = _runs(which[order], start[order], length)
                base = np.maximum(pos - reach, 0)[at]
                taken = pa.array(at, pa.int64())
                yield pa.RecordBatch.from_arrays([part.field("c1").take(taken), part.field("c2").take(taken), pa.array(base + a), pa.array(base + z)], names=["c1", "c2", "from", "to"])
                k = stop

    def listed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for k in range(0, b.num_rows, 512):
                part = b.slice(k, 512)
                pos = part.column(2).to_numpy()
                # the string itself is part of the name, in place of the group's number
                for which, start, h in _windows(part.column(4).to_pylist(), np.minimum(pos, reach), part.column(3).to_numpy(), length, reach, MOST_WINDOWS):
                    taken = pa.array(which, pa.int64())
                    yield pa.RecordBatch.from_arrays([part.column(0).take(taken), part.column(1).take(taken), pa.array(np.maximum(pos - reach, 0)[which] + start), pa.array(h.view(np.int64)), part.column(5).take(taken)], names=["c1", "c2", "from", "h", "n"])

    many = contexts.filter(F.col("d") > MOST_CONTEXTS).select("c1", "c2", "pos", "g", "context", "n").mapInArrow(listed, "c1 long, c2 long, `from` long, h long, n long")
    again = many.groupBy("h").agg(F.count("*").alias("k")).filter("k > 1").select("h")
    counted = many.filter("n = 1").join(again, "h", "left_semi").select("c1", "c2", "from", (F.col("from") + length).alias("to"))
    return whole.unionByName(few.select("m").mapInArrow(compared, kind)).unionByName(counted)


def remove_repeats(docs: DataFrame, key: str = "doc_id", text: str = "text", length: int = LENGTH, gram: int = GRAM, kept_bytes: bool = False) -> DataFrame:
    """(key, n_bytes, n_removed, n_spans, kept_sha256), and what is left as ``kept`` if wanted (null where nothing went)."""
    ship(docs.sparkSession)
    if not 0 < gram < length < PIECE:
        raise ValueError(f"an anchor's string is shorter than the length, and that shorter than {PIECE}")
    scanned = durable(scan(docs, key, text, length, gram), "anchors")
    spans = stretches(docs, scanned, text, length, gram)
    spans = durable(spans.groupBy("c1", "c2").agg(F.sort_array(F.collect_set(F.struct("from", "to"))).alias("spans")), "spans")

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            removed, runs, sha, kept = [], [], [], []
            for data, spans in zip(b.column(2), b.column(3), strict=True):
                data, spans = data.as_py(), spans.values
                parts, done, n = [], 0, 0
                for a, z in zip(spans.field("from").to_pylist(), spans.field("to").to_pylist(), strict=True):
                    if a > done or n == 0:
                        parts.append(data[done:a])
                        n += 1
                    done = max(done, z)
                left = b"".join([*parts, data[done:]])
                removed.append(len(data) - len(left))
                runs.append(n)
                sha.append(hashlib.sha256(left).hexdigest())
                kept.append(left)
            columns = [b.column(0), b.column(1), pa.array(removed, pa.int64()), pa.array(runs, pa.int64()), pa.array(sha, pa.string())]
            yield pa.RecordBatch.from_arrays(columns + [pa.array(kept, pa.binary())] * kept_bytes, names=["c1", "c2", "n_removed", "n_spans", "kept_sha256", *["kept"] * kept_bytes])

    texts = _needed_texts(docs, text, spans.select("c1")).dropDuplicates(["c1", "c2"])
    cuts = texts.join(spans, ["c1", "c2"]).select("c1", "c2", "data", "spans").mapInArrow(cut, "c1 long, c2 long, n_removed long, n_spans long, kept_sha256 string" + ", kept binary" * kept_bytes)
    out = scanned.select(key, "c1", "c2", "n_bytes", "sha256").join(cuts, ["c1", "c2"], "left")
    zero = lambda c: F.coalesce(F.col(c), F.lit(0).cast("long")).alias(c)
    return out.select(key, "n_bytes", zero("n_removed"), zero("n_spans"), F.coalesce("kept_sha256", "sha256").alias("kept_sha256"), *["kept"] * kept_bytes)
