"""Benchmark decontamination: one Aho-Corasick automaton over all windows of benchmark words, one scan of each text.

Words are maximal runs of digits, letters and non-ASCII characters, A-Z lower-cased.
A window is ``size`` consecutive words of an item, or all words of a shorter one. A
text is normalised to its words between single spaces; every match then starts and
ends at a space, and its words are mapped back to character offsets of the original.

Null texts and texts without words have no hit. Items that are null or without words
have no window; repeated items count by their distinct ids. Texts of any length are
scanned whole; repeated rows are judged each for itself; an empty benchmark hits
nothing and an empty table gives an empty result. Other columns stay, but for those
named as one of the result (n_words, n_hit, items, spans). The items are gathered only while
their texts stay below ``MOST_BYTES``; beyond that the rows are scanned once for each
part of the benchmark that does.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from itertools import pairwise

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from ..runtime import ship

WINDOW = 10
#: Bytes of benchmark text that one automaton may hold.
MOST_BYTES = 8 << 20

_TABLE = bytes(c + 32 if 65 <= c <= 90 else c if 48 <= c <= 57 or 97 <= c <= 122 or c >= 128 else 32 for c in range(256))
_WORD = re.compile(r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+")


def words(text: str | None) -> list[bytes]:
    return (text or "").encode("utf-8", "surrogatepass").translate(_TABLE).split()


class Matcher:
    """The automaton; values are the words of a window and the ids of the items that have it."""

    def __init__(self, items: list[tuple[str, str]], size: int = WINDOW):
        import ahocorasick

        windows: dict[bytes, tuple[int, set[str]]] = {}
        for name, text in items:
            w = words(text)
            for i in range(max(1, len(w) - size + 1) if w else 0):
                part = w[i : i + size]
                windows.setdefault(b" ".join(part), (len(part), set()))[1].add(name)
        self.machine = ahocorasick.Automaton()
        for text, (n, names) in windows.items():
            self.machine.add_word(f" {text.decode('latin-1')} ", (n, frozenset(names)))
        if windows:
            self.machine.make_automaton()
        self.empty = not windows

    def scan(self, text: str | None) -> tuple[int, list[tuple[int, int]], set[str]]:
        """Words of the text; its hit words as ranges [from, to); items with an occurring window."""
        w = words(text)
        if self.empty or not w:
            return len(w), [], set()
        line = f" {b' '.join(w).decode('latin-1')} "
        found, names = [], set()
        ends = None
        for at, (n, who) in self.machine.iter(line):
            if ends is None:
                ends = np.cumsum(np.fromiter(map(len, w), np.int64, len(w)) + 1)  # place of the space after each word
            last = int(np.searchsorted(ends, at)) + 1
            names |= who
            found.append((last - n, last))
        found.sort()
        spans: list[tuple[int, int]] = []
        for a, b in found:
            if spans and a <= spans[-1][1]:
                spans[-1] = (spans[-1][0], max(b, spans[-1][1]))
            else:
                spans.append((a, b))
        return len(w), spans, names


_known: dict[bytes, Matcher] = {}


def _matcher(key: bytes, items: list[tuple[str, str]], size: int) -> Matcher:
    if key not in _known:
        _known.clear()
        _known[key] = Matcher(items, size)
    return _known[key]


def _parts(benchmark: DataFrame, key: str, text: str, most: int) -> Iterator[list[tuple[str, str]]]:
    """The benchmark in parts of bounded bytes; one item alone may be larger."""
    rows = benchmark.select(F.col(key).cast("string"), F.col(text).cast("string")).filter(F.col(text).isNotNull() & F.col(key).isNotNull()).distinct()
    part, held = [], 0
    for name, t in rows.toLocalIterator():
        if part and held + len(t) > most:
            yield part
            part, held = [], 0
        part.append((name, t))
        held += len(t)
    yield part


def find(docs: DataFrame, benchmark: DataFrame, text: str = "text", item: str = "item_id", item_text: str = "text", size: int = WINDOW, keep: list[str] | None = None, most: int = MOST_BYTES) -> DataFrame:
    """``docs`` (or its columns in ``keep``) with n_words, n_hit, items (sorted ids) and spans (character offsets of the hit passages)."""
    ship(docs.sparkSession)
    fresh = ["n_words", "n_hit", "items", "spans"]
    keep = [c for c in docs.columns if c not in fresh] if keep is None else keep
    out = None
    for part in _parts(benchmark, item, item_text, most):
        part.sort()
        key = hashlib.sha256(repr((size, part)).encode()).digest()
        shared = docs.sparkSession.sparkContext.broadcast((key, part))
        out = _scan(docs if out is None else out, shared, text, keep if out is None else [*keep, text] if text not in keep else keep, size, out is not None)
    return out.select(*keep, *fresh)


def _scan(docs: DataFrame, shared, text: str, keep: list[str], size: int, again: bool) -> DataFrame:
    spot, places = docs.columns.index(text), [docs.columns.index(c) for c in keep]
    before = [docs.columns.index(c) for c in ("items", "spans")] if again else []

    def scanned(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, part = shared.value
        m = _matcher(key, part, size)
        for b in batches:
            n_words, n_hit, items, spans = [], [], [], []
            for i, t in enumerate(b.column(spot).to_pylist()):
                n, found, names = m.scan(t)
                where = []
                if found:
                    at = [x.span() for x in _WORD.finditer(t)]
                    where = [{"from": at[a][0], "to": at[z - 1][1]} for a, z in found]
                if before and b.column(before[1])[i].as_py():
                    names |= set(b.column(before[0])[i].as_py())
                    where = sorted(where + b.column(before[1])[i].as_py(), key=lambda x: x["from"])
                    for x, y in [*pairwise(where)]:
                        if y["from"] <= x["to"]:
                            y["from"], y["to"] = x["from"], max(x["to"], y["to"])
                            where.remove(x)
                    found = [(0, sum(1 for _ in _WORD.finditer(t[x["from"] : x["to"]]))) for x in where]
                n_words.append(n)
                n_hit.append(sum(z - a for a, z in found))
                items.append(sorted(names))
                spans.append(where)
            yield pa.RecordBatch.from_arrays(
                [*(b.column(i) for i in places), pa.array(n_words, pa.int64()), pa.array(n_hit, pa.int64()), pa.array(items, pa.list_(pa.string())), pa.array(spans, pa.list_(pa.struct([("from", pa.int64()), ("to", pa.int64())])))],
                names=[*keep, "n_words", "n_hit", "items", "spans"],
            )

    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.select(*keep).schema)
    return docs.mapInArrow(scanned, f"{fields}, n_words long, n_hit long, items array<string>, spans array<struct<from: long, to: long>>")
