"""SimHash near-duplicates: pigeonring candidates, full Hamming check, connected components.

A fingerprint of 64 bits is cut into five segments on a ring. If two fingerprints
differ in at most four bits, then from some segment on every chain of consecutive
segments keeps within its share of the differences: none in the first, at most one in
the first two, two in three, three in four, four in five. The first two conditions
are the join key: a fingerprint is filed under each segment with one bit of the next
one left out, so that two fingerprints meet exactly if they fulfil both; the longer
chains are checked before the full distance.

Only distinct fingerprints are compared, so that copies cost nothing. A key shared by
many is cut into blocks, and each pair of blocks gives back only a spanning forest of
its links; no pairs of a whole group are ever listed, and no link between components
is lost. Components of up to ``FINISH`` links come from one task; more links are first
made fewer by rounds of hooking to the smallest neighbour and pointer jumping, with
durable tables between the rounds, as each round costs the driver several jobs.

Null texts and texts without words have the fingerprint zero and are linked like any
other. Texts count whole. Repeated rows stay rows; their component is the same. A null
id stays a row, but never names a component unless all its members are null. Other
columns don't matter. An empty table gives an empty result.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window, functions as F

from ..runtime import durable, ship
from ._marks import is_marked, mark

SEED = 42
#: First bits and widths of the segments, from the lowest bit.
SEGMENTS = ((0, 13), (13, 13), (26, 13), (39, 13), (52, 12))
RADIUS = 4
#: Fingerprints of a key that are compared in one piece.
BLOCK = 4096
#: Links, whatever the table's size, whose components one task finds (about 40 MB).
FINISH = 1 << 18


def shingle_hashes(text: str | None, size: int) -> np.ndarray:
    from xxhash import xxh64_intdigest

    w = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not w:
        return np.zeros(0, np.uint64)
    if len(w) <= size:
        return np.array([xxh64_intdigest(b" ".join(w), SEED)], np.uint64)
    line = b" ".join(w)
    end = np.cumsum(np.fromiter(map(len, w), np.int64, len(w)) + 1) - 1
    start = np.concatenate([[0], end[:-1] + 1])
    a, b = start[: len(w) - size + 1].tolist(), end[size - 1 :].tolist()
    return np.fromiter((xxh64_intdigest(line[i:j], SEED) for i, j in zip(a, b, strict=True)), np.uint64, len(a))


def vote(hashes: np.ndarray) -> int:
    """Bits set in more than half of the hashes."""
    if not len(hashes):
        return 0
    votes = np.zeros(64, np.int64)
    for i in range(0, len(hashes), 1 << 14):
        bits = np.unpackbits(hashes[i : i + (1 << 14)].astype(">u8").view(np.uint8).reshape(-1, 8), axis=1)
        votes += np.add.reduce(bits, axis=0, dtype=np.uint16).astype(np.int64)
    return int.from_bytes(np.packbits(2 * votes > len(hashes)).tobytes(), "big", signed=True)


def fingerprints(docs: DataFrame, key: str = "doc_id", text: str = "text", size: int = 4) -> DataFrame:
    """(key, fp): the signed 64-bit fingerprint of every row."""
    ship(docs.sparkSession)

    def prints(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            got = pa.array([vote(shingle_hashes(t, size)) for t in b.column(1).to_pylist()], pa.int64())
            yield pa.RecordBatch.from_arrays([b.column(0), got], names=[key, "fp"])

    rows = docs.select(F.col(key), F.col(text).cast("string").alias("_text"))
    return rows.mapInArrow(prints, f"`{key}` {docs.schema[key].dataType.simpleString()}, fp long")


def _segment(column, i: int):
    start, width = SEGMENTS[i % len(SEGMENTS)]
    return F.shiftrightunsigned(column, start).bitwiseAND(F.lit((1 << width) - 1))


def _keys():
    """Array of all keys of a fingerprint: chain start and left-out bit in the high bits, the first segment, the next without that bit."""
    fp, out = F.col("fp"), []
    for i in range(len(SEGMENTS)):
        one, two = _segment(fp, i), _segment(fp, i + 1)
        for bit in range(SEGMENTS[(i + 1) % len(SEGMENTS)][1]):
            rest = two.bitwiseAND(F.lit(0x1FFF & ~(1 << bit)))
            out.append(F.shiftleft(one, 13).bitwiseOR(rest).bitwiseOR(F.lit((i * 13 + bit) << 26)))
    return F.array(*out)


def _ring(x: np.ndarray, radius: int, first: int | None) -> np.ndarray:
    """Which differences keep every budget of the chains from segment ``first`` (from some segment, if none), and the full radius."""
    n = len(SEGMENTS)
    parts = [np.bitwise_count((x >> np.uint64(a)) & np.uint64((1 << w) - 1)) for a, w in SEGMENTS]
    out = np.zeros(x.shape, bool)
    for i in range(n) if first is None else (first,):
        used, ok = np.zeros(x.shape, np.uint8), np.ones(x.shape, bool)
        for k in range(n):
            used += parts[(i + k) % n]
            ok &= used <= (k + 1) * radius // n
        out |= ok
    return out


def forest(fps: np.ndarray, radius: int, first: int | None) -> list[tuple[int, int]]:
    """Spanning forest of the links among fingerprints, the nearest links first: a tree grows by its closest neighbour."""
    n = len(fps)
    far = np.uint8(255)
    gap, near = np.full(n, far), np.full(n, -1)
    todo = np.ones(n, bool)
    out, at = [], 0
    for _ in range(n):
        todo[at] = False
        gap[at] = far
        x = fps ^ fps[at]
        d = np.where(todo & _ring(x, radius, first), np.bitwise_count(x), far)
        closer = d < gap
        gap[closer], near[closer] = d[closer], at
        nxt = int(gap.argmin())
        if gap[nxt] == far:  # the tree is complete; the next one starts anywhere
            left = np.flatnonzero(todo)
            if not len(left):
                break
            nxt = int(left[0])
        else:
            out.append((int(near[nxt]), nxt))
        at = nxt
    return out


def dealt(filed: DataFrame, members: list[str]) -> DataFrame:
    """(key, m): the members of every key with more than one; of a key with more than ``BLOCK``, of every pair of its blocks."""
    sizes = filed.groupBy("key").agg(F.count("*").alias("_count")).filter("_count > 1")
    # a plan takes exploded keys for as small as what they come from, and would broadcast all of them through the driver
    met = filed.join(sizes.hint("merge"), "key").withColumn("blocks", F.ceil(F.col("_count") / BLOCK).cast("int"))
    member = F.struct(*members)
    small = met.filter("blocks = 1").groupBy("key").agg(F.collect_list(member).alias("m"))
    # each member of a large key goes to every pair of blocks that has its own
    own = met.filter("blocks > 1").withColumn("own", F.pmod(F.xxhash64(*members), "blocks").cast("int"))
    each = own.select("key", "own", *members, F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other"))
    each = each.groupBy("key", F.least("own", "other").alias("x"), F.greatest("own", "other").alias("y")).agg(F.collect_list(member).alias("m"))
    return small.unionByName(each.select("key", "m"))


def bucket_links(filed: DataFrame, radius: int, chained: bool) -> DataFrame:
    """(a, b): for rows (key, fp, name), links within keys at most ``radius`` bits apart, enough to connect each key's components.

    A key with more than ``BLOCK`` rows is cut into blocks; every pair of blocks is a
    task's work of its own, and gives at most as many links as it has rows. With ``chained``, the
    high bits of a key tell from which segment its chains start.
    """
    kind = filed.schema["name"].dataType.simpleString()

    def linked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            lists = b.column(1)
            fps, names = lists.flatten().field("fp").to_numpy(zero_copy_only=False).view(np.uint64), lists.flatten().field("name")
            ends = np.concatenate([[0], np.cumsum(lists.value_lengths().to_numpy(zero_copy_only=False))])
            starts = (b.column(0).to_numpy() >> 26) // 13
            left, right = [], []
            two = np.flatnonzero(np.diff(ends) == 2)
            for first in range(len(SEGMENTS)) if chained else (None,):  # most keys have two members
                i = ends[two if first is None else two[starts[two] == first]]
                i = i[_ring(fps[i] ^ fps[i + 1], radius, first)]
                left += i.tolist()
                right += (i + 1).tolist()
            for k in np.flatnonzero(np.diff(ends) > 2):
                for i, j in forest(fps[ends[k] : ends[k + 1]], radius, int(starts[k]) if chained else None):
                    left.append(int(ends[k]) + i)
                    right.append(int(ends[k]) + j)
            yield pa.RecordBatch.from_arrays([names.take(pa.array(left, pa.int64())), names.take(pa.array(right, pa.int64()))], names=["a", "b"])

    ship(filed.sparkSession)
    found = dealt(filed, ["fp", "name"]).mapInArrow(linked, f"a {kind}, b {kind}")
    return found.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def links(distinct: DataFrame, radius: int = RADIUS) -> DataFrame:
    """(a, b): links between distinct fingerprints at most ``radius`` apart, enough to connect every component."""
    if not 0 <= radius <= RADIUS:
        raise ValueError(f"the segments serve radii up to {RADIUS}")
    return bucket_links(distinct.select("fp", F.col("fp").alias("name"), F.explode(_keys()).alias("key")), radius, chained=True)


def _roots(a: pa.Array, b: pa.Array) -> tuple[pa.Array, pa.Array]:
    """All nodes of the links, and for each the smallest node reachable."""
    nodes = pc.unique(pa.chunked_array([a, b], a.type))
    nodes = nodes.take(pc.array_sort_indices(nodes))
    ia, ib = (pc.index_in(x, nodes).to_numpy(zero_copy_only=False) for x in (a, b))
    root = np.arange(len(nodes))
    while True:
        x, y = root[ia], root[ib]
        apart = x != y
        if not apart.any():
            return nodes, nodes.take(pa.array(root))
        ia, ib, x, y = ia[apart], ib[apart], x[apart], y[apart]
        np.minimum.at(root, np.maximum(x, y), np.minimum(x, y))
        while not np.array_equal(root, further := root[root]):
            root = further


def components(edges: DataFrame) -> DataFrame:
    """(node, root): for every node with an edge the smallest node reachable, by hooking and pointer jumping."""
    edges = durable(edges.select("a", "b"), "edges")
    kind = edges.schema["a"].dataType.simpleString()

    def joined(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if all_ := list(batches):
            t = pa.Table.from_batches(all_).combine_chunks()
            a, b = (pa.concat_arrays(t.column(i).chunks) for i in (0, 1))
            yield pa.RecordBatch.from_arrays(list(_roots(a, b)), names=["node", "root"])

    ship(edges.sparkSession)
    if edges.count() <= FINISH:
        return durable(edges.coalesce(1).mapInArrow(joined, f"node {kind}, root {kind}"), "label")
    both = edges.union(edges.select(F.col("b"), F.col("a"))).toDF("node", "near")
    label = durable(both.groupBy("node").agg(F.min("near").alias("m")).select("node", F.least("node", "m").alias("root")), "label")
    while True:  # to the label's label
        jump = label.toDF("root", "further")
        label = durable(label.join(jump, "root").select("node", F.col("further").alias("root"), (F.col("further") < F.col("root")).alias("moved")), "label")
        moved = not label.filter("moved").isEmpty()
        label = label.select("node", "root")
        if not moved:
            break
    left = edges.join(label.toDF("a", "ra"), "a").join(label.toDF("b", "rb"), "b").filter("ra <> rb")
    rest = components(left.select(F.least("ra", "rb").alias("a"), F.greatest("ra", "rb").alias("b")).distinct())
    return durable(label.join(rest.toDF("root", "to"), "root", "left").select("node", F.coalesce("to", "root").alias("root")), "label")


def components_of(docs: DataFrame, key: str = "doc_id", text: str = "text", size: int = 4, radius: int = RADIUS) -> DataFrame:
    """(key, fp, component): component is the smallest key reachable by links, for every row."""
    prints = durable(fingerprints(docs, key, text, size), "prints")
    distinct = durable(prints.groupBy("fp").agg(F.min(key).alias("least")), "distinct")
    found = components(links(distinct.select("fp"), radius))
    named = distinct.join(found.withColumnRenamed("node", "fp"), "fp", "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    named = named.join(named.groupBy("root").agg(F.min("least").alias("component")), "root").select("fp", "component")
    return prints.join(durable(named, "named"), "fp").select(key, "fp", "component")


# Near duplicates by the share of distinct five-word shingles, decided on whole texts.
# Shingles have one order for all texts: rare before common, then by hash. Two texts that
# share 0.8 of their union share a shingle among the first 0.2 of each (the prefix), so
# filing by prefix misses no pair. Only connection matters: a star around the member with
# the most company is tried first, then all pairs that are still in different components.

SIMILARITY = 0.8
#: One text in so many is looked at to tell common shingles; a shingle in this many of those is common.
SAMPLED, COMMON = 32, 4
SIZE = "struct<n: int, last: bigint>"


def _words(text: str | None) -> bytes:
    return b" ".join((text or "").encode("utf-8", "surrogatepass").lower().split())


def _name(text: str | None) -> bytes:
    from xxhash import xxh3_128_digest

    return xxh3_128_digest(_words(text))


def prefix_length(n: int, similarity: float) -> int:
    """First shingles of ``n`` in the order of all of which a text with enough similarity shares one."""
    return min(n, n - math.ceil(similarity * n - 1e-6) + 1)


def names(docs: DataFrame, key: str = "doc_id", text: str = "text", size: int = 4) -> DataFrame:
    """(key, name, fp): a digest of the words of every row, and their fingerprint."""
    ship(docs.sparkSession)

    def named(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = b.column(1).to_pylist()
            prints = pa.array([vote(shingle_hashes(t, size)) for t in texts], pa.int64())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([_name(t) for t in texts], pa.binary()), prints], names=[key, "name", "fp"])

    rows = docs.select(F.col(key), F.col(text).cast("string").alias("_text"))
    return rows.mapInArrow(named, f"`{key}` {docs.schema[key].dataType.simpleString()}, name binary, fp long")


def print_links(table: DataFrame, radius: int = RADIUS) -> DataFrame:
    """(a, b): for rows (name, fp), links between names whose fingerprints are at most ``radius`` apart, enough to connect every component."""
    each = table.select("name", "fp").distinct()
    distinct = durable(each.groupBy("fp").agg(F.min("name").alias("least")), "distinct")
    same = each.join(distinct, "fp").filter("name <> least").select(F.col("least").alias("a"), F.col("name").alias("b"))
    found = links(distinct.select("fp"), radius).toDF("x", "y")
    near = found.join(distinct.toDF("x", "a"), "x").join(distinct.toDF("y", "b"), "y").select("a", "b")
    return durable(same.unionByName(near), "print_links")


def common_shingles(docs: DataFrame, text: str = "text", size: int = 5):
    """Broadcast bits of shingles that many texts have. Others may be marked too: they only settle the order."""

    def sampled(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            got = [(n, t) for t in b.column(0).to_pylist() if (n := _name(t))[0] % SAMPLED == 0]
            hashes = [np.unique(shingle_hashes(t, size)).view(np.int64) for _, t in got]
            yield pa.RecordBatch.from_arrays([pa.array([n for n, _ in got], pa.binary()), pa.array(hashes, pa.list_(pa.int64()))], names=["name", "hashes"])

    ship(docs.sparkSession)
    some = docs.select(F.col(text).cast("string").alias("_text")).mapInArrow(sampled, "name binary, hashes array<long>").dropDuplicates(["name"])
    return mark(some.select(F.explode("hashes").alias("number")).groupBy("number").count().filter(F.col("count") >= COMMON), "number")


def prefixes(docs: DataFrame, common, similarity: float, text: str = "text", size: int = 5) -> DataFrame:
    """(key, name, s): every shingle of the prefix of every text; s is the number of all its distinct shingles and where the prefix ends."""

    def filed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[bytes] = set()  # copies in other tasks are dropped later
        for b in batches:
            keys, found, counts, sizes, last = [], [], [], [], []
            for t in b.column(0).to_pylist():
                if (name := _name(t)) in seen:
                    continue
                seen.add(name)
                h = np.unique(shingle_hashes(t, size)).view(np.int64)
                if not len(h):
                    continue
                sizes.append(len(h))
                late = is_marked(common.value, h)
                h = np.concatenate([h[~late], h[late]])[: prefix_length(len(h), similarity)]
                last.append(int(h[-1] >> 2) + (1 << 62) * bool(is_marked(common.value, h[-1:])[0]))
                keys.append(h)
                found.append(name)
                counts.append(len(h))
            each = np.repeat(np.arange(len(found)), counts)
            s = pa.StructArray.from_arrays([pa.array(sizes, pa.int32()), pa.array(last, pa.int64())], names=["n", "last"])
            each = pa.array(each, pa.int64())
            columns = [pa.array(np.concatenate([np.zeros(0, np.int64), *keys])), pa.array(found, pa.binary()).take(each), s.take(each)]
            yield pa.RecordBatch.from_arrays(columns, names=["key", "name", "s"])

    ship(docs.sparkSession)
    return docs.select(F.col(text).cast("string").alias("_text")).mapInArrow(filed, f"key long, name binary, s {SIZE}")


def _possible(pairs: DataFrame, similarity: float) -> DataFrame:
    """Pairs (a, b, sa, sb) once, unless sizes or the number of shared prefix shingles rule the similarity out.

    Of two texts one prefix ends first; what both texts share up to its end lies in both
    prefixes, and what they share beyond is at most the rest of that text.
    """
    na, nb = F.col("sa.n"), F.col("sb.n")
    least = F.ceil(F.lit(similarity / (1 + similarity)) * (na + nb) - 1e-6)
    ra, rb = (F.greatest(F.ceil(F.lit(similarity) * n - 1e-6) - 1, F.lit(0)) for n in (na, nb))
    rest = F.when(F.col("sa.last") < F.col("sb.last"), ra).when(F.col("sa.last") > F.col("sb.last"), rb).otherwise(F.greatest(ra, rb))
    met = pairs.filter(F.least(na, nb) >= least).groupBy("a", "b", "sa", "sb").agg(F.count("*").alias("shared"))
    return met.filter(F.col("shared") + rest >= least).select("a", "b")


def _across(shared: DataFrame, label: DataFrame, similarity: float) -> DataFrame:
    """(a, b, sa, sb): per key all pairs of members in different components whose sizes allow the similarity."""

    def crossed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            lists = b.column(1)
            ends = np.concatenate([[0], np.cumsum(lists.value_lengths().to_numpy(zero_copy_only=False))])
            m = lists.flatten()
            found, s = m.field("name"), m.field("s")
            n = s.field("n").to_numpy(zero_copy_only=False)
            root = pc.dictionary_encode(m.field("root")).indices.to_numpy(zero_copy_only=False)
            left, right, many = [], [], 0
            for first, e in zip(ends[:-1], ends[1:], strict=True):
                if (root[first:e] == root[first]).all():
                    continue
                for i in range(first, e - 1):
                    o = n[i + 1 : e]
                    j = np.flatnonzero((root[i + 1 : e] != root[i]) & (np.minimum(o, n[i]) >= similarity * np.maximum(o, n[i]) - 1e-6)) + i + 1
                    left.append(np.full(len(j), i))
                    right.append(j)
                    many += len(j)
                    if many > 1 << 16:
                        yield paired(found, s, left, right)
                        left, right, many = [], [], 0
            yield paired(found, s, left, right)

    def paired(found, s, left, right) -> pa.RecordBatch:
        i, j = (pa.array(np.concatenate([np.zeros(0, np.int64), *x])) for x in (left, right))
        return pa.RecordBatch.from_arrays([found.take(i), found.take(j), s.take(i), s.take(j)], names=["a", "b", "sa", "sb"])

    own = shared.join(label.toDF("name", "root"), "name", "left").withColumn("root", F.coalesce("root", "name"))
    mixed = own.groupBy("key").agg(F.min("root").alias("lo"), F.max("root").alias("hi")).filter("lo <> hi").select("key")
    pairs = dealt(own.join(mixed, "key", "left_semi"), ["name", "s", "root"]).mapInArrow(crossed, f"a binary, b binary, sa {SIZE}, sb {SIZE}")
    return _ordered(pairs)


def _ordered(pairs: DataFrame) -> DataFrame:
    right = F.col("a") < F.col("b")
    one, two = F.struct(F.col("a").alias("name"), F.col("sa").alias("s")), F.struct(F.col("b").alias("name"), F.col("sb").alias("s"))
    both = pairs.select(F.when(right, one).otherwise(two).alias("x"), F.when(right, two).otherwise(one).alias("y"))
    return both.select(F.col("x.name").alias("a"), F.col("y.name").alias("b"), F.col("x.s").alias("sa"), F.col("y.s").alias("sb"))


def _similar(docs: DataFrame, pairs: DataFrame, least: float, text: str = "text", size: int = 5) -> DataFrame:
    """Pairs (a, b) of texts that share at least ``least`` of all their distinct shingles."""
    needed = durable(pairs.select(F.col("a").alias("name")).union(pairs.select("b")).distinct(), "needed")
    marked = mark(needed.select(F.conv(F.hex(F.substring("name", 1, 7)), 16, 10).cast("long").alias("number")), "number")

    def held(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[bytes] = set()
        for b in batches:
            found = [_name(t) for t in b.column(0).to_pylist()]
            good = is_marked(marked.value, np.array([int.from_bytes(n[:7], "big") for n in found], np.int64))
            good = [bool(g) and n not in seen and not seen.add(n) for g, n in zip(good, found, strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(found, pa.binary()), b.column(0)], names=["name", "_text"]).filter(pa.array(good, pa.bool_()))

    def checked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last: dict[bytes, np.ndarray] = {}
        for b in batches:
            good = []
            for a, b_, ta, tb in zip(*(c.to_pylist() for c in b.columns), strict=True):
                last = {n: last[n] if n in last else np.unique(shingle_hashes(t, size)) for n, t in ((a, ta), (b_, tb))}
                x, y = last[a], last[b_]
                both = len(np.intersect1d(x, y, assume_unique=True))
                good.append(both >= least * (len(x) + len(y) - both))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1)], names=["a", "b"]).filter(pa.array(good, pa.bool_()))

    rows = docs.select(F.col(text).cast("string").alias("_text")).mapInArrow(held, "name binary, _text string")
    whole = durable(rows.join(needed, "name", "left_semi").dropDuplicates(["name"]), "held")
    met = pairs.join(whole.toDF("a", "ta"), "a").join(whole.toDF("b", "tb"), "b").select("a", "b", "ta", "tb")
    return durable(met.mapInArrow(checked, "a binary, b binary"), "similar")


def near_duplicates(docs: DataFrame, key: str = "doc_id", text: str = "text", size: int = 5, similarity: float = SIMILARITY, radius: int | None = None) -> DataFrame:
    """(key, component): rows whose texts are linked by a shingle similarity of at least ``similarity``; component is the smallest key.

    With a ``radius``, texts whose fingerprints (of four-word shingles) are at most so many bits apart are linked first, by pigeonring;
    the shingles then find what no chain of fingerprints links.
    """
    table = durable(names(docs, key, text), "names") if radius is not None else durable(names(docs, key, text).select(key, "name"), "names")
    known = print_links(table, radius) if radius is not None else None
    once = table.groupBy("name").agg(F.min(key).alias("least"))
    filed = prefixes(docs, common_shingles(docs, text, size), similarity, text, size)
    of = Window.partitionBy("key")
    met = filed.withColumn("lo", F.min("name").over(of)).withColumn("hi", F.max("name").over(of)).filter("lo <> hi")
    shared = durable(met.select("key", "name", "s").distinct(), "shared")
    # the member of each key that meets the most others in all its keys
    company = shared.join(shared.groupBy("key").agg(F.count("*").alias("m")), "key").groupBy("name").agg(F.sum("m").alias("company"))
    centre = shared.join(company, "name").groupBy("key").agg(F.max(F.struct("company", "name", "s")).alias("c"))
    star = shared.join(centre, "key").select(F.col("name").alias("a"), F.col("c.name").alias("b"), F.col("s").alias("sa"), F.col("c.s").alias("sb")).filter("a <> b")
    tried = durable(_possible(_ordered(star), similarity), "tried")
    edges = _similar(docs, tried, similarity, text, size)
    edges = edges if known is None else edges.unionByName(known)
    roots = components(edges)
    rest = durable(_possible(_across(shared, roots, similarity), similarity).join(tried, ["a", "b"], "left_anti"), "rest")
    if not rest.isEmpty():
        roots = components(edges.union(_similar(docs, rest, similarity, text, size)))
    named = once.join(roots.withColumnRenamed("node", "name"), "name", "left").select("name", "least", F.coalesce("root", "name").alias("root"))
    named = named.join(named.groupBy("root").agg(F.min("least").alias("component")), "root").select("name", "component")
    return table.select(key, "name").join(durable(named, "named"), "name").select(key, "component")
