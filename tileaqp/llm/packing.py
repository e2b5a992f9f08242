"""Best-fit packing of token sequences: local best fit, then rounds that merge what is left.

A text becomes the ids of a byte-level vocabulary and an end id. One longer than a
sequence is cut into full pieces, the shorter piece first. Full pieces are sequences
already. The others are packed within their partition, the longest first, each into
the fullest bin that takes it. Bins filled to ``full`` tokens or more are done; the
rest go on as items of the next round, on an ``fan``-th of the partitions, until one
partition has packed the last ones. Best fit leaves at most one bin in a partition that is at most
half full, and fuller ones can't join one another: so of these only ``fan`` of
each fill go on, as many as the small ones of the next round could need. What a
later round's task reads is thus bounded by ``fan`` and the length, whatever the
table's size. A bin carries its pieces, so no join is needed.

Null texts are empty and give the end id alone. Texts of any length are packed whole.
Repeated rows are packed each. Columns besides the key and the text are not looked
at. An empty table gives an empty result. Rounds end in durable tables, and items
are ordered before packing, so a task that runs again packs the same.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from ..runtime import durable, ship

LENGTH = 1024
END_ID = 2
#: Fill from which a bin is not opened again: half a percent of slack.
FULL = 1019
FAN = 8

_encoders: dict[str, object] = {}


def encoder(path: str):
    """The vocabulary at ``path``: a .tiktoken rank file, or a tokenizers .json."""
    if path not in _encoders:
        if path.endswith(".tiktoken"):
            import base64

            import public_tokenizers
            import tiktoken

            with open(path, "rb") as f:
                ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
            _encoders[path] = tiktoken.Encoding("ranks", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={}).encode_to_numpy
        else:
            from tokenizers import Tokenizer

            t = Tokenizer.from_file(path)
            t.encode_special_tokens = True
            _encoders[path] = lambda text: np.array(t.encode(text, add_special_tokens=False).ids, np.uint32)
    return _encoders[path]


def vocabulary() -> str:
    """Rank file of the 50k byte vocabulary; the same ids as its .json, at several times the speed."""
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.tiktoken")


def pieces(docs: DataFrame, key: str = "doc_id", text: str = "text", vocabulary_path: str | None = None, length: int = LENGTH, end_id: int = END_ID, ids: bool = False) -> DataFrame:
    """A row per piece: key, piece, start, length, ids_crc32, uid (unique), and the ids if wanted."""
    ship(docs.sparkSession)
    path = vocabulary_path or vocabulary()

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        encode, uid = encoder(path), TaskContext.get().partitionId() << 40
        for b in batches:
            row, piece, start, size, crc, kept = [], [], [], [], [], []
            for i, t in enumerate(b.column(1).to_pylist()):
                got = np.append(encode(t), np.uint32(end_id)).astype("<u4") if t else np.array([end_id], "<u4")
                n = len(got)
                at = [0, *range(n % length or length, n + 1, length)]
                for k in range(len(at) - 1):
                    part = got[at[k] : at[k + 1]]
                    row.append(i)
                    piece.append(k)
                    start.append(at[k])
                    size.append(len(part))
                    crc.append(zlib.crc32(part.tobytes()))
                    if ids:
                        kept.append(part.astype(np.int32))
            n = len(row)
            columns = [b.column(0).take(pa.array(row, pa.int64())), pa.array(piece, pa.int32()), pa.array(start, pa.int64()), pa.array(size, pa.int64()), pa.array(crc, pa.int64()), pa.array(np.arange(uid, uid + n))]
            yield pa.RecordBatch.from_arrays(columns + [pa.array(kept, pa.list_(pa.int32()))] * ids, names=[key, "piece", "start", "length", "ids_crc32", "uid", *["ids"] * ids])
            uid += n

    rows = docs.select(F.col(key), F.col(text).cast("string").alias("_text"))
    return rows.mapInArrow(cut, f"`{key}` {docs.schema[key].dataType.simpleString()}, piece int, start long, length long, ids_crc32 long, uid long" + ", ids array<int>" * ids)


def best_fit(sizes: np.ndarray, length: int) -> list[list[int]]:
    """Bins of indices, the largest sizes first, each into the fullest bin with room; room is looked up in one integer's bits."""
    bins: list[list[int]] = []
    open_bins: list[list[int]] = [[] for _ in range(length + 1)]  # by room
    rooms = 0
    for i in np.argsort(-sizes, kind="stable").tolist():
        n = int(sizes[i])
        fit = rooms >> n
        if fit:
            room = n + (fit & -fit).bit_length() - 1
            k = open_bins[room].pop()
            if not open_bins[room]:
                rooms &= ~(1 << room)
        else:
            room, k = length, len(bins)
            bins.append([])
        bins[k].append(i)
        if room - n:
            open_bins[room - n].append(k)
            rooms |= 1 << room - n
    return bins


def pack(items: DataFrame, length: int = LENGTH, full: int = FULL, fan: int = FAN) -> DataFrame:
    """(uid, sequence_id, offset) for items (uid, length): no sequence longer than ``length``."""
    spark = items.sparkSession
    ship(spark)
    whole = items.filter(F.col("length") >= full).select("uid", F.col("uid").alias("sequence_id"), F.lit(0).cast("long").alias("offset"))
    kind = "fill long, uids array<long>, sizes array<int>, open boolean"

    def packed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got = [b for b in batches if b.num_rows]
        if not got:
            return
        table = pa.Table.from_batches(got)
        first = np.array([u[0] for u in table["uids"].to_pylist()])
        table = table.take(pa.array(np.argsort(first)))
        uids, sizes = table["uids"].combine_chunks(), table["sizes"].combine_chunks()
        bins = best_fit(table["fill"].to_numpy(), length)
        order = pa.array([i for b in bins for i in b], pa.int64())

        def joined(lists):
            taken = lists.take(order)
            ends = np.concatenate([[0], np.cumsum([len(b) for b in bins])])
            return pa.ListArray.from_arrays(pa.array(taken.offsets.to_numpy()[ends], pa.int32()), taken.values)

        fills = np.add.reduceat(table["fill"].to_numpy()[order.to_numpy()], np.cumsum([0, *map(len, bins[:-1])]))
        # of bins alike that are over half full the first ``fan`` may still take something
        by = np.argsort(fills, kind="stable")
        new = np.concatenate([[True], fills[by][1:] != fills[by][:-1]])
        nth = np.empty(len(fills), np.int64)
        nth[by] = np.arange(len(fills)) - np.flatnonzero(new)[np.cumsum(new) - 1]
        open_ = (fills < full) & ((2 * fills <= length) | (nth < fan))
        out = pa.Table.from_arrays([pa.array(fills), joined(uids), joined(sizes), pa.array(open_)], names=["fill", "uids", "sizes", "open"])
        yield from out.to_batches(max_chunksize=8192)

    left = items.filter(F.col("length") < full).select(F.col("length").alias("fill"), F.array("uid").alias("uids"), F.array(F.col("length").cast("int")).alias("sizes"), F.lit(True).alias("open"))
    parts = max(1, left.rdd.getNumPartitions())
    left = durable(left.mapInArrow(packed, kind), "bins")
    done = []
    while parts > 1:
        done.append(left.filter(~F.col("open")))
        parts = -(-parts // fan)
        left = durable(left.filter("open").repartition(parts, F.xxhash64(F.col("uids")[0])).mapInArrow(packed, kind), "bins")
    for d in done:
        left = left.unionByName(d)
    sums = F.transform(F.sequence(F.lit(0), F.size("sizes") - 1), lambda i: F.aggregate(F.slice("sizes", 1, i), F.lit(0).cast("long"), lambda a, x: a + x))
    laid = left.select(F.array_min("uids").alias("sequence_id"), F.inline(F.arrays_zip(F.col("uids").alias("uid"), sums.alias("offset"))))
    return whole.unionByName(laid.select(F.col("uid"), F.col("sequence_id"), F.col("offset")))


def pack_documents(docs: DataFrame, key: str = "doc_id", text: str = "text", vocabulary_path: str | None = None, length: int = LENGTH, end_id: int = END_ID, ids: bool = False) -> DataFrame:
    """Every piece with its sequence and its place there."""
    table = durable(pieces(docs, key, text, vocabulary_path, length, end_id, ids), "pieces")
    return table.join(pack(table.select("uid", "length"), length, min(FULL, length)), "uid").drop("uid")
