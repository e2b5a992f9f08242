"""A CSV source that knows where each row starts in its file, and can read just the rows at given places.

``format('csv_offsets')`` reads files split by bytes; a split holds the rows that start in
it. Columns are those of the given schema, plus ``file`` and ``pos`` if the schema has
them. Ranges on numeric columns are pushed down. With the option ``offsets`` (a folder of
Parquet rows file, pos, written beforehand) only those rows are read, in the order of
their places. Paths are local or mounted ones.
"""

from __future__ import annotations

import csv
import glob
import io
import os
from collections.abc import Iterator

import pyarrow as pa
import pyarrow.parquet as pq
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, GreaterThan, GreaterThanOrEqual, InputPartition, LessThan, LessThanOrEqual
from pyspark.sql.types import DoubleType, FloatType, IntegerType, LongType, StringType, StructType
from pyspark.sql.pandas.types import to_arrow_schema

SPLIT_BYTES = 32 << 20
BATCH_ROWS = 4096
_READ = {IntegerType: int, LongType: int, DoubleType: float, FloatType: float, StringType: str}


class Piece(InputPartition):
    def __init__(self, path: str, start: int, end: int, places: list[int] | None = None):
        self.path, self.start, self.end, self.places = path, start, end, places


def files_of(path: str) -> list[str]:
    path = path.removeprefix("file:")
    if os.path.isdir(path):
        return sorted(f for f in glob.glob(f"{path}/**", recursive=True) if os.path.isfile(f) and not os.path.basename(f).startswith(("_", ".")))
    return sorted(glob.glob(path))


class OffsetReader(DataSourceReader):
    def __init__(self, schema: StructType, options: dict):
        self.schema, self.options, self.tests = schema, options, []
        for f in schema:
            if type(f.dataType) not in _READ:
                raise TypeError(f"{f.name}: read it as a number or a string")

    def pushFilters(self, filters):
        signs = {GreaterThanOrEqual: ">=", GreaterThan: ">", LessThanOrEqual: "<=", LessThan: "<", EqualTo: "="}
        kinds = {f.name: type(f.dataType) for f in self.schema}
        for f in filters:
            if type(f) in signs and len(f.attribute) == 1 and kinds.get(f.attribute[0]) in (IntegerType, LongType, DoubleType, FloatType):
                self.tests.append((f.attribute[0], signs[type(f)], f.value))
            else:
                yield f

    def partitions(self):
        size = int(self.options.get("splitbytes", SPLIT_BYTES))
        files = files_of(self.options["path"])
        if "offsets" in self.options:
            table = pq.read_table(self.options["offsets"].removeprefix("file:"), columns=["file", "pos"])
            wanted: dict[str, list[int]] = {}
            for f, p in zip(table["file"].to_pylist(), table["pos"].to_pylist(), strict=True):
                wanted.setdefault(f, []).append(p)
            out = []
            for f in sorted(wanted):
                places = sorted(set(wanted[f]))
                out += [Piece(f, 0, 0, places[i : i + 100_000]) for i in range(0, len(places), 100_000)]
            return out or [Piece("", 0, 0, [])]
        return [Piece(f, a, min(a + size, n)) for f in files for n in [os.path.getsize(f)] for a in range(0, n, size)] or [Piece("", 0, 0, [])]

    def _lines(self, piece: Piece) -> Iterator[tuple[int, bytes]]:
        if not piece.path:
            return
        with open(piece.path, "rb") as f:
            if piece.places is not None:
                for p in piece.places:  # in file order: one pass forward
                    f.seek(p)
                    yield p, f.readline()
                return
            header = self.options.get("header", "true").lower() == "true"
            at = piece.start
            f.seek(at)
            if at:
                f.seek(at - 1)
                at = at - 1 + len(f.readline())  # the row that started before belongs to the split before
            while at < piece.end:
                line = f.readline()
                if not line:
                    return
                if not (header and at == 0) and line.strip():
                    yield at, line
                at += len(line)

    def read(self, piece: Piece) -> Iterator[pa.RecordBatch]:
        if not piece.path:
            return
        with open(piece.path, "rb") as f:
            names = next(csv.reader([f.readline().decode()])) if self.options.get("header", "true").lower() == "true" else [x.name for x in self.schema if x.name not in ("file", "pos")]
        schema = to_arrow_schema(self.schema)
        where = {n: i for i, n in enumerate(names)}
        tests = {">=": lambda a, b: a >= b, ">": lambda a, b: a > b, "<=": lambda a, b: a <= b, "<": lambda a, b: a < b, "=": lambda a, b: a == b}
        columns: list[list] = [[] for _ in self.schema]

        def batch() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, schema.types, strict=True)], schema=schema)

        for at, line in self._lines(piece):
            fields = next(csv.reader(io.StringIO(line.decode("utf-8"))))
            row = {}
            for f in self.schema:
                if f.name in ("file", "pos") and f.name not in where:
                    row[f.name] = piece.path if f.name == "file" else at
                    continue
                i = where.get(f.name)
                text = fields[i] if i is not None and i < len(fields) else ""
                row[f.name] = None if text == "" else _READ[type(f.dataType)](text)
            if any(row[n] is None or not tests[s](row[n], v) for n, s, v in self.tests):
                continue
            for c, f in zip(columns, self.schema, strict=True):
                c.append(row[f.name])
            if len(columns[0]) == BATCH_ROWS:
                yield batch()
                columns = [[] for _ in self.schema]
        if columns[0]:
            yield batch()


class CsvOffsets(DataSource):
    @classmethod
    def name(cls) -> str:
        return "csv_offsets"

    def schema(self):
        raise ValueError("csv_offsets needs a schema")

    def reader(self, schema: StructType) -> OffsetReader:
        return OffsetReader(schema, {k.lower(): v for k, v in self.options.items()})


def register(spark) -> None:
    from ..runtime import ship

    ship(spark)
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(CsvOffsets)


def fetch(spark, path: str, schema: StructType, places, order: str = "offset"):
    """Rows of a CSV at the places (file, pos) of a DataFrame: sorted by place first, or as they come."""
    from ..runtime import durable

    register(spark)
    chosen = places.select("file", "pos").distinct()
    if order == "offset":
        chosen = chosen.repartition("file").sortWithinPartitions("file", "pos")
    table = durable(chosen, "places")
    return spark.read.format("csv_offsets").schema(schema).option("offsets", table.inputFiles()[0].rsplit("/", 1)[0]).load(path)
