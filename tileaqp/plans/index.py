"""The tile index: objects with path codes and draw keys, tiles on the driver, statistics of what was read."""

from __future__ import annotations

import json
import math
import uuid
from dataclasses import asdict, dataclass, field

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window, functions as F

from .estimators import Moments, Stratum, answer, moment_columns, moments_of
from .geometry import CELL_BITS, Domain, Tile, classify, with_codes
from ..runtime import durable
from .model import KEY_SPACE, AxisSpec, IndexConfig, QueryResult, Viewport, ViewportQuery

#: Above so many cells a plan prunes by their range instead of their list.
MOST_LITERALS = 256

TILES_SCHEMA = "tile_id long, parent_id long, depth int, root int, zlo long, zhi long, x_lo double, x_hi double, y_lo double, y_hi double, n_objects long, is_leaf boolean, version int"
STATS_SCHEMA = "tile_id long, attr string, theta long, n long, filled long, sum double, mean double, m2 double, m3 double, m4 double, min double, max double, status string"


def draw_key(identity: list[str], seed: int, portable: bool = False) -> Column:
    """A 60-bit number that depends on an object's identity and the seed alone: the same on every engine if portable."""
    if portable:
        text = F.concat(F.lit(f"s{seed}|"), F.concat_ws("|", *(F.col(c).cast("string") for c in identity)))
        return F.conv(F.substring(F.md5(text.cast("binary")), 1, 15), 16, 10).cast("long")
    return F.xxhash64(*identity, F.lit(seed)).bitwiseAND(F.lit(KEY_SPACE - 1))


def status(n: int, pop: int) -> str:
    return "exact" if n == pop else "approximate" if n else "not_available"


def status_column(n: Column, pop: Column) -> Column:
    return F.when(n == pop, "exact").when(n > 0, "approximate").otherwise("not_available")


def domain_of(df: DataFrame, axes: AxisSpec, grid: tuple[int, int]) -> Domain:
    """The box of all objects: one pass over two columns."""
    x, y = axes.columns(df)
    rows = df.select(x.alias("x"), y.alias("y")).filter("x is not null and y is not null and not isnan(x) and not isnan(y)")
    r = rows.agg(F.min("x"), F.max("x"), F.min("y"), F.max("y")).first()
    if r[0] is None:
        raise ValueError("no object has both axes")
    return Domain(Viewport(*map(float, r)), *grid)


def bind_objects(df: DataFrame, axes: AxisSpec, identity: list[str], attrs: list[str], domain: Domain, seed: int = 7, portable: bool = False) -> DataFrame:
    """OBJECTS: ax, ay, root, zcode, rkey and the measures, without a shuffle. Objects outside the domain or without an axis are in no tile."""
    x, y = axes.columns(df)
    kinds = df.select(*(F.expr(a).alias(a) for a in attrs)).schema if attrs else None
    measures = [AxisSpec.number(a, kinds[a].dataType).alias(a) for a in attrs]
    rows = df.select(x.alias("ax"), y.alias("ay"), draw_key(identity, seed, portable).alias("rkey"), *measures)
    rows = rows.filter(domain.covers(F.col("ax"), F.col("ay")))
    return with_codes(rows, domain).select("ax", "ay", "root", "zcode", "rkey", *attrs)


@dataclass
class Stats:
    """A measure's statistics of one tile: the objects with draw keys below theta were read."""

    theta: int = 0
    moments: Moments = field(default_factory=Moments)


class TileIndex:
    """Tiles and their statistics; the objects stay in Spark."""

    def __init__(self, objects: DataFrame, domain: Domain, config: IndexConfig):
        self.objects, self.domain, self.config = objects, domain, config
        self.tiles: dict[int, Tile] = {}
        self.roots: dict[int, int] = {}
        self.stats: dict[tuple[int, str], Stats] = {}
        #: Mean and variance of the tile that a part came from: a guess for planning, never part of an answer.
        self.hints: dict[tuple[int, str], tuple[float, float]] = {}
        #: Parts that are to inherit a sample, and the key limit up to which they do.
        self.heirs: dict[tuple[int, str], int] = {}
        self._kept: DataFrame | None = None
        self.version = 0
        self.init_ms = 0.0
        self._view: str | None = None
        self._files: bool | None = None

    @property
    def spark(self) -> SparkSession:
        return self.objects.sparkSession

    @property
    def prunes(self) -> bool:
        """Whether the objects are files with cells and keys as columns, so that literals prune them.

        Cells computed from axes prune nothing, and objects in memory gain little; plans without literals are compiled once for all queries.
        """
        if self._files is None:
            level = self.objects.storageLevel
            plan = self.objects._jdf.queryExecution().analyzed()
            while plan.nodeName() == "SubqueryAlias":
                plan = plan.children().head()
            self._files = plan.nodeName() in ("LogicalRelation", "DataSourceV2Relation") or str(plan).startswith("Relation ")
            self._files = self._files and not (level.useMemory or level.useDisk)
        return self._files

    def add(self, depth: int, root: int, zlo: int, zhi: int, n: int, parent: int | None = None) -> Tile:
        t = Tile(len(self.tiles), parent, depth, root, zlo, zhi, n)
        self.tiles[t.tile_id] = t
        if parent is None:
            self.roots[root] = t.tile_id
        return t

    def leaves(self) -> list[Tile]:
        return [t for t in self.tiles.values() if t.is_leaf]

    def leaves_overlapping(self, q: Viewport, attrs: tuple[str, ...] = ()) -> list[tuple[Tile, str]]:
        """Leaves that the window meets, by descent from the root cells it meets, each full or partial.

        With ``reuse_parent`` a divided tile inside the window whose measures ``attrs`` are known
        exactly stands for its parts.
        """
        d = self.domain
        box = d.box
        if classify(box, q) == "disjoint":
            return []
        at = lambda v, lo, hi, n: 0 if hi == lo else min(n - 1, max(0, math.floor((v - lo) / (hi - lo) * n)))
        # a cell further on each side, in case rounding puts a border next door
        columns = range(max(0, at(q.x1, box.x1, box.x2, d.gx) - 1), min(d.gx, at(q.x2, box.x1, box.x2, d.gx) + 2))
        lines = range(max(0, at(q.y1, box.y1, box.y2, d.gy) - 1), min(d.gy, at(q.y2, box.y1, box.y2, d.gy) + 2))
        out, todo = [], [self.tiles[self.roots[r]] for y in lines for x in columns if (r := y * d.gx + x) in self.roots]
        while todo:
            t = todo.pop()
            kind = classify(t.bounds(d), q)
            if kind == "disjoint":
                continue
            known = self.config.reuse_parent and attrs and kind == "full" and all(self.stat(t.tile_id, a).moments.n == t.n_objects for a in attrs)
            if t.is_leaf or known:
                out.append((t, kind))
            else:
                todo += [self.tiles[c] for c in t.children]
        return sorted(out, key=lambda p: p[0].start)

    def split(self, tile: Tile, counts: list[int]) -> list[Tile]:
        """As many equal parts as there are object counts; what was known of the whole isn't known of them, unless rows were kept."""
        depth = tile.depth + (len(counts).bit_length() - 1) // 2
        parts = [self.add(depth, tile.root, lo, hi, n, tile.tile_id) for (lo, hi), n in zip(tile.parts(len(counts)), counts, strict=True)]
        if self.config.keep_rows:
            limit = int(self.config.keep_rows * KEY_SPACE)
            for a in self.attrs():
                if theta := min(limit, max(self.stat(tile.tile_id, a).theta, self.heirs.get((tile.tile_id, a), 0))):
                    self.heirs |= {(p.tile_id, a): theta for p in parts if p.n_objects}
        tile.is_leaf, tile.children = False, tuple(p.tile_id for p in parts)
        for a in self.attrs():
            if (guess := self.guess(tile.tile_id, a)) is not None:
                self.hints.update({(p.tile_id, a): guess for p in parts})
        if not self.config.reuse_parent:
            for key in [k for k in self.stats if k[0] == tile.tile_id]:
                del self.stats[key]
        return parts

    @property
    def kept(self) -> DataFrame:
        """Rows with the smallest draw keys, written once: the part of every sample that divided tiles pass on."""
        if self._kept is None:
            self._kept = durable(self.objects.filter(F.col("rkey") < int(self.config.keep_rows * KEY_SPACE)), "kept")
        return self._kept

    def inherit(self) -> None:
        """Statistics of parts from the kept rows of the tiles they came from: samples by the same keys, without reading the objects again."""
        todo = {k: t for k, t in self.heirs.items() if k not in self.stats and self.tiles[k[0]].is_leaf}
        self.heirs = {}
        if not todo:
            return
        attrs = sorted({a for _, a in todo})
        tiles = [self.tiles[i] for i in sorted({i for i, _ in todo})]
        cut = {f"_cut{i}": pa.array([todo.get((t.tile_id, a), 0) for t in tiles], pa.int64()) for i, a in enumerate(attrs)}
        columns = [c for i, a in enumerate(attrs) for c in moment_columns(a, F.col("rkey") < F.col(f"_cut{i}"))]
        got = {r["tile_id"]: r.asDict() for r in self.with_tile(self.kept, tiles, **cut).groupBy("tile_id").agg(*columns).collect()}  # a row per part
        for (tile, a), theta in todo.items():
            m = moments_of(got[tile], a) if tile in got else Moments()
            self.stats[tile, a] = Stats(KEY_SPACE if m.n == self.tiles[tile].n_objects else theta, m)

    def with_tile(self, rows: DataFrame, tiles: list[Tile], **columns: list) -> DataFrame:
        """``rows`` inside the tiles (disjoint ones), with ``tile_id`` and whatever ``columns`` say of each tile.

        The tiles of a query are few: they are broadcast as a local table and met by cell
        and code range, so that the plan is the same for all queries but for its pruning.
        """
        if self.prunes:
            roots = sorted({t.root for t in tiles})
            rows = rows.filter(F.col("root").isin(roots) if len(roots) <= MOST_LITERALS else F.col("root").between(roots[0], roots[-1]))
        table = {"_root": pa.array([t.root for t in tiles], pa.int32()), "_lo": [t.zlo for t in tiles], "_hi": [t.zhi for t in tiles], "tile_id": pa.array([t.tile_id for t in tiles], pa.int64()), **columns}
        local = self.spark.createDataFrame(pa.table(table))
        near = (F.col("root") == F.col("_root")) & (F.col("zcode") >= F.col("_lo")) & (F.col("zcode") < F.col("_hi"))
        return rows.join(F.broadcast(local), near).drop("_root", "_lo", "_hi")

    def view(self) -> str:
        """The objects' name in SQL. It is never dropped: with its name Spark would drop what it holds of them in memory."""
        if self._view is None:
            self._view = f"_tileaqp_{uuid.uuid4().hex}"
            self.objects.createOrReplaceTempView(self._view)
        return self._view

    def attrs(self) -> list[str]:
        return [c for c in self.objects.columns if c not in ("ax", "ay", "root", "zcode", "rkey")]

    def guess(self, tile: int, attr: str) -> tuple[float, float] | None:
        """Mean and variance that a tile's objects may have: its own sample's, or that of the tile it came from."""
        m = self.stat(tile, attr).moments
        return (m.mean, m.s2) if m.n > 1 else self.hints.get((tile, attr))

    def stat(self, tile: int, attr: str) -> Stats:
        return self.stats.get((tile, attr), Stats())

    def size(self) -> dict[str, int]:
        """Cost of what is kept: tiles, statistics, and bits of the bitmaps that the draw keys stand for."""
        leaves = self.leaves()
        return {"tiles": len(self.tiles), "leaves": len(leaves), "stats": len(self.stats), "bitmap_bits": sum(t.n_objects for t in leaves) * len({a for _, a in self.stats}), "bytes": 96 * len(self.tiles) + 112 * len(self.stats)}

    def bitmap(self, tile: Tile, attr: str) -> DataFrame:
        """(bucket, bitmap, n_objects, n_read) of one tile: which of its objects, in the order of their draw keys, were read."""
        return self.bitmap_frame(attr, [tile]).drop("tile_id")

    def bitmap_frame(self, attr: str, leaves: list[Tile] | None = None) -> DataFrame:
        """(tile_id, bucket, bitmap, n_objects, n_read): the same for all leaves, as Spark bitmaps (positions count from one)."""
        leaves = self.leaves() if leaves is None else leaves
        cuts = self.spark.createDataFrame([(t.tile_id, self.stat(t.tile_id, attr).theta) for t in leaves], "tile_id long, theta long")
        w = F.row_number().over(Window.partitionBy("tile_id").orderBy("rkey"))
        rows = self.with_tile(self.objects, leaves).withColumn("pos", w.cast("long")).join(F.broadcast(cuts), "tile_id")
        bucket, bit = F.bitmap_bucket_number("pos"), F.bitmap_bit_position("pos")
        read = F.when(F.col("rkey") < F.col("theta"), bit)
        return rows.groupBy("tile_id", bucket.alias("bucket")).agg(F.bitmap_construct_agg(read).alias("bitmap"), F.count("*").alias("n_objects")).withColumn("n_read", F.bitmap_count("bitmap"))

    def tiles_frame(self) -> DataFrame:
        rows = []
        for t in self.tiles.values():
            b = t.bounds(self.domain)
            rows.append((t.tile_id, t.parent_id, t.depth, t.root, t.zlo, t.zhi, b.x1, b.x2, b.y1, b.y2, t.n_objects, t.is_leaf, self.version))
        return self.spark.createDataFrame(rows, TILES_SCHEMA)

    def stats_frame(self) -> DataFrame:
        rows = []
        for (tile, attr), s in self.stats.items():
            m = s.moments
            rows.append((tile, attr, s.theta, m.n, m.filled, m.total, m.mean, m.m2, m.m3, m.m4, m.low if m.n else None, m.high if m.n else None, status(m.n, self.tiles[tile].n_objects)))
        return self.spark.createDataFrame(rows, STATS_SCHEMA)

    def save(self, path: str) -> None:
        """Objects clustered by cell and draw key, tiles, statistics and layout under one folder."""
        write_objects(self.objects, f"{path}/objects")
        self.tiles_frame().write.parquet(f"{path}/tiles")
        self.stats_frame().write.parquet(f"{path}/stats")
        layout = {"box": asdict(self.domain.box), "gx": self.domain.gx, "gy": self.domain.gy, "config": asdict(self.config), "version": self.version}
        self.spark.createDataFrame([(json.dumps(layout),)], "layout string").write.parquet(f"{path}/layout")

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> TileIndex:
        layout = json.loads(spark.read.parquet(f"{path}/layout").first()[0])
        config = IndexConfig(**layout["config"] | {"grid": tuple(layout["config"]["grid"])})
        out = cls(spark.read.parquet(f"{path}/objects"), Domain(Viewport(**layout["box"]), layout["gx"], layout["gy"]), config)
        out.version = layout["version"]
        for r in spark.read.parquet(f"{path}/tiles").orderBy("tile_id").toLocalIterator():
            t = out.add(r.depth, r.root, r.zlo, r.zhi, r.n_objects, r.parent_id)
            t.is_leaf = r.is_leaf
            if r.parent_id is not None:
                out.tiles[r.parent_id].children += (t.tile_id,)
        for r in spark.read.parquet(f"{path}/stats").toLocalIterator():
            out.stats[r.tile_id, r.attr] = Stats(r.theta, Moments(r.n, r.mean, r.m2, math.inf if r.min is None else r.min, -math.inf if r.max is None else r.max, r.filled, r.m3, r.m4))
        return out


def write_objects(objects: DataFrame, path: str, partitions: int | None = None) -> None:
    """Files sorted by cell and draw key, so that a window's cells and a sample's keys are ranges of row groups."""
    n = partitions or max(1, int(objects.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    objects.repartitionByRange(n, "root", "rkey").sortWithinPartitions("root", "rkey").write.parquet(path)


def plan_layout(domain: Domain, config: IndexConfig, q0: Viewport | None) -> dict[int, int]:
    """Depth of the leaves of each root cell that isn't left whole: those nearest the first window are divided until the extra tiles are spent."""
    if config.init == "flat":
        return {}
    if q0 is None:
        raise ValueError("a layout by the first query needs that query")
    budget = int(config.extra * domain.gx * domain.gy)
    cx, cy = (q0.x1 + q0.x2) / 2, (q0.y1 + q0.y2) / 2
    box = domain.box
    wx, wy = (box.width / domain.gx) or 1.0, (box.height / domain.gy) or 1.0

    def distance(r: int) -> float:
        x, y = box.x1 + (r % domain.gx + 0.5) * wx, box.y1 + (r // domain.gx + 0.5) * wy
        return math.hypot((x - cx) / wx, (y - cy) / wy)

    out: dict[int, int] = {}
    order = sorted(range(domain.gx * domain.gy), key=lambda r: (distance(r), r))
    ring = [r for r in order if distance(r) <= 2 * max(q0.width / wx, q0.height / wy)]
    for depth, cells, cost in ((1, order, 3), (2, ring, 12)):
        if depth == 2 and len(out) < len(ring):
            break
        for r in cells:
            if budget < cost:
                return out
            if depth > config.max_depth:
                return out
            out[r] = depth
            budget -= cost
    return out


def build_index(df: DataFrame, axes: AxisSpec, identity: list[str], attrs: list[str], config: IndexConfig | None = None, q0: ViewportQuery | None = None, domain: Domain | None = None, cache: bool = False, objects: DataFrame | None = None) -> tuple[TileIndex, QueryResult | None]:
    """One pass over the objects: exact statistics of every leaf and listed measure, and the first query's exact answer."""
    import time

    config = config or IndexConfig()
    began = time.time()
    domain = domain or domain_of(df, axes, config.grid)
    objects = bind_objects(df, axes, identity, attrs, domain, config.seed, config.portable_key) if objects is None else objects
    if cache:
        objects = objects.persist()
    index = TileIndex(objects, domain, config)
    layout = plan_layout(domain, config, q0.window if q0 else None)
    depth = F.lit(0)
    for d in sorted(set(layout.values())):
        depth = F.when(F.col("root").isin([r for r, k in layout.items() if k == d]), d).otherwise(depth)
    prefix = F.expr(f"shiftright(zcode, {CELL_BITS} - 2 * depth)") if layout else F.lit(0).cast("long")
    inside = q0.window.condition() if q0 else F.lit(False)
    wanted = q0.attrs() if q0 else ()
    measures = [c for a in attrs for c in moment_columns(a)]
    first = [c for a in wanted for c in moment_columns(a, inside, f"q0_{a}")]
    rows = objects.withColumn("depth", depth).groupBy("root", "depth", prefix.alias("prefix")).agg(F.count("*").alias("n"), F.count(F.when(inside, 1)).alias("q0_n"), *measures, *first)
    got = {(r["root"], r["depth"], r["prefix"]): r.asDict() for r in rows.collect()}  # a row per leaf
    seen, pop, merged = 0, 0, {a: Moments() for a in wanted}
    for root in range(domain.gx * domain.gy):
        d = layout.get(root, 0)
        total = sum(got[root, d, p]["n"] for p in range(4**d) if (root, d, p) in got)
        todo = [index.add(0, root, 0, 1 << CELL_BITS, total)]
        for level in range(d):
            nxt = []
            for t in todo:
                shift = 2 * (d - level - 1)
                counts = []
                for i in range(4):
                    head = (t.zlo >> (CELL_BITS - 2 * level)) * 4 + i
                    counts.append(sum(got[root, d, p]["n"] for p in range(head << shift, (head + 1) << shift) if (root, d, p) in got))
                nxt += index.split(t, counts)
            todo = nxt
        for t in todo:
            r = got.get((root, d, t.zlo >> (CELL_BITS - 2 * d)))
            for a in attrs:
                index.stats[t.tile_id, a] = Stats(KEY_SPACE, moments_of(r, a) if r else Moments())
            if r:
                seen += r["n"]
                pop += r["q0_n"]
                for a in wanted:
                    merged[a] = merged[a].merge(moments_of(r, f"q0_{a}"))
    index.version = 1
    index.init_ms = (time.time() - began) * 1000
    if not q0:
        return index, None
    whole = [Stratum(-1, "full", pop, 1, {}, merged)] if pop else []
    answers = [answer(whole, a, q0.gamma) for a in q0.aggs]
    return index, QueryResult(q0, answers, pop, pop, seen, 1, [{"round": 0, "rate": 1.0, "new_reads": seen, "eps_est": 0.0}], index.init_ms)

