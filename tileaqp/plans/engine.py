"""Answering a query: leaves, splits, strata, and rounds of sampling until the bound is met."""

from __future__ import annotations

import math
import time
from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import pyarrow as pa
from pyspark.sql import Window, functions as F

from ..functions.quantiles import two_sided_z
from .estimators import Moments, Stratum, answer, moment_columns, moments_of
from .geometry import CELL_BITS, Tile, classify
from .index import MOST_LITERALS, Stats, TileIndex
from .model import KEY_SPACE, Answer, QueryResult, SamplingPolicy, Viewport, ViewportQuery


def should_split(index: TileIndex, tile: Tile, kind: str, in_window: int, rate: float, window: Viewport) -> bool:
    """Enough objects, some of them in the window, levels left, and a gain."""
    c = index.config
    if not c.adapt or not tile.is_leaf or tile.n_objects <= c.split_min or not in_window or tile.depth + c.split_levels > c.max_depth:
        return False
    if c.split_scope == "partial" and kind != "partial":
        return False
    if c.gain == "count_threshold":
        return True
    # expected reuse: reads that the parts inside the window will save a next window that overlaps by nine tenths
    each = tile.n_objects / c.fan_out
    parts = sum(classify(Tile(-1, None, tile.depth + c.split_levels, tile.root, lo, hi, 0).bounds(index.domain), window) == "full" for lo, hi in tile.parts(c.fan_out))
    return 0.9 * rate * each * parts > c.gain_min


def _part_codes(index: TileIndex, tile: Tile, below: bool) -> tuple[int, int]:
    """Shift and mask that give the part of a tile in which a path code lies; one part where it can't be divided."""
    levels = index.config.split_levels
    if not below or tile.depth + levels > CELL_BITS // 2:
        return max(0, CELL_BITS - 2 * tile.depth - 2), 0
    return CELL_BITS - 2 * (tile.depth + levels), index.config.fan_out - 1


_INSIDE = "ax >= _x1 AND ax <= _x2 AND ay >= _y1 AND ay <= _y2"


def _window_columns(w: Viewport, n: int) -> dict[str, list[float]]:
    """The window as columns beside the tiles: plans that differ in data alone are compiled once."""
    return {"_x1": [float(w.x1)] * n, "_x2": [float(w.x2)] * n, "_y1": [float(w.y1)] * n, "_y2": [float(w.y2)] * n}


def count_regions(index: TileIndex, tiles: list[Tile], window: Viewport, below: bool) -> dict[int, list[tuple[int, int]]]:
    """For each tile the objects of its parts (or of the whole, in the first place): all of them, and those in the window. Axes only."""
    if not tiles:
        return {}
    shift, mask = zip(*(_part_codes(index, t, below) for t in tiles), strict=True)
    rows = index.with_tile(index.objects.select("ax", "ay", "root", "zcode"), tiles, _shift=pa.array(shift, pa.int32()), _mask=list(mask), **_window_columns(window, len(tiles)))
    part = F.expr("cast(shiftright(zcode, _shift) & _mask as int)").alias("part")
    rows = rows.groupBy("tile_id", part).agg(F.count("*").alias("n"), F.count(F.when(F.expr(_INSIDE), 1)).alias("w")).collect()  # a row per part
    out = {t.tile_id: [(0, 0)] * index.config.fan_out for t in tiles}
    for r in rows:
        out[r.tile_id][r.part] = (r.n, r.w)
    return out


def plan_strata(index: TileIndex, q: ViewportQuery, policy: SamplingPolicy) -> list[Stratum]:
    """Leaves of the window, split where that pays, as strata with what is known of them; empty ones are left out."""
    out: list[Stratum] = []
    todo = index.leaves_overlapping(q.window, q.attrs() if policy.reuse else ())
    rounds = index.config.depth_per_query if policy.reuse else 0
    single: list[Stratum] = []
    # an empty leaf has nothing to count
    todo = [(t, k) for t, k in todo if t.n_objects]
    known: dict[int, int] = {}
    for step in range(rounds + 1):
        ask = [t for t, k in todo if t.tile_id not in known and (k == "partial" or (step < rounds and index.config.split_scope == "all_overlapping"))]
        may = step < rounds and index.config.adapt
        counts = count_regions(index, ask, q.window, may)
        nxt: list[tuple[Tile, str]] = []
        for t, k in todo:
            if t.tile_id not in counts:
                nxt.append((t, k))
                continue
            parts = counts[t.tile_id]
            inside = sum(w for _, w in parts)
            known[t.tile_id] = inside
            if may and should_split(index, t, k, inside, policy.rate0, q.window):
                for child, (n, w) in zip(index.split(t, [n for n, _ in parts]), parts, strict=True):
                    kind = classify(child.bounds(index.domain), q.window)
                    if n and kind != "disjoint":
                        nxt.append((child, kind))
                        if step + 1 >= rounds:
                            known[child.tile_id] = w
            else:
                nxt.append((t, k))
        todo = nxt
    if policy.reuse:
        index.inherit()
    for t, kind in todo:
        pop = t.n_objects if kind == "full" else known[t.tile_id]
        if not pop:
            continue
        s = Stratum(t.tile_id, kind, pop)
        for a in q.attrs():
            known_stat = index.stat(t.tile_id, a) if policy.reuse and kind == "full" else Stats()
            s.theta[a], s.sample[a] = known_stat.theta, known_stat.moments
        n = min((s.moments(a).n for a in q.attrs()), default=pop)
        s.case = 3 if kind == "partial" and (policy.reuse and any((t.tile_id, a) in index.stats for a in q.attrs())) else 1 if n == pop else 2 if n else 4
        out.append(s)
    if policy.strata == "single" and out:
        single = [Stratum(-1, "partial", sum(s.pop for s in out), 4, {a: 0 for a in q.attrs()}, {a: Moments() for a in q.attrs()})]
    return single or out


def _moments_sql(attr: str, i: int, high: bool) -> list[str]:
    """The aggregates of :func:`moment_columns` over rows marked ``_d{i}``."""
    v, f = f"_v{i}", f"FILTER (WHERE _d{i})"
    out = [f"count({v}) {f} AS `{attr}__n`", f"avg({v}) {f} AS `{attr}__mean`", f"var_pop({v}) {f} AS `{attr}__var`", f"min({v}) {f} AS `{attr}__low`", f"max({v}) {f} AS `{attr}__high`", f"count(`{attr}`) {f} AS `{attr}__filled`"]
    return out + [f"skewness({v}) {f} AS `{attr}__skew`", f"kurtosis({v}) {f} AS `{attr}__kurt`"] if high else out


@dataclass(frozen=True)
class Ask:
    """What one job is to find out of a tile: counts of its parts and the moments of objects with keys from ``own`` (by measure) to ``to``."""

    tile: Tile
    full: bool
    own: tuple[int, ...]
    to: int
    count: bool = False


def read_tiles(index: TileIndex, q: ViewportQuery, asks: list[Ask]) -> dict[tuple[int, int], dict]:
    """By tile and part (parts only where counts are asked): objects, objects in the window, objects read, moments.

    One job whose text is the same for all queries of the same measures, so that it is
    compiled once; tiles, window and limits are a small broadcast table. Where the
    objects are in files, cells and the largest limit are literals, for row groups and pages to be pruned.
    """
    if not asks:
        return {}
    attrs, w = q.attrs(), q.window
    shift, mask = zip(*(_part_codes(index, a.tile, a.count) for a in asks), strict=True)
    table = {
        "_root": pa.array([a.tile.root for a in asks], pa.int32()), "_lo": [a.tile.zlo for a in asks], "_hi": [a.tile.zhi for a in asks], "tile_id": pa.array([a.tile.tile_id for a in asks], pa.int64()),
        "_shift": pa.array(shift, pa.int32()), "_mask": list(mask), "_full": [a.full for a in asks], "_count": [a.count for a in asks], "_low": pa.array([min(a.own, default=KEY_SPACE) for a in asks], pa.int64()), "_high": pa.array([a.to for a in asks], pa.int64()),
        **{f"_own{i}": pa.array([a.own[i] for a in asks], pa.int64()) for i in range(len(attrs))}, **_window_columns(w, len(asks)),
    }
    drawn = f"rkey >= _low AND rkey < _high AND (_full OR {_INSIDE})"
    marks = "".join(f", coalesce(cast(`{a}` AS double), 0D) AS _v{i}, {drawn} AND rkey >= _own{i} AS _d{i}" for i, a in enumerate(attrs))
    high = any(a.ci == "delta" for a in q.aggs)
    moments = "".join(f", {c}" for i, a in enumerate(attrs) for c in _moments_sql(a, i, high))
    prune = ""
    if index.prunes:
        counted, read = sorted({a.tile.root for a in asks if a.count}), sorted({a.tile.root for a in asks if not a.count})
        most = max((a.to for a in asks if not a.count), default=0)
        parts = [f"({_runs_sql(counted)})"] * bool(counted) + [f"(({_runs_sql(read)}) AND rkey < {most}L)"] * bool(read)
        prune = f"({' OR '.join(parts)}) AND "
    text = f"""
        SELECT /*+ BROADCAST(_t) */ tile_id, cast(shiftright(zcode, _shift) & _mask AS int) AS part,
               count(*) AS n, count(1) FILTER (WHERE _in) AS w, count(1) FILTER (WHERE _dr) AS _n{moments}
        FROM (SELECT *, {_INSIDE} AS _in, {drawn} AS _dr{marks} FROM {index.view()} JOIN {index.view()}_tiles AS _t ON root = _root AND zcode >= _lo AND zcode < _hi WHERE {prune}(_count OR ({drawn})))
        GROUP BY 1, 2"""
    spark = index.spark
    spark.createDataFrame(pa.table(table)).createOrReplaceTempView(f"{index.view()}_tiles")
    rows = spark.sql(text).collect()  # a row per part of a tile
    return {(r["tile_id"], r["part"]): r.asDict() for r in rows}


def _runs_sql(roots: list[int]) -> str:
    """Cells as few ranges, one for each line of the grid that a window meets."""
    runs: list[list[int]] = []
    for r in roots:
        if runs and r == runs[-1][1] + 1:
            runs[-1][1] = r
        else:
            runs.append([r, r])
    if len(runs) > MOST_LITERALS:
        runs = [[runs[0][0], runs[-1][1]]]
    return " OR ".join(f"root BETWEEN {a} AND {b}" for a, b in runs)


def draw(index: TileIndex, q: ViewportQuery, strata: list[Stratum], to: dict[int, int], policy: SamplingPolicy) -> int:
    """Read the objects of each stratum whose draw keys are below ``to`` and weren't read; returns how many."""
    attrs = q.attrs()
    goes = [s for s in strata if s.tile_id in to and any(s.theta[a] < to[s.tile_id] and not s.exact(a) for a in attrs)]
    if not goes:
        return 0
    # from the lowest key that some measure lacks; each measure then takes what it didn't have
    own = {s.tile_id: tuple(KEY_SPACE if s.exact(a) else s.theta[a] for a in attrs) for s in goes}
    if policy.strata == "single":
        got = _draw_pooled(index, q, own[-1], to[-1])
    else:
        got = {tile: r for (tile, _), r in read_tiles(index, q, [Ask(index.tiles[s.tile_id], s.kind == "full", own[s.tile_id], to[s.tile_id]) for s in goes]).items()}
    read = 0
    for s in goes:
        r = got.get(s.tile_id)
        read += r["_n"] if r else 0
        for a in attrs:
            if not s.exact(a) and s.theta[a] < to[s.tile_id]:
                if r:
                    s.sample[a] = s.moments(a).merge(moments_of(r, a))
                s.theta[a] = to[s.tile_id]
    return read


def _draw_pooled(index: TileIndex, q: ViewportQuery, own: tuple[int, ...], to: int) -> dict[int, dict]:
    """The same for the whole window as one stratum."""
    attrs = q.attrs()
    rows = index.objects.filter(F.col("root").isin(sorted({t.root for t, _ in index.leaves_overlapping(q.window)}))).filter(q.window.condition())
    rows = rows.filter((F.col("rkey") >= min(own)) & (F.col("rkey") < to))
    high = any(a.ci == "delta" for a in q.aggs)
    columns = [c for i, a in enumerate(attrs) for c in moment_columns(a, F.col("rkey") >= own[i], high=high)]
    r = rows.agg(F.count("*").alias("_n"), *columns).first().asDict()
    return {-1: r} if r["_n"] else {}


def first_round(index: TileIndex, q: ViewportQuery, policy: SamplingPolicy, whole: bool) -> tuple[list[Stratum], int, float]:
    """Strata with a first sample, how many objects that read, and its rate: counting and reading in one job.

    What is known of tiles, or of the tiles they came from, gives the variances by which
    a rate is chosen that is likely to meet the bound; populations of border tiles are guessed from their
    area until the job has counted them. A divided tile's parts are strata of their own
    if each got a sample, else the tile's part of the window stays one.
    """
    attrs = q.attrs()
    leaves = [(t, k) for t, k in index.leaves_overlapping(q.window, attrs if policy.reuse else ()) if t.n_objects]
    strata, guesses = [], []
    for t, kind in leaves:
        share = 1.0
        if kind == "partial":
            b, w = t.bounds(index.domain), q.window
            share = max(0.0, min(b.x2, w.x2) - max(b.x1, w.x1)) * max(0.0, min(b.y2, w.y2) - max(b.y1, w.y1)) / ((b.width or 1.0) * (b.height or 1.0))
        s = Stratum(t.tile_id, kind, t.n_objects if kind == "full" else max(1, round(share * t.n_objects)))
        for a in attrs:
            known = index.stat(t.tile_id, a) if policy.reuse and kind == "full" else Stats()
            s.theta[a], s.sample[a] = known.theta, known.moments
        strata.append(s)
        guesses.append({a: index.guess(t.tile_id, a) for a in attrs} if policy.reuse else {})
    rate = 1.0 if whole else policy.rate0
    if not whole and policy.reuse and attrs and all(g.get(a) for g in guesses for a in attrs):
        known = [[(s.pop, s.moments(a).n, *g[a]) for s, g in zip(strata, guesses, strict=True)] for a in attrs]
        rate = smallest_rate(known, q, policy.rate0 / 8, 0.9)
    to = {s.tile_id: KEY_SPACE for s in strata if any(not s.exact(a) for a in attrs)} if whole else _targets(strata, attrs, rate, policy)
    if not whole:  # a stratum without two objects would cost another round: aim at nine, so that few miss
        for s in strata:
            if s.tile_id in to and min(s.moments(a).n for a in attrs) < 2:
                to[s.tile_id] = max(to[s.tile_id], int(min(1.0, 9 / s.pop) * KEY_SPACE))
    asks = []
    for (t, kind), s in zip(leaves, strata, strict=True):
        high = to.get(t.tile_id, 0)
        own = tuple(KEY_SPACE if s.exact(a) and kind == "full" else s.theta[a] for a in attrs)
        if kind == "partial":
            asks.append(Ask(t, False, tuple(0 for _ in attrs), high or KEY_SPACE, True))
        elif any(o < high for o in own):
            asks.append(Ask(t, True, own, high))
    got = read_tiles(index, q, asks)
    limits = {a.tile.tile_id: a.to for a in asks}
    out: list[Stratum] = []
    for (t, kind), s in zip(leaves, strata, strict=True):
        limit = limits.get(t.tile_id, 0)
        parts = [got.get((t.tile_id, i)) for i in range(index.config.fan_out)]
        sample = lambda rows, a: reduce(Moments.merge, (moments_of(r, a) for r in rows if r), Moments())
        if kind == "full":
            for a in attrs:
                if s.theta[a] < limit and not s.exact(a):
                    s.sample[a], s.theta[a] = s.moments(a).merge(sample(parts, a)), limit
            n = min((s.moments(a).n for a in attrs), default=s.pop)
            s.case = 1 if n == s.pop else 2
            out.append(s)
            continue
        counts = [(r["n"], r["w"]) if r else (0, 0) for r in parts]
        inside = sum(w for _, w in counts)
        pieces = []
        if policy.reuse and should_split(index, t, kind, inside, rate, q.window):
            for child, (n, w), r in zip(index.split(t, [n for n, _ in counts]), counts, parts, strict=True):
                how = classify(child.bounds(index.domain), q.window)
                one = Stratum(child.tile_id, how, w, 4, dict.fromkeys(attrs, limit), {a: sample([r], a) for a in attrs})
                if how == "full" and n:
                    for a in attrs:
                        index.stats[child.tile_id, a] = Stats(KEY_SPACE if one.exact(a) else limit, one.sample[a])
                if w:
                    pieces.append(one)
        if not inside:
            continue
        if not pieces or any(p.moments(a).n < min(2, p.pop) for p in pieces for a in attrs):
            pieces = [Stratum(t.tile_id, "partial", inside, 3, dict.fromkeys(attrs, limit), {a: sample(parts, a) for a in attrs})]
        out += pieces
    if policy.reuse:
        index.inherit()
    return out, sum(r["_n"] for r in got.values()), rate


def fixed_limits(index: TileIndex, q: ViewportQuery, strata: list[Stratum], to: dict[int, int]) -> dict[int, int]:
    """Key limits that give each stratum exactly its share of objects, rounded up, instead of about that many: one sort of the keys within tiles."""
    goes = [s for s in strata if s.tile_id in to and to[s.tile_id] < KEY_SPACE]
    out = dict(to)
    if not goes:
        return out
    n = [math.ceil(to[s.tile_id] / KEY_SPACE * s.pop) for s in goes]
    rows = index.with_tile(index.objects.select("ax", "ay", "root", "zcode", "rkey"), [index.tiles[s.tile_id] for s in goes], _n=n, _full=[s.kind == "full" for s in goes])
    rows = rows.filter(F.col("_full") | q.window.condition()).withColumn("_r", F.row_number().over(Window.partitionBy("tile_id").orderBy("rkey")))
    for r in rows.filter(F.col("_r") == F.col("_n")).select("tile_id", "rkey").collect():  # a row per stratum
        out[r.tile_id] = r.rkey + 1
    return out


def next_rate(rate: float, eps: float, eps_max: float, cap: float = 2.0, min_step: float = 1.1) -> float:
    """The rate times the squared ratio of error and bound, at least ``min_step`` and at most ``cap`` times."""
    ratio = cap if not eps_max or math.isinf(eps) else (eps / eps_max) ** 2
    return min(1.0, rate * min(cap, max(min_step, ratio)))


def smallest_rate(known: list[list[tuple[float, int, float, float]]], q: ViewportQuery, low: float, margin: float = 0.97) -> float:
    """The smallest common rate, not below ``low``, at which given variances would meet the bound.

    ``known`` has for each measure (population, sample so far, mean, variance) of every stratum. Strata
    that have more than the rate keep what they have, and none can have more than
    all of its objects. The error of a sum and that of a mean are the same.
    """
    z = two_sided_z(q.gamma)

    def met(rate: float) -> bool:
        for strata in known:
            total = var = 0.0
            for pop, had, mean, s2 in strata:
                total += pop * mean
                n = min(float(pop), max(float(had), rate * pop))
                if had < pop and n < pop:
                    var += pop**2 * s2 / n * (1 - n / pop)
            if z * math.sqrt(var) > margin * q.eps_max * abs(total):
                return False
        return True

    if met(low):
        return low
    high = 1.0
    for _ in range(40):
        mid = (low + high) / 2
        low, high = (low, mid) if met(mid) else (mid, high)
    return high


def rate_for_bound(strata: list[Stratum], q: ViewportQuery, low: float) -> float:
    return smallest_rate([[(s.pop, s.moments(a).n, s.moments(a).mean, s.moments(a).s2) for s in strata] for a in q.attrs()], q, low)


def _next(policy: SamplingPolicy, rate: float, eps: float, q: ViewportQuery, strata: list[Stratum]) -> float:
    """The common rate of the next round: from that of the strata which the last rate governed, not of those that earlier queries took further."""
    attrs = q.attrs()
    got = [(min(s.moments(a).n for a in attrs), s.pop) for s in strata if any(not s.exact(a) for a in attrs)]
    behind = got if policy.draw == "neyman" else [(n, pop) for n, pop in got if n <= 1.25 * rate * pop] or got
    now = sum(n for n, _ in behind) / sum(pop for _, pop in behind)
    if policy.kind == "fixed_step":
        return min(1.0, now * policy.cap)
    if policy.kind == "fpc_aware" and q.eps_max and not math.isinf(eps) and all(a.fn in ("sum", "mean", "count") for a in q.aggs):
        return min(1.0, now * policy.cap, rate_for_bound(strata, q, min(1.0, now * policy.min_step)))
    return next_rate(now, eps, q.eps_max, policy.cap, policy.min_step)


def _targets(strata: list[Stratum], attrs: tuple[str, ...], rate: float, policy: SamplingPolicy) -> dict[int, int]:
    """Key limits for a common rate, raised where a stratum would get fewer than the floor; small strata are read whole."""
    floor = policy.floor if sum(s.pop * rate for s in strata) < 100 else min(policy.floor, policy.pooled_floor)
    share = neyman_rates(strata, attrs, rate) if policy.draw == "neyman" else {}
    out = {}
    for s in strata:
        if all(s.exact(a) for a in attrs):
            continue
        short = min(s.moments(a).n for a in attrs) < min(floor, s.pop)
        r = share.get(s.tile_id, rate)
        if s.pop <= policy.exhaust_below:
            r = 1.0
        elif 2 * r * s.pop < floor and short:
            r = min(1.0, 3.0 * floor / s.pop)
        theta = KEY_SPACE if r >= 1 else int(r * KEY_SPACE)
        if short and theta <= min(s.theta[a] for a in attrs):
            theta = min(KEY_SPACE, 2 * max(s.theta[a] for a in attrs))
        out[s.tile_id] = theta
    return out


def neyman_rates(strata: list[Stratum], attrs: tuple[str, ...], rate: float) -> dict[int, float]:
    """The total of a common rate, dealt by population times spread, so that the sum's variance is the least for its reads.

    With several measures a stratum has the largest of its shares. Strata that are to have all their
    objects leave the rest to the others; without a variance the common rate stays.
    """
    open_ = [s for s in strata if any(not s.exact(a) for a in attrs)]
    if not open_ or any(s.moments(a).n < 2 for s in open_ for a in attrs):
        return {}
    out: dict[int, float] = {}
    for a in attrs:
        left, total = list(open_), rate * sum(s.pop for s in open_)
        while left:
            weight = sum(s.pop * math.sqrt(s.moments(a).s2) for s in left)
            if not weight:
                break
            dealt = {s.tile_id: total * math.sqrt(s.moments(a).s2) / weight for s in left}
            whole = [s for s in left if dealt[s.tile_id] >= 1]
            for s in whole or left:
                out[s.tile_id] = max(out.get(s.tile_id, 0.0), min(1.0, dealt[s.tile_id]))
            if not whole:
                break
            total, left = total - sum(s.pop for s in whole), [s for s in left if s not in whole]
            if total <= 0:
                break
    # what is behind its share must grow, or a round would read nothing
    behind = any(r * KEY_SPACE > min(s.theta[a] for a in attrs) for s in open_ if (r := out.get(s.tile_id)))
    return {s.tile_id: out.get(s.tile_id, rate) for s in open_} if behind else {}


def evaluate_progressive(index: TileIndex, q: ViewportQuery, policy: SamplingPolicy | None = None) -> Iterator[QueryResult]:
    """A result after every round, the last one final; the index keeps what it learned once the last was taken."""
    policy = policy or SamplingPolicy()
    began = time.time()
    attrs = q.attrs()
    whole = q.eps_max == 0 or any(a.fn in ("min", "max") for a in q.aggs)
    ahead = policy.ahead and policy.strata == "tiles" and policy.draw == "threshold" and index.config.depth_per_query == 1 and index.config.split_scope == "partial"
    strata, done, rate = first_round(index, q, policy, whole) if ahead else (plan_strata(index, q, policy), None, 1.0 if whole else policy.rate0)
    pop = sum(s.pop for s in strata)
    log: list[dict] = []
    io = 0

    def result(answers: list[Answer]) -> QueryResult:
        return QueryResult(q, answers, pop, sum(min((s.moments(a).n for a in attrs), default=0) for s in strata), io, len(log), [*log], (time.time() - began) * 1000)

    open_ = [s for s in strata if any(not s.exact(a) for a in attrs)]
    if whole:
        to = {s.tile_id: KEY_SPACE for s in open_}
    else:
        # what has a sample answers first; only strata without one are read
        bare = [s for s in open_ if min(s.moments(a).n for a in attrs) < 2]
        to = _targets(bare, attrs, rate, policy)
    while True:
        if policy.draw == "fixed_n" and policy.strata == "tiles":
            to = fixed_limits(index, q, strata, to)
        read, done = draw(index, q, strata, to, policy) if done is None else done, None
        io += read
        # too few objects had keys low enough: reach further before judging
        thin = [s for s in strata if any(s.moments(a).n < min(2, s.pop) for a in attrs)]
        if thin and not whole:
            log.append({"round": len(log) + 1, "rate": rate, "new_reads": read, "eps_est": math.inf})
            to = {s.tile_id: min(KEY_SPACE, 4 * max(s.theta.values())) for s in thin}
            continue
        answers = [answer(strata, a, q.gamma) for a in q.aggs]
        worst = max((a.eps_est for a in answers), default=0.0)
        log.append({"round": len(log) + 1, "rate": rate, "new_reads": read, "eps_est": worst})
        open_ = [s for s in strata if any(not s.exact(a) for a in attrs)]
        if worst <= q.eps_max or not open_:
            if policy.reuse:
                commit(index, strata, attrs)
            yield result(answers)
            return
        yield result(answers)
        if len(log) >= policy.max_rounds:
            rate = 1.0
        else:
            rate = _next(policy, rate, worst, q, strata)
        to = {s.tile_id: KEY_SPACE for s in open_} if rate >= 1 else _targets(open_, attrs, rate, policy)


def evaluate(index: TileIndex, q: ViewportQuery, policy: SamplingPolicy | None = None) -> QueryResult:
    out = None
    for out in evaluate_progressive(index, q, policy):  # noqa: B007
        pass
    return out


def commit(index: TileIndex, strata: list[Stratum], attrs: tuple[str, ...]) -> None:
    """Samples of whole tiles are kept; those of a window's part of a tile are not."""
    for s in strata:
        if s.kind == "full":
            for a in attrs:
                if s.theta[a] > index.stat(s.tile_id, a).theta:
                    index.stats[s.tile_id, a] = Stats(KEY_SPACE if s.exact(a) else s.theta[a], s.sample[a])
    index.version += 1


def count_window(index: TileIndex, q: Viewport) -> int:
    """Objects in the window: full leaves are known, partial ones counted on their axes."""
    leaves = index.leaves_overlapping(q)
    partial = [t for t, k in leaves if k == "partial" and t.n_objects]
    counts = count_regions(index, partial, q, False)
    return sum(t.n_objects for t, k in leaves if k == "full") + sum(w for c in counts.values() for _, w in c)


def exact_extreme(index: TileIndex, window: Viewport, attr: str, fn: str = "max") -> tuple[float | None, int]:
    """Smallest or largest value in the window, and the objects read for it: all that stored exact tiles don't answer."""
    from .model import Agg

    r = evaluate(index, ViewportQuery(window, (Agg(fn, attr),), 0.0))
    return r.answers[0].estimate, r.io_ops


def window_objects(index: TileIndex, window: Viewport, limit: int | None = None):
    """Places and keys of the objects in the window; no measure is read."""
    rows = index.with_tile(index.objects.select("ax", "ay", "root", "zcode", "rkey"), [t for t, _ in index.leaves_overlapping(window)]) if index.leaves_overlapping(window) else index.objects.select("ax", "ay", "root", "zcode", "rkey").filter(F.lit(False)).withColumn("tile_id", F.lit(-1).cast("long"))
    rows = rows.filter(window.condition()).select("tile_id", "ax", "ay", "rkey")
    return rows if limit is None else rows.limit(limit)
