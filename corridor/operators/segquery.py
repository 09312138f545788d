"""Questions answered on pieces, without expanding them: points, ranges, velocities, aggregates, distances."""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from corridor.options import Options


def value_at(p: DataFrame | None, t: Column, o: Options) -> Column:
    """Height of the piece in columns t0, dt, p0, dq at step t."""
    return F.lit(o.grid) * (F.col("p0") + F.col("dq") * (t - F.col("t0")) / F.col("dt"))


def at(pieces: DataFrame, t: int, o: Options, ks: list[int] | None = None) -> DataFrame:
    """(k, x) at one step; only that step's block is touched.  A step where two pieces join belongs to the later-started one."""
    rows = pieces.where((F.col("block") == t // o.block) & (F.col("t0") <= t) & (F.col("t0") + F.col("dt") >= t))
    if ks is not None:
        rows = rows.where(F.col("k").isin(ks))
    return rows.groupBy("k").agg(F.max_by(value_at(None, F.lit(t), o), "t0").alias("x"))


def between(pieces: DataFrame, a: int, b: int, o: Options) -> DataFrame:
    """(k, t, x) for steps a to b."""
    rows = pieces.where(F.col("block").between(a // o.block, b // o.block) & (F.col("t0") <= b) & (F.col("t0") + F.col("dt") >= a))
    first = F.col("t0") % o.block == 0
    low = F.greatest(F.lit(a), F.when(first, F.col("t0")).otherwise(F.col("t0") + 1))
    rows = rows.withColumn("low", low).withColumn("high", F.least(F.lit(b), F.col("t0") + F.col("dt"))).where("low <= high")
    return rows.select("k", F.explode(F.sequence("low", "high")).alias("t"), "t0", "dt", "p0", "dq").select("k", "t", value_at(None, F.col("t"), o).alias("x"))


def velocity(pieces: DataFrame, o: Options) -> DataFrame:
    """Pieces with their slope per step."""
    return pieces.withColumn("v", F.lit(o.grid) * F.col("dq") / F.col("dt"))


def seg_agg(pieces: DataFrame, o: Options, level: float) -> DataFrame:
    """Per series, over the samples that pieces stand for after each block's first: count, sum, min, max, steps above a level, and, over time,
    integral, displacement and path length; all in closed form."""
    g = F.lit(o.grid)
    total = F.col("dt") * F.col("p0") + F.col("dq") * (F.col("dt") + 1) / 2
    near = F.col("p0") + F.col("dq") / F.col("dt")
    end = (F.col("p0") + F.col("dq")).cast("double")
    lv = F.lit(level / o.grid)
    # steps s in 1..dt with p0 + dq s / dt > level
    s = (lv - F.col("p0")) * F.col("dt") / F.col("dq")
    above = (
        F.when(F.col("dq") == 0, F.when(F.col("p0") > lv, F.col("dt")).otherwise(0))
        .when(F.col("dq") > 0, F.greatest(F.lit(0), F.least(F.col("dt"), F.col("dt") - F.floor(s))))
        .otherwise(F.greatest(F.lit(0), F.least(F.col("dt"), F.ceil(s) - 1)))
    )
    return pieces.groupBy("k").agg(
        F.sum("dt").cast("long").alias("n"),
        F.round(g * F.sum(total), 4).alias("total"),
        F.round(g * F.min(F.least(near, end)), 6).alias("low"),
        F.round(g * F.max(F.greatest(near, end)), 6).alias("high"),
        F.sum(above).cast("long").alias("above"),
        F.round(g * F.sum(F.col("dt") * (F.col("p0") + F.col("dq") / 2)), 4).alias("integral"),
        F.round(g * F.sum("dq"), 6).alias("displacement"),
        F.round(g * F.sum(F.abs("dq")), 6).alias("path"),
    )


def relative(pieces: DataFrame, pairs: DataFrame, d: int, o: Options) -> DataFrame:
    """Stretches (a, b, block, s, e, x0, v0, x1, v1, ...) on which both particles of each pair move evenly on all d axes.

    ``pairs(a, b)``; x is the difference at step s and v its change per step.  Each step from two pieces to one stretch is an equi-join on
    block and pair with an overlap test, never a product.
    """
    p = pieces.select("block", F.floor(F.col("k") / d).alias("particle"), (F.col("k") % d).alias("axis"), "t0", (F.col("t0") + F.col("dt")).alias("t1"), (F.lit(o.grid) * F.col("p0")).alias("x"), (F.lit(o.grid) * F.col("dq") / F.col("dt")).alias("v"))
    pairs = pairs.select(F.col("a").cast("long").alias("a"), F.col("b").cast("long").alias("b"))

    def side(name: str) -> DataFrame:
        return pairs.join(p, F.col(name) == F.col("particle")).select("a", "b", "block", "axis", *[F.col(c).alias(f"{c}_{name}") for c in ("t0", "t1", "x", "v")])

    left, right = side("a"), side("b")
    both = left.join(right, ["a", "b", "block", "axis"]).where("t0_a < t1_b AND t0_b < t1_a")
    s = F.greatest("t0_a", "t0_b")
    both = both.select("a", "b", "block", "axis", s.alias("s"), F.least("t1_a", "t1_b").alias("e"), (F.col("x_a") + F.col("v_a") * (s - F.col("t0_a")) - F.col("x_b") - F.col("v_b") * (s - F.col("t0_b"))).alias("x"), (F.col("v_a") - F.col("v_b")).alias("v"))
    out = both.where("axis = 0").select("a", "b", "block", "s", "e", F.col("x").alias("x0"), F.col("v").alias("v0"))
    for axis in range(1, d):
        other = both.where(F.col("axis") == axis).select("a", "b", "block", F.col("s").alias("s2"), F.col("e").alias("e2"), F.col("x").alias(f"x{axis}"), F.col("v").alias(f"v{axis}"))
        out = out.join(other, ["a", "b", "block"]).where("s < e2 AND s2 < e")
        start = F.greatest("s", "s2")
        moved = [(F.col(f"x{i}") + F.col(f"v{i}") * (start - F.col("s" if i < axis else "s2"))).alias(f"x{i}") for i in range(axis + 1)]
        out = out.select("a", "b", "block", start.alias("start"), F.least("e", "e2").alias("e"), *moved, *[F.col(f"v{i}") for i in range(axis + 1)]).withColumnRenamed("start", "s")
    return out


def _square(s: Column, d: int) -> Column:
    out = None
    for i in range(d):
        term = F.pow(F.col(f"x{i}") + F.col(f"v{i}") * s, F.lit(2.0))
        out = term if out is None else out + term
    return out


def min_distance(pieces: DataFrame, pairs: DataFrame, d: int, o: Options) -> DataFrame:
    """(a, b, continuous, sampled): least distance of each pair over time, and over whole steps; of the true tracks it is off by at
    most 2 eps sqrt(d), given as low and high."""
    rows = relative(pieces, pairs, d, o)
    xv, vv = F.lit(0.0), F.lit(0.0)
    for i in range(d):
        xv, vv = xv + F.col(f"x{i}") * F.col(f"v{i}"), vv + F.col(f"v{i}") * F.col(f"v{i}")
    span = F.col("e") - F.col("s")
    vertex = F.least(F.greatest(F.when(vv > 0, -xv / vv).otherwise(F.lit(0.0)), F.lit(0.0)), span)
    rows = rows.withColumn("u", vertex)
    cont = _square(F.col("u"), d)
    grid = F.least(_square(F.floor("u"), d), _square(F.ceil("u"), d))
    slack = 2 * o.bound * d**0.5
    near = rows.groupBy("a", "b").agg(F.sqrt(F.min(cont)).alias("c"), F.sqrt(F.min(grid)).alias("g"))
    return near.select("a", "b", F.round("c", 6).alias("continuous"), F.round("g", 6).alias("sampled"), F.round(F.greatest(F.lit(0.0), F.col("c") - slack), 6).alias("low"), F.round(F.col("c") + slack, 6).alias("high"))


TILE = 64  # particles


def by_tiles(rows: DataFrame, d: int, run) -> DataFrame:
    """(a, b, d2): least of ``run(left, right)`` over blocks for all pairs of particles, from ``rows(block, k, ..)``.

    A task has one block of two tiles of particles; a row goes once to each tile, so rows moved grow with particles times tiles and pairs
    are never rows before they have their distance.  ``run`` gives a matrix, infinite where a pair has no common step.
    """
    rows = rows.withColumn("tile", F.floor(F.col("k") / (d * TILE)))
    tiles = rows.select("tile").distinct()
    left = rows.join(F.broadcast(tiles.toDF("j")), F.col("tile") <= F.col("j")).withColumn("i", F.col("tile")).withColumn("right", F.lit(False))
    right = rows.join(F.broadcast(tiles.toDF("i")), F.col("i") < F.col("tile")).withColumn("j", F.col("tile")).withColumn("right", F.lit(True))

    def task(table: pa.Table) -> pa.Table:
        sides = table.filter(pc.invert(table.column("right"))), table.filter(table.column("right"))
        if table.column("i")[0] == table.column("j")[0]:
            sides = sides[0], sides[0]
        a, b = (np.unique(np.asarray(x.column("k")) // d) for x in sides)
        d2 = run(*sides, a, b) if len(a) and len(b) else np.zeros((len(a), len(b)))
        at = np.nonzero(np.isfinite(d2) & (a[:, None] < b[None]))
        return pa.table({"a": pa.array(a[at[0]], pa.int64()), "b": pa.array(b[at[1]], pa.int64()), "d2": pa.array(d2[at], pa.float64())})

    return left.unionByName(right).drop("tile").groupBy("i", "j", "block").applyInArrow(task, "a long, b long, d2 double").groupBy("a", "b").agg(F.min("d2").alias("d2"))


def lay(s: np.ndarray, row: np.ndarray, n: int, k: np.ndarray, t0: np.ndarray, dt: np.ndarray, p0: np.ndarray, dq: np.ndarray, d: int, o: Options) -> tuple[np.ndarray, np.ndarray]:
    """Start and change per step, (stretches x axes x n), of pieces on the stretches between ascending steps ``s``, which hold all their ends; no piece: infinite."""
    x, v = np.full((len(s) - 1, d, n), np.inf), np.zeros((len(s) - 1, d, n))
    first, last = np.searchsorted(s, t0), np.searchsorted(s, t0 + dt)
    of = np.repeat(np.arange(len(k)), last - first)
    j = np.arange(len(of)) - np.repeat(np.cumsum(last - first) - last, last - first)
    slope = o.grid * dq / np.maximum(dt, 1)
    at = j, k[of] % d, row[of]
    x[at], v[at] = (o.grid * p0)[of] + slope[of] * (s[j] - t0[of]), slope[of]
    return x, v


def tile_distances(pieces: DataFrame, d: int, o: Options) -> DataFrame:
    """(a, b, sampled) as in ``min_distance``, for all pairs: on each stretch between ends of pieces the least square is in closed form."""

    def run(left: pa.Table, right: pa.Table, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        columns = [[np.asarray(x.column(c)) for c in ("k", "t0", "dt", "p0", "dq")] for x in (left, right)]
        s = np.unique(np.concatenate([v for _, t0, dt, *_ in columns for v in (t0, t0 + dt)]))
        laid = []
        for ids, rows in zip((a, b), columns, strict=True):
            x, v = (c.transpose(2, 1, 0) for c in lay(s, np.searchsorted(ids, rows[0] // d), len(ids), *rows, d, o))
            laid.append((np.where(np.isinf(x), np.nan, x), v))
        x, v = (laid[0][i][:, None] - laid[1][i][None] for i in (0, 1))
        vv = (v * v).sum(axis=2)
        u = np.clip(np.where(vv > 0, -(x * v).sum(axis=2) / np.where(vv > 0, vv, 1.0), 0.0), 0.0, np.diff(s))
        least = np.minimum(*(((x + v * w[:, :, None]) ** 2).sum(axis=2) for w in (np.floor(u), np.ceil(u))))
        return np.where(np.isnan(least), np.inf, least).min(axis=2, initial=np.inf)

    rows = by_tiles(pieces.select("block", "k", "t0", "dt", "p0", "dq"), d, run)
    return rows.select("a", "b", F.round(F.sqrt("d2"), 6).alias("sampled"))


def frame_distances(track: DataFrame, d: int, o: Options) -> DataFrame:
    """(a, b, frames): least distance over common steps of all pairs of a track ``(k, t, x)``."""

    def run(left: pa.Table, right: pa.Table, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        columns = [[np.asarray(x.column(c)) for c in ("k", "t", "x")] for x in (left, right)]
        steps = np.unique(np.concatenate([t for _, t, _ in columns]))
        laid = []
        for ids, (k, t, v) in zip((a, b), columns, strict=True):
            x = np.full((len(ids), d, len(steps)), np.nan)
            x[np.searchsorted(ids, k // d), k % d, np.searchsorted(steps, t)] = v
            laid.append(x)
        least = ((laid[0][:, None] - laid[1][None]) ** 2).sum(axis=2)
        return np.where(np.isnan(least), np.inf, least).min(axis=2)

    rows = by_tiles(track.select(F.floor(F.col("t") / o.block).alias("block"), "k", "t", "x"), d, run)
    return rows.select("a", "b", F.sqrt("d2").alias("frames"))


TILE_SAMPLES = 3 << 18  # what a tile of whole tracks holds, about
LEFT, RIGHT = 4, 4096  # particles that meet at once: their squares stay in a core's cache


def _packed(a: np.ndarray) -> bytes:
    """Numbers of 8 bytes, first bytes first."""
    return zlib.compress(np.ascontiguousarray(a).view(np.uint8).reshape(-1, 8).T.tobytes(), 1)


def _unpacked(raw: bytes, kind: type) -> np.ndarray:
    return np.ascontiguousarray(np.frombuffer(zlib.decompress(raw), np.uint8).reshape(8, -1).T).reshape(-1).view(kind)


def _packed_tiles(rows: DataFrame, tile: Column, name: str) -> DataFrame:
    """(tile, name): one row for a tile, its columns packed in order of series and step."""
    columns = rows.columns

    def run(table: pa.Table) -> pa.Table:
        table = table.sort_by([(c, "ascending") for c in columns[:2]])
        return pa.table({"tile": table.column("tile").slice(0, 1), name: pa.array([[_packed(np.asarray(table.column(c))) for c in columns]], pa.list_(pa.binary()))})

    return rows.withColumn("tile", tile).groupBy("tile").applyInArrow(run, f"tile long, {name} array<binary>")


class _Side:
    """A tile's pieces and frames; the longest tracks come first, so those that reach a step are a prefix."""

    def __init__(self, pieces: list[bytes], frames: list[bytes], d: int):
        self.k, self.t0, self.dt, self.p0, self.dq = (_unpacked(raw, np.int64) for raw in pieces)
        self.fk, self.ft, self.fx = (_unpacked(raw, kind) for raw, kind in zip(frames, (np.int64, np.int64, np.float64), strict=True))
        self.d, (ids, count) = d, np.unique(self.fk // d, return_counts=True)
        place = np.empty(len(ids), np.int64)
        place[np.argsort(-count, kind="stable")] = np.arange(len(ids))
        self.n, self.row, self.frow = len(ids), place[np.searchsorted(ids, self.k // d)], place[np.searchsorted(ids, self.fk // d)]

    def stretches(self, s: np.ndarray, o: Options, block: int):
        at = np.flatnonzero(self.t0 // o.block == block)
        return lay(s, self.row[at], self.n, *(c[at] for c in (self.k, self.t0, self.dt, self.p0, self.dq)), self.d, o)

    def steps(self, steps: np.ndarray) -> np.ndarray:
        x = np.full((len(steps), self.d, self.n), np.inf)
        at = np.flatnonzero((self.ft >= steps[0]) & (self.ft <= steps[-1])) if len(steps) else np.zeros(0, np.int64)
        x[np.searchsorted(steps, self.ft[at]), self.fk[at] % self.d, self.frow[at]] = self.fx[at]
        return x


def _covered(x: np.ndarray) -> np.ndarray:
    """Whether all axes are there, (steps x particles)."""
    return np.isfinite(x).all(axis=1)


def _reach(covered: np.ndarray) -> list[tuple[int, int]]:
    """First and one after the last particle of each row."""
    some, n = covered.any(axis=1), covered.shape[1]
    return [(int(a), int(b)) if c else (0, 0) for a, b, c in zip(covered.argmax(axis=1), n - covered[:, ::-1].argmax(axis=1), some, strict=True)]


def _nearer(best: np.ndarray, a: np.ndarray, b: np.ndarray, work: np.ndarray) -> None:
    """Squares of distances, (left x right), of places (axes x left) from places (axes x right), where they are less than the best."""
    u, w = work[0, : len(best), : best.shape[1]], work[1, : len(best), : best.shape[1]]
    for i in range(len(a)):
        out = w if i else u
        np.subtract(b[i], a[i][:, None], out=out)
        np.multiply(out, out, out=out)
        if i:
            np.add(u, w, out=u)
    np.minimum(best, u, out=best)


class _BlockPair:
    """One block of two tiles: stretches between all ends of pieces, and frames."""

    def __init__(self, left: _Side, right: _Side, block: int, o: Options, wide: int):
        self.wide = wide
        ends = [c[x.t0 // o.block == block] for x in (left, right) for c in (x.t0, x.t0 + x.dt)]
        self.s = np.unique(np.concatenate(ends))
        (self.xa, self.va), (self.xb, self.vb) = (x.stretches(self.s, o, block) for x in (left, right))
        self.span = np.diff(self.s)
        self.in_a, in_b = _covered(self.xa), _covered(self.xb)
        # where a stretch ends and no stretch goes on from there
        self.ends_a, ends_b = (self._stops(x, v, inside) for x, v, inside in ((self.xa, self.va, self.in_a), (self.xb, self.vb, in_b)))
        steps = np.unique(np.concatenate([x.ft[x.ft // o.block == block] for x in (left, right)]))
        self.fa, self.fb = left.steps(steps), right.steps(steps)
        self.f_in_a = _covered(self.fa)
        self.reach, self.stops, self.f_reach = ([_reach(c[:, at : at + wide]) for at in range(0, right.n, wide)] for c in (in_b, ends_b, _covered(self.fb)))
        for x in (self.xa, self.fa):  # infinite the other way, so that what isn't there is infinitely far
            x[np.isinf(x)] = -np.inf

    def _stops(self, x: np.ndarray, v: np.ndarray, inside: np.ndarray) -> np.ndarray:
        end, following = x[:-1] + v[:-1] * self.span[:-1, None, None], x[1:]
        with np.errstate(invalid="ignore"):
            goes_on = (np.abs(end - following) <= 1e-9 * (1 + np.abs(end))).all(axis=1)
        return inside & ~np.concatenate([goes_on & inside[1:], np.zeros((min(1, len(x)), x.shape[2]), bool)])

    def pieces(self, a: slice, at: int, best: np.ndarray, work: np.ndarray) -> None:
        """Least squares at whole steps, from pieces, of particles a from those of the right at ``at`` and on.

        On a stretch of one step they are at its ends, and an end is mostly the next stretch's start.
        """
        reach, stops = self.reach[at // self.wide], self.stops[at // self.wide]
        for j in np.flatnonzero(self.in_a[:, a].any(axis=1)).tolist():
            lo, hi = reach[j]
            if lo >= hi:
                continue
            x, v, right = self.xa[j][:, a], self.va[j][:, a], slice(at + lo, at + hi)
            if self.span[j] > 1:
                self._inside(x, v, self.xb[j][:, right], self.vb[j][:, right], self.span[j], best[:, lo:hi])
                continue
            _nearer(best[:, lo:hi], x, self.xb[j][:, right], work)
            if not self.ends_a[j, a].any():
                lo, hi = stops[j]
                right = slice(at + lo, at + hi)
            if lo < hi:
                _nearer(best[:, lo:hi], x + v, self.xb[j][:, right] + self.vb[j][:, right], work)

    @staticmethod
    def _inside(xa: np.ndarray, va: np.ndarray, xb: np.ndarray, vb: np.ndarray, span: int, best: np.ndarray) -> None:
        with np.errstate(invalid="ignore", over="ignore"):
            x, v = xa[:, :, None] - xb[:, None], va[:, :, None] - vb[:, None]
            vv = (v * v).sum(axis=0)
            u = np.clip(np.where(vv > 0, -(x * v).sum(axis=0) / np.where(vv > 0, vv, 1.0), 0.0), 0.0, span)
            for w in (np.floor(u), np.ceil(u)):
                np.fmin(best, ((x + v * w) ** 2).sum(axis=0), out=best)

    def frames(self, a: slice, at: int, best: np.ndarray, work: np.ndarray) -> None:
        """The same from frames."""
        for j in np.flatnonzero(self.f_in_a[:, a].any(axis=1)).tolist():
            lo, hi = self.f_reach[at // self.wide][j]
            if lo < hi:
                _nearer(best[:, lo:hi], self.fa[j][:, a], self.fb[j][:, at + lo : at + hi], work)


def distance_gap(pieces: DataFrame, track: DataFrame, d: int, o: Options) -> DataFrame:
    """(pairs, difference): pairs that both ``tile_distances`` and ``frame_distances`` give, and how far the two differ at most.

    A task has two tiles of whole tracks and takes all blocks of some particles against some at a time; it gives one row, so pairs are never
    rows.  A tile is one packed row and goes once to each other tile.
    """
    samples = pieces.agg(F.sum("dt")).first()[0] or 0
    tiles = max(1, -(-samples // TILE_SAMPLES))
    tile = F.pmod(F.xxhash64(F.floor(F.col("k") / d)), F.lit(tiles))
    long = [F.col(c).cast("long").alias(c) for c in ("k", "t0", "dt", "p0", "dq")]
    both = _packed_tiles(pieces.select(*long), tile, "pieces").join(_packed_tiles(track.select("k", "t", "x"), tile, "frames"), "tile")
    other = F.explode(F.sequence(F.lit(0).cast("long"), F.lit(tiles - 1).cast("long"))).alias("other")
    groups = both.select("*", other).withColumn("i", F.least("tile", "other")).withColumn("j", F.greatest("tile", "other")).drop("other")

    def run(table: pa.Table) -> pa.Table:
        same = table.column("i")[0] == table.column("j")[0]
        sides = [_Side(table.column("pieces")[r].as_py(), table.column("frames")[r].as_py(), d) for r in range(len(table))]
        pairs, worst = 0, None
        if same or len(sides) == 2:  # else one of the tiles has no particle
            left, right = sides[0], sides[-1]
            blocks = [_BlockPair(left, right, b, o, RIGHT) for b in np.unique(np.concatenate([x.t0 // o.block for x in (left, right)])).tolist()]
            work = np.empty((2, LEFT, min(RIGHT, right.n)))
            for at in range(0, right.n, RIGHT):
                n = min(RIGHT, right.n - at)
                for p in range(0, min(left.n, at + n) if same else left.n, LEFT):
                    a = slice(p, min(p + LEFT, left.n))
                    quick, slow = np.full((2, a.stop - p, n), np.inf)
                    for b in blocks:
                        b.pieces(a, at, quick, work)
                        b.frames(a, at, slow, work)
                    both = np.isfinite(quick) & np.isfinite(slow)
                    if same:
                        both &= np.arange(p, a.stop)[:, None] < np.arange(at, at + n)
                    if both.any():
                        off = np.abs(np.round(np.sqrt(quick[both]), 6) - np.sqrt(slow[both]))
                        pairs, worst = pairs + len(off), max(worst or 0.0, float(off.max()))
        return pa.table({"pairs": pa.array([pairs], pa.int64()), "difference": pa.array([worst], pa.float64())})

    tasks = 2 * tiles * (tiles + 1)  # few bytes, much work: never merged into one task
    found = groups.repartition(tasks, "i", "j").groupBy("i", "j").applyInArrow(run, "pairs long, difference double")
    return found.agg(F.coalesce(F.sum("pairs"), F.lit(0)).alias("pairs"), F.round(F.max("difference"), 5).alias("difference"))


def encounters(pieces: DataFrame, pairs: DataFrame, d: int, radius: float, o: Options) -> DataFrame:
    """(a, b, s, e): spans of time, in steps, in which a pair is nearer than the radius on one stretch of even motion."""
    rows = relative(pieces, pairs, d, o)
    aa, bb, cc = F.lit(0.0), F.lit(0.0), F.lit(-radius * radius)
    for i in range(d):
        aa, bb, cc = aa + F.col(f"v{i}") * F.col(f"v{i}"), bb + 2 * F.col(f"x{i}") * F.col(f"v{i}"), cc + F.col(f"x{i}") * F.col(f"x{i}")
    rows = rows.withColumn("aa", aa).withColumn("bb", bb).withColumn("cc", cc).withColumn("disc", F.col("bb") * F.col("bb") - 4 * F.col("aa") * F.col("cc"))
    span = (F.col("e") - F.col("s")).cast("double")
    root = F.sqrt(F.greatest(F.col("disc"), F.lit(0.0)))
    low = F.when(F.col("aa") > 0, F.greatest(F.lit(0.0), (-F.col("bb") - root) / (2 * F.col("aa")))).otherwise(F.lit(0.0))
    high = F.when(F.col("aa") > 0, F.least(span, (-F.col("bb") + root) / (2 * F.col("aa")))).otherwise(span)
    inside = ((F.col("aa") > 0) & (F.col("disc") > 0)) | ((F.col("aa") == 0) & (F.col("cc") < 0))
    return rows.where(inside).withColumn("l", low).withColumn("h", high).where("l < h").select("a", "b", F.round(F.col("s") + F.col("l"), 4).alias("s"), F.round(F.col("s") + F.col("h"), 4).alias("e"))


AGGREGATES = {"min": "low", "max": "high", "sum": "total", "count": "n", "avg": None}


def rewrite_agg(pieces: DataFrame, aggregate: str, o: Options) -> DataFrame:
    """``aggregate(x)`` per series over expanded samples, rewritten to the closed form on pieces."""
    rows = seg_agg(pieces, o, 0.0)
    value = F.round(F.col("total") / F.col("n"), 6) if aggregate == "avg" else F.col(AGGREGATES[aggregate])
    return rows.select("k", value.alias("value"))
