"""Greedy piecewise lines inside a tolerance, one pass per series and block.

Two physical forms of one method.  ``fold_scan`` is a fold over each series' sorted samples inside the JVM, for modest blocks and SQL
users.  ``vector_scan`` takes a block and a bucket of series as a matrix and advances all series by one sample at a time, with a few
array operations per step and five numbers of state per series; it is the form for volume.  Both give the same rows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from corridor.options import Options

SEGMENT = "block long, k long, t0 long, dt int, p0 long, dq long"
NEVER = float("inf")


def cut_blocks(track: DataFrame, o: Options) -> DataFrame:
    """``track(k, t, x)`` with block, bucket and grid height y; the only shuffle key of raw samples."""
    return track.select(F.floor(F.col("t") / o.block).alias("block"), F.floor(F.col("k") / o.width).cast("int").alias("bucket"), "k", "t", (F.col("x") / F.lit(o.grid)).alias("y"))


def _let(value: Column, body) -> Column:
    """Bind a value once inside an expression."""
    return F.transform(F.array(value), body)[0]


def fold_scan(track: DataFrame, o: Options) -> DataFrame:
    """Pieces of every series and block, by a fold."""
    g, half = o.slack, F.lit(0.5)
    free = F.lit(NEVER)

    def point(t, p):
        return {"t0": t, "p": p, "lo": -free, "hi": free, "last": F.lit(0.0), "d": F.lit(0).cast("long")}

    def state(values: dict, out: Column) -> Column:
        return F.struct(*[values[n].alias(n) for n in ("t0", "p", "lo", "hi", "last", "d")], out.alias("out"))

    def end(s):
        lo, hi = s["d"] * s["lo"], s["d"] * s["hi"]
        value = {"nearest": F.least(F.greatest(s["last"], lo), hi), "mid": (lo + hi) / 2, "low": lo, "high": hi}[o.end]
        return F.floor(value + half).cast("double")

    def piece(s):
        return F.struct(s["t0"].alias("t0"), s["d"].cast("int").alias("dt"), s["p"].cast("long").alias("p0"), end(s).cast("long").alias("dq"))

    def height(e):
        return e["y"] if o.mode == "supports" else F.floor(e["y"] + half).cast("double")

    def step(s, e):
        def with_cone(c):
            ok = c["lo"] <= c["hi"]
            if o.mode == "feasible":
                ok = ok & (F.ceil(c["lo"] * c["d"]) <= F.floor(c["hi"] * c["d"]))
            grown = state({"t0": s["t0"], "p": s["p"], "lo": c["lo"], "hi": c["hi"], "last": c["u"], "d": c["d"]}, s["out"])
            out = F.concat(s["out"], F.array(piece(s)))
            if not o.connect:
                return F.when(ok, grown).otherwise(state(point(e["t"], F.floor(e["y"] + half).cast("double")), out))
            p = s["p"] + end(s)
            u = height(e) - p
            return F.when(ok, grown).otherwise(state({"t0": s["t0"] + s["d"], "p": p, "lo": u - g, "hi": u + g, "last": u, "d": F.lit(1).cast("long")}, out))

        def with_sample(v):
            lo, hi = (v["u"] - g) / v["d"], (v["u"] + g) / v["d"]
            return _let(F.struct(v["u"].alias("u"), v["d"].alias("d"), F.greatest(s["lo"], lo).alias("lo"), F.least(s["hi"], hi).alias("hi")), with_cone)

        return _let(F.struct((height(e) - s["p"]).alias("u"), (s["d"] + 1).alias("d")), with_sample)

    empty = F.expr("cast(array() as array<struct<t0:bigint,dt:int,p0:bigint,dq:bigint>>)")
    first = state(point(F.col("s")[0]["t"], F.floor(F.col("s")[0]["y"] + half).cast("double")), empty)
    finish = lambda s: F.when((s["d"] >= 1) | F.lit(not o.connect), F.concat(s["out"], F.array(piece(s)))).otherwise(s["out"])
    if not o.connect:  # a piece of one sample ends where it starts
        end_of = end
        end = lambda s: F.when(s["d"] == 0, F.lit(0.0)).otherwise(end_of(s))
    series = cut_blocks(track, o).groupBy("block", "k").agg(F.array_sort(F.collect_list(F.struct("t", "y"))).alias("s"))  # at most one block long
    scanned = series.select("block", "k", F.aggregate(F.slice("s", 2, o.block), first, step, finish).alias("pieces"))
    return scanned.select("block", "k", F.explode("pieces").alias("r")).select("block", "k", "r.t0", "r.dt", "r.p0", "r.dq")


def scan_matrix(y: np.ndarray, length: np.ndarray, t0: np.ndarray, o: Options, failed: list | None = None):
    """Pieces of the columns of ``y`` (steps x series), whose first ``length`` rows count: series index, t0, dt, p0, dq.

    failed: gets the series of every failed test, step by step, which is all that a kernel must hand on.
    """
    n = y.shape[1]
    g = o.slack
    if o.mode != "supports":
        raw, y = y, np.floor(y + 0.5)
    else:
        raw = y
    p = np.floor(raw[0] + 0.5)
    start = t0.astype(np.int64).copy()
    lo, hi, last = np.full(n, -NEVER), np.full(n, NEVER), np.zeros(n)
    # division-free form: bounds as height over time
    lo_n, lo_d, hi_n, hi_d = np.full(n, -NEVER), np.ones(n), np.full(n, NEVER), np.ones(n)
    d = np.zeros(n, np.int64)
    out: list[tuple] = []

    def ends(at):
        k = d[at]
        with np.errstate(invalid="ignore"):
            a, b = lo[at] * k, hi[at] * k
            v = {"nearest": np.minimum(np.maximum(last[at], a), b), "mid": (a + b) / 2, "low": a, "high": b}[o.end]
        return np.where(k == 0, 0.0, np.floor(v + 0.5))

    def close(at):
        dq = ends(at)
        out.append((at, start[at].copy(), d[at].copy(), p[at].copy(), dq))
        return dq

    steps = int(length.max()) if n else 0
    alive = np.arange(n)
    shortest = int(length.min()) if n else 0
    for i in range(1, steps):
        if i >= shortest:
            alive = np.flatnonzero(length > i)
        whole = len(alive) == n
        a = slice(None) if whole else alive
        u, k = y[i][a] - p[a], d[a] + 1
        if o.test == "cross":
            with np.errstate(invalid="ignore"):
                below = lo_n[a] * k > (u + g) * lo_d[a]
                above = hi_n[a] * k < (u - g) * hi_d[a]
            bad = below | above
            raise_lo, drop_hi = ~bad & (lo_n[a] * k < (u - g) * lo_d[a]), ~bad & (hi_n[a] * k > (u + g) * hi_d[a])
            new_lo, new_hi = np.where(raise_lo, (u - g) / k, lo[a]), np.where(drop_hi, (u + g) / k, hi[a])
        else:
            new_lo, new_hi = np.maximum(lo[a], (u - g) / k), np.minimum(hi[a], (u + g) / k)
            bad = new_lo > new_hi
        if o.mode == "feasible":
            bad |= np.ceil(new_lo * k) > np.floor(new_hi * k)
        plain = whole and o.connect and o.test != "cross"  # nothing is picked: all take the new state, then those that failed start anew
        if bad.any():
            at = np.flatnonzero(bad) if whole else alive[bad]
            if failed is not None:
                failed.append((i, at))
            dq = close(at)
            ended = d[at]
            good = None if plain else ~bad
        else:
            at, good = None, slice(None)
        if plain:
            lo, hi, last, d = new_lo, new_hi, u, k
            if at is not None:
                p[at] += dq
                start[at] += ended
                v = y[i][at] - p[at]
                lo[at], hi[at], last[at], d[at] = v - g, v + g, v, 1
            continue
        b = (np.flatnonzero(good) if whole else alive[good]) if at is not None else a
        lo[b], hi[b], last[b], d[b] = new_lo[good], new_hi[good], u[good], k[good]
        if o.test == "cross":
            r, h = raise_lo[good], drop_hi[good]
            lo_n[b], lo_d[b] = np.where(r, u[good] - g, lo_n[b]), np.where(r, k[good], lo_d[b])
            hi_n[b], hi_d[b] = np.where(h, u[good] + g, hi_n[b]), np.where(h, k[good], hi_d[b])
        if at is None:
            continue
        if o.connect:
            p[at] += dq
            start[at] += ended
            v = y[i][at] - p[at]
            lo[at], hi[at], last[at], d[at] = v - g, v + g, v, 1
            lo_n[at], hi_n[at], lo_d[at], hi_d[at] = v - g, v + g, 1, 1
        else:
            p[at], start[at] = np.floor(raw[i][at] + 0.5), t0[at] + i
            lo[at], hi[at], last[at], d[at] = -NEVER, NEVER, 0, 0
            lo_n[at], hi_n[at], lo_d[at], hi_d[at] = -NEVER, NEVER, 1, 1
    rest = np.flatnonzero(d >= 1) if o.connect else np.arange(n)
    if len(rest):
        close(rest)
    if not out:
        return tuple(np.zeros(0, np.int64) for _ in range(5))
    k, s, dt, p0, dq = (np.concatenate(c) for c in zip(*out, strict=True))
    return k, s, dt, p0.astype(np.int64), dq.astype(np.int64)


def matrix(k: np.ndarray, t: np.ndarray, y: np.ndarray):
    """Long samples as (series, first step, length, steps x series matrix); a gap inside a series is an error."""
    order = np.lexsort((t, k))
    k, t, y = k[order], t[order], y[order]
    ids, at, length = np.unique(k, return_index=True, return_counts=True)
    row = np.arange(len(k)) - np.repeat(at, length)
    if not (t == np.repeat(t[at], length) + row).all():
        raise ValueError("a series has a gap or a repeated step; clean() mends both")
    out = np.zeros((int(length.max()) if len(ids) else 0, len(ids)))
    out[row, np.repeat(np.arange(len(ids)), length)] = y
    return ids, t[at], length, out


def vector_scan(track: DataFrame, o: Options) -> DataFrame:
    """Pieces of every series and block, by arrays over all series of a bucket."""

    def run(table: pa.Table) -> pa.Table:
        block = table.column("block")[0].as_py()
        ids, t0, length, y = matrix(*(np.asarray(table.column(c)) for c in ("k", "t", "y")))
        k, s, dt, p0, dq = scan_matrix(y, length, t0, o)
        return pa.table({"block": pa.array(np.full(len(k), block)), "k": pa.array(ids[k]), "t0": pa.array(s), "dt": pa.array(dt.astype(np.int32)), "p0": pa.array(p0), "dq": pa.array(dq)})

    return cut_blocks(track, o).groupBy("block", "bucket").applyInArrow(run, SEGMENT)


def segment(track: DataFrame, o: Options, how: str = "auto") -> DataFrame:
    """Pieces ``(block, k, t0, dt, p0, dq)``; ``fold`` and ``vector`` choose the physical form, auto the vector one."""
    if o.test == "cross" and how == "fold":
        raise ValueError("the division-free test is in the vector form")
    return fold_scan(track, o) if how == "fold" else vector_scan(track, o)


def failed_dims(track: DataFrame, o: Options) -> DataFrame:
    """(block, k, t) of every failed test: all that leaves the scanning kernel when the host does the rest."""

    def run(table: pa.Table) -> pa.Table:
        block = table.column("block")[0].as_py()
        ids, t0, length, y = matrix(*(np.asarray(table.column(c)) for c in ("k", "t", "y")))
        failed: list = []
        scan_matrix(y, length, t0, o, failed)
        k = np.concatenate([at for _, at in failed]) if failed else np.zeros(0, np.int64)
        i = np.concatenate([np.full(len(at), i) for i, at in failed]) if failed else np.zeros(0, np.int64)
        return pa.table({"block": pa.array(np.full(len(k), block, np.int64)), "k": pa.array(ids[k]), "t": pa.array(t0[k] + i)})

    return cut_blocks(track, o).groupBy("block", "bucket").applyInArrow(run, "block long, k long, t long")


def expand(pieces: DataFrame, track_start: DataFrame | None, o: Options) -> DataFrame:
    """Samples ``(k, t, x)`` that pieces stand for; never a join.

    Each piece gives the steps after its start; the first step of a series in a block comes from the piece that starts there, which
    is its key frame.  ``track_start(block, k, t, q)`` adds key frames of series with one sample in a block, which have no piece.
    """
    first = F.col("t0") == F.col("start")
    if o.connect:
        from pyspark.sql import Window

        rows = pieces.withColumn("start", F.min("t0").over(Window.partitionBy("block", "k")))
        steps = F.sequence(F.when(first, F.lit(0)).otherwise(F.lit(1)), F.col("dt"))
    else:
        rows, steps = pieces, F.sequence(F.lit(0), F.col("dt"))
    rows = rows.select("k", "t0", "dt", "p0", "dq", F.explode(steps).alias("s"))
    x = F.lit(o.grid) * (F.col("p0") + F.when(F.col("dt") == 0, F.lit(0.0)).otherwise(F.col("dq") * F.col("s") / F.col("dt")))
    out = rows.select("k", (F.col("t0") + F.col("s")).alias("t"), x.alias("x"))
    if track_start is not None:
        lone = track_start.join(pieces.select("block", "k").distinct(), ["block", "k"], "left_anti")
        out = out.union(lone.select("k", "t", (F.col("q") * F.lit(o.grid)).alias("x")))
    return out


def key_frames(track: DataFrame, o: Options) -> DataFrame:
    """(block, k, t, q): grid value of the first sample of each series in each block."""
    rows = cut_blocks(track, o)
    first = rows.groupBy("block", "k").agg(F.min_by("y", "t").alias("y"), F.min("t").alias("t"))
    return first.select("block", "k", "t", F.floor(F.col("y") + 0.5).cast("long").alias("q"))


# --- the same scan for DuckDB, as a recursive query that advances every series by one step ---
def scan_sql(track_cte: str, o: Options, select: str = "SELECT block, k, t0, dt, p0, dq FROM pieces") -> str:
    """SQL with CTEs ``track`` and ``pieces``, in the order of operations of the scans above."""
    y = "x / {:r}".replace("{:r}", repr(o.grid))
    seen = "y" if o.mode == "supports" else "floor(y + 0.5)"
    g = repr(o.slack)
    end = {"nearest": "least(greatest(last, d * lo), d * hi)", "mid": "(d * lo + d * hi) / 2", "low": "d * lo", "high": "d * hi"}[o.end]
    end = f"(CASE WHEN d = 0 THEN 0.0 ELSE floor({end} + 0.5) END)"
    ok = "nlo <= nhi" + (" AND ceil(nlo * (d + 1)) <= floor(nhi * (d + 1))" if o.mode == "feasible" else "")
    if o.connect:
        new = {"t0": "t0 + d", "p": f"p + {end}", "lo": f"u2 - p - {end} - {g}", "hi": f"u2 - p - {end} + {g}", "last": f"u2 - p - {end}", "d": "1"}
        new |= {"lo": f"u2 - (p + {end}) - {g}", "hi": f"u2 - (p + {end}) + {g}", "last": f"u2 - (p + {end})"}
    else:
        new = {"t0": "nt", "p": "floor(raw + 0.5)", "lo": "CAST('-inf' AS DOUBLE)", "hi": "CAST('inf' AS DOUBLE)", "last": "0.0", "d": "0"}
    old = {"t0": "t0", "p": "p", "lo": "nlo", "hi": "nhi", "last": "u2 - p", "d": "d + 1"}
    pick = ", ".join(f"CASE WHEN ok THEN {old[c]} ELSE {new[c]} END AS {c}" for c in ("t0", "p", "lo", "hi", "last", "d"))
    last = "d >= 1" if o.connect else "TRUE"
    return f"""WITH RECURSIVE {track_cte},
samples AS MATERIALIZED (SELECT k, t, t // {o.block} AS block, {y} AS y FROM track),
ends AS MATERIALIZED (SELECT k, block, min(t) AS a, max(t) AS z FROM samples GROUP BY ALL),
scan AS (
  SELECT s.k, s.block, s.t, s.t AS t0, floor(s.y + 0.5) AS p, CAST('-inf' AS DOUBLE) AS lo, CAST('inf' AS DOUBLE) AS hi, CAST(0.0 AS DOUBLE) AS last, CAST(0 AS BIGINT) AS d,
    CAST(NULL AS BIGINT) AS e_t0, CAST(NULL AS BIGINT) AS e_dt, CAST(NULL AS DOUBLE) AS e_p, CAST(NULL AS DOUBLE) AS e_dq
  FROM samples s JOIN ends e ON s.k = e.k AND s.block = e.block AND s.t = e.a
  UNION ALL
  SELECT k, block, nt AS t, {pick}, CASE WHEN ok THEN NULL ELSE t0 END, CASE WHEN ok THEN NULL ELSE d END, CASE WHEN ok THEN NULL ELSE p END, CASE WHEN ok THEN NULL ELSE {end} END
  FROM (SELECT *, {ok} AS ok FROM (
    SELECT c.k, c.block, c.t0, c.p, c.lo, c.hi, c.last, c.d, s.t AS nt, s.y AS raw, {seen.replace("y", "s.y")} AS u2,
      greatest(c.lo, ({seen.replace("y", "s.y")} - c.p - {g}) / (c.d + 1)) AS nlo, least(c.hi, ({seen.replace("y", "s.y")} - c.p + {g}) / (c.d + 1)) AS nhi
    FROM scan c JOIN samples s ON s.k = c.k AND s.block = c.block AND s.t = c.t + 1))
),
pieces AS (
  SELECT block, k, e_t0 AS t0, CAST(e_dt AS INTEGER) AS dt, CAST(e_p AS BIGINT) AS p0, CAST(e_dq AS BIGINT) AS dq FROM scan WHERE e_dt IS NOT NULL
  UNION ALL
  SELECT c.block, c.k, c.t0, CAST(d AS INTEGER), CAST(p AS BIGINT), CAST({end} AS BIGINT) FROM scan c JOIN ends e ON c.k = e.k AND c.block = e.block AND c.t = e.z WHERE {last}
)
{select}"""
