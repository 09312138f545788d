"""Greedy search over any family of functions: a piece grows while the family can still fit all its samples."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from corridor.baselines.codecs import _chain, strip
from corridor.operators.segment import cut_blocks, matrix
from corridor.options import Options


class Constant:
    """Constants: the range of the samples is at most the corridor's width."""

    def __init__(self, g: float) -> None:
        self.g, self.low, self.high = g, np.inf, -np.inf

    def push(self, t: int, y: float) -> bool:
        low, high = min(self.low, y), max(self.high, y)
        if high - low > 2 * self.g:
            return False
        self.low, self.high = low, high
        return True

    def fit(self) -> list[float]:
        return [(self.low + self.high) / 2]


class FreeLine:
    """Lines with any start: the vertical width of the samples' hull is at most the corridor's."""

    def __init__(self, g: float) -> None:
        self.g, self.t, self.y = g, [], []

    def push(self, t: int, y: float) -> bool:
        tt, yy = np.array([*self.t, t], float), np.array([*self.y, y])
        if strip(tt, yy) > self.g + 1e-12:
            return False
        # only hull vertices can matter later
        keep = sorted({*_chain(tt, yy, 1), *_chain(tt, yy, -1)})
        self.t, self.y = tt[keep].tolist(), yy[keep].tolist()
        return True

    def fit(self) -> list[float]:
        t, y = np.array(self.t), np.array(self.y)
        if len(t) == 1:
            return [float(y[0]), 0.0]
        slopes = [(y[b] - y[a]) / (t[b] - t[a]) for h in (_chain(t, y, 1), _chain(t, y, -1)) for a, b in zip(h, h[1:], strict=False)]
        s = min(slopes, key=lambda s: np.ptp(y - s * t))
        r = y - s * t
        return [float((r.max() + r.min()) / 2), float(s)]


class Poly:
    """Polynomials of one degree by least squares, accepted if no residual exceeds the corridor."""

    def __init__(self, g: float, degree: int = 2) -> None:
        self.g, self.degree, self.t, self.y = g, degree, [], []

    def push(self, t: int, y: float) -> bool:
        self.t.append(t)
        self.y.append(y)
        m = min(self.degree, len(self.t) - 1)
        s = np.array(self.t) - self.t[0]
        p = np.polynomial.Polynomial.fit(s, self.y, m, domain=[0, max(1, s[-1])])
        if np.abs(p(s) - self.y).max() > self.g + 1e-12:
            self.t.pop()
            self.y.pop()
            return False
        self.best = p.coef.tolist()
        return True

    def fit(self) -> list[float]:
        return self.best


FAMILIES = {"constant": Constant, "free_line": FreeLine, "poly": Poly}


def segment_with(track: DataFrame, family: str, o: Options) -> DataFrame:
    """Disjoint pieces ``(block, k, t0, n, params)`` of a family within the line tolerance, in grid units."""
    kind = FAMILIES[family]

    def run(table: pa.Table) -> pa.Table:
        ids, t0, length, y = matrix(*(np.asarray(table.column(c)) for c in ("k", "t", "y")))
        rows = []
        for c, i in enumerate(ids.tolist()):
            piece, start = kind(o.slack), 0
            for s in range(int(length[c])):
                if not piece.push(s, float(y[s, c])):
                    rows.append((i, int(t0[c]) + start, s - start, piece.fit()))
                    piece, start = kind(o.slack), s
                    piece.push(s, float(y[s, c]))
            rows.append((i, int(t0[c]) + start, int(length[c]) - start, piece.fit()))
        block = table.column("block")[0].as_py()
        k, a, n, p = zip(*rows, strict=True)
        return pa.table({"block": pa.array([block] * len(rows), pa.int64()), "k": pa.array(k, pa.int64()), "t0": pa.array(a, pa.int64()), "n": pa.array(n, pa.int64()), "params": pa.array(p, pa.list_(pa.float64()))})

    return cut_blocks(track, o).groupBy("block", "bucket").applyInArrow(run, "block long, k long, t0 long, n long, params array<double>")


def constant_sql(track_cte: str, o: Options) -> str:
    """Constant pieces in DuckDB's SQL."""
    return f"""WITH RECURSIVE {track_cte}, samples AS MATERIALIZED (SELECT k, t, t // {o.block} AS block, x / {o.grid!r} AS y FROM track),
ends AS MATERIALIZED (SELECT k, block, min(t) AS a, max(t) AS z FROM samples GROUP BY ALL),
scan AS (SELECT s.k, s.block, s.t, s.t AS t0, s.y AS lo, s.y AS hi, CAST(NULL AS BIGINT) AS e0, CAST(NULL AS BIGINT) AS en FROM samples s JOIN ends e ON s.k = e.k AND s.block = e.block AND s.t = e.a
UNION ALL SELECT k, block, nt, CASE WHEN ok THEN t0 ELSE nt END, CASE WHEN ok THEN nlo ELSE y END, CASE WHEN ok THEN nhi ELSE y END, CASE WHEN ok THEN NULL ELSE t0 END, CASE WHEN ok THEN NULL ELSE nt - t0 END
FROM (SELECT *, nhi - nlo <= 2 * {o.slack!r} AS ok FROM (SELECT c.k, c.block, c.t0, s.t AS nt, s.y, least(c.lo, s.y) AS nlo, greatest(c.hi, s.y) AS nhi FROM scan c JOIN samples s ON s.k = c.k AND s.block = c.block AND s.t = c.t + 1)))
SELECT block, k, e0 AS t0, en AS n FROM scan WHERE e0 IS NOT NULL UNION ALL SELECT c.block, c.k, c.t0, c.t - c.t0 + 1 FROM scan c JOIN ends e ON c.k = e.k AND c.block = e.block AND c.t = e.z"""
