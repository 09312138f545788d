"""Comparison codecs whose cost is arithmetic on neighbours: one SQL text each over ``{track}(k, t, x)``.

The text is declarative and portable; Spark plans it, and DuckDB can check it.  Sizes are exact bit counts of the named code
without container overhead.
"""

from __future__ import annotations

from pyspark.sql import DataFrame

from corridor.options import Options

BITLEN = "CASE WHEN {u} = 0 THEN 0 ELSE length(bin({u})) END"


def run(track: DataFrame, body: str) -> DataFrame:
    return track.sparkSession.sql(body, track=track)


def oracle(track_cte: str, body: str) -> str:
    text = body.replace("{track}", "track")
    return f"WITH {track_cte}, {text[5:]}" if text.startswith("WITH ") else f"WITH {track_cte} {text}"


def bitlen(u: str) -> str:
    return "(" + BITLEN.replace("{u}", f"({u})") + ")"


def zig(i: str) -> str:
    return f"(CASE WHEN ({i}) >= 0 THEN 2 * ({i}) ELSE -2 * ({i}) - 1 END)"


def code_bits(code: str, u: str) -> str:
    """Bits of one unsigned number under a code."""
    return {
        "varint": f"8 * greatest(1, CAST(ceil({bitlen(u)} / 7.0) AS BIGINT))",
        "unary": f"({u}) + 1",
        "gamma": f"2 * ({bitlen(f'{u} + 1')} - 1) + 1",
        "delta": f"({bitlen(f'{u} + 1')} - 1) + 2 * ({bitlen(bitlen(f'{u} + 1'))} - 1) + 1",
    }[code]


def grid(o: Options) -> str:
    return f"SELECT k, t, CAST(floor(x / {o.grid!r} + 0.5) AS BIGINT) AS q FROM {{track}}"


def raw_bytes(width: int = 8) -> str:
    """B1: no compression."""
    return f"SELECT count(*) AS n, CAST(count(*) * {width} AS BIGINT) AS raw_bytes FROM {{track}}"


def subsample(n: int) -> str:
    """B2: every n-th frame, rebuilt by holding and by lines; worst errors."""
    return f"""WITH kept AS (SELECT k, t, x, lead(t) OVER (PARTITION BY k ORDER BY t) AS t2, lead(x) OVER (PARTITION BY k ORDER BY t) AS x2 FROM {{track}} WHERE t % {n} = 0),
rebuilt AS (SELECT s.k, s.t, s.x, f.x AS held, CASE WHEN f.t2 IS NULL THEN f.x ELSE f.x + (f.x2 - f.x) * (s.t - f.t) / (f.t2 - f.t) END AS line FROM {{track}} s JOIN kept f ON s.k = f.k AND f.t = s.t - s.t % {n})
SELECT {n} AS stride, count(*) AS n, count(CASE WHEN t % {n} = 0 THEN 1 END) AS kept, round(max(abs(x - held)), 6) AS hold_err, round(max(abs(x - line)), 6) AS line_err FROM rebuilt"""


def spotlight(coarse: int, fine: int, every: int, length: int) -> str:
    """B2: a fine rate inside recurring windows, a coarse one outside, rebuilt by holding and by lines; ``fine`` divides ``every``.

    The last kept step is reckoned from t, so samples meet it in a join of equal keys.
    """
    inside = f"CASE WHEN t % {every} < {length} THEN t - t % {fine} ELSE t - t % {every} + {(length - 1) // fine * fine} END"
    return f"""WITH kept AS (SELECT k, t, x, lead(t) OVER (PARTITION BY k ORDER BY t) AS t2, lead(x) OVER (PARTITION BY k ORDER BY t) AS x2 FROM {{track}} WHERE t % {coarse} = 0 OR (t % {every} < {length} AND t % {fine} = 0)),
s AS (SELECT k, t, x, greatest(t - t % {coarse}, {inside}) AS f FROM {{track}}),
rebuilt AS (SELECT s.t, s.x, s.f, f.x AS held, CASE WHEN f.t2 IS NULL THEN f.x ELSE f.x + (f.x2 - f.x) * (s.t - f.t) / (f.t2 - f.t) END AS line FROM s JOIN kept f ON s.k = f.k AND f.t = s.f)
SELECT count(*) AS n, count(CASE WHEN t = f THEN 1 END) AS kept, round(max(abs(x - held)), 6) AS hold_err, round(max(abs(x - line)), 6) AS line_err FROM rebuilt"""


def grid_only(o: Options) -> str:
    """Grid values at one width."""
    return f"WITH g AS ({grid(o)}) SELECT count(*) AS n, CAST({bitlen('max(q) - min(q)')} AS BIGINT) AS width, CAST(count(*) * {bitlen('max(q) - min(q)')} AS BIGINT) AS packed_bits FROM g"


def residuals(o: Options, axis: str) -> str:
    """Grid values minus their neighbours': in time, in space (the series before in the same frame), or both."""
    time, space = "q - coalesce(lag(q) OVER (PARTITION BY k ORDER BY t), 0)", "q - coalesce(lag(q) OVER (PARTITION BY t ORDER BY k), 0)"
    if axis == "time":
        return f"SELECT k, t, {time} AS r FROM (SELECT * FROM g)"
    if axis == "space":
        return f"SELECT k, t, {space} AS r FROM (SELECT * FROM g)"
    return f"SELECT k, t, d - coalesce(lag(d) OVER (PARTITION BY t ORDER BY k), 0) AS r FROM (SELECT k, t, {time} AS d FROM g)"


def delta(o: Options, axis: str, code: str = "gamma") -> str:
    """Differences under a whole-number code."""
    return f"WITH g AS ({grid(o)}), d AS ({residuals(o, axis)}), z AS (SELECT {zig('r')} AS u FROM d) SELECT '{axis}' AS axis, count(*) AS n, CAST(sum({code_bits(code, 'u')}) AS BIGINT) AS packed_bits FROM z"


def native_like(o: Options) -> str:
    """Grid, differences in time and space, byte-wise variable length."""
    return delta(o, "both", "varint")


def predictive(o: Options, order: int) -> str:
    """Residuals of order 0 or 1 extrapolation on the grid, at their empirical entropy."""
    r = "q - coalesce(l1, 0)" if order == 0 else "q - CASE WHEN l2 IS NULL THEN coalesce(l1, 0) ELSE 2 * l1 - l2 END"
    return f"""WITH g AS ({grid(o)}), l AS (SELECT q, lag(q) OVER (PARTITION BY k ORDER BY t) AS l1, lag(q, 2) OVER (PARTITION BY k ORDER BY t) AS l2 FROM g),
c AS (SELECT {r} AS r, count(*) AS c FROM l GROUP BY 1), s AS (SELECT sum(c) AS n FROM c)
SELECT {order} AS ord, CAST(max(n) AS BIGINT) AS n, count(*) AS symbols, round(sum(c * -log2(c / CAST(n AS DOUBLE))) / max(n), 6) AS bits_per_value FROM c CROSS JOIN s"""


def predictive_group(o: Options, size: int) -> str:
    """Residuals against the leader of a group of neighbouring series, as a stand-in for structure known beforehand."""
    return f"""WITH g AS ({grid(o)}), d AS (SELECT k, t, q - coalesce(lag(q) OVER (PARTITION BY k ORDER BY t), 0) AS d FROM g),
l AS (SELECT k, d - CASE WHEN k % {size} = 0 THEN 0 ELSE first_value(d) OVER (PARTITION BY t, CAST(floor(k / {size}) AS BIGINT) ORDER BY k) END AS r FROM d),
c AS (SELECT r, count(*) AS c FROM l GROUP BY 1), s AS (SELECT sum(c) AS n FROM c)
SELECT {size} AS grp, CAST(max(n) AS BIGINT) AS n, round(sum(c * -log2(c / CAST(n AS DOUBLE))) / max(n), 6) AS bits_per_value FROM c CROSS JOIN s"""


def legacy_like(o: Options) -> str:
    """Grid, differences in time, series ordered by height in each frame, a static code; the order is paid for."""
    return f"""WITH g AS ({grid(o)}), d AS (SELECT k, t, q - coalesce(lag(q) OVER (PARTITION BY k ORDER BY t), 0) AS d FROM g),
o AS (SELECT t, d - coalesce(lag(d) OVER (PARTITION BY t ORDER BY d, k), 0) AS r, count(*) OVER (PARTITION BY t) AS w FROM d), z AS (SELECT {zig('r')} AS u, w FROM o)
SELECT count(*) AS n, CAST(sum({code_bits('gamma', 'u')}) AS BIGINT) AS value_bits, CAST(sum({bitlen('w - 1')}) AS BIGINT) AS order_bits FROM z"""


def reorder(o: Options, keep_ids: bool) -> str:
    """Series sorted by height in each frame, with or without the bits that give their identity back."""
    ids = f"sum({bitlen('w - 1')})" if keep_ids else "0"
    return f"""WITH g AS ({grid(o)}), o AS (SELECT q - coalesce(lag(q) OVER (PARTITION BY t ORDER BY q, k), 0) AS r, count(*) OVER (PARTITION BY t) AS w FROM g), z AS (SELECT {zig('r')} AS u, w FROM o)
SELECT {str(keep_ids).lower()} AS keep_ids, count(*) AS n, CAST(sum({code_bits('gamma', 'u')}) + {ids} AS BIGINT) AS packed_bits FROM z"""


def int_sizes() -> str:
    """Sizes of whole numbers under each code, and the best Rice parameter."""
    u = "CAST(x AS BIGINT)"
    codes = " UNION ALL ".join(f"SELECT '{c}' AS code, CAST(sum({code_bits(c, 'u')}) AS BIGINT) AS bits FROM v" for c in ("varint", "unary", "gamma", "delta"))
    rice = "SELECT 'rice' AS code, min(bits) AS bits FROM rice"
    shifts = " UNION ALL ".join(f"SELECT {r} AS r, CAST(sum(CAST(floor(u / {1 << r}.0) AS BIGINT) + 1 + {r}) AS BIGINT) AS bits FROM v" for r in range(21))
    return f"""WITH v AS (SELECT {u} AS u FROM {{track}}), rice AS ({shifts})
SELECT code, bits FROM ({codes} UNION ALL SELECT 'fixed' AS code, CAST(count(*) * {bitlen('max(u)')} + 6 AS BIGINT) AS bits FROM v UNION ALL {rice}) a"""


def entropy(o: Options) -> str:
    """Empirical entropy of the pieces' numbers, displacements and durations apart; over ``{track}`` of pieces."""
    return """WITH c AS (SELECT 'dq' AS part, dq AS v, count(*) AS c FROM {track} GROUP BY 2 UNION ALL SELECT 'dt' AS part, CAST(dt AS BIGINT) AS v, count(*) AS c FROM {track} GROUP BY 2),
s AS (SELECT part, sum(c) AS n FROM c GROUP BY 1)
SELECT c.part, CAST(max(n) AS BIGINT) AS n, count(*) AS symbols, round(sum(c * -log2(c / CAST(n AS DOUBLE))) / max(n), 6) AS bits_per_number FROM c JOIN s ON c.part = s.part GROUP BY c.part"""


def regress(width: int) -> str:
    """A least-squares line for each window of fixed length; worst error of all."""
    return f"""WITH w AS (SELECT k, CAST(floor(t / {width}) AS BIGINT) AS w, t, x FROM {{track}}),
f AS (SELECT k, w, count(*) AS n, avg(x) AS mx, avg(t) AS mt, sum(t * x) AS stx, sum(t * t) AS stt FROM w GROUP BY k, w),
c AS (SELECT k, w, mx, mt, CASE WHEN n < 2 THEN 0.0 ELSE (stx - n * mt * mx) / (stt - n * mt * mt) END AS slope FROM f)
SELECT {width} AS width, count(DISTINCT c.k * 1000000 + c.w) AS lines, round(max(abs(x - (mx + slope * (t - mt)))), 4) AS max_err FROM w JOIN c ON w.k = c.k AND w.w = c.w"""
