"""The scan as a stateful stream operator: samples in, closed pieces out, five numbers of state per series."""

from __future__ import annotations

import math
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle
from pyspark.sql.types import DoubleType, LongType, StructField, StructType

from corridor.operators.segment import SEGMENT
from corridor.options import Options

STATE = StructType([StructField("t0", LongType()), StructField("t", LongType()), StructField("d", LongType()), StructField("late", LongType()), *[StructField(n, DoubleType()) for n in ("p", "lo", "hi", "last")]])
END_OF_SERIES = -1


class Scanner(StatefulProcessor):
    """One series: a sample narrows the cone or closes the piece; a block's last sample closes it too.

    Samples must come in order of t within a series; those at or before the newest one are counted as late and left out.  A row with
    step END_OF_SERIES closes what is open.
    """

    def __init__(self, o: Options) -> None:
        self.o = o

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.state = handle.getValueState("piece", STATE)

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timer) -> Iterator[pd.DataFrame]:  # noqa: N802
        o, g = self.o, self.o.slack
        s = list(self.state.get()) if self.state.exists() else None
        out: list[tuple] = []
        k = key[0]

        def close() -> float:
            t0, _, d, _, p, lo, hi, last = s
            dq = math.floor(min(max(last, d * lo), d * hi) + 0.5)
            out.append(((t0 + d) // o.block if d and (t0 // o.block) == (t0 + d) // o.block else t0 // o.block, k, t0, d, int(p), dq))
            return dq

        samples = pd.concat(list(rows)).sort_values("t")
        for t, x in zip(samples["t"].tolist(), samples["x"].tolist(), strict=True):
            if t == END_OF_SERIES:
                continue
            if s is not None and t <= s[1]:
                s[3] += 1
                continue
            y = x / o.grid
            if s is None or t // o.block != s[1] // o.block:
                if s is not None and s[2] >= 1:
                    close()
                s = [t, t, 0, s[3] if s else 0, math.floor(y + 0.5), -math.inf, math.inf, 0.0]
                continue
            u, d = y - s[4], s[2] + 1
            lo, hi = max(s[5], (u - g) / d), min(s[6], (u + g) / d)
            if lo <= hi:
                s[1], s[2], s[5], s[6], s[7] = t, d, lo, hi, u
                continue
            dq = close()
            p = s[4] + dq
            u = y - p
            s = [s[0] + s[2], t, 1, s[3], p, u - g, u + g, u]
        if (samples["t"] == END_OF_SERIES).any() and s is not None:
            if s[2] >= 1:
                close()
            self.state.clear()
        elif s is not None:
            self.state.update((*map(int, s[:4]), *map(float, s[4:])))
        if out:
            frame = pd.DataFrame(out, columns=["block", "k", "t0", "dt", "p0", "dq"])
            yield frame.astype({"block": "int64", "k": "int64", "t0": "int64", "dt": "int32", "p0": "int64", "dq": "int64"})

    def close(self) -> None:
        pass


def encode_stream(samples: DataFrame, o: Options) -> DataFrame:
    """Pieces of a stream ``(k, t, x)`` of unit steps, mode supports, connected, nearest end; append mode."""
    if (o.mode, o.connect, o.end) != ("supports", True, "nearest"):
        raise ValueError("the stream operator has the default variant only")
    rows = samples.select("k", "t", F.col("x").cast("double").alias("x"))
    return rows.groupBy("k").transformWithStateInPandas(statefulProcessor=Scanner(o), outputStructType=SEGMENT, outputMode="Append", timeMode="None")
