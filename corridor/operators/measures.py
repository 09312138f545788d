"""What storing costs and loses: sizes, ratios, errors, pieces, memory, operations."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.functions import arrow_udf

from corridor.functions import vwidth
from corridor.functions.quant import bit_length, gamma_bits, zigzag
from corridor.operators.segment import expand, key_frames, segment
from corridor.options import Options
from corridor.plans.codec import compress, packed_bits

OPERATIONS = {"divide": (4, 2, 0, 3, 3), "cross": (13, 0, 6, 0, 1)}  # additions, divisions, multiplications, comparisons, branches


def metric(track: DataFrame, o: Options, stride: int = 1, dims: int = 1) -> DataFrame:
    """One row: raw and packed size, ratio with and without the stride, bits per particle sample, of the stored bytes."""
    n = track.agg(F.count("*").alias("n"))
    rows = packed_bits(compress(track, o)).crossJoin(n)
    raw = F.col("n") * o.value_bytes
    return rows.select(
        F.lit("corridor").alias("method"), F.lit(o.eps).alias("eps"), F.lit(o.lam).alias("lambda"), F.lit(stride).alias("stride"), raw.cast("long").alias("raw_bytes"), "packed_bits",
        F.round(raw * 8 * stride / F.col("packed_bits"), 4).alias("ratio"), F.round(raw * 8 / F.col("packed_bits"), 4).alias("net_ratio"),
        F.round(F.col("packed_bits") * dims / F.col("n"), 4).alias("bits_per_sample"), F.round(F.col("packed_bits") / (raw * 8), 6).alias("relative"),
        "frame_bits", "header_bits", "chunk_bits",
    )


def gamma_metric(pieces: DataFrame, frames: DataFrame, n: DataFrame, o: Options) -> DataFrame:
    """Sizes with Elias gamma in place of the shared-width code: a closed form that any engine can check.

    Key frames cost the width of their values' span in each block.
    """
    numbers = pieces.agg(F.count("*").alias("pieces"), F.sum(gamma_bits(zigzag(F.col("dq")))).alias("dq_bits"), F.sum(gamma_bits((F.col("dt") - 1).cast("long"))).alias("dt_bits"))
    kf = frames.groupBy("block").agg(F.count("*").alias("c"), bit_length(F.max("q") - F.min("q")).alias("w")).agg(F.sum(F.col("c") * F.col("w")).alias("frame_bits"))
    rows = numbers.crossJoin(kf).crossJoin(n)
    packed = F.col("dq_bits") + F.col("dt_bits") + F.col("frame_bits")
    return rows.select("pieces", "dq_bits", "dt_bits", "frame_bits", packed.cast("long").alias("packed_bits"), F.round(F.col("n") * 8 * o.value_bytes / packed, 4).alias("ratio"), F.round(packed / F.col("n"), 4).alias("bits_per_value"))


def errors(track: DataFrame, o: Options, how: str = "vector") -> DataFrame:
    """One row: samples, worst, mean and root-mean-square error, and how many lie beyond the bound."""
    back = expand(segment(track, o, how), key_frames(track, o), o).withColumnRenamed("x", "z")
    e = F.abs(F.col("x") - F.col("z"))
    beyond = e > o.bound * (1 + 1e-9) + F.abs("x") * 2.3e-16
    return track.join(back, ["k", "t"], "left").agg(F.count("*").alias("n"), F.count("z").alias("rebuilt"), F.round(F.max(e), 6).alias("max_err"), F.round(F.avg(e), 6).alias("mean_err"), F.round(F.sqrt(F.avg(e * e)), 6).alias("rms_err"), F.coalesce(F.sum(beyond.cast("long")), F.lit(0)).alias("beyond"))


def piece_stats(pieces: DataFrame) -> DataFrame:
    return pieces.agg(F.count("*").alias("pieces"), F.round(F.avg("dt"), 6).alias("mean_dt"), F.max("dt").alias("max_dt"), F.round(F.avg((F.col("dt") == 1).cast("double")), 6).alias("share_one"))


def peak_pending(pieces: DataFrame, o: Options) -> DataFrame:
    """(block, peak): most pieces that a writer holds at once, found but with an earlier one of another series still open.

    A piece is found at t0 + dt and can be written once every piece before it in wire order has been found.
    """
    wire = Window.partitionBy("block").orderBy("t0", "k")
    rows = pieces.withColumn("found", F.col("t0") + F.col("dt")).withColumn("out", F.max("found").over(wire.rowsBetween(Window.unboundedPreceding, 0)))
    events = rows.select("block", F.explode(F.array(F.struct(F.col("found").alias("t"), F.lit(1).alias("d")), F.struct(F.col("out").alias("t"), F.lit(-1).alias("d")))).alias("e")).select("block", "e.t", "e.d")
    net = events.groupBy("block", "t").agg(F.sum("d").alias("d"))
    level = net.withColumn("level", F.sum("d").over(Window.partitionBy("block").orderBy("t")))
    return level.groupBy("block").agg(F.max("level").alias("peak"))


def vwidth_bits(numbers: DataFrame) -> DataFrame:
    """``numbers(.., numbers array)`` with the size of the shared-width code, by an Arrow UDF."""
    @arrow_udf("long")
    def bits(column: pa.Array) -> pa.Array:
        return pa.array([vwidth.size(row.values.to_numpy(zero_copy_only=False)) for row in column], pa.int64())

    return numbers.withColumn("bits", bits("numbers"))


def position_bits(track: DataFrame, o: Options) -> DataFrame:
    """Bits of a position at this grid: those of the number of grid steps in the box."""
    span = track.agg((F.max("x") - F.min("x")).alias("edge"))
    return span.select(F.round("edge", 6).alias("edge"), F.ceil(F.log2(F.col("edge") / F.lit(o.grid))).cast("long").alias("bits"))
