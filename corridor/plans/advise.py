"""Choosing the split of the tolerance and the block length on a sample of blocks."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corridor.functions.quant import gamma_bits, zigzag
from corridor.operators.segment import segment
from corridor.options import Options


def advise(track: DataFrame, o: Options, lams: tuple[float, ...] = (0.1, 0.3, 0.5, 0.7, 1.0), share: float = 0.1) -> DataFrame:
    """(lambda, pieces, bits): estimated size on a share of the blocks, picked by hash, for each split; the best is the least."""
    from dataclasses import replace

    block = F.floor(F.col("t") / o.block)
    sample = track.where(F.pmod(F.xxhash64(block), F.lit(1000)) < int(share * 1000)) if share < 1 else track
    out = None
    for lam in lams:
        p = segment(sample, replace(o, lam=lam))
        row = p.agg(F.lit(lam).alias("lambda"), F.count("*").alias("pieces"), F.coalesce(F.sum(gamma_bits(zigzag(F.col("dq"))) + gamma_bits((F.col("dt") - 1).cast("long"))), F.lit(0)).alias("bits"))
        out = row if out is None else out.union(row)
    return out
