"""Names for SQL users: scalar expressions, a table function that expands a piece, an aggregate for a chunk's size."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import LongType

from corridor.functions import vwidth


def register(spark: SparkSession) -> None:
    """Temporary functions corridor_quantize, corridor_zigzag, corridor_value, corridor_expand and corridor_vwidth_bits."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION corridor_quantize(x DOUBLE, step DOUBLE) RETURNS BIGINT RETURN cast(floor(x / step + 0.5) AS BIGINT)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION corridor_zigzag(i BIGINT) RETURNS BIGINT RETURN CASE WHEN i >= 0 THEN 2 * i ELSE -2 * i - 1 END")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION corridor_value(t0 BIGINT, dt INT, p0 BIGINT, dq BIGINT, step DOUBLE, t BIGINT) RETURNS DOUBLE RETURN step * (p0 + dq * (t - t0) / dt)")
    spark.udtf.register("corridor_expand", Expand)
    spark.udf.register("corridor_vwidth_bits", vwidth_bits)


@udtf(returnType="t: bigint, q: double")
class Expand:
    """The samples after a piece's start."""

    def eval(self, t0: int, dt: int, p0: int, dq: int):
        for s in range(1, dt + 1):
            yield t0 + s, p0 + dq * s / dt


@pandas_udf(LongType())  # a type, not its name: parsing a name asks for a session
def vwidth_bits(u: pd.Series) -> int:
    """Bits of a group's numbers under the shared-width code, in the order they come."""
    return vwidth.size(u.to_numpy())
