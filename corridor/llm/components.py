"""Connected components of a link table, without bringing links or components to the driver.

Links are first contracted inside each partition by a union-find, which keeps a star for each local group.
What is left goes through alternating star contractions until nothing changes: "large" steps hang a vertex's
larger neighbours on the smallest vertex it sees, "small" steps do the same with its smaller neighbours.
Each is an aggregate and a join on the vertex, so a hub's links are split like any skewed join's.
Only a row count and a checksum reach the driver in each round.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corridor.llm.texthash import tidy
from corridor.runtime import cut


def spanning_stars(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Links (vertex, smallest vertex of its group), one for each vertex that isn't the smallest."""
    ids, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y = at[: len(a)], at[len(a) :]
    root = np.arange(len(ids))
    while len(x):  # ids are sorted, so the smallest index is the smallest vertex
        low, high = np.minimum(x, y), np.maximum(x, y)
        np.minimum.at(root, high, low)
        while True:
            up = root[root]
            if (up == root).all():
                break
            root = up
        x, y = root[x], root[y]
        keep = x != y
        x, y = x[keep], y[keep]
    hung = np.flatnonzero(root != np.arange(len(ids)))
    return ids[hung], ids[root[hung]]


def _contract(batches):
    a, b = [], []
    size = 0

    def stars():
        x, y = spanning_stars(np.concatenate(a), np.concatenate(b))
        return x, y

    for batch in batches:
        a.append(batch.column(0).to_numpy(zero_copy_only=False))
        b.append(batch.column(1).to_numpy(zero_copy_only=False))
        size += len(a[-1])
        if size > 1 << 22:  # keeps the state near the number of vertices seen
            x, y = stars()
            a, b, size = [x], [y], 0
    if a:
        x, y = stars()
        for i in range(0, len(x), 1 << 16):
            yield pa.RecordBatch.from_arrays([pa.array(x[i : i + (1 << 16)], pa.int64()), pa.array(y[i : i + (1 << 16)], pa.int64())], ["u", "v"])


def components(links: DataFrame, rounds: int = 60) -> DataFrame:
    """(vertex, component) of every vertex in ``links(a, b)``; the component is its smallest vertex.

    Loops, null ends and repeated links are ignored; an empty table gives an empty one.
    """
    a, b = links.columns[:2]
    links = links.select(F.col(a).cast("long").alias("u"), F.col(b).cast("long").alias("v")).where("u is not null and v is not null and u <> v")
    edges = cut(links.mapInArrow(tidy(_contract), "u long, v long").distinct())
    seen = None
    for _ in range(rounds):
        both = edges.union(edges.select("v", "u"))
        least = both.groupBy("u").agg(F.least("u", F.min("v")).alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        lower = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(lower, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").union(lower.select("u", F.col("m"))).distinct()
        edges = cut(small)
        now = edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if now == seen:
            break
        seen = now
    else:
        raise RuntimeError("star contraction did not settle")
    return edges.select(F.col("u").alias("vertex"), F.col("v").alias("component")).union(edges.select("v", "v").distinct())
