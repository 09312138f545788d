"""Links of embeddings at high cosine, by int8 tile products with error bounds.

A unit vector x is stored as scale * q with q of small integers, and the length of what that leaves out, e = |x - scale * q|.
For two vectors the dot product of the stored forms differs from the true cosine by at most e_x + e_y + 3 e_x e_y
(e <= 1), so a pair whose stored product stays further than that below the threshold can't be a link.  Products
of a tile are one matrix product of integers below 2**24, exact in single precision; only pairs that
the bound leaves open are computed again, in double precision.

Equal vectors are one class with a count, so a large group of copies costs one row.  Classes are dealt to blocks by hash; a
task has two blocks.  It returns link counts per vector and a spanning forest of its links, never the pairs.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corridor.llm.components import components, spanning_stars
from corridor.llm.texthash import tidy
from corridor.runtime import cut

BLOCK, TILE, EXACT_DIMS = 4096, 1024, 1024


def unit(x: np.ndarray) -> np.ndarray:
    """Rows at length 1, in double precision."""
    x = x.astype(np.float64)
    x = x / np.abs(x).max(axis=1, keepdims=True)
    return x / np.sqrt(np.einsum("ij,ij->i", x, x))[:, None]


def quantise(x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Integers of at most 127, scale and left-out length of each unit vector; the length is rounded up."""
    scale = np.abs(x).max(axis=1) / 127
    q = np.rint(x / scale[:, None])
    left = x - q * scale[:, None]
    return q.astype(np.float32), scale, np.sqrt(np.einsum("ij,ij->i", left, left)) * (1 + 1e-9) + 1e-12


def tile_links(x, qx, sx, ex, y, qy, sy, ey, threshold: float) -> tuple[np.ndarray, np.ndarray]:
    """Index pairs (i, j) with cosine of x[i] and y[j] at or above the threshold."""
    product = np.zeros((len(qx), len(qy)), np.float32)
    if qx.shape[1] <= EXACT_DIMS:
        np.matmul(qx, qy.T, out=product)
    else:
        total = np.zeros(product.shape)
        for a in range(0, qx.shape[1], EXACT_DIMS):
            total += qx[:, a : a + EXACT_DIMS] @ qy[:, a : a + EXACT_DIMS].T
        product = total
    most = ey.max()
    need = (threshold - ex - most - 3 * ex * most - 1e-9) / sx
    product *= (sy * (1 + 1e-6)).astype(product.dtype)[None, :]
    i, j = np.nonzero(product >= (need - np.abs(need) * 1e-6).astype(product.dtype)[:, None])
    if not len(i):
        return i, j
    near = product[i, j] * sx[i] >= threshold - ex[i] - ey[j] - 3 * ex[i] * ey[j] - 1e-5
    i, j = i[near], j[near]
    keep = np.zeros(len(i), bool)
    for a in range(0, len(i), 1 << 14):
        s = slice(a, a + (1 << 14))
        keep[s] = np.einsum("ij,ij->i", x[i[s]], y[j[s]]) >= threshold
    return i[keep], j[keep]


def block_links(left, right, threshold: float):
    """Link counts and spanning links of two blocks (ids, counts, vectors), or within one if right is None."""
    same = right is None
    ids, weight, x = left
    ids2, weight2, y = left if same else right
    a, b = (x, *quantise(x)), (y, *quantise(y))
    n, n2 = np.zeros(len(ids), np.int64), np.zeros(len(ids2), np.int64)
    us, vs = [], []
    for i0 in range(0, len(ids), TILE):
        for j0 in range(i0 if same else 0, len(ids2), TILE):
            i, j = tile_links(*(p[i0 : i0 + TILE] for p in a), *(p[j0 : j0 + TILE] for p in b), threshold)
            i, j = i + i0, j + j0
            if same:
                up = j > i
                i, j = i[up], j[up]
            np.add.at(n, i, weight2[j])
            np.add.at(n2, j, weight[i])
            u, v = spanning_stars(ids[i], ids2[j])
            us.append(u)
            vs.append(v)
    return n + n2 if same else n, n2, np.concatenate(us), np.concatenate(vs)


def near_duplicates(vectors: DataFrame, threshold: float = 0.95, block: int = BLOCK) -> DataFrame:
    """(vec_id, n_links, component_id, kept) of every row of ``vectors(vec_id, embedding)``.

    Two vectors link when their cosine in double precision is at or above the threshold.  Vectors that are null, empty or zero, or that
    hold null or non-finite components, link with nothing, and so do vectors of different lengths.  Equal vectors
    are always linked.  Rows that repeat a vec_id count as vectors of their own.  component_id is the smallest vec_id reachable;
    kept says whether it is the row's own.  A row without vec_id gets no component and is kept.
    """
    spread = int(vectors.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    e = F.col("embedding")
    good = e.isNotNull() & (F.size(e) > 0) & F.forall(e, lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < float("inf"))) & F.exists(e, lambda v: v != 0)
    double = F.transform(e, lambda v: v.cast("double"))
    own = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.when(good & F.col("vec_id").isNotNull(), double).alias("v"))
    classes = cut(own.where("v is not null").groupBy("v").agg(F.min("vec_id").alias("rep"), F.count("*").alias("copies")))
    blocks = classes.groupBy(F.size("v").alias("dims")).agg(F.ceil(F.count("*") / block).cast("int").alias("blocks"))
    dealt = classes.join(blocks, F.size("v") == F.col("dims")).withColumn("own", F.pmod(F.xxhash64("rep"), F.col("blocks")).cast("int"))
    pairs = F.expr("transform(sequence(0, blocks - 1), j -> struct(dims, least(own, j) as i, greatest(own, j) as j))")
    dealt = dealt.withColumn("pair", F.explode(pairs)).select("pair.*", "own", "rep", "copies", "v")

    def judge(t: pa.Table) -> pa.Table:
        dims, i, j = (t.column(c)[0].as_py() for c in ("dims", "i", "j"))
        v = t.column("v").combine_chunks()
        x = np.asarray(v.flatten()).reshape(-1, dims)
        side, ids, copies = (np.asarray(t.column(c)) for c in ("own", "rep", "copies"))
        x = unit(x)
        parts = [(ids[m], copies[m], x[m]) for m in ((side == i), (side == j))]
        n, n2, u, w = block_links(parts[0], parts[1] if i != j else None, threshold) if len(parts[0][0]) and len(parts[1][0]) else (np.zeros(0, np.int64),) * 4
        found = [(parts[0][0], n)] + ([(parts[1][0], n2)] if i != j else [])
        seen = [(a[m > 0], m[m > 0]) for a, m in found if len(m)]
        a = np.concatenate([u, *(s[0] for s in seen)]).astype(np.int64)
        b = pa.array(np.concatenate([w, *(np.zeros(len(s[0]), np.int64) for s in seen)]).astype(np.int64), mask=np.arange(len(a)) >= len(u))
        m = pa.array(np.concatenate([np.zeros(len(u), np.int64), *(s[1] for s in seen)]).astype(np.int64))
        return pa.table({"a": pa.array(a), "b": b, "n": m})

    found = cut(dealt.repartition(max(spread, 64), "dims", "i", "j").groupBy("dims", "i", "j").applyInArrow(tidy(judge), "a long, b long, n long"))
    counts = found.where("b is null").groupBy(F.col("a").alias("rep")).agg(F.sum("n").alias("found"))
    groups = components(found.where("b is not null").select("a", "b"))
    told = classes.join(counts, "rep", "left").join(groups, F.col("rep") == F.col("vertex"), "left")
    told = told.select(F.col("v"), (F.coalesce("found", F.lit(0)) + F.col("copies") - 1).alias("n_links"), F.coalesce("component", "rep").alias("component_id"))
    out = own.join(told, "v", "left").select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("component_id", "vec_id").alias("component_id"))
    return out.withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True)))
