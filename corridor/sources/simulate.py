"""A small particle simulation as a source of tracks: pair wells, velocity Verlet, open box, seeded."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

BOX = (15.0, 16.0, 17.0)
MASS, DT = 2.0, 2e-4
CUTOFF = np.pi / 2


def forces(x: np.ndarray) -> np.ndarray:
    """Pair energy sin^2(min(r, pi/2)): pulls of sin(2 r) towards each other, none beyond the cutoff."""
    n, axes = len(x), np.ascontiguousarray(x.T)
    d = [c[:, None] - c[None] for c in axes]
    i, j = np.nonzero(sum(c * c for c in d) < 1.001 * CUTOFF**2)  # few pairs are near; the others pull by nothing
    d = [c[i, j] for c in d]
    r = np.sqrt(sum(c * c for c in d))
    f = np.where((r < CUTOFF) & (r > 0), -np.sin(2 * r) / np.where(r > 0, r, 1.0), 0.0)
    return np.stack([np.bincount(i, f * c, n) for c in d], axis=1)


def frames(n: int, warm: int, steps: int, seed: int, dt: float = DT):
    """Positions of n particles for each recorded step, from rest at drawn places."""
    return run_from(np.random.default_rng(seed).uniform(0, BOX, (n, 3)), warm, steps, dt)


def run_from(x: np.ndarray, warm: int, steps: int, dt: float = DT):
    """Positions for each recorded step, from rest at given places."""
    v, f = np.zeros(x.shape), forces(x)
    for i in range(warm + steps):
        v += f * (dt / 2 / MASS)
        x = x + v * dt
        f = forces(x)
        v += f * (dt / 2 / MASS)
        if i >= warm:
            yield x


def sim_wells(spark: SparkSession, n: int = 16, warm: int = 500, steps: int = 1000, seeds: tuple[int, ...] = (1,), dt: float = DT) -> DataFrame:
    """tracks of all coordinates; each seed is a replica in a task of its own, with its own series."""

    def run(batches):
        for b in batches:
            for s in b.column("seed").to_pylist():
                part, at = [], 0
                for x in frames(n, warm, steps, s, dt):
                    part.append(x.ravel())
                    if len(part) == 256 or at + len(part) == steps:
                        y = np.array(part)
                        k = np.tile(np.arange(3 * n) + list(seeds).index(s) * 3 * n, len(y))
                        yield pa.RecordBatch.from_arrays([pa.array(k, pa.int64()), pa.array(np.repeat(np.arange(at, at + len(y)), 3 * n), pa.int64()), pa.array(y.ravel())], ["k", "t", "x"])
                        at, part = at + len(y), []

    rows = spark.createDataFrame([(s,) for s in seeds], "seed long").repartition(len(seeds), "seed")
    return rows.mapInArrow(run, "k long, t long, x double")


def vector_wells(vectors: DataFrame, n: int, warm: int, steps: int, dt: float = DT) -> DataFrame:
    """F9 from given places: n vectors in order of ``vec_id`` are a replica, their first three elements, times 32 and folded
    into the box, the places; every vector is a particle.  A replica is a task's group; vector i's series are 3 i to 3 i + 2.
    """

    def run(rows: pa.Table) -> pa.Table:
        rows = rows.sort_by("vec_id")
        ids = np.asarray(rows.column("vec_id"))
        x = np.stack([np.asarray(rows.column(c)) for c in ("a", "b", "c")], axis=1) * 32 % 1 * BOX
        y = np.array([p.ravel() for p in run_from(x, warm, steps, dt)])
        k = (3 * ids[:, None] + np.arange(3)).ravel()
        return pa.table({"k": pa.array(np.tile(k, steps)), "t": pa.array(np.repeat(np.arange(steps), len(k))), "x": pa.array(y.ravel())})

    at = [F.col("embedding")[i].cast("double").alias(c) for i, c in enumerate("abc")]
    tasks = 4 * vectors.sparkSession.sparkContext.defaultParallelism  # few bytes, much work: never merged into one task
    rows = vectors.select("vec_id", *at).withColumn("replica", F.floor(F.col("vec_id") / n)).repartition(tasks, "replica")
    return rows.groupBy("replica").applyInArrow(run, "k long, t long, x double")


def sim_still(spark: SparkSession, k: int = 64, steps: int = 4096) -> DataFrame:
    """constant positions."""
    return spark.range(k * steps).selectExpr(f"id % {k} AS k", f"id div {k} AS t", f"cast(id % {k} as double) AS x")


def sim_noise(spark: SparkSession, k: int = 64, steps: int = 4096) -> DataFrame:
    """positions drawn anew at every step, by a hash."""
    return spark.range(k * steps).selectExpr(f"id % {k} AS k", f"id div {k} AS t", "pmod(xxhash64(id), 1000000) / 1000.0 AS x").selectExpr("k", "t", "cast(x as double) AS x")
