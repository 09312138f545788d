"""Tracks ``(k, t, x)`` on the given tables, dense in t for each k, and the same in DuckDB's SQL.

Running sums are taken over whole numbers and divided once, so any engine gets the same doubles.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from corridor.runtime import table

CENTS, MICRO = 100, 1_000_000
START_HOUR, HOURS = "2024-01-01", 720
START_DAY = "1995-01-01"


def running_total(df: DataFrame, key: str, order: str, value: str, span: int = 4096) -> DataFrame:
    """``df`` with column ``total``: sums of ``value`` up to each row, in two levels.

    A window runs over a span of the order only; the totals of earlier spans, one row each, are added by a join, so that
    no task holds a whole series.
    """
    cut = df.withColumn("__span", F.floor(F.col(order) / span))
    inner = Window.partitionBy(key, "__span").orderBy(order)
    outer = Window.partitionBy(key).orderBy("__span").rowsBetween(Window.unboundedPreceding, -1)
    before = cut.groupBy(key, "__span").agg(F.sum(value).alias("__sum")).select(key, "__span", F.coalesce(F.sum("__sum").over(outer), F.lit(0)).alias("__before"))
    summed = cut.withColumn("__inner", F.sum(value).over(inner))
    return summed.join(before, [key, "__span"]).withColumn("total", F.col("__inner") + F.col("__before")).drop("__span", "__inner", "__before")


def embed_raw(spark: SparkSession, sf_dir: str, dims: int = 64) -> DataFrame:
    """each embedding element over the vectors; random."""
    e = table(spark, sf_dir, "embeddings").select("vec_id", F.posexplode(F.slice("embedding", 1, dims)).alias("k", "v"))
    return e.select(F.col("k").cast("long").alias("k"), F.col("vec_id").alias("t"), F.col("v").cast("double").alias("x"))


def embed_walk(spark: SparkSession, sf_dir: str, dims: int = 64) -> DataFrame:
    """running sums of F1; smooth."""
    e = embed_raw(spark, sf_dir, dims).withColumn("v", F.floor(F.col("x") * MICRO + 0.5).cast("long"))
    return running_total(e, "k", "t", "v").select("k", "t", (F.col("total") / MICRO).alias("x"))


def event_steps(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = table(spark, sf_dir, "events").select("user_id", "ts", "event_id", F.floor(F.col("value") * CENTS + 0.5).cast("long").alias("v"))
    return e.withColumn("t", (F.row_number().over(Window.partitionBy("user_id").orderBy("ts", "event_id")) - 1).cast("long"))


def event_walk(spark: SparkSession, sf_dir: str) -> DataFrame:
    """per user, a running sum and the values themselves."""
    e = running_total(event_steps(spark, sf_dir), "user_id", "t", "v")
    rows = F.explode(F.array(F.struct((F.col("user_id") * 2).alias("k"), (F.col("total") / CENTS).alias("x")), F.struct((F.col("user_id") * 2 + 1).alias("k"), (F.col("v") / CENTS).alias("x"))))
    return e.select("t", rows.alias("r")).select("r.k", "t", "r.x")


def event_hourly(spark: SparkSession, sf_dir: str) -> DataFrame:
    """per user and hour of a month, the running sum carried forward; mostly still."""
    e = table(spark, sf_dir, "events").select("user_id", F.floor((F.unix_micros(F.col("ts").cast("timestamp")) - F.unix_micros(F.lit(START_HOUR).cast("timestamp"))) / 3_600_000_000).alias("t"), F.floor(F.col("value") * CENTS + 0.5).cast("long").alias("v"))
    e = e.where(F.col("t").between(0, HOURS - 1)).groupBy("user_id", "t").agg(F.sum("v").alias("v"))
    grid = e.select("user_id").distinct().select("user_id", F.explode(F.expr(f"sequence(0L, {HOURS - 1}L)")).alias("t"))
    full = grid.join(e, ["user_id", "t"], "left").withColumn("v", F.coalesce("v", F.lit(0)))
    return running_total(full, "user_id", "t", "v").select(F.col("user_id").alias("k"), "t", (F.col("total") / CENTS).alias("x"))


def _days(df: DataFrame, key: str, day: str, values: list[str]) -> DataFrame:
    """(key, t, last, v0, v1, ..): whole-number sums by key and day that has any, and the table's last day."""
    t = F.datediff(F.col(day).cast("date"), F.lit(START_DAY).cast("date")).cast("long")
    rows = df.select(F.col(key).cast("long").alias("key"), t.alias("t"), *values).where("key IS NOT NULL AND t IS NOT NULL")
    last = rows.agg(F.max("t").alias("last"))
    return rows.groupBy("key", "t").agg(*[F.coalesce(F.sum(v), F.lit(0)).alias(f"v{i}") for i, v in enumerate(values)]).crossJoin(F.broadcast(last))


def fill_days(table: pa.Table, values: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Running totals (k, t, x) on a dense calendar from each key's first day to the last, of sums by day."""
    key, t = np.asarray(table.column("key")), np.asarray(table.column("t"))
    ids, of = np.unique(key, return_inverse=True)
    first = np.full(len(ids), np.iinfo(np.int64).max)
    np.minimum.at(first, of, t)
    length = table.column("last")[0].as_py() + 1 - first
    start = np.cumsum(length) - length
    step = np.arange(int(length.sum())) - np.repeat(start, length)
    out = []
    for i in range(values):
        v = np.zeros(len(step), np.int64)
        v[start[of] + t - first[of]] = np.asarray(table.column(f"v{i}"))
        total = np.cumsum(v)
        before = (total - v)[start]
        out.append((np.repeat(ids * values + i, length), step, (total - np.repeat(before, length)) / CENTS))
    return tuple(np.concatenate(c) for c in zip(*out, strict=True))


def fill_frames(table: pa.Table, values: int, n: int = 1) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(series, length, steps x series matrix) of every n-th frame of the track that ``fill_days`` gives; only those frames are made."""
    key, t = np.asarray(table.column("key")), np.asarray(table.column("t"))
    ids, of = np.unique(key, return_inverse=True)
    first = np.full(len(ids), np.iinfo(np.int64).max)
    np.minimum.at(first, of, t)
    length = (table.column("last")[0].as_py() - first) // n + 1
    frame = -((first[of] - t) // n)  # the first frame that counts the day
    seen = np.flatnonzero(frame < length[of])
    out = np.zeros((int(length.max()), len(ids), values), np.int64)
    for i in range(values):
        np.add.at(out.reshape(-1), (frame[seen] * len(ids) + of[seen]) * values + i, np.asarray(table.column(f"v{i}"))[seen])
    for before, now in zip(out, out[1:], strict=False):
        now += before
    x = out / CENTS
    shortest = int(length.min())
    x[shortest:][np.arange(shortest, len(x))[:, None] >= length] = 0.0
    return (ids[:, None] * values + np.arange(values)).ravel(), length.repeat(values), x.reshape(len(x), -1)


def _daily(days: DataFrame, values: int, keys: int = 64) -> DataFrame:
    """The dense track of days, some keys to a group; only days that have a sum are shuffled."""

    def run(table: pa.Table) -> pa.Table:
        return pa.table(dict(zip("ktx", map(pa.array, fill_days(table, values)), strict=True)))

    return days.groupBy(F.floor(F.col("key") / keys).alias("group")).applyInArrow(run, "k long, t long, x double")


def supplier_days(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What F5 is made of: quantity and revenue by supplier and day."""
    li = table(spark, sf_dir, "lineitem").select("l_suppkey", "l_shipdate", F.floor(F.col("l_quantity") * CENTS + 0.5).cast("long").alias("q"), F.floor(F.col("l_extendedprice") * CENTS + 0.5).cast("long").alias("r"))
    return _days(li, "l_suppkey", "l_shipdate", ["q", "r"])


def supplier_daily(spark: SparkSession, sf_dir: str) -> DataFrame:
    """per supplier and day, running quantity and revenue."""
    return _daily(supplier_days(spark, sf_dir), 2)


def nation_daily(spark: SparkSession, sf_dir: str) -> DataFrame:
    """per nation and day, running order value; few and busy."""
    o = table(spark, sf_dir, "orders").select("o_custkey", "o_orderdate", F.floor(F.col("o_totalprice") * CENTS + 0.5).cast("long").alias("v"))
    c = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey")
    return _daily(_days(o.join(c, o.o_custkey == c.c_custkey), "c_nationkey", "o_orderdate", ["v"]), 1, keys=1)


def part_price(spark: SparkSession, sf_dir: str) -> DataFrame:
    """unit prices of each part's deliveries; short and volatile."""
    li = table(spark, sf_dir, "lineitem").select("l_partkey", "l_shipdate", "l_orderkey", "l_linenumber", "l_extendedprice", "l_quantity")
    t = F.row_number().over(Window.partitionBy("l_partkey").orderBy("l_shipdate", "l_orderkey", "l_linenumber")) - 1
    return li.select(F.col("l_partkey").alias("k"), t.cast("long").alias("t"), (F.col("l_extendedprice") / F.col("l_quantity")).alias("x"))


def doc_lengths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """F8: text lengths by language; heavy-tailed whole numbers."""
    d = table(spark, sf_dir, "documents").where("lang is not null").select("doc_id", "lang", "n_chars")
    k = F.when(F.col("lang") == "de", 0).when(F.col("lang") == "en", 1).when(F.col("lang") == "es", 2).otherwise(3)
    return d.select(k.cast("long").alias("k"), (F.row_number().over(Window.partitionBy(k).orderBy("doc_id")) - 1).cast("long").alias("t"), F.col("n_chars").cast("double").alias("x"))


def hand(spark: SparkSession) -> DataFrame:
    """one short series with a ramp, a plateau, a spike and a zero crossing."""
    x = [0, 1, 2.25, 3, 3.25, 3, 3, -1, -1.5, -2.25, 0.25, 0]
    return spark.createDataFrame([(0, t, float(v)) for t, v in enumerate(x)], "k long, t long, x double")


def dirty(spark: SparkSession) -> DataFrame:
    """gaps, nulls, values that aren't numbers, and a repeated sample."""
    nan, inf = float("nan"), float("inf")
    rows = [(0, 0, 1.0), (0, 1, None), (0, 2, 3.0), (0, 3, nan), (0, 4, 5.0), (1, 0, 1.0), (1, 1, inf), (1, 2, 2.0), (1, 2, 2.0), (2, 0, 0.0), (2, 1, 1.0), (2, 5, 5.0), (2, 6, 6.0)]
    return spark.createDataFrame(rows, "k long, t long, x double")


def dirty_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """F12 on events: values by user and hour as they come, with missing and repeated hours; errors are null, some ids NaN or infinite."""
    x = F.when(F.col("event_type") == "error", None)
    for n, v in ((11, "NaN"), (13, "Infinity"), (17, "-Infinity")):
        x = x.when(F.col("event_id") % n == 0, F.lit(float(v)))
    hour = F.floor((F.unix_micros(F.col("ts").cast("timestamp")) - F.unix_micros(F.lit(START_HOUR).cast("timestamp"))) / 3_600_000_000)
    return table(spark, sf_dir, "events").select(F.col("user_id").alias("k"), hour.alias("t"), x.otherwise(F.col("value")).alias("x"))


def clean(track: DataFrame, policy: str = "split") -> DataFrame:
    """A track fit for compression.

    Repeated (k, t): the smallest value stays.  A null, NaN or infinite value: ``fail`` raises when read, ``drop`` leaves it out and closes
    the gap, ``split`` leaves it out and starts a new series after it and after any missing step; part n of series k
    becomes series k * 2**20 + n.
    """
    bad = F.col("x").isNull() | F.isnan("x") | (F.abs("x") == float("inf"))
    if policy == "fail":
        return track.withColumn("x", F.when(bad, F.raise_error(F.lit("a sample is null or not finite"))).otherwise(F.col("x")))
    good = track.where(~bad).groupBy("k", "t").agg(F.min("x").alias("x"))
    by = Window.partitionBy("k").orderBy("t")
    if policy == "drop":
        return good.select("k", (F.row_number().over(by) - 1).cast("long").alias("t"), "x")
    if policy != "split":
        raise ValueError(f"unknown policy {policy}")
    part = F.sum(F.when(F.col("t") - F.lag("t").over(by) > 1, 1).otherwise(0)).over(by)
    cut = good.withColumn("part", part)
    return cut.select((F.col("k") * (1 << 20) + F.col("part")).alias("k"), F.col("t"), "x")


def strided(track: DataFrame, n: int) -> DataFrame:
    """Every n-th frame, numbered anew."""
    return track.where(F.col("t") % n == 0).select("k", F.floor(F.col("t") / n).alias("t"), "x")


def frames(track: DataFrame) -> DataFrame:
    """Row per frame with the positions of all series in order."""
    return track.groupBy("t").agg(F.array_sort(F.collect_list(F.struct("k", "x"))).alias("pos")).select("t", F.transform("pos", lambda p: p["x"]).alias("pos"))


# --- the same tracks as DuckDB common table expressions named ``track`` ---
def _daily_sql(src: str, values: int) -> str:
    unions = " UNION ALL ".join(
        f"SELECT g.key * {values} + {i} AS k, g.t - g.a AS t, CAST(sum(coalesce(d.v{i}, 0)) OVER (PARTITION BY g.key ORDER BY g.t) AS BIGINT) / {CENTS}.0 AS x FROM grid g LEFT JOIN days d USING (key, t)" for i in range(values)
    )
    return f"""src AS ({src}), days AS (SELECT key, date_diff('day', DATE '{START_DAY}', CAST(day AS DATE)) AS t, {", ".join(f"sum(v{i}) AS v{i}" for i in range(values))} FROM src GROUP BY 1, 2),
grid AS (SELECT key, a, unnest(range(a, (SELECT max(t) FROM days) + 1)) AS t FROM (SELECT key, min(t) AS a FROM days GROUP BY 1)),
track AS ({unions})"""


DIRTY_SQL = f"""track AS (SELECT user_id AS k, date_diff('hour', TIMESTAMP '{START_HOUR}', date_trunc('hour', ts)) AS t,
CASE WHEN event_type = 'error' THEN NULL WHEN event_id % 11 = 0 THEN 'NaN'::DOUBLE WHEN event_id % 13 = 0 THEN 'Infinity'::DOUBLE WHEN event_id % 17 = 0 THEN '-Infinity'::DOUBLE ELSE value END AS x FROM events)"""


def _cents(c: str) -> str:
    return f"CAST(floor({c} * {CENTS} + 0.5) AS BIGINT)"


def track_sql(name: str, dims: int = 64) -> str:
    raw = f"SELECT CAST(i - 1 AS BIGINT) AS k, vec_id AS t, CAST(embedding[i] AS DOUBLE) AS x FROM embeddings, (SELECT unnest(range(1, {dims} + 1)) AS i)"
    steps = f"SELECT user_id, ts, event_id, {_cents('value')} AS v, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) - 1 AS t FROM events"
    return {
        "embed_raw": f"track AS ({raw})",
        "embed_walk": f"track AS (SELECT k, t, CAST(sum(CAST(floor(x * {MICRO} + 0.5) AS BIGINT)) OVER (PARTITION BY k ORDER BY t) AS BIGINT) / {MICRO}.0 AS x FROM ({raw}))",
        "event_walk": f"steps AS ({steps}), summed AS (SELECT *, CAST(sum(v) OVER (PARTITION BY user_id ORDER BY t) AS BIGINT) AS total FROM steps), track AS (SELECT user_id * 2 AS k, t, total / {CENTS}.0 AS x FROM summed UNION ALL SELECT user_id * 2 + 1, t, v / {CENTS}.0 FROM summed)",
        "event_hourly": f"""hours AS (SELECT user_id, date_diff('hour', TIMESTAMP '{START_HOUR}', date_trunc('hour', ts)) AS t, sum({_cents("value")}) AS v FROM events GROUP BY 1, 2),
track AS (SELECT g.user_id AS k, g.t, CAST(sum(coalesce(h.v, 0)) OVER (PARTITION BY g.user_id ORDER BY g.t) AS BIGINT) / {CENTS}.0 AS x FROM (SELECT DISTINCT user_id, unnest(range(0, {HOURS})) AS t FROM hours WHERE t BETWEEN 0 AND {HOURS - 1}) g LEFT JOIN hours h USING (user_id, t))""",
        "supplier_daily": _daily_sql(f"SELECT l_suppkey AS key, l_shipdate AS day, {_cents('l_quantity')} AS v0, {_cents('l_extendedprice')} AS v1 FROM lineitem", 2),
        "nation_daily": _daily_sql(f"SELECT CAST(c_nationkey AS BIGINT) AS key, o_orderdate AS day, {_cents('o_totalprice')} AS v0 FROM orders JOIN customer ON o_custkey = c_custkey", 1),
        "part_price": "track AS (SELECT l_partkey AS k, row_number() OVER (PARTITION BY l_partkey ORDER BY l_shipdate, l_orderkey, l_linenumber) - 1 AS t, l_extendedprice / l_quantity AS x FROM lineitem)",
        "doc_lengths": "docs AS (SELECT CAST(CASE lang WHEN 'de' THEN 0 WHEN 'en' THEN 1 WHEN 'es' THEN 2 ELSE 3 END AS BIGINT) AS k, doc_id, n_chars FROM documents WHERE lang IS NOT NULL), track AS (SELECT k, row_number() OVER (PARTITION BY k ORDER BY doc_id) - 1 AS t, CAST(n_chars AS DOUBLE) AS x FROM docs)",
    }[name]
