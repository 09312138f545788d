"""Queries do the whole job on tables that are larger than the given ones."""

import duckdb
from pyspark.sql import functions as F
from test_given_sql import against_sql


def plan_of(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_linear_fill_carries_knots_across_spans(spark, tmp_path):
    """No frame reaches to a series' last row, which is read anew for each row; spans of 4096 steps, with holes and one span missing, pass knots on."""
    from corridor.queries import registry

    ids = [i for i in range(4210) if i % 97 and not 4089 < i < 4101] + list(range(8195, 8300))
    duckdb.sql(f"select unnest({ids})::bigint as vec_id").create("ids")
    duckdb.sql("select vec_id, list_transform(range(64), lambda i: ((vec_id * 7 + i) % 11 - 5)::FLOAT) as embedding from ids").write_parquet(str(tmp_path / "embeddings.parquet"))
    assert "unboundedfollowing" not in plan_of(registry.queries()["op_linear_fill_f2"](spark, str(tmp_path))).lower()
    got, want = against_sql(spark, "op_linear_fill_f2", tmp_path, ["embeddings"])
    assert got == want and len(got) > 64 * 4000


def test_distance_gap_over_tiles(spark, monkeypatch):
    """Tracks that start and end anywhere, in smooth and rough stretches: pairs and difference are those of the joined rows, also where the two differ, and there is no join of pairs."""
    import numpy as np

    from corridor.operators import segquery
    from corridor.operators.segment import expand, segment
    from corridor.options import Options

    rng = np.random.default_rng(3)
    rows = []
    for p in range(23):
        a, z = sorted(rng.choice(90, 2, replace=False).tolist())
        x = rng.normal(size=(2, 90)).cumsum(axis=1) * (0.2 if p % 3 else 6.0)
        rows += [(2 * p * 10**9 + axis, t, float(x[axis, t])) for axis in (0, 1) for t in range(a, z + 1 + (p % 2 and axis)) if t < 90]
    t = spark.createDataFrame(rows, "k long, t long, x double")
    for o in (Options(eps=1.0, block=32), Options(eps=1.0, block=32, connect=False)):
        pieces = segment(t, o).persist()
        frames = expand(pieces, None, o)
        for shown in (frames, frames.withColumn("x", F.col("x") + F.when(F.expr("k = 4000000000 AND t = 40"), 3.0).otherwise(0.0))):
            both = segquery.tile_distances(pieces, 2, o).join(segquery.frame_distances(shown, 2, o), ["a", "b"])
            want = both.agg(F.count("*"), F.round(F.max(F.abs(F.col("sampled") - F.col("frames"))), 5)).first()
            for samples, right in ((1 << 20, 7), (300, 4096)):
                monkeypatch.setattr(segquery, "TILE_SAMPLES", samples)
                monkeypatch.setattr(segquery, "RIGHT", right)
                df = segquery.distance_gap(pieces, shown, 2, o)
                got = df.first()
                assert got["pairs"] == want[0] > 50 and abs(got["difference"] - want[1]) < 2e-5
                assert plan_of(df).count("Join") == 1
        pieces.unpersist()


def test_pairs_of_w10_are_never_rows(spark, sf):
    from corridor.queries import registry

    plan = registry.queries()["w10_distances_f3"](spark, sf)._jdf.queryExecution().optimizedPlan().toString()
    assert "Aggregate [a#" not in plan and "[a#" not in plan


def test_forces_of_near_pairs():
    """Pairs out of reach are left out; the sums are to the bit those over all pairs."""
    import numpy as np

    from corridor.sources import simulate as S

    def dense(x):
        d = x[:, None] - x[None]
        r = np.sqrt((d * d).sum(axis=2))
        f = np.where((r < S.CUTOFF) & (r > 0), -np.sin(2 * r) / np.where(r > 0, r, 1.0), 0.0)
        return (f[..., None] * d).sum(axis=1)

    rng = np.random.default_rng(4)
    for n, scale in ((1, 1.0), (2, 0.1), (64, 1.0), (64, 0.2), (200, 0.5)):
        x = rng.uniform(0, S.BOX, (n, 3)) * scale
        x[n // 2] = x[0]  # two in one place
        assert (S.forces(x) == dense(x)).all()


def test_replicas_run_in_many_tasks(spark, sf):
    from corridor.sources.simulate import vector_wells

    t = vector_wells(spark.read.parquet(f"{sf}/embeddings.parquet"), 8, 0, 2)
    assert t.select(F.spark_partition_id()).distinct().count() > 4


def test_grid_from_days_is_that_of_the_track(spark, sf):
    """Parts give the bits of one track, native bits across edges of small parts included, and no frame is a row."""
    from corridor.queries import workloads as W
    from corridor.queries.methods import opt, track

    o = opt("f5", block=2048)
    df = W.ratio_grid_days(spark, sf, o, (1, 64))
    plan = df._jdf.queryExecution().optimizedPlan().toString()
    assert "Window" not in plan and " x#" not in plan
    t = track(spark, sf, "f5")
    rows = lambda df: sorted(map(tuple, df.collect()))
    want = rows(W.ratio_grid_axes(t, o, (1, 64)))
    assert rows(df) == want and len(want) == 12
    cut = W.ratio_grid_days(spark, sf, o, (1, 64), keys=2)  # edges between five parts; only whole buckets have the other bits
    assert sorted((r.axis, r.eps, r.stride, r.native_bits) for r in cut.collect()) == sorted((r[0], r[1], r[2], r[4]) for r in want)


def test_edges_of_parts():
    """A native code of series cut into parts has the bits of the uncut one, also where a part has no series that long."""
    import numpy as np

    from corridor.queries import workloads as W

    rng = np.random.default_rng(8)
    length = np.array([9, 4, 7, 2, 3, 9, 1, 5])
    y = rng.normal(size=(9, 8)).cumsum(axis=0) * 500
    y[np.arange(9)[:, None] >= length] = 0.0
    bits, first, last = W.native_edges(y, length)
    q = np.floor(y + 0.5).astype(np.int64)
    want = 0
    for t in range(9):
        d = [int(q[t, k] - (q[t - 1, k] if t else 0)) for k in range(8) if length[k] > t]
        want += W.varint_bits(np.diff(np.array(d)))
        assert (first[t], last[t]) == (d[0], d[-1])
    assert bits == want
