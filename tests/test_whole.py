"""Registered queries cover their whole track or table."""

from pyspark.sql import functions as F


def run(spark, sf, name):
    from corridor.queries import registry

    return registry.queries()[name](spark, sf)


def test_embedding_tracks_have_every_element(spark, sf):
    from corridor.queries.methods import track

    for name in ("f1", "f2"):
        assert track(spark, sf, name).agg(F.countDistinct("k")).first()[0] == 64
    assert run(spark, sf, "m15_at_f2").count() == 64
    assert run(spark, sf, "b1_raw_f2").first()["n"] == 64 * 500
    assert sorted(r.buckets for r in run(spark, sf, "m19_buckets_f2").collect()) == [1, 2, 4, 8, 16, 32, 64]


def test_queries_take_every_particle_series_and_event(spark, sf):
    for name in ("m17_min_distance_f2", "m17_min_distance_bounds_f2"):
        assert run(spark, sf, name).count() == 32 * 31 // 2
    assert run(spark, sf, "m17_encounters_f2").where("b = 31").count() > 0
    assert run(spark, sf, "w10_distances_f2").first().asDict() == {"pairs": 32 * 31 // 2, "difference": 0.0}
    for name in ("b14_optimal_pieces_free_line_f2", "b14_optimal_pieces_constant_f2", "b14_optimal_cover_f2", "op_table_function_f2"):
        assert run(spark, sf, name).agg(F.countDistinct("k")).first()[0] == 64
    more = sf.replace("sf0.001", "sf0.01")
    events = spark.read.parquet(f"{more}/events.parquet").count()
    assert run(spark, more, "op_aggregate_list").agg(F.sum(F.size(F.split("ids", ",")))).first()[0] == events
    assert {r.n for r in run(spark, more, "op_formats").collect()} == {events}
    stream = run(spark, more, "stream_encoder_f3").first()
    assert stream["different"] == 0 and stream["pieces"] == run(spark, more, "m4_segment_f3").count()


def test_optimal_pieces_against_strips(spark):
    """The slope test allows the same pieces as the least strip around the samples."""
    import numpy as np

    from corridor.baselines.codecs import optimal_pieces, strip
    from corridor.options import Options

    rng = np.random.default_rng(5)
    x = rng.normal(size=(6, 40)).cumsum(axis=1)
    o = Options(eps=2.0, block=64)
    got = optimal_pieces(spark.createDataFrame([(k, t, float(x[k, t])) for k in range(6) for t in range(40)], "k long, t long, x double"), o)
    want = {}
    for k in range(6):
        y, best = x[k] / o.grid, [0]
        for b in range(1, 41):
            best.append(min(best[a] + 1 for a in range(b) if strip(np.arange(a, b), y[a:b]) <= o.slack + 1e-12))
        want[k] = best[-1]
    assert {r.k: r.pieces for r in got.collect()} == want


def test_linear_fill_reaches_the_last_step(spark, tmp_path):
    spark.createDataFrame([(i, [float(i % 7)] * 64) for i in range(703)], "vec_id long, embedding array<float>").write.parquet(f"{tmp_path}/embeddings.parquet")
    rows = run(spark, str(tmp_path), "op_linear_fill_f2")
    assert rows.count() == 64 * 703
    r = rows.agg(F.min("t").alias("a"), F.max("t").alias("z"), F.sum(F.col("x").isNull().cast("int")).alias("none")).first()
    assert (r.a, r.z, r.none) == (0, 702, 0)


def test_throughput_gives_every_codec_the_whole_track(spark, sf, monkeypatch):
    from corridor.baselines import codecs
    from corridor.queries import workloads
    from corridor.queries.methods import track

    seen = []
    for name in ("native_full", "general"):
        monkeypatch.setattr(codecs, name, lambda t, *a, f=getattr(codecs, name), **kw: seen.append(t.count()) or f(t, *a, **kw))
    rows = workloads.throughput(spark, sf, (1, 512)).collect()
    t = track(spark, sf, "f5")
    assert seen == [t.count()] * 2 + [t.where("t % 512 = 0").count()] * 2
    assert {(r.method, r.stride) for r in rows} == {(m, n) for m in ("corridor", "native", "general") for n in (1, 512)}


def test_throughput_strides(spark):
    import inspect

    from corridor.queries import workloads

    assert inspect.signature(workloads.throughput).parameters["strides"].default == tuple(2**j for j in range(12))


def test_workloads_cover_the_tracks_of_the_survey(spark):
    from corridor.queries import registry, workloads

    assert {"w1_ratio_grid_f5", "w1_ratio_grid_f9", "w2_bits_per_sample_f9", "w6_split_f5", "w6_split_f9", "w7_predictive_f9", "w12_division_free_rest"} <= set(registry.queries())
    assert len(workloads.SMOOTH) == 5
    assert workloads.halvings(spark.range(500).selectExpr("0L AS k", "id AS t", "0D AS x")) == (1, 2, 4, 8, 16, 32)


def test_one_bucket_is_stored_by_many_tasks(spark, sf):
    """The stored rows of F5 are those of one task a bucket, for odd and even widths and chunks across slots; parts of a bucket are scanned apart."""
    from dataclasses import replace

    from corridor.plans import codec
    from corridor.queries.methods import opt, track
    from corridor.queries.workloads import day_parts
    from corridor.sources.tracks import fill_frames

    t, days = track(spark, sf, "f5").persist(), day_parts(spark, sf, keys=2).persist()
    series = t.select("k").distinct().count()
    assert days.select("part").distinct().count() > 1
    for width, chunk in ((series, 1024), (3, 100), (4, 7)):
        o = replace(opt("f5", block=1 << 20), width=width, chunk=chunk)
        want = sorted(map(tuple, codec.compress(t, o).collect()))
        assert sorted(map(tuple, codec.compress_spread(days, lambda table: fill_frames(table, 2), o).collect())) == want
    t.unpersist()
    days.unpersist()


def test_codes_of_many_lists():
    """Lists cut together get the bytes they get one by one."""
    import numpy as np

    from corridor.functions import vwidth

    rng = np.random.default_rng(9)
    rows = [rng.integers(0, 1 << int(rng.integers(1, 60)), n).astype(np.uint64) for n in [0, 1, 2, 7, 9, 63, 64, 65, 100, 700] * 4]
    rows += [np.where(rng.random(2048) < 0.9, rng.integers(0, 8, 2048), rng.integers(0, 1 << 14, 2048)).astype(np.uint64) for _ in range(5)]
    assert vwidth.encode_many(rows, at_once=3) == [vwidth.encode(r) for r in rows]


def test_parts_give_the_rows_of_the_track(spark, sf):
    """Blocks from packed days, filled by stride where they are compressed, are those of the strided track, for all three codecs."""
    from dataclasses import replace

    from corridor.baselines import codecs
    from corridor.plans import codec
    from corridor.queries.methods import opt, track
    from corridor.queries.workloads import day_parts, samples
    from corridor.sources.tracks import fill_frames, strided

    t, o = track(spark, sf, "f5").persist(), replace(opt("f5", block=100), width=4)
    parts = codec.pack_parts(day_parts(spark, sf, keys=2), ["key", "t", "last", "v0", "v1"]).persist()
    rows = lambda df: sorted(map(tuple, df.collect()))
    counts = samples(parts, (1, 7))
    for n in (1, 7):
        s, fill = strided(t, n), lambda table, n=n: fill_frames(table, 2, n)
        assert counts[n] == s.count()
        assert rows(codec.compress_parts(parts, fill, o)) == rows(codec.compress(s, o))
        assert rows(codecs.native_full(parts, o, True, fill)) == rows(codecs.native_full(s, o))
        assert rows(codecs.general(parts, o, ("bz2",), True, fill)) == rows(codecs.general(s, o, ("bz2",)))
    t.unpersist()
    parts.unpersist()


def test_transform_of_periodic_bytes():
    """Equal rotations stand in the order of their starts, as sorted by Python; a run's ranks are 0."""
    import numpy as np

    from corridor.baselines import codecs

    rng = np.random.default_rng(2)
    for data in (b"a", b"ab" * 20, b"abc" * 7, bytes(300), b"abcdefgh" * 9, b"banana" * 4 + b"x" * 30, bytes(rng.integers(0, 3, 400).astype(np.uint8))):
        order = sorted(range(len(data)), key=lambda i: (data[i:] + data[:i], i))
        last = bytes(data[i - 1] for i in order)
        assert codecs.bwt(data) == (last, order.index(0)) and codecs.unbwt(*codecs.bwt(data)) == data
        assert codecs.unfront(codecs.front(last)) == last
    assert codecs.front(b"") == b""
