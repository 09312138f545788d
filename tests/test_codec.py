import json

import pytest

from corridor.baselines import codecs
from corridor.operators import families, measures, segquery
from corridor.operators.segment import expand, key_frames, vector_scan
from corridor.options import Options
from corridor.plans import codec
from corridor.sources import simulate
from corridor.sources import tracks as T


def rows(df):
    return sorted(map(tuple, df.collect()))


@pytest.mark.parametrize("change", [{}, {"layout": "interleaved", "zigzag": "sparse"}, {"layout": "forward"}], ids=str)
def test_round_trip(spark, sf, change):
    t = T.embed_walk(spark, sf, 8)
    o = Options(eps=1.0, block=64, chunk=50, width=4, **change)
    stored = codec.compress(t, o).persist()
    assert rows(stored) == rows(codec.compress(t, o, fused=False))
    p = vector_scan(t, o)
    assert rows(codec.pieces_of(stored, o)) == rows(p)
    assert rows(codec.decompress(stored, o)) == rows(expand(p, key_frames(t, o), o))


def test_wire_order_is_queue_order(spark, sf):
    o = Options(eps=1.0, block=64, width=4)
    p = vector_scan(T.embed_walk(spark, sf, 8), o)
    want = rows(codec.wire_order(p, o).selectExpr("block", "k", "t0", "cast(place as long)"))
    for dense in (False, True):
        assert rows(codec.queue_order(p, o, dense)) == want


def test_greedy_is_optimal_for_disjoint_families(spark, sf):
    t = T.embed_walk(spark, sf, 3)
    o = Options(eps=1.0, block=64)
    for family in ("constant", "free_line"):
        greedy = families.segment_with(t, family, o).groupBy("block", "k").count()
        best = codecs.optimal_pieces(t, o, family).select("block", "k", "pieces")
        assert rows(greedy) == rows(best)
    lines = families.segment_with(t, "free_line", o).count()
    assert vector_scan(t, o).count() >= lines


def test_simplify_and_polynomials_keep_the_bound(spark, sf):
    t = T.embed_walk(spark, sf, 3)
    o = Options(eps=0.5, block=64)
    assert codecs.simplify(t, o).where("err > 0.5000001").count() == 0
    assert codecs.poly_window(t, o).where("err > 0.5000001").count() == 0
    errors = [r.max_err for r in codecs.pca(t, [1, 2, 3]).orderBy("r").collect()]
    assert errors == sorted(errors, reverse=True) and errors[-1] < 1e-6


def test_still_and_moving_particles(spark):
    still = measures.metric(simulate.sim_still(spark, 16, 512), Options(eps=0.01, block=512)).first()
    assert still["ratio"] > 500
    wells = simulate.sim_wells(spark, 8, 20, 200, dt=1e-2).persist()
    o = Options(eps=0.01, block=200)
    e = measures.errors(wells, o).first()
    assert e.n == e.rebuilt == 8 * 3 * 200 and e.beyond == 0
    assert measures.metric(wells, o).first()["ratio"] > 20


def test_distances_from_pieces(spark, sf):
    t = T.embed_walk(spark, sf, 8)
    o = Options(eps=1.0, block=64)
    p = vector_scan(t, o)
    pairs = spark.createDataFrame([(0, 1), (2, 3)], "a long, b long")
    got = {(r.a, r.b): r.sampled for r in segquery.min_distance(p, pairs, 2, o).collect()}
    x = {(r.k, r.t): r.x for r in expand(p, None, o).collect()}
    steps = {t for _, t in x}
    for a, b in got:
        want = min(sum((x[2 * a + i, s] - x[2 * b + i, s]) ** 2 for i in (0, 1)) ** 0.5 for s in steps)
        assert abs(got[a, b] - want) < 1e-5


def test_data_source_reads_one_block(spark, sf, tmp_path):
    from corridor.sources.datasource import CorridorSource, write_blocks

    t = T.embed_walk(spark, sf, 8)
    o = Options(eps=1.0, block=64, width=4)
    write_blocks(codec.compress(t, o), str(tmp_path / "store"), o)
    spark.dataSource.register(CorridorSource)
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    r = spark.read.format("corridor").option("path", str(tmp_path / "store")).option("options", json.dumps({"eps": 1.0, "block": 64, "width": 4})).load()
    assert rows(r.where("t = 70 AND k = 5")) == [x for x in rows(codec.decompress(codec.compress(t, o), o)) if x[:2] == (5, 70)]
    again = spark.read.format("corridor").option("path", str(tmp_path / "store")).option("options", json.dumps({"eps": 1.0, "block": 64, "width": 4})).load()
    assert again.count() == t.count()


@pytest.mark.parametrize("symbols", [4, 256])
def test_predictive_coder_writes_its_escapes(symbols):
    import numpy as np

    rng = np.random.default_rng(4)
    u = np.concatenate([rng.integers(0, 9, 400), rng.integers(0, 1 << 40, 20), [symbols - 2, symbols - 1, symbols, 0]])
    packed, beside = codecs.residual_encode(u, symbols)
    assert len(beside) == 8 * (u >= symbols - 1).sum() > 0
    assert (codecs.residual_decode(packed, beside, len(u), symbols) == u).all()


@pytest.mark.parametrize("order", [0, 1])
def test_predictive_coder_gives_ragged_series_back(spark, order):
    rows = [(k, t, float((k + 1) * t * t * 50 + t % 3)) for k, n in ((0, 40), (1, 7), (2, 23)) for t in range(n)]
    got = codecs.predictive_coder(spark.createDataFrame(rows, "k long, t long, x double"), Options(eps=1.0, block=32, width=4), order).collect()
    assert all(r.lossless for r in got) and sum(r.n for r in got) == len(rows)


def test_own_sink_files_rows_by_their_range(spark, sf, tmp_path):
    """One task with blocks of several ranges: each row lies under the range of its own block."""
    from corridor.sources.datasource import BLOCKS_IN_RANGE, CorridorSource, read_blocks

    o = Options(eps=1.0, block=2, width=8)
    stored = codec.compress(T.embed_walk(spark, sf, 8), o).persist()
    spark.dataSource.register(CorridorSource)
    for path in (str(tmp_path / "plain"), f"file://{tmp_path / 'uri'}"):
        stored.coalesce(1).write.format("corridor").option("path", path).mode("append").save()
        laid = spark.read.parquet(path)
        assert laid.select("block_range").distinct().count() > 1
        assert laid.where(f"block_range <> floor(block / {BLOCKS_IN_RANGE})").count() == 0
        assert rows(read_blocks(spark, path)) == rows(stored)
    stored.unpersist()
