import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from corridor.operators.segment import expand, fold_scan, key_frames, scan_sql, vector_scan
from corridor.options import Options
from corridor.sources import tracks as T

HAND = [(0, 0, 0, 4, 0, 4), (0, 0, 4, 2, 4, -1), (0, 0, 6, 1, 3, -4), (0, 0, 7, 2, -1, -1), (0, 0, 9, 1, -2, 2), (0, 0, 10, 1, 0, 0)]
VARIANTS = [{}, {"mode": "inputs"}, {"mode": "feasible"}, {"connect": False}, {"end": "mid"}, {"lam": 1.0}, {"lam": 0.1}, {"step": "eq"}]


def rows(df):
    return sorted(map(tuple, df.collect()))


def test_hand_track(spark):
    o = Options(eps=1, block=64)
    assert rows(vector_scan(T.hand(spark), o)) == HAND
    assert rows(fold_scan(T.hand(spark), o)) == HAND
    back = [r.x for r in expand(vector_scan(T.hand(spark), o), key_frames(T.hand(spark), o), o).orderBy("t").collect()]
    assert back == [0, 1, 2, 3, 4, 3.5, 3, -1, -1.5, -2, 0, 0]


@pytest.mark.parametrize("change", VARIANTS, ids=str)
def test_both_forms_and_the_bound(spark, sf, change):
    t = T.embed_walk(spark, sf, 4)
    o = Options(eps=1.0, block=100, **change)
    v = vector_scan(t, o)
    assert rows(v) == rows(fold_scan(t, o))
    con = duckdb.connect()
    con.execute(f"create view embeddings as select * from '{sf}/embeddings.parquet'")
    assert rows(v) == sorted(con.execute(scan_sql(T.track_sql("embed_walk", 4), o)).fetchall())
    back = expand(v, key_frames(t, o), o).withColumnRenamed("x", "z").join(t, ["k", "t"])
    n, worst = back.agg(F.count("*"), F.max(F.abs(F.col("x") - F.col("z")))).first()
    assert n == t.count() and worst <= o.bound * (1 + 1e-9)


def test_division_free_test_gives_the_same_pieces(spark, sf):
    t = T.event_walk(spark, sf)
    a, b = (rows(vector_scan(t, Options(eps=10.0, block=32, mode="inputs", test=x))) for x in ("divide", "cross"))
    assert a == b


@pytest.mark.parametrize("n", [1, 7, 8, 9])
def test_block_edges(spark, n):
    rng = np.random.default_rng(n)
    t = spark.createDataFrame([(3, i, float(x)) for i, x in enumerate(rng.normal(size=n).cumsum())], "k long, t long, x double")
    o = Options(eps=0.5, block=8)
    p = vector_scan(t, o)
    assert (p.agg(F.sum("dt")).first()[0] or 0) == n - len({i // 8 for i in range(n)})
    assert expand(p, key_frames(t, o), o).count() == n


@pytest.mark.parametrize("bad", [{"eps": 0}, {"eps": 1, "lam": 0}, {"eps": 1, "lam": 1.5}, {"eps": 1, "mode": "x"}])
def test_options_are_checked(bad):
    with pytest.raises(ValueError):
        Options(**bad)


def test_dirty_samples(spark):
    assert rows(T.clean(T.dirty(spark), "drop").where("k = 0")) == [(0, 0, 1.0), (0, 1, 3.0), (0, 2, 5.0)]
    with pytest.raises(Exception, match="not finite"):
        T.clean(T.dirty(spark), "fail").collect()
    with pytest.raises(Exception, match="gap"):
        vector_scan(T.dirty(spark).where("k = 2"), Options()).collect()
