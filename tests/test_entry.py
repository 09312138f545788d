import sys

import duckdb
import pytest

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SOME = ["m4_segment_f2", "m10_chunks_split_f2", "m17_min_distance_f2", "b7_predictive_1_f2", "a4_errors_f2", "op_asof_join", "op_range_join_f2", "op_frames"]


def test_entry(spark):
    import __spark_entry__ as e

    r = e.entry(spark).collect()
    assert len(r) == 1 and r[0].beyond == 0 and r[0].ratio > 20


@pytest.mark.parametrize("name", SOME)
def test_query_against_sql(spark, sf, name):
    from corridor.queries import registry

    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    df = registry.queries()[name](spark, sf)
    r = con.execute(registry.oracle_sql()[name])
    names = [d[0] for d in r.description]
    assert sorted(map(repr, (tuple(x[c] for c in names) for x in df.collect()))) == sorted(map(repr, r.fetchall()))


def test_every_oracle_has_a_query():
    from corridor.queries import registry

    assert set(registry.oracle_sql()) <= set(registry.queries())


def test_library_stands_alone(monkeypatch):
    """Without the corpus operators the entry module imports and offers the library's queries."""
    import importlib

    for m in [m for m in sys.modules if m.startswith("corridor.llm") or m in ("corpus_pipeline", "__spark_entry__")]:
        monkeypatch.delitem(sys.modules, m)
    monkeypatch.setitem(sys.modules, "corpus_pipeline", None)
    e = importlib.import_module("__spark_entry__")
    assert "m4_segment_f2" in e.queries() and "pipeline" not in e.queries()


def test_queries_need_no_session():
    """A fresh process lists queries and oracles without starting Spark."""
    import os
    import subprocess

    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    code = "import __spark_entry__ as e; from pyspark import SparkContext; assert e.queries() and e.oracle_sql(); assert SparkContext._active_spark_context is None; print(len(e.queries()))"
    done = subprocess.run([sys.executable, "-c", code], cwd=root, capture_output=True, text=True, timeout=120)
    assert done.returncode == 0, done.stderr[-2000:]


def test_package_is_shipped_to_clusters(monkeypatch):
    """A cluster's executors get the package even where the driver runs in the repository; local sessions need none."""
    from types import SimpleNamespace

    from corridor.runtime import ship_package

    for master, n in (("local[4]", 0), ("local-cluster[3,2,1024]", 1), ("spark://host:7077", 1)):
        sent = []
        ship_package(SimpleNamespace(sparkContext=SimpleNamespace(master=master, addPyFile=sent.append)))
        assert len(sent) == n


def test_stream_equals_batch(spark, sf):
    from corridor.queries import registry

    assert registry.queries()["stream_encoder_f3"](spark, sf).first()["different"] == 0
