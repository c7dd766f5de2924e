"""Every query against its SQL on the smallest tables; the operators without the optional
subpackage; streams whatever the order of messages."""

import subprocess
import sys
from pathlib import Path

import duckdb
import numpy as np
import pytest
from conftest import ROOT

import __spark_entry__ as entry
from evenkeel.operators import codes
from evenkeel.plans import catalogue
from evenkeel.plans.stream_queries import finish
from evenkeel.sources import pyds
from evenkeel.streaming import mailbox

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SLOW = {"auc_by_time", "sparse_round_times", "recovered_model"}


@pytest.fixture(scope="module")
def sql(small):
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"create view {t} as select * from '{small}/{t}.parquet'")
    return c


def _sorted(frame):
    frame = frame[sorted(frame.columns)]
    return frame.sort_values(list(frame.columns)).reset_index(drop=True)


@pytest.mark.parametrize("name", [n for n in catalogue.queries() if n not in SLOW])
def test_query(name, spark, small, sql):
    got = catalogue.queries()[name](spark, small).toPandas()
    assert len(got)
    if name in catalogue.oracle_sql():
        a, b = _sorted(got), _sorted(sql.execute(catalogue.oracle_sql()[name]).df())
        assert list(a.columns) == list(b.columns) and len(a) == len(b)
        for c in a.columns:
            if a[c].dtype == object:
                assert (a[c].fillna("") == b[c].fillna("")).all(), c
            else:
                assert np.allclose(a[c].to_numpy(dtype=float), b[c].to_numpy(dtype=float), atol=1e-9, equal_nan=True), c


def test_entry(spark):
    rows = entry.entry(spark).collect()
    assert len(rows) == 5 and max(r.gradient_error for r in rows) < 1e-6


def test_works_without_the_optional_subpackage(tmp_path):
    """As if it were deleted: entry imports and only its own queries are gone."""
    import shutil

    copy = tmp_path / "repo"
    shutil.copytree(ROOT, copy, ignore=shutil.ignore_patterns(".git", "llm", "corpus_pipeline.py", "__pycache__"))
    said = subprocess.run([sys.executable, "-c", "import __spark_entry__ as e; q = e.queries(); assert 'pipeline' not in q and not any(k.startswith('op1') for k in q); assert len(q) > 80; e.oracle_sql(); print('fine')"], cwd=copy, capture_output=True, text=True, env={"PATH": "/usr/bin:/bin"}, timeout=300)
    assert said.stdout.strip() == "fine", said.stderr


def test_nothing_else_imports_it():
    for p in (ROOT / "evenkeel").rglob("*.py"):
        if "llm" not in p.parts:
            assert "evenkeel.llm" not in p.read_text(), p


@pytest.mark.parametrize("seed", [1, 2])
def test_stream_equals_batch_in_any_order(spark, tmp_path, seed):
    rng = np.random.default_rng(seed)
    code, g = codes.ring_code(5, 1), rng.standard_normal((5, 3))
    vectors = code.matrix @ g
    rows = [(t, w, vectors[w].tolist()) for t in range(4) for w in range(5)] + [(t, 2, vectors[2].tolist()) for t in range(4)]
    rng.shuffle(rows)
    for i in range(0, len(rows), 8):
        part = spark.createDataFrame([(int(t), int(w), v, float(t)) for t, w, v in rows[i : i + 8]], "round int, worker int, vec array<double>, s double").selectExpr("round", "worker", "vec", "timestamp_seconds(s + 1000000) as sent_at")
        part.coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(mailbox.MESSAGE).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    out = finish(mailbox.aggregate_rounds(stream, code), "append").collect()
    assert sorted(r["round"] for r in out) == [0, 1, 2, 3]
    assert all(np.allclose(r["g"], g.sum(axis=0), atol=1e-7) for r in out)


@pytest.mark.parametrize("mode", ["append", "complete"])
def test_stream_results_do_not_come_to_the_driver(spark, tmp_path, mode):
    for i in range(3):
        spark.range(10 * i, 10 * i + 10).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema("id bigint").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    out = finish(stream if mode == "append" else stream.groupBy((stream.id % 7).alias("id")).count(), mode)
    assert "LocalTableScan" not in (plan := out._jdf.queryExecution().executedPlan().toString()) and "parquet" in plan
    want = [(i,) for i in range(30)] if mode == "append" else [(k, len(range(k, 30, 7))) for k in range(7)]
    assert sorted(map(tuple, out.collect())) == want


def test_python_sources(spark):
    pyds.register(spark)
    a = spark.read.format("mixture_logistic").option("d", 3000).option("p", 4).option("partitions", 3).load()
    b = spark.read.format("mixture_logistic").option("d", 3000).option("p", 4).option("partitions", 7).load()
    assert a.count() == 3000 and a.exceptAll(b).count() == 0


def test_dedup_state_is_not_on_the_heap(spark, small, monkeypatch):
    """Its checkpoint has files of the store on disk, and the session's settings are as before."""
    from evenkeel.plans import stream_queries

    kept = []
    monkeypatch.setattr(stream_queries.shutil, "rmtree", lambda folder, **_: kept.append(folder))
    assert stream_queries.stream_dedup(spark, small).count()
    files = [p.name for p in Path(kept[0]).rglob("state/**/*")]
    assert any(f.endswith((".zip", ".changelog")) for f in files) and not any(f.endswith(".delta") for f in files)
    assert all(spark.conf.get(k, None) != v for k, v in stream_queries.STATE.items() if k.endswith(("providerClass", "boundedMemoryUsage")))
