import pathlib
import shutil
import subprocess
import sys

import __spark_entry__ as entry


def test_contract(spark):
    q, sql = entry.queries(), entry.oracle_sql()
    assert set(sql) <= set(q) and len(q) > 140
    assert entry.entry(spark).columns == ["cb", "col_id", "x"]


def test_contract_without_the_training_data_operators(tmp_path):
    """Also where the pipeline's file is left behind."""
    root = pathlib.Path(entry.__file__).parent
    shutil.copytree(root / "blocksolve", tmp_path / "blocksolve", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    for f in ("__spark_entry__.py", "corpus_pipeline.py"):
        if (root / f).exists():
            shutil.copy(root / f, tmp_path / f)
    told = "import __spark_entry__ as e; q = e.queries(); assert set(e.oracle_sql()) <= set(q) and 'pipeline' not in q; print(len(q))"
    out = subprocess.run([sys.executable, "-c", told], cwd=tmp_path, capture_output=True, text=True, timeout=120)
    assert out.returncode == 0 and int(out.stdout) > 140, out.stderr


def test_streams_equal_batches(spark, tables):
    from blocksolve.plans import streams

    n = spark.read.parquet(f"{tables}/events.parquet").count()
    assert streams.QUERIES["stream_dedup"](spark, tables).count() == n


def test_arrivals_reach_the_truth_and_go_on_after_a_restart(spark, tmp_path):
    from blocksolve.operators import measures
    from blocksolve.sources import systems
    from blocksolve.streaming import arrivals

    s = systems.f1(spark)

    def run(path, ids):
        for i in ids:
            s.y.select("row_id", "y").where(f"row_id = {i}").write.mode("append").parquet(f"{path}-y")
        stream = spark.readStream.schema("row_id bigint, y double").option("maxFilesPerTrigger", 1).parquet(f"{path}-y")
        q, x = arrivals.descend_on_arrival(stream, s.entries, s.x_zero(), path=path)
        q.awaitTermination()
        return x()

    whole = run(str(tmp_path / "a"), [1, 2, 3])
    run(str(tmp_path / "b"), [1, 2])
    again = run(str(tmp_path / "b"), [3])  # a new query over the same checkpoint
    assert sorted(map(tuple, again.collect())) == sorted(map(tuple, whole.collect()))
    assert measures.gap_db(s.entries, whole, s.y).first()[0] > 3
