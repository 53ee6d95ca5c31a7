"""The engine without the corpus operators, and where written tables go."""

import shutil
import subprocess
import sys
from pathlib import Path
from types import SimpleNamespace

import pytest
from pyspark.sql import functions as F

from ripplegraph import experiments
from ripplegraph.plans import scratch
from ripplegraph.queries import QUERIES

REPO = Path(__file__).resolve().parent.parent


@pytest.mark.parametrize("pipeline", [True, False])
def test_entry_without_the_corpus_operators(tmp_path, pipeline):
    shutil.copytree(REPO, tmp_path / "r", ignore=shutil.ignore_patterns("llm", ".git", "__pycache__", *([] if pipeline else ["corpus_pipeline.py"])))
    code = "import __spark_entry__ as e; print(len(e.queries()), len(e.oracle_sql()), 'pipeline' in e.queries())"
    out = subprocess.run([sys.executable, "-c", code], cwd=tmp_path / "r", capture_output=True, text=True, check=True).stdout.split()
    assert int(out[0]) == len(QUERIES | experiments.QUERIES) and int(out[1]) <= int(out[0]) and out[2] == "False"


def test_no_local_folder_on_a_cluster():
    conf = {"spark.master": "spark://host:7077"}
    with pytest.raises(ValueError, match="checkpoint"):
        scratch.Scratch(SimpleNamespace(conf=SimpleNamespace(get=conf.get)), "t")


def test_tables_can_be_dropped(spark):
    s = scratch.Scratch(spark, "t")
    assert s.save(spark.range(3), "a").count() == 3
    s.drop()
    with pytest.raises(Exception, match="PATH_NOT_FOUND|does not exist"):
        spark.read.parquet(s.path("a")).count()


def test_broadcast_needs_few_rows_and_few_bytes(spark, monkeypatch):
    s = scratch.Scratch(spark, "t")
    df = s.save(spark.range(100).select("id", F.repeat(F.sha2(F.col("id").cast("string"), 256), 20).alias("x")))
    hinted = lambda: scratch.bounded_broadcast(df, 100) is not df
    assert hinted()
    monkeypatch.setattr(scratch, "BROADCAST_BYTES", 100)
    assert not hinted()
    monkeypatch.setattr(scratch, "BROADCAST_BYTES", 1 << 30)
    monkeypatch.setattr(scratch, "BROADCAST_ROWS", 99)
    assert not hinted()
