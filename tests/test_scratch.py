"""Where scratch tables go, and that they go away."""

from types import SimpleNamespace

import pytest
from pyspark.sql import functions as F

from flowrings import scratch


def session(**conf):
    return SimpleNamespace(conf=SimpleNamespace(get=lambda key, default=None: conf.get(key.split(".", 1)[1].replace(".", "_"), default)))


def test_only_a_single_machine_gets_a_folder_of_its_own(monkeypatch, tmp_path):
    monkeypatch.setattr(scratch, "_OWN", [str(tmp_path)])
    assert scratch.scratch_root(session(checkpoint_dir="hdfs://x/y/", master="yarn")) == "hdfs://x/y"
    for master in ("local", "local[4]", "local[*]"):
        assert scratch.scratch_root(session(master=master)) == str(tmp_path)
    for master in ("yarn", "spark://host:7077", "local-cluster[3,2,1024]", "k8s://https://host"):
        with pytest.raises(RuntimeError, match="spark.checkpoint.dir"):
            scratch.scratch_root(session(master=master))


def test_tables_are_freed(spark):
    kept = scratch.materialize(spark.range(10), "t")
    assert kept.count() == 10
    scratch.release(kept, None, spark.range(3))
    assert not spark._jvm.org.apache.hadoop.fs.Path(kept.scratch_path).getFileSystem(spark._jsc.hadoopConfiguration()).exists(spark._jvm.org.apache.hadoop.fs.Path(kept.scratch_path))


def test_aggregates_of_the_rows_written(spark):
    rows, seen = scratch.materialize_observed(spark.range(100).repartition(3), "t", n=F.count(F.lit(1)), total=F.sum("id"))
    assert rows.count() == 100 and seen == {"n": 100, "total": 4950}
