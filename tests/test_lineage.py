"""Where checkpoints go."""

from types import SimpleNamespace

import pytest

from cohort_engine.functions import lineage


def _session(master, folder=None):
    held = []
    context = SimpleNamespace(master=master, getCheckpointDir=lambda: held[-1] if held else None, setCheckpointDir=held.append)
    return SimpleNamespace(sparkContext=context, conf=SimpleNamespace(get=lambda key, default=None: folder))


def test_a_cluster_needs_a_shared_folder():
    for master in ("yarn", "spark://host:7077", "k8s://x", "local-cluster[3,2,1024]"):
        with pytest.raises(RuntimeError):
            lineage.shared_folder(_session(master))
        assert lineage.shared_folder(_session(master, "hdfs://shared")) == "hdfs://shared"
    assert lineage.shared_folder(_session("local[4]")) and lineage.shared_folder(_session("local"))


def test_folders_come_and_go(spark):
    path = lineage.fresh_folder(spark, "x")
    spark.range(3).write.parquet(path)
    assert spark.read.parquet(path).count() == 3 and lineage.fresh_folder(spark, "x") != path
    lineage.drop_folder(spark, path)
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        spark.read.parquet(path)
