import shutil

import pytest
from pyspark.sql import functions as F

from purchase_planner.streaming import live
from tests.conftest import SMALL


@pytest.fixture
def folder(tmp_path):
    (tmp_path / "in").mkdir()
    shutil.copy(f"{SMALL}/events.parquet", tmp_path / "in/events.parquet")
    return f"{tmp_path}/in"


def test_streams_equal_their_batch_twins(spark, folder):
    batch = spark.read.parquet(f"{SMALL}/events.parquet")
    got = live.run_to_table(live.key_counts(live.stream_of(spark, folder)), "complete")
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, live.key_counts(batch).collect()))
    got = live.quality_of(live.run_to_table(live.windowed_quality(live.stream_of(spark, folder)), "complete"))
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, live.quality_of(live.windowed_quality(batch)).collect()))


def test_incremental_counts(spark, folder, tmp_path):
    live.incremental_counts(live.stream_of(spark, folder), f"{tmp_path}/counts")
    total = spark.read.parquet(f"{tmp_path}/counts").agg(F.sum("n")).first()[0]
    assert total == spark.read.parquet(f"{SMALL}/events.parquet").count()
