"""Small tables take few files and few tasks, whatever the number of shuffle partitions."""

import numpy as np
import pytest

from purchase_planner.functions import storage
from purchase_planner.llm import components as stars
from purchase_planner.llm import jaccard_regions


@pytest.fixture
def many_partitions(spark):
    """As the check tool holds them on its input of large groups."""
    conf = {"spark.sql.shuffle.partitions": "96", "spark.sql.adaptive.coalescePartitions.enabled": "false"}
    before = {k: spark.conf.get(k) for k in conf}
    for k, v in conf.items():
        spark.conf.set(k, v)
    yield
    for k, v in before.items():
        spark.conf.set(k, v)


def test_small_tables_in_few_files(spark, many_partitions, monkeypatch, tmp_path):
    """One region above LOCAL, so that all levels write their tables; each had a file for every shuffle partition with rows."""
    monkeypatch.setattr(storage, "folder", lambda _: f"file://{tmp_path}")
    monkeypatch.setattr(jaccard_regions, "LOCAL", 100)
    rng = np.random.default_rng(3)
    base = [f"w{x}" for x in rng.integers(0, 500, 60)]
    rows = [(i, " ".join([*base[:k], f"n{i}", *base[k + 1 :]])) for i in range(300) for k in (int(rng.integers(0, 60)),)]
    rows += [(1000 + i, " ".join(f"u{x}" for x in rng.integers(0, 1 << 40, 20))) for i in range(300)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").coalesce(4)
    got = {r["doc_id"]: r["component_id"] for r in jaccard_regions.groups(docs, words=4, percent=80).collect()}
    assert got == {i: 0 if i < 1000 else i for i, _ in rows}
    files = {t.name: len(list(t.glob("part-*"))) for t in tmp_path.glob("table-*")}
    assert files and max(files.values()) <= 2 * spark.sparkContext.defaultParallelism


@pytest.mark.parametrize("one_task", [0, 100_000])
@pytest.mark.parametrize("size", [None, 1000])
def test_components_by_rounds_and_in_one_task(spark, monkeypatch, one_task, size):
    monkeypatch.setattr(stars, "ONE_TASK", one_task)
    rng = np.random.default_rng(8)
    edges = [(int(a), int(b)) for a, b in rng.integers(0, 600, (250, 2))] + [(1000 + i, 1001 + i) for i in range(60)] + [(5000 + i, 5000) for i in range(80)] + [(7, 7), (9000, 9000), (None, 3)]
    root = {}

    def find(v):
        while root.setdefault(v, v) != v:
            v = root[v]
        return v

    for a, b in edges:
        if a is not None:
            x, y = find(a), find(b)
            root[max(x, y)] = min(x, y)
    got = [(r["node"], r["component"]) for r in stars.components(spark.createDataFrame(edges, "src long, dst long").repartition(5), size=size).collect()]
    assert len(got) == len(root) and dict(got) == {v: find(v) for v in root}
