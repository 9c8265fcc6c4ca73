"""What builds and experiments leave in the shared folder."""

import pickle
from pathlib import Path

import pyarrow.parquet as pq
import pytest

from series_engine import measures, workloads
from series_engine.plans import build, storage
from series_engine.plans.build import build_index
from series_engine.sources import builders


def folders(spark) -> set[str]:
    return {x.name for x in Path(storage.shared_dir(spark).removeprefix("file://")).glob("*-*") if x.is_dir()}


@pytest.mark.parametrize("policy", ["adaptive", "fuzzy", "fullary", "dynseg"])
def test_a_build_leaves_its_data_alone_and_may_do_without(spark, sf_dir, policy):
    walks, p = builders.walks(spark, sf_dir), workloads.params_for(policy, 5)
    before = folders(spark)
    bare = build_index(walks, p, data=False)
    assert folders(spark) == before
    ix = build_index(walks, p)
    assert [x.split("-")[0] for x in folders(spark) - before] == ["segment"]
    assert pickle.dumps(bare.tree) == pickle.dumps(ix.tree) and measures.structure(bare) == measures.structure(ix)
    assert ix.data(None, ("series_id",)).distinct().count() == walks.count()


@pytest.mark.parametrize("name", ["w_alpha", "w_uneven", "w_upper_bounds", "w_structure"])
def test_experiments_leave_nothing(spark, sf_dir, name, monkeypatch):
    monkeypatch.setattr(workloads, "FOUR", ("walks",))
    before = folders(spark)
    assert workloads.WORKLOADS[name](spark, sf_dir).count() > 0
    assert folders(spark) == before


def test_a_file_of_small_row_groups(spark):
    table = storage.written(builders.synthetic_walks(spark, 4_000, 128).coalesce(1), "walks", 1 << 20)
    (path,) = (x.removeprefix("file://") for x in table.inputFiles())
    assert pq.ParquetFile(path).num_row_groups > 1 and table.count() == 4_000


def test_copies_are_not_sent_through_the_driver(spark, monkeypatch):
    """Neither copies made inside subtrees nor many copies of rows are broadcast; few of them may be."""
    ids = spark.range(50).withColumnRenamed("id", "series_id")
    inside = storage.written(ids.selectExpr("0L start", "series_id", "series_id % 3 leaf"), "inside")
    named = spark.createDataFrame([(0, i, 10 + i) for i in range(3)], "start long, leaf long, leaf_id long")
    leaves = build._leaves_of_copies(inside, named)
    rows = storage.written(ids.selectExpr("0L leaf_id", "series_id", "cast('w' as binary) word", "array(1D) values", "false is_copy"), "rows")
    copies = storage.written(leaves, "copies")
    monkeypatch.setattr(build, "SENT_COPIES", 49)
    many, few = build._copied(rows, copies, 50), build._copied(rows, copies, 49)
    plan = lambda d: d._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" in plan(leaves) and "Broadcast" not in plan(leaves)
    assert "SortMergeJoin" in plan(many) and "Broadcast" not in plan(many)
    want = sorted((10 + i % 3, i, True) for i in range(50))
    for out in (many, few):
        assert sorted((r["leaf_id"], r["series_id"], r["is_copy"]) for r in out.collect()) == want
