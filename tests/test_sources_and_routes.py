"""Raw records, the neighbours' table function and routes of arriving series."""

import numpy as np
import pytest

from series_engine.functions.registered import register
from series_engine.plans import update
from series_engine.plans.build import build_index
from series_engine.plans.params import BuildParams
from series_engine.plans.storage import written
from series_engine.sources import builders, rawfloat
from series_engine.streaming import streams

SERIES = "series_id long, values array<double>"


def test_records_of_a_split_file(spark, tmp_path):
    x = np.arange(30_000, dtype="<f4").reshape(-1, 6)
    (tmp_path / "a.bin").write_bytes(x.tobytes())
    got = rawfloat.read_records(spark, str(tmp_path / "a.bin"), 6).orderBy("record").collect()
    assert [r["record"] for r in got] == list(range(len(x))) and [r["values"] for r in got] == x.tolist()


def test_records_of_an_empty_and_of_a_cut_file(spark, tmp_path):
    (tmp_path / "empty.bin").write_bytes(b"")
    assert rawfloat.read_records(spark, str(tmp_path / "empty.bin"), 6).count() == 0
    (tmp_path / "cut.bin").write_bytes(b"\0" * 25)
    with pytest.raises(Exception, match="[Pp]artial record"):
        rawfloat.read_records(spark, str(tmp_path / "cut.bin"), 6).count()


def test_written_and_read_again(spark, tmp_path):
    s = spark.createDataFrame([(3, [3.0, 4.0]), (1, [1.0, 2.0])], SERIES)
    rawfloat.write_raw(s, str(tmp_path / "out.bin"), 2)
    assert [r["values"] for r in rawfloat.read_records(spark, str(tmp_path / "out.bin"), 2).orderBy("record").collect()] == [[1.0, 2.0], [3.0, 4.0]]
    with pytest.raises(ValueError, match="series 3"):
        rawfloat.write_raw(spark.createDataFrame([(3, [1.0])], SERIES), str(tmp_path / "bad.bin"), 2)


@pytest.mark.parametrize("k, want", [(0, []), (2, [(2, 0.0), (5, 0.0)]), (9, [(2, 0.0), (5, 0.0), (1, 1.0)])])
def test_nearest_skip_bad_rows_and_break_ties_by_id(spark, k, want):
    register(spark)
    rows = [(5, [0.0, 1.0]), (2, [0.0, 1.0]), (1, [1.0, 1.0]), (4, [0.0]), (6, None), (None, [0.0, 1.0]), (7, [None, 1.0])]
    spark.createDataFrame(rows, SERIES).createOrReplaceTempView("few")
    got = spark.sql(f"SELECT * FROM series_knn(TABLE(few) WITH SINGLE PARTITION, array(0D, 1D), {k})").collect()
    assert [(r["series_id"], r["distance"]) for r in got] == want


def test_routes_are_the_leaves_of_an_insertion(spark):
    s = written(builders.synthetic_walks(spark, 400, 64), "walks")
    old, new = s.where("series_id % 2 = 0"), s.where("series_id % 2 = 1")
    ix = build_index(old, BuildParams(w=8, th=20))
    got = dict(streams.routed(ix, new.union(spark.createDataFrame([(-1, [1.0]), (-2, None)], SERIES))).collect())
    known = {r["leaf_id"] for r in ix.data(None, ("leaf_id",)).distinct().collect()}
    update.insert(ix, new)
    after = {r["series_id"]: r["leaf_id"] for r in ix.data(None, ("series_id", "leaf_id")).where("series_id % 2 = 1").collect()}
    assert got.keys() == after.keys() and len(got) == 200
    assert all(after[i] == leaf if leaf is not None else after[i] not in known for i, leaf in got.items())
    with pytest.raises(ValueError, match="words"):
        streams.routed(build_index(old, BuildParams(w=8, th=20, policy="dynseg")), new)
