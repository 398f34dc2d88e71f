"""Running sketches, sinks and restarts."""

import pytest
from pyspark.sql import functions as F

from steadysketch.catalog import QUERIES
from steadysketch.operators import sketch as S
from steadysketch.operators.layouts import RowHashed
from steadysketch.sources import io
from steadysketch.streaming.continuous import RunningSketch

LAYOUT = RowHashed(5, 8, seed=2)
DATA = "/root/testdata/sf0.001"


def rows(spark, n):
    return spark.createDataFrame([(k, n) for k in range(4)], "key bigint, value bigint")


def totals(cells):
    return {(r.row, r.bucket): r.c for r in cells.collect() if r.c}


def test_running_sketch_goes_on_after_a_restart(spark, tmp_path):
    path = str(tmp_path / "state")
    first = RunningSketch(spark, path, LAYOUT)
    first(rows(spark, 1), 0)
    first(rows(spark, 2), 1)
    again = RunningSketch(spark, path, LAYOUT)
    assert again.done == 1
    again(rows(spark, 2), 1)
    again(rows(spark, 4), 2)
    whole = S.build(rows(spark, 7).withColumn("query_id", F.lit(0).cast("bigint")), LAYOUT)
    assert totals(again.cells()) == totals(whole)


def test_a_half_written_batch_does_not_count(spark, tmp_path):
    path = str(tmp_path / "state")
    RunningSketch(spark, path, LAYOUT)(rows(spark, 1), 0)
    (tmp_path / "state" / "batch=1").mkdir()
    assert RunningSketch(spark, path, LAYOUT).done == 0


def test_batches_are_written_once_over_restarts(spark, tmp_path):
    path = str(tmp_path / "out")
    for _ in range(2):
        write = io.once_per_batch(spark, path)
        write(rows(spark, 1), 0)
        write(rows(spark, 1), 1)
    assert spark.read.parquet(path).count() == 8


def test_formats_need_what_they_lack(spark, tmp_path):
    with pytest.raises(ValueError):
        io.read_rows(spark, str(tmp_path), "csv")
    with pytest.raises(ValueError):
        io.read_rows(spark, str(tmp_path), "xml")


def test_cells_are_saved_and_loaded_by_layout(spark, tmp_path):
    cells = S.build(rows(spark, 3).withColumn("query_id", F.lit(0).cast("bigint")), LAYOUT)
    S.save(cells, str(tmp_path / "cells"), LAYOUT)
    assert totals(S.load(spark, str(tmp_path / "cells"), LAYOUT)) == totals(cells)
    with pytest.raises(ValueError):
        S.load(spark, str(tmp_path / "cells"), RowHashed(5, 8, seed=3))


def test_all_output_modes_agree_with_the_batch(spark):
    for r in QUERIES["stream_modes"](spark, DATA).collect():
        assert r.rows == r.as_in_batch > 0
