"""Sources, sinks and SQL views."""

from __future__ import annotations

import pytest

from blocksketch import sqlapi
from blocksketch.sources import generated


def test_matrix_is_the_same_however_split(spark):
    generated.register(spark)
    read = lambda parts: sorted(map(str, spark.read.format("blocksketch_t").option("n", "50").option("d", "3").option("partitions", parts).load().collect()))
    assert read("1") == read("7") and len(read("7")) == 50


@pytest.mark.parametrize("form", generated.FORMATS)
def test_round_trips(spark, tmp_path, form):
    df = spark.createDataFrame([(1, "a", 2.5), (2, "b", -1.0)], "i int, s string, v double")
    generated.write_any(df, str(tmp_path / form), form)
    back = generated.read_any(spark, str(tmp_path / form), form, "i int, s string, v double")
    assert sorted(map(tuple, back.collect())) == [(1, "a", 2.5), (2, "b", -1.0)]
    with pytest.raises(ValueError, match="one of"):
        generated.read_any(spark, "x", "avro2")


def test_views(spark, sf_dir):
    names = sqlapi.register_views(spark, sf_dir)
    assert len(names) == len(sqlapi.VIEWS)
    assert spark.sql("SELECT count(DISTINCT block_id) FROM bs_allocation").first()[0] == 20
    assert spark.sql("SELECT count(*) FROM bs_trace").first()[0] == 6
