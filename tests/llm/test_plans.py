"""Native operators stay inside Spark; pair operators form no cross product."""

from __future__ import annotations

import re

import pytest

from blocksketch.llm import queries

PYTHON = re.compile("ArrowEval|BatchEvalPython|MapInArrow|MapInPandas|FlatMapGroups|PythonUDF")


def plan_of(df):
    return df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))


@pytest.mark.parametrize("name", ["op2_url_filter", "op8_benchmark_decontamination"])
def test_native_operators_run_no_python(spark, sf_dir, name):
    assert not PYTHON.search(plan_of(queries.QUERIES[name](spark, sf_dir)))


@pytest.mark.parametrize("name", ["op2_url_filter", "op6_line_dedup", "op8_benchmark_decontamination", "op9_ngram_jaccard_join", "op10_embedding_near_dedup"])
def test_no_cross_products(spark, sf_dir, name):
    text = plan_of(queries.QUERIES[name](spark, sf_dir))
    assert "CartesianProduct" not in text and "BroadcastNestedLoopJoin" not in text


def test_url_filter_reads_two_columns(spark, sf_dir):
    text = plan_of(queries.op2_url_filter(spark, sf_dir))
    assert "html" not in text and "ReadSchema: struct<page_id:bigint,url:string>" in text
