"""The stages one by one: what stays, with which columns, and that clean documents do."""

from __future__ import annotations

import corpus_pipeline
import pytest
from pyspark.sql import functions as F

from blocksketch.llm import decontaminate, line_dedup, ngram_join, quality

SF = "/root/testdata/sf0.01"
COLUMNS = list(corpus_pipeline.COLUMNS)


@pytest.fixture(scope="module")
def stages(spark):
    docs, out = spark.read.parquet(f"{SF}/documents.parquet"), []
    for _, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, SF).cache()
        docs.count()
        out.append(docs)
    return out


def test_order_and_columns(stages):
    assert len(corpus_pipeline.STAGES) == 5
    assert all(s.columns == COLUMNS for s in stages[:-1])
    assert {"doc_id", "piece", "sequence_id", "offset"} <= set(stages[-1].columns)


def test_quality_keeps_good_documents(spark, stages):
    labels = spark.read.parquet(f"{SF}/labels.parquet")
    kept = labels.join(stages[0].select("doc_id"), "doc_id")
    good, bad = labels.where("quality = 1").count(), labels.where("quality = 0").count()
    assert kept.where("quality = 1").count() >= 0.98 * good
    assert kept.where("quality = 0").count() <= 0.1 * bad


def test_each_stage_works_on_what_is_left(stages):
    ids = [{r.doc_id for r in s.select("doc_id").distinct().collect()} for s in stages]
    assert all(b <= a for a, b in zip(ids, ids[1:], strict=False))
    assert len(ids[2]) < len(ids[1])
    assert ids[3] == ids[4]


def test_decontamination_agrees_with_the_report(spark, stages):
    found = decontaminate.decontaminate(stages[2], spark.read.parquet(f"{SF}/benchmark.parquet"))
    clean = {r.doc_id for r in found.where("not contaminated").collect()}
    assert clean == {r.doc_id for r in stages[3].collect()}


def test_run_equals_the_stages(spark, stages):
    assert corpus_pipeline.run(spark, SF).count() == stages[-1].count()


DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def test_lines(spark):
    many = [(i, f"own line number {i} of this text\nthe very same line everywhere\nshort", "en", f"s{i}", 0) for i in range(12)]
    odd = [(20, None, "en", "s1", 0), (21, "", "en", None, 0), (22, "the very same line everywhere", "en", None, 7), (0, many[0][1], "en", "s0", 0), (None, "the very same line everywhere\nx", None, None, 3)]
    docs = spark.createDataFrame(many + odd, DOCS).withColumn("_text", F.lit("clash")).withColumn("gone", F.lit(1))
    out = {(r.doc_id, i): r for i, r in enumerate(sorted(line_dedup.dedup_lines(docs, min_sites=10).collect(), key=str))}
    by: dict = {}
    for (d, _), r in out.items():
        by.setdefault(d, []).append(r)
    assert len(out) == 17 and all(r._text == "clash" for r in out.values())
    assert sorted(r._n_removed for r in by[None]) == [0]  # a null id sorts first and holds the first occurrence
    assert all(r._n_removed == 1 and r._kept == f"own line number {i} of this text\nshort" for i in range(12) for r in by[i])
    assert by[20][0]._kept is None and by[21][0]._kept == "" and by[22][0]._kept == ""
    kept = line_dedup.without_boilerplate(docs, min_sites=10)
    assert kept.columns == docs.columns
    assert {r.doc_id for r in kept.collect()} == {*range(12), 20, 21, None}
    assert line_dedup.dedup_lines(docs, min_sites=13).where("_n_removed > 0").count() == 0
    assert line_dedup.dedup_lines(docs.limit(0)).count() == 0


def test_marks_by_salted_join_and_by_broadcast_agree(spark, monkeypatch):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    report = lambda: sorted(map(str, line_dedup.dedup_lines(docs, min_sites=3, min_chars=1).select("doc_id", "_kept", "_n_removed").collect()))
    by_broadcast = report()
    monkeypatch.setattr(line_dedup, "MOST_BROADCAST_LINES", -1)
    assert report() == by_broadcast


def test_empty_tables_pass_every_stage(spark):
    none = spark.createDataFrame([], DOCS)
    for stage in (corpus_pipeline.quality_stage, corpus_pipeline.line_stage, corpus_pipeline.near_duplicate_stage, corpus_pipeline.decontamination_stage):
        assert stage(spark, none, SF).collect() == []


def test_exact_counts_decide_near_the_threshold(spark):
    rows = [(i * 100 + j, f"line {i} that is long enough", "en", f"s{j}", 0) for i in range(30) for j in range(i + 1)]
    lines = line_dedup.lines_of(spark.createDataFrame(rows, DOCS), "source", 5)
    assert sorted(r.sites for r in line_dedup.site_spread(lines, 12, lg=4).collect() if r.sites <= 20) == list(range(12, 21))


def test_windows_by_join_and_by_set_agree(spark, monkeypatch):
    docs = spark.createDataFrame([(1, "a b c d e f", "x", "s", 0), (2, "x Y z c d é", "x", "s", 0), (2, "x Y z c d é", "x", "s", 0), (3, None, "x", "s", 0), (4, "", "x", "s", 0), (None, "c d", "x", "s", 0), (5, "c d " * 20_000, "x", "s", 0)], DOCS).withColumn("items", F.lit(1))
    bench = spark.createDataFrame([(10, "b c d"), (11, "C d."), (9, "x y z c d e"), (None, "q q"), (12, None), (13, "...")], "item_id long, text string")
    report = lambda: sorted((tuple(r) for r in decontaminate.decontaminate(docs, bench, n=3).collect()), key=str)
    by_set = report()
    short = {(r[0], r[1], r[2], tuple(r[3])) for r in by_set if r[0] != 5}
    assert short == {(1, 6, 4, ("10", "11", "9")), (2, 6, 5, ("11", "9")), (3, 0, 0, ()), (4, 0, 0, ()), (None, 2, 2, ("11",))}
    monkeypatch.setattr(decontaminate, "MOST_WINDOWS", 2)
    assert report() == by_set
    by_join = sorted(map(str, decontaminate.clean_documents(docs, bench, n=3).collect()))
    monkeypatch.setattr(decontaminate, "MOST_WINDOWS", 200_000)
    assert by_join == sorted(map(str, decontaminate.clean_documents(docs, bench, n=3).collect()))
    assert decontaminate.decontaminate(docs.limit(0), bench).count() == 0
    assert decontaminate.decontaminate(docs, bench.limit(0)).where("n_hit > 0").count() == 0
    assert decontaminate.clean_documents(docs, bench, n=3).columns == docs.columns


def test_quality_stage_without_labels_keeps_all(spark):
    docs = spark.createDataFrame([(1, "x", "en", "s", 1), (None, None, None, None, None)], DOCS)
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert quality.keep_good(docs, labels).count() == 2


def test_one_row_of_each_group_whatever_its_id(spark):
    say = lambda i: " ".join(f"w{i}x{j}" for j in range(40))
    texts = [(5, say(1)), (None, say(1)), (None, say(2)), (3, say(3)), (7, say(3)), (7, say(4)), (8, say(5)), (8, say(5)), (9, say(5)), (None, say(6)), (None, say(6)), (None, say(6) + " more")]
    empty = [(11, None), (11, None), (12, "..."), (None, None), (None, None)]
    docs = spark.createDataFrame([(i, t, "en", f"s{n}", n) for n, (i, t) in enumerate(texts + empty)], DOCS).repartition(4)
    left = ngram_join.one_of_each(docs)
    assert left.columns == docs.columns
    got = [(r.doc_id, r.text) for r in left.collect()]
    sixth = [g for g in got if g in ((None, say(6)), (None, say(6) + " more"))]
    assert len(sixth) == 1
    want = [(5, say(1)), (None, say(2)), (3, say(3)), (7, say(4)), (8, say(5)), (11, None), (12, "..."), (None, None), (None, None)]
    assert sorted(got, key=str) == sorted(want + sixth, key=str)
    assert ngram_join.one_of_each(docs.limit(0)).count() == 0


def test_lines_on_a_few_sites_go_from_small_corpora(spark):
    shared = {n: (n, f"a passage that stands on {n} sites of this small corpus") for n in range(2, 10)} | {30: (3, "Go."), 40: (2, "Up.")}
    rows = [(i * 100 + j, f"own words of {i} and {j}\n{line}\n\nend of {i} and {j}", "en", f"s{j}", 0) for i, (n, line) in shared.items() for j in range(n)]
    kept = {r.doc_id: r.text for r in corpus_pipeline.line_stage(spark, spark.createDataFrame(rows, DOCS), "").collect()}
    stays = {i for i, *_ in rows if i % 100 == 0 or shared[i // 100][0] < 3}
    assert kept == {i: t if i in stays else t.replace("\n" + shared[i // 100][1], "") for i, t, *_ in rows}
