"""Streams against their batch twins, and late rows."""

from __future__ import annotations

import datetime as dt

import __spark_entry__ as contract
from pyspark.sql import functions as F

from blocksketch.streaming import events as ev


def replay(spark, tmp_path, parts):
    """Writes rows as files that a stream reads one by one."""
    schema = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"
    for i, rows in enumerate(parts):
        spark.createDataFrame(rows, schema).coalesce(1).write.mode("append").parquet(str(tmp_path / "events.parquet" / f"p{i}"))
    files = sorted((tmp_path / "events.parquet").rglob("part-*.parquet"), key=lambda p: p.parent.name)
    out = tmp_path / "in"
    out.mkdir()
    for i, f in enumerate(files):
        target = out / f"f{i}.parquet"
        target.write_bytes(f.read_bytes())
        import os

        os.utime(target, (1_700_000_000 + i, 1_700_000_000 + i))
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(str(out))
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def row(i, hour, value=1.0, user=1):
    return (i, dt.datetime(2024, 1, 1) + dt.timedelta(hours=hour), user, "a", value, "{}")


def test_tumbling_equals_batch(spark, sf_dir):
    key = lambda df: sorted((str(r.start), r.n, round(r.g01, 6)) for r in df.collect())
    assert key(ev.finish(ev.tumbling_stats(ev.read_events(spark, sf_dir)))) == key(ev.tumbling_stats(ev.batch_events(spark, sf_dir)))


def test_rows_behind_the_watermark_are_dropped(spark, tmp_path):
    stream = replay(spark, tmp_path, [[row(1, 1)], [row(2, 60)], [row(6, 61)], [row(3, 2)], [row(4, 130)], [row(5, 200)]])
    out = {r.start.day: r.n for r in ev.finish(ev.tumbling_stats(stream), "append").collect()}
    assert out == {1: 1, 3: 2, 6: 1}  # row 3 came 59 hours late, after the watermark took effect, and is not in day 1


def test_repeated_events_count_once(spark, tmp_path):
    stream = replay(spark, tmp_path, [[row(1, 1), row(2, 1)], [row(1, 1), row(3, 2)]])
    assert sorted(r.event_id for r in ev.finish(ev.first_of_each(stream), "append").collect()) == [1, 2, 3]


def test_running_gram_over_batches(spark, tmp_path):
    seen = []
    stream = replay(spark, tmp_path, [[row(1, 1, 100.0)], [row(2, 2, 300.0)]])
    out = ev.running_gram(stream, lambda i, df: seen.append(df.first()["n"])).first()
    assert (out.n, out.g01, out.g11) == (2, 4.0, 10.0) and seen == [1, 2]


def test_deadline_counts_erasures(spark, tmp_path):
    stream = replay(spark, tmp_path, [[row(1, 1, 5.0), row(2, 2, 50.0)], [row(3, 3, 24.0)]])
    out = ev.finish(ev.replies_by_deadline(stream, 24.0)).first()
    assert (out.came, out.late) == (2, 1)


def test_late_rows_are_counted_without_keeping_the_others(spark, sf_dir):
    before = {t.name for t in spark.catalog.listTables()}
    got = contract.queries()["t4_late_rows"](spark, sf_dir).first()
    day = F.col("ts") >= F.lit("2024-01-20").cast("timestamp")
    want = ev.batch_events(spark, sf_dir).agg(F.count_if(day), F.count_if(~day)).first()
    assert tuple(got) == tuple(want)
    assert {t.name for t in spark.catalog.listTables()} == before  # a table in the driver's memory would be listed
