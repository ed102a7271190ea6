"""Files, streams and plans."""

import json

import pytest
from pyspark.sql import functions as F

from mutualgraph.linalg import factorised
from mutualgraph.operators import closeness
from mutualgraph.sources import files, networks
from mutualgraph.streaming import events


@pytest.mark.parametrize("kind", ["csv", "json", "orc", "parquet"])
def test_edges_from_files(spark, tmp_path, kind):
    df = spark.createDataFrame([(1, 2), (2, 3)], files.EDGES)
    df.write.format(kind).save(str(tmp_path / kind))
    assert sorted(map(tuple, files.read(spark, str(tmp_path / kind), files.EDGES, kind).collect())) == [(1, 2), (2, 3)]


def test_malformed_rows_are_dropped(spark, tmp_path):
    (tmp_path / "x.csv").write_text("1,2\nfoo,3\n4,5\n")
    assert len(files.read(spark, str(tmp_path / "x.csv"), files.EDGES, "csv").collect()) == 2


def test_sinks(spark, tmp_path):
    df = spark.createDataFrame([(1, 2, 0.5, 1), (2, 3, 0.7, 2)], "src long, dst long, s double, path int")
    files.write_partitioned(df, str(tmp_path / "p"), "path")
    assert "PartitionFilters: [isnotnull(path" in plan(spark.read.parquet(str(tmp_path / "p")).filter("path = 2"))
    files.append_trace(df, str(tmp_path / "t"))
    files.append_trace(df, str(tmp_path / "t"))
    assert spark.read.parquet(str(tmp_path / "t")).count() == 4
    files.write_report(df, str(tmp_path / "r"))
    lines = [line for f in (tmp_path / "r").glob("*.json") for line in f.read_text().splitlines()]
    assert sorted(json.loads(line)["s"] for line in lines) == [0.5, 0.7]


def plan(df):
    return df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))


def test_plans_push_down_and_never_cross_join(spark, tiny):
    text = plan(networks.table(spark, tiny, "events").filter("user_id = 3").select("event_id"))
    assert "PushedFilters: [IsNotNull(user_id), EqualTo(user_id,3)]" in text and "ReadSchema: struct<event_id:bigint,user_id:bigint>" in text
    text = plan(closeness.closeness(networks.events_net(spark, tiny)))
    assert "CartesianProduct" not in text and "BroadcastNestedLoopJoin" not in text


def test_factorised_product_equals_closeness(spark, small):
    net = networks.events_net(spark, small).stored()
    x = net.users.select("user_id", F.array((F.col("user_id") % 7).cast("double"), F.lit(1.0)).alias("vec"))
    S = closeness.closeness(net, form="matrix")
    want = S.join(x, F.col("dst") == F.col("user_id")).groupBy("src").agg(F.sum(F.col("s") * F.col("vec")[0]).alias("a"))
    off = factorised.closeness_times(net, x).join(want, F.col("user_id") == F.col("src"), "full").filter((F.abs(F.col("vec")[0] - F.col("a")) > 1e-9) | F.col("a").isNull() | F.col("vec").isNull())
    assert off.count() == 0


def drained(df, spark, name, mode):
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination(120)
    assert not q.exception()
    return spark.table(name)


def test_event_streams_equal_batches(spark, tiny, tmp_path):
    e = spark.read.parquet(f"{tiny}/events.parquet").orderBy("ts", "event_id")
    e.coalesce(1).write.option("maxRecordsPerFile", 300).parquet(str(tmp_path / "in"))
    stream = lambda: events.read(spark, str(tmp_path / "in"), 100)
    batch = events.prepared(spark.read.parquet(f"{tiny}/events.parquet"))
    got = drained(events.tumbling(stream()), spark, "tumbling", "complete")
    assert got.exceptAll(events.tumbling(batch)).count() == 0 and got.count() == events.tumbling(batch).count()
    got = drained(events.follow_links(stream()), spark, "links", "append")
    assert got.distinct().exceptAll(networks.events_net(spark, tiny).follow).count() == 0
    assert networks.events_net(spark, tiny).follow.exceptAll(got.distinct()).count() == 0
    got = drained(events.distinct_events(stream()), spark, "once", "append")
    assert got.select("event_id").distinct().count() == got.count() == 1000
    path = str(tmp_path / "counts")
    q = events.read(spark, str(tmp_path / "in"), 1).writeStream.foreachBatch(lambda b, i: events.merge_counts(b, i, path)).option("checkpointLocation", str(tmp_path / "cp")).trigger(availableNow=True).start()
    q.awaitTermination(120)
    want = batch.groupBy("user_id", F.col("word").alias("attr")).agg(F.count("*").alias("cnt"))
    assert events.merged_counts(spark, path).exceptAll(want).count() == 0 and events.merged_counts(spark, path).count() == want.count()


def test_sessions_and_sliding_windows(spark, tiny):
    e = events.prepared(spark.read.parquet(f"{tiny}/events.parquet"))
    assert events.sessions(e).agg(F.sum("cnt")).first()[0] == 1000
    assert events.sliding(e).agg(F.sum("cnt")).first()[0] == 2000
