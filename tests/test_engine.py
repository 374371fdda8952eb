"""Sources, Python extension points, plans and streams."""

import math

import pandas as pd
import pytest
from pyspark.sql import functions as F

from vintage import workloads
from vintage.functions import udfs
from vintage.operators.joins import checked_cross, row_salt, salted_count, salted_join
from vintage.plans import curves
from vintage.sources import tables
from vintage.streaming import histograms


def test_round_trips(spark, sf, tmp_path):
    df = tables.table(spark, sf, "nation")
    want = sorted(map(tuple, df.collect()))
    for kind, opts in (("csv", {"header": True}), ("json", {}), ("orc", {}), ("parquet", {})):
        df.write.format(kind).options(**opts).save(f"{tmp_path}/{kind}")
        assert sorted(map(tuple, spark.read.format(kind).options(**opts).schema(df.schema).load(f"{tmp_path}/{kind}").select(df.columns).collect())) == want
    parted = tables.stored(df, "n_regionkey")
    assert sorted(map(tuple, parted.select(df.columns).collect())) == want


def test_imported_and_outside_scores(spark):
    lp = spark.createDataFrame([(1, 0, math.log(0.5)), (1, 1, math.log(0.25)), (1, 2, math.log(0.125))], "id long, pos int, logprob double")
    assert udfs.from_logprobs(lp, ["id"]).first().ppl == pytest.approx(4)
    assert udfs.from_logprobs(lp, ["id"], 2).first().ppl == pytest.approx(math.sqrt(8))
    probes = spark.createDataFrame([(1, ["a", "b"]), (2, [])], "id long, toks array<string>")
    got = {r.id: r.ppl for r in udfs.score_with(probes, lambda: lambda lists: [[math.log(0.1)] * len(x) for x in lists]).collect()}
    assert got[1] == pytest.approx(10) and (got[2] is None or math.isnan(got[2]))


def test_python_forms_equal_native_ones(spark):
    df = spark.createDataFrame([("m", i % 2, i, float(i * i % 97)) for i in range(160)], "model string, month_ix int, topic_id long, ppl double")
    native = {r.month_ix: r.ppl for r in curves.trimmed_mean(df).collect()}
    assert {r.month_ix: r.p for r in df.groupBy("month_ix").agg(udfs.trimmed_mean_udaf()("ppl").alias("p")).collect()} == pytest.approx(native)
    curve = curves.relative(curves.trimmed_mean(df))
    assert udfs.cutoff_with(curve, lambda p: p.loc[p["rel"].idxmin(), "month_ix"]).first().cutoff == curves.effective_cutoff(curve).first().cutoff
    spark.udtf.register("ngrams", udfs.ngrams_udtf())
    assert [r.gram for r in spark.sql("SELECT gram FROM ngrams('a b c', 2) ORDER BY pos").collect()] == ["a b", "b c"]


def test_cross_join_is_guarded(spark):
    with pytest.raises(ValueError):
        checked_cross(spark.range(5), spark.range(50), most=10)


def test_salts_depend_on_no_order(spark):
    rows = [(k % 3, f"t{k}", {"a": k}) for k in range(300)]
    kind = "k long, `t.x` string, m map<string,int>"
    one, other = (spark.createDataFrame(r, kind).coalesce(1) for r in (rows, rows[::-1]))
    salts = [sorted((r["t.x"], r["s"]) for r in df.withColumn("s", row_salt(df, 8)).collect()) for df in (one, other)]
    assert salts[0] == salts[1] and {s for _, s in salts[0]} == set(range(8))

    side = spark.createDataFrame([(0, "zero"), (1, "one"), (9, "none")], "k long, name string")
    for how, n in (("inner", 200), ("left", 300), ("left_semi", 200), ("left_anti", 100)):
        assert salted_join(one, side, "k", 4, how).count() == one.join(side, "k", how).count() == n
    for how in ("right", "full", "outer"):
        with pytest.raises(ValueError, match="repeated side"):
            salted_join(one, side, "k", 4, how)
    assert {tuple(r) for r in salted_count(one.repartition(5), ["k"], 3).collect()} == {(0, 100), (1, 100), (2, 100)}


@pytest.mark.parametrize("name,has,lacks", [
    ("scan_prune", ["PushedFilters: [IsNotNull(l_quantity)", "ReadSchema: struct<l_orderkey:bigint,l_quantity:double,l_shipdate:"], ["Python"]),
    ("topk_group", ["WindowGroupLimit"], ["Python"]),
    ("join_broadcast", ["BroadcastHashJoin"], ["Cartesian"]),
    ("dt_curve", ["HashAggregate"], ["Python", "CartesianProduct"]),
    ("ev_curve_curated", ["HashAggregate"], ["Python", "CartesianProduct"]),
    ("bm25_top10_scan", ["WindowGroupLimit", "MapInArrow"], ["SortMergeJoin", "BatchEvalPython", "CartesianProduct"]),
    ("dedup_paras", ["HashAggregate"], ["Python", "Window"]),
])
def test_plans(spark, sf, name, has, lacks):
    plan = workloads.QUERIES[name](spark, sf)._jdf.queryExecution().explainString(spark._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))
    assert all(x in plan for x in has), plan
    assert not any(x in plan for x in lacks), plan


def run_stream(spark, df, mode="append"):
    name = f"t{abs(hash(id(df)))}"
    df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start().awaitTermination()
    return spark.table(name)


def test_streams_equal_batches(spark, sf, tmp_path):
    events = tables.table(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    events.repartitionByRange(4, "ts").sortWithinPartitions("ts").write.parquet(f"{tmp_path}/in")
    stream = spark.readStream.schema(events.schema).parquet(f"{tmp_path}/in")
    for f, cols in ((histograms.tumbling, ["start", "event_type", "n"]), (histograms.sliding, ["start", "n"])):
        got = {tuple(r) for r in run_stream(spark, f(stream, late="40 days"), "complete").select(cols).collect()}
        assert got == {tuple(r) for r in f(events).select(cols).collect()}
    keys = ["user_id", "event_type"]
    got = run_stream(spark, histograms.distinct_copies(stream, keys, "40 days")).select(keys)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, histograms.distinct_copies(events, keys).select(keys).collect()))


def written(rows, path, per=1):
    """Rows as one file each, in order of their times."""
    for k in range(0, len(rows), per):
        rows.iloc[k : k + per].to_parquet(f"{path}/{k:04d}.parquet", coerce_timestamps="us", index=False)


def staged(spark, path, schema):
    path.mkdir()
    return lambda rows, per=1: (written(rows, path, per), spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(str(path)))[1]


def test_streaming_sessions_equal_batches(spark, sf, tmp_path):
    events = tables.table(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    events.repartitionByRange(4, "ts").sortWithinPartitions("ts").write.parquet(f"{tmp_path}/in")
    stream = spark.readStream.schema(events.schema).parquet(f"{tmp_path}/in")
    closing = F.expr("timestamp '2024-03-01'")  # far behind, so that the watermark closes every session
    last = events.limit(1).withColumn("ts", closing).withColumn("user_id", F.lit(-1).cast("long"))
    last.write.mode("append").parquet(f"{tmp_path}/in")
    cols = ["user_id", "start", "end", "n"]
    got = {tuple(r) for r in run_stream(spark, histograms.sessions(stream, late="1 day")).select(cols).where("user_id >= 0").collect()}
    assert got == {tuple(r) for r in histograms.sessions(events).select(cols).collect()}


def test_stream_meets_static_table_and_other_stream(spark, tmp_path):
    t = lambda d, h=0: pd.Timestamp(2024, 1, d, h)
    edits = pd.DataFrame({"topic_id": [1, 1, 2], "ts": [t(1), t(9), t(3)]})
    crawls = pd.DataFrame({"topic_id": [1, 1, 2, 3], "ts": [t(2), t(8, 1), t(20), t(4)]})
    schema = "topic_id long, ts timestamp"
    e, c = staged(spark, tmp_path / "e", schema)(edits), staged(spark, tmp_path / "c", schema)(crawls)
    got = {(r.topic_id, r.edit_ts.day, r.crawl_ts.day) for r in run_stream(spark, histograms.edits_meet_crawls(e, c, late="30 days")).collect()}
    batch = histograms.edits_meet_crawls(spark.read.schema(schema).parquet(f"{tmp_path}/e"), spark.read.schema(schema).parquet(f"{tmp_path}/c"))
    assert got == {(r.topic_id, r.edit_ts.day, r.crawl_ts.day) for r in batch.collect()} == {(1, 1, 2)}
    known = spark.createDataFrame([(1, "a"), (3, "b")], "topic_id long, tag string")
    more = run_stream(spark, histograms.with_static(spark.readStream.schema(schema).parquet(f"{tmp_path}/c"), known, "topic_id"))
    assert sorted((r.topic_id, r.tag) for r in more.collect()) == [(1, "a"), (1, "a"), (3, "b")]


def test_late_rows_are_counted(spark, tmp_path):
    t = lambda d: pd.Timestamp(2024, 1, d)
    rows = pd.DataFrame({"event_type": ["a"] * 5, "ts": [t(1), t(10), t(11), t(2), t(12)]})
    stream = staged(spark, tmp_path / "in", "event_type string, ts timestamp")(rows)
    query = histograms.tumbling(stream, late="1 day").writeStream.format("memory").queryName("late").outputMode("append").trigger(availableNow=True).start()
    query.awaitTermination()
    assert histograms.late_rows(query) == 1
    assert {r.start.day: r.n for r in spark.table("late").collect()}.get(1) == 1


def test_costs_of_a_run(spark):
    from vintage.operators.costs import run_cost

    cost = run_cost(lambda: spark.range(100_000).repartition(4, "id"), spark)
    assert cost.seconds > 0 and cost.shuffle_bytes > 100_000
    assert run_cost(lambda: spark.range(10), spark).shuffle_bytes == 0


def test_scratch_is_released(spark):
    from pathlib import Path

    before = len(tables.scratch())
    kept = tables.stored(spark.range(3).toDF("id"))
    paths = [p.removeprefix("file://") for p in tables.scratch()[before:]]
    assert kept.count() == 3 and all(Path(p).exists() for p in paths)
    assert tables.release(spark, before) == 1 and not any(Path(p).exists() for p in paths) and len(tables.scratch()) == before


def test_nothing_imports_the_optional_part():
    from pathlib import Path

    import vintage

    root = Path(vintage.__file__).parent
    for path in root.rglob("*.py"):
        if "llm" not in path.relative_to(root).parts:
            assert "llm" not in path.read_text().split("import", 1)[-1].split() and ".llm" not in path.read_text(), path


def test_running_nearest_months(spark, tmp_path):
    rows = pd.DataFrame({"doc_id": [1, 1, 1, 2], "month_ix": [5, 7, 9, 3], "dist": [4, 2, 2, 8]})
    df = spark.createDataFrame(rows, "doc_id long, month_ix int, dist int")
    df.write.parquet(f"{tmp_path}/m")
    stream = spark.readStream.schema(df.schema).parquet(f"{tmp_path}/m")
    got = {r.doc_id: (r.dist, r.months) for r in run_stream(spark, histograms.nearest_months(stream), "update").collect()}
    assert got == {1: (2, "7,9"), 2: (8, "3")}


def test_additive_sink(spark, tmp_path):
    write = histograms.add_counts(f"{tmp_path}/counts")
    batch = spark.createDataFrame([("a", 2)], "gram string, n long")
    for number in (0, 1, 1):
        write(batch, number)
    assert spark.read.parquet(f"{tmp_path}/counts").agg(F.sum("n")).first()[0] == 4


def test_leaving_out_the_optional_part():
    import __spark_entry__

    assert set(workloads.QUERIES) <= set(__spark_entry__.queries())
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())
