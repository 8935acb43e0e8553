"""Scorers, encoders, SQL functions, sinks, readers, views and streaming forms as a user would call them."""

import math
import time

import pandas as pd
import pytest
from pyspark.sql import functions as F

from curator.functions import sql as sql_functions
from curator.operators import embed, evaluate, kmeans, packing, scoring
from curator.sources import checkpoints, sinks, tables
from curator.streaming import flows

PAIRS = "sample_id long, instr array<string>, resp array<string>"


def test_table_and_function_scorers(spark):
    lp = spark.createDataFrame([(1, 1, -1.0, -2.0), (1, 2, -1.0, -2.0), (2, 1, -3.0, -1.0), (9, 1, 0.0, 0.0)], tables.SCHEMAS["token_logprobs"])
    pairs = spark.createDataFrame([(1, ["a"], ["b", "c"]), (2, [], ["d"])], PAIRS)
    got = {r.sample_id: r.ifd for r in scoring.difficulty(scoring.TableScorer(lp).score(pairs)).collect()}
    assert got == {1: pytest.approx(math.exp(-1.0)), 2: pytest.approx(math.exp(2.0))}

    def halves(frames):
        for frame in frames:
            rows = [(i, p + 1, math.log(0.5), math.log(0.25)) for i, r in zip(frame["sample_id"], frame["resp"], strict=True) for p in range(len(r))]
            yield pd.DataFrame(rows, columns=["sample_id", "pos", "lp_with", "lp_without"])

    rows = scoring.difficulty(scoring.FunctionScorer(halves).score(pairs)).collect()
    assert {r.sample_id: (r.n_tokens, round(r.ifd, 9)) for r in rows} == {1: (2, 0.5), 2: (1, 0.5)}


def test_function_vectors(spark):
    def lengths(texts):
        for t in texts:
            yield t.map(lambda x: [float(len(x)), 1.0])

    rows = embed.function_vectors(spark.createDataFrame([(1, "abc"), (2, "")], "sample_id long, instruction string"), lengths).collect()
    assert {r.sample_id: r.v for r in rows} == {1: [3.0, 1.0], 2: [0.0, 1.0]}


def test_sql_functions_and_table_function(spark):
    sql_functions.register(spark)
    r = spark.sql("SELECT ifd(array(-1D, -1D), array(-2D, -2D)) a, l2(array(0D, 3D), array(4D, 0D)) b, padding(30, 40) c, padding(0, 0) d").first()
    assert (round(r.a, 9), r.b, r.c, r.d) == (round(math.exp(-1), 9), 5.0, 0.25, 0.0)
    spark.createDataFrame([(0, i, n) for i, n in enumerate([3000, 2000, 1500, 1000, 900])] + [(1, 9, 5)], "batch_id long, sample_id long, n_tokens int").createOrReplaceTempView("to_pack")
    rows = spark.sql("SELECT * FROM pack_rows(TABLE(to_pack) PARTITION BY batch_id ORDER BY (n_tokens DESC, sample_id))").collect()
    assert sorted(map(tuple, rows)) == [(0, 0, 0, 3000), (0, 3, 3000, 1000), (0, 9, 0, 5), (1, 1, 0, 2000), (1, 2, 2000, 1500), (2, 4, 0, 900)]


def test_sinks_readers_and_views(spark, tmp_path):
    picked = spark.createDataFrame([(1, "combined", 40), (2, "random", 40)], "sample_id long, strategy string, rate_pct int")
    sinks.write_selection(picked, f"{tmp_path}/selection")
    assert sorted(map(tuple, spark.read.parquet(f"{tmp_path}/selection").select("sample_id", "strategy", "rate_pct").collect())) == [(1, "combined", 40), (2, "random", 40)]
    samples = spark.createDataFrame([(1, "ask", "answer"), (2, "", "x")], tables.SCHEMAS["samples"])
    sinks.write_jsonl(samples, f"{tmp_path}/samples")
    assert sorted(map(tuple, tables.read_samples(spark, f"{tmp_path}/samples").collect())) == [(1, "ask", "answer"), (2, "", "x")]
    for fmt in ("csv", "orc", "parquet"):
        samples.filter("sample_id = 1").write.format(fmt).option("header", True).save(f"{tmp_path}/{fmt}")
        assert tables.read_samples(spark, f"{tmp_path}/{fmt}", fmt).collect() == [(1, "ask", "answer")]
    lens = spark.createDataFrame([(i, 100 + i) for i in range(20)], "sample_id long, n_tokens int")
    packed = packing.dynamic_pack(packing.form_batches(lens, 8), 512)
    sinks.write_packed(packed, f"{tmp_path}/packed", 3)
    assert spark.read.parquet(f"{tmp_path}/packed").agg(F.sum("used")).first()[0] == sum(100 + i for i in range(20))
    for rows in (2, 5):
        sinks.write_manifest(spark, f"{tmp_path}/manifest", "packed", rows, context=512)
    assert sorted(r.n_rows for r in spark.read.json(f"{tmp_path}/manifest").collect()) == [2, 5]
    sinks.register_views(spark, seen_samples=samples)
    assert spark.table("seen_samples").count() == 2
    with pytest.raises(ValueError, match="missing columns"):
        tables.require(samples, "sample_id", "nothing")


def test_stage_checkpoints_end_the_plan(spark):
    made = checkpoints.stage(spark.range(10).withColumn("x", F.col("id") * 2), "numbers")
    plan = made._jdf.queryExecution().optimizedPlan().toString()
    assert made.agg(F.sum("x")).first()[0] == 90 and "Range" not in plan


def test_savings_and_best_strategy(spark):
    assert evaluate.savings(47, 34) == pytest.approx(0.2766, abs=1e-4) and evaluate.savings(0, 1) == 0
    rows = spark.createDataFrame([("d", "m", "a", 30, 1.0), ("d", "m", "b", 40, 2.0), ("d", "m", "c", 60, 9.0)], "dataset string, model string, strategy string, rate_pct int, value double")
    assert [(r.strategy, r.value) for r in evaluate.best_strategy(rows, 40).collect()] == [("b", 2.0)]


def test_models_side_by_side_equal_single_ones(spark):
    train = spark.createDataFrame([("a", ["x", "y", "x", "z"]), ("a", ["y", "y"]), ("b", ["z"]), ("b", [])], "variant string, t array<string>")
    held = spark.createDataFrame([(1, ["x", "y", "q", "q", "x"]), (2, ["z", "z"])], "id long, t array<string>")
    got = {r.variant: (r.heldout_ppl, r.greedy_accuracy) for r in evaluate.heldout_by_variant(train, held, ["a", "b"]).collect()}
    for v in ("a", "b"):
        ppl, hits = evaluate.heldout_quality(train.filter(F.col("variant") == v), held)
        assert got[v] == (pytest.approx(ppl.first().value), pytest.approx(hits.first().value))


def test_online_selection_equals_batch(spark, tmp_path):
    rows = spark.createDataFrame([(i, [float(i % 2), 0.0], i / 10) for i in range(20)], "sample_id long, v array<double>, ifd double")
    rows.write.parquet(f"{tmp_path}/scored")
    stream = spark.readStream.schema(rows.schema).parquet(f"{tmp_path}/scored")
    got = flows.drain(flows.online_selection(stream, [[0.0, 0.0], [1.0, 0.0]], {0: 1.0, 1: 1.5}), "append").collect()
    assert sorted(map(tuple, got)) == [(i, i % 2, i / 10) for i in range(20) if i / 10 >= (1.5 if i % 2 else 1.0)]


def test_drift(spark):
    rows = spark.sql("SELECT timestamp'2024-01-01 01:00:00' ts, 0 cluster_id UNION ALL SELECT timestamp'2024-01-01 02:00:00', 1 UNION ALL SELECT timestamp'2024-01-02 01:00:00', 1")
    got = [r.tv for r in flows.drift(rows, {0: 0.5, 1: 0.5}).orderBy("start_ts").collect()]
    assert got == [0.0, 0.5]


def test_stateful_packing_in_a_running_query(spark, tmp_path):
    """Samples of several files leave the buffer in full batches; what is left over stays in the state."""
    pytest.importorskip("google.protobuf")
    for part in range(3):
        spark.createDataFrame([(part * 5 + i, 10 + i, 0) for i in range(5)], "sample_id long, n_tokens int, key int").coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")

    class Small(flows.PackBuffer):
        SIZE, WAIT_MS = 4, 3_600_000

    provider = "spark.sql.streaming.stateStore.providerClass"
    spark.conf.set(provider, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        stream = spark.readStream.schema("sample_id long, n_tokens int, key int").option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in")
        made = stream.groupBy("key").transformWithStateInPandas(Small(), "key int, batch long, sample_id long, n_tokens int", "append", "processingTime")
        query = made.writeStream.format("memory").queryName("packed_stream").outputMode("append").start()
        # Waiting timers keep the query alive, so it is stopped here.
        ends = time.time() + 60
        while time.time() < ends and query.isActive and spark.table("packed_stream").count() < 12:
            time.sleep(1)
        query.stop()
        assert query.exception() is None
        rows = spark.table("packed_stream").collect()
    finally:
        spark.conf.unset(provider)
    assert len(rows) == 12 and {r.batch for r in rows} == {0, 1, 2} and len({r.sample_id for r in rows}) == 12




def test_micro_batches_carry_the_rest(spark, tmp_path):
    out = []
    run = flows.pack_micro_batches(lambda rows, epoch: out.append((epoch, sorted(r.sample_id for r in packing.segments(rows).collect()))), 512, 4, f"{tmp_path}/carry")
    for epoch, ids in enumerate(([0, 1, 2], [3, 4], [], [5, 6, 7, 8])):
        run(spark.createDataFrame([(i, 10) for i in ids], "sample_id long, n_tokens int"), epoch)
    run(spark.createDataFrame([(i, 10) for i in [5, 6, 7, 8]], "sample_id long, n_tokens int"), 3)  # a repeated one
    assert out == [(0, []), (1, [0, 1, 2, 3]), (2, []), (3, [4, 5, 6, 7]), (3, [4, 5, 6, 7])]
    assert [r.sample_id for r in spark.read.parquet(f"{tmp_path}/carry/epoch=3").collect()] == [8]


def test_stream_joins_a_table(spark, tmp_path):
    spark.createDataFrame([(1, 10), (2, 20), (9, 90)], "user_id long, event_id long").write.parquet(f"{tmp_path}/events")
    users = spark.createDataFrame([(1, "a"), (2, "b")], "user_id long, name string")
    stream = spark.readStream.schema("user_id long, event_id long").parquet(f"{tmp_path}/events")
    assert sorted(map(tuple, flows.drain(flows.with_reference(stream, users), "append").fillna("-").collect())) == [(1, 10, "a"), (2, 20, "b"), (9, 90, "-")]


def test_models_side_by_side_share_their_rows(spark):
    """A text of several models is read once, and the measures are those of each model alone, with unknown words and an empty model."""
    texts = [(["a", "b"], "x y z x y".split()), (["a"], "z z y q".split()), (["b"], "y x q q z".split()), (["a", "b"], [])]
    train = spark.createDataFrame(texts, "variants array<string>, t array<string>")
    held = spark.createDataFrame([(1, "x y new z other z new x".split()), (2, "q q odd x".split()), (3, [])], "id long, t array<string>")
    made, stage = {}, evaluate.stage
    evaluate.stage = lambda df, name: made.setdefault(name, stage(df, name))
    try:
        got = {r.variant: (r.heldout_ppl, r.greedy_accuracy) for r in evaluate.heldout_by_variant(train, held, ["a", "b", "none"]).collect()}
    finally:
        evaluate.stage = stage
    assert set(got) == {"a", "b"}
    for name, values in got.items():
        own = spark.createDataFrame([(t,) for v, t in texts if name in v], "t array<string>")
        assert values == pytest.approx(tuple(x.first().value for x in evaluate.heldout_quality(own, held)), abs=1e-9)
    pairs = {p for _, t in texts for p in zip(["<s>", *t], t, strict=False)}
    assert made["bigrams"].count() == len(pairs)  # one row per pair, however many models count it
    assert checkpoints.CLEANUP.endswith("fileCleanup.enabled") and spark.conf.get(checkpoints.CLEANUP, "false") == "false"
