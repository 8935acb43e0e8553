"""Hand-made cases and invariants of the methods."""

import math
import random

import pytest
from pyspark.sql import functions as F

from curator.operators.ranks import ranked_in_ranges
from curator.operators import blocks, embed, kmeans, packing, samples, scoring, select


def test_three_token_example(spark):
    lp = spark.createDataFrame([(1, 1, math.log(1 / 2), math.log(1 / 4)), (1, 2, math.log(1 / 4), math.log(1 / 4)), (1, 3, math.log(1 / 8), math.log(1 / 16))], "sample_id long, pos int, lp_with double, lp_without double")
    r = scoring.difficulty(lp).first()
    assert r.ppl_with == pytest.approx(4) and r.ppl_without == pytest.approx(2 ** (8 / 3)) and r.ifd == pytest.approx(2 ** (-2 / 3))


def test_empty_instruction_has_difficulty_one(spark):
    toks = spark.createDataFrame([(["a", "b", "a"],), (["b", "c"],)], "t array<string>")
    pairs = spark.createDataFrame([(1, [], ["a", "b", "zz"]), (2, ["c"], ["a"])], "sample_id long, instr array<string>, resp array<string>")
    got = {r.sample_id: r.ifd for r in scoring.difficulty(scoring.NGramScorer.of_arrays(toks).score(pairs)).collect()}
    assert got[1] == pytest.approx(1.0) and got[2] > 0


def test_probabilities_sum_to_one(spark):
    toks = spark.createDataFrame([(["a", "b", "a", "c"],), (["b", "c", "d"],)], "t array<string>")
    model = scoring.NGramScorer.of_arrays(toks)
    vocab = ["a", "b", "c", "d", "unseen"]
    for history in (["a"], ["d"], ["unseen", "b"], []):
        rows = spark.createDataFrame([(i, history, [w]) for i, w in enumerate(vocab)], "sample_id long, instr array<string>, resp array<string>")
        assert model.score(rows).agg(F.sum(F.exp("lp_with"))).first()[0] == pytest.approx(1.0)


@pytest.mark.parametrize(("rounding", "want"), [("ceil", [2, 2]), ("floor", [1, 1]), ("round", [2, 2]), ("largest_remainder", [2, 1])])
def test_quota_rounding(spark, rounding, want):
    rows = spark.createDataFrame([(i, i // 5, float(i)) for i in range(10)], "sample_id long, cluster_id int, ifd double")
    got = select.select_stratified(rows, 30, rounding=rounding).groupBy("cluster_id").count().orderBy("cluster_id").collect()
    assert [r["count"] for r in got] == want


def test_ties_go_to_the_lowest_id_in_both_plans(spark):
    rows = spark.createDataFrame([(i, 0, 1.0) for i in range(10)], "sample_id long, cluster_id int, ifd double")
    for plan in ("window", "threshold"):
        assert sorted(r.sample_id for r in select.select_stratified(rows, 30, plan=plan).collect()) == [0, 1, 2]


def test_threshold_equals_window(spark):
    rng = random.Random(1)
    rows = spark.createDataFrame([(i, rng.randrange(3), round(rng.random(), 2)) for i in range(2000)], "sample_id long, cluster_id int, ifd double")
    for pct in (7, 40):
        a, b = (sorted(map(tuple, select.select_stratified(rows, pct, plan=p).select("sample_id", "cluster_id", "rank").collect())) for p in ("window", "threshold"))
        assert a == b


LENS = [5, 4, 3, 3, 2, 1]


def _pack(spark, lens, context, **kw):
    b = spark.createDataFrame([(0, i, n) for i, n in enumerate(lens)], "batch_id long, sample_id long, n_tokens int")
    return packing.dynamic_pack(b, context, **kw)


def test_first_fit_example(spark):
    rows = _pack(spark, LENS, 8).orderBy("row_id").collect()
    assert [[s.length for s in r.segments] for r in rows] == [[5, 3], [4, 3, 1], [2]]
    assert [r.used for r in rows] == [8, 8, 2] and sum(r.pad for r in rows) == 6


def test_next_fit_example(spark):
    rows = _pack(spark, LENS, 8, fit="next", descending=False).orderBy("row_id").collect()
    assert [r.used for r in rows] == [6, 7, 5] and sum(r.pad for r in rows) == 3


def test_packing_may_lose_on_tiny_batches(spark):
    packed = packing.batch_layout(_pack(spark, [3, 3, 2], 5, fit="next", descending=False)).first()
    assert packed.rows * packed.width == 10


def test_oversize(spark):
    assert [r.oversize for r in _pack(spark, [9, 2], 8).orderBy("row_id").collect()] == [True, False]
    assert _pack(spark, [9, 2], 8, oversize="drop").count() == 1
    with pytest.raises(Exception, match="longer than the context"):
        _pack(spark, [9, 2], 8, oversize="fail").collect()


@pytest.mark.parametrize("fit", ["next", "first", "best"])
def test_every_sample_once_and_arrow_agrees(spark, fit):
    rng = random.Random(3)
    lens = [rng.randrange(1, 60) for _ in range(120)]
    native, arrow = (packing.segments(_pack(spark, lens, 64, fit=fit, engine=e)) for e in ("native", "arrow"))
    a, b = (sorted(map(tuple, x.collect())) for x in (native, arrow))
    assert a == b and sorted(r[2] for r in a) == list(range(120))
    assert native.groupBy("row_id").agg(F.sum("length").alias("u")).agg(F.max("u")).first()[0] <= 64


def test_global_rank_equals_direct_window(spark):
    rows = spark.createDataFrame([(i, (i * 37) % 11) for i in range(500)], "sample_id long, n_tokens int")
    got = [r.sample_id for r in packing.global_rank(rows, F.col("n_tokens"), [F.col("sample_id")]).orderBy("rank").collect()]
    assert got == [i for _, i in sorted(((i * 37) % 11, i) for i in range(500))]


def test_kmeans_cost_never_rises_and_empty_input(spark, sf):
    v = embed.table_vectors(spark.read.parquet(f"{sf}/embeddings.parquet"))
    cost = [kmeans.report(kmeans.assign(v, kmeans.fit(v, 5, i))).agg(F.sum("sse")).first()[0] for i in (1, 3, 6)]
    assert cost == sorted(cost, reverse=True)
    assert kmeans.fit(v.limit(0), 5, 2) == []
    assert len(kmeans.fit(v.limit(3), 5, 2)) == 3


def test_empty_pairs(spark):
    empty = spark.createDataFrame([], "conv_id long, turn long, role string, text string")
    pairs = samples.token_pairs(samples.build_pairs(empty))
    assert pairs.count() == 0
    assert packing.dynamic_pack(packing.form_batches(samples.sample_lengths(pairs))).count() == 0


def _skewed(spark, n=4000):
    """Nearly all rows in one cluster, with one outlying score and a score that half of the rows have."""
    rows = [(i, 0 if i % 50 else 1, 1e9 if i == 7 else 0.5 if i % 2 else (i * 7919 % 1000) / 1000) for i in range(n)]
    return spark.createDataFrame(rows, "sample_id long, cluster_id int, ifd double").repartition(6)


def test_threshold_plan_deals_a_hot_cluster_and_score_evenly(spark):
    rows = _skewed(spark)
    for quota in ({"rate_pct": 40}, {"budget": 777}, {"count": 30}):
        for order in ("desc", "asc"):
            a, b = (sorted(map(tuple, select.select_stratified(rows, plan=p, order=order, **quota).select("sample_id", "cluster_id", "rank").collect())) for p in ("window", "threshold"))
            assert a == b and a
    sizes = ranked_in_ranges(rows, ["cluster_id"], [F.col("ifd"), F.col("sample_id")])
    assert sizes.select("cluster_id", "rank").distinct().count() == 4000
    wide = spark.conf.get("spark.sql.adaptive.enabled")
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    try:
        dealt = rows.repartitionByRange("cluster_id", "ifd", "sample_id").groupBy(F.spark_partition_id()).count().agg(F.max("count")).first()[0]
    finally:
        spark.conf.set("spark.sql.adaptive.enabled", wide)
    assert dealt < 2000  # of 4,000 rows over four partitions


def test_threshold_plan_sorts_stored_ranges_only(spark):
    plan = select.select_stratified(_skewed(spark), 40, plan="threshold")._jdf.queryExecution().optimizedPlan().toString()
    assert "Python" not in plan and plan.count("Window") == 1 and "row_number" not in plan  # the window adds up one row per range


def test_approximate_plan_keeps_the_quota_within_its_bound(spark):
    rows = spark.createDataFrame([(i, i % 3, (i * 7919 % 6007) / 6007) for i in range(6000)], "sample_id long, cluster_id int, ifd double")
    slack = 2000 / select.STEPS + 2 * 2000 / select.ACCURACY + 1
    for quota, want in (({"rate_pct": 40}, 800), ({"budget": 300}, 100), ({"count": 50}, 50), ({"rate_pct": 100}, 2000), ({"count": 0}, 0)):
        for order in ("desc", "asc"):
            kept = select.select_stratified(rows, plan="approx", order=order, **quota)
            got = {r.cluster_id: r for r in kept.groupBy("cluster_id").agg(F.count("*").alias("n"), F.min("ifd").alias("lo"), F.max("ifd").alias("hi")).collect()}
            assert all(abs((got[c].n if c in got else 0) - want) <= slack for c in range(3)), (quota, order)
            if 0 < want < 2000:
                assert all(r.lo > 0.5 if order == "desc" else r.hi < 0.5 for r in got.values())


def test_quotas_of_very_many_samples(spark):
    sizes = spark.createDataFrame([(0, 10**10), (1, 5 * 10**9), (2, 3 * 10**11)], "cluster_id int, n long")
    got = {r.cluster_id: r.quota for r in select.quotas(sizes, budget=6 * 10**9).collect()}
    assert sum(got.values()) == 6 * 10**9 and abs(got[2] - 6 * 10**9 * 300 / 315) <= 1
    assert sum(r.quota for r in select.quotas(sizes, rate_pct=40, rounding="largest_remainder").collect()) == 126 * 10**9


def test_global_rank_of_equal_and_outlying_lengths(spark):
    rows = spark.createDataFrame([(i, 10**6 if i == 3 else 512 if i % 3 else i % 40) for i in range(3000)], "sample_id long, n_tokens int").repartition(5)
    got = packing.global_rank(rows, F.col("n_tokens"), [F.col("sample_id")]).collect()
    order = sorted((r.n_tokens, r.sample_id) for r in got)
    assert [r.rank for r in sorted(got, key=lambda r: (r.n_tokens, r.sample_id))] == list(range(3000)) and order[-1] == (10**6, 3)


def test_kmeans_updates_agree(spark, sf):
    v = embed.table_vectors(spark.read.parquet(f"{sf}/embeddings.parquet"))
    a, b = (kmeans.fit(v, 4, 3, update=u) for u in ("average", "summarizer"))
    assert all(x == pytest.approx(y) for c, d in zip(a, b, strict=True) for x, y in zip(c, d, strict=True))
    far = [[0.0, 0.0], [1.0, 1.0], [50.0, 50.0]]
    points = spark.createDataFrame([(i, p) for i, p in enumerate([[0.0, 0.0], [1.0, 1.0], [0.0, 0.0], [1.0, 1.0]])], "sample_id long, v array<double>")
    assert kmeans.fit(points, 3, 5)[2] == [0.0, 0.0] and len(far) == 3  # an empty cluster keeps its centroid
    assert kmeans.fit(points, 2, 50, tol=0.0) == kmeans.fit(points, 2, 1)  # nothing moves after the first round
    assert 0 < len(kmeans.fit(v, 4, 2, fit_pct=30)) <= 4


def test_embeddings_of_instruction_and_response(spark):
    pairs = spark.createDataFrame([(1, ["a"], ["b"]), (2, ["a"], [])], "sample_id long, instr array<string>, resp array<string>")
    both = {r.sample_id: r.v for r in embed.hashed_vectors(pairs, 16, column="both").collect()}
    alone = {r.sample_id: r.v for r in embed.hashed_vectors(pairs, 16).collect()}
    assert both[2] == alone[2] and both[1] != alone[1]


def test_subword_mode_equals_the_library(spark, sf):
    import public_tokenizers
    from tokenizers import Tokenizer

    path = str(public_tokenizers.path("word_bpe_49k.json"))
    lib = Tokenizer.from_file(path)
    rows = [(1, "Sort the list, please", "def f(x): return sorted(x)"), (2, "", "é ß 漢字"), (3, None, "a" * 5000)]
    pairs = spark.createDataFrame(rows, "sample_id long, instruction string, response string")
    got = {r.sample_id: (r.instr, r.resp) for r in samples.token_pairs(pairs, "bpe", path).collect()}
    assert got == {i: tuple(lib.encode(t or "", add_special_tokens=False).tokens for t in (a, b)) for i, a, b in rows}
    with pytest.raises(ValueError, match="vocabulary"):
        samples.token_pairs(pairs, "bpe")


def test_micro_batches_are_packed_whole(spark, tmp_path):
    from curator.streaming.flows import pack_micro_batches

    for part in range(2):
        rows = spark.createDataFrame([(part * 50 + i, 1 + (i * 7) % 40) for i in range(50)], "sample_id long, n_tokens int")
        rows.coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    stream = spark.readStream.schema("sample_id long, n_tokens int").option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in")
    seen = []
    run = pack_micro_batches(lambda packed, epoch: seen.extend((epoch, *r) for r in packing.segments(packed).select("sample_id", "length").collect()), context=64, size=16)
    query = stream.writeStream.foreachBatch(run).option("checkpointLocation", f"{tmp_path}/state").trigger(availableNow=True).start()
    query.awaitTermination(120)
    assert sorted(s for _, s, _ in seen) == list(range(100)) and {e for e, _, _ in seen} == {0, 1}
    assert all(n == 1 + (s % 50 * 7) % 40 for _, s, n in seen)


def test_pack_buffer_emits_full_batches_and_the_rest_on_time(monkeypatch):
    import pandas as pd

    from curator.streaming.flows import PackBuffer

    class State:
        def __init__(self):
            self.now = []

        def get(self):
            return self.now

        def put(self, rows):
            self.now = rows

        def update(self, row):
            self.now = row

        def exists(self):
            return bool(self.now)

        def clear(self):
            self.now = []

    class Handle:
        def getListState(self, *_):
            return State()

        getValueState = getListState

        def registerTimer(self, at):
            self.timer = at

    class Clock:
        def getCurrentProcessingTimeInMs(self):
            return 1000

    monkeypatch.setattr(PackBuffer, "SIZE", 4)
    buffer, handle = PackBuffer(), Handle()
    buffer.init(handle)
    frame = lambda ids: pd.DataFrame({"sample_id": ids, "n_tokens": [i + 1 for i in ids]})
    first = list(buffer.handleInputRows((7,), iter([frame([0, 1, 2]), frame([3, 4, 5])]), Clock()))
    assert [f["sample_id"].tolist() for f in first] == [[0, 1, 2, 3]] and handle.timer == 1000 + PackBuffer.WAIT_MS
    rest = list(buffer.handleExpiredTimer((7,), Clock(), None))
    assert [f["sample_id"].tolist() for f in rest] == [[4, 5]] and rest[0]["batch"].tolist() == [1, 1]
    assert list(buffer.handleExpiredTimer((7,), Clock(), None)) == []


def test_padding_comparison_keeps_long_samples(spark, monkeypatch):
    from curator.plans import workloads

    lengths = [300, 200, 700, 100, 512]
    n = spark.createDataFrame(list(enumerate(lengths)), "sample_id long, n_tokens int")
    monkeypatch.setattr(workloads.m, "lengths", lambda s, d, data: n)
    monkeypatch.setattr(workloads, "PAD_CONTEXTS", (512, 1024), raising=False)
    monkeypatch.setattr(workloads, "PAD_SIZES", (16,), raising=False)
    got = {(r.context, r.layout): r for r in workloads.padding_comparison(spark, "").filter("dataset = 'pairs' and batch = 16").collect()}
    assert {k for c, k in got if c == 512} == {"pad_longest", "pad_model_max", "fixed_pack", "next_fit_asc", "next_fit_desc", "first_fit_desc", "best_fit_desc"}
    cells = {k: got[512, k].cells for c, k in got if c == 512}
    assert cells["pad_longest"] == 5 * 700 and cells["pad_model_max"] == 5 * 512 and got[512, "pad_model_max"].truncated == 188
    # Descending: 700 alone, 512 alone, then 300 + 200 and 100.
    assert cells["first_fit_desc"] == cells["best_fit_desc"] == cells["next_fit_desc"] == 4 * 700 and cells["next_fit_asc"] == 4 * 700
    assert all((r.long_samples, r.long_tokens) == ((0.2, round(700 / 1812, 6)) if c == 512 else (0, 0)) for (c, _), r in got.items())


def test_difficulty_in_slices_is_that_of_all_samples(spark, monkeypatch):
    """Slices cover every sample once with the same scores, unknown words and unknown predecessors included."""
    toks = spark.createDataFrame([(["a", "b", "<unk>", "a"],), (["b", "a", "c"],), (["<unk>", "b"],)], "t array<string>")
    rows = [(i, ["a", "zz"][: i % 3], [["b", "a", "b", "yy"], ["yy", "yy", "a"], ["<unk>", "c"]][i % 3]) for i in range(40)]
    made = spark.createDataFrame(rows, "sample_id long, instr array<string>, resp array<string>")
    model = scoring.NGramScorer.of_arrays(toks)
    whole = {r.sample_id: tuple(r) for r in scoring.difficulty(model.score(made)).collect()}
    monkeypatch.setattr(scoring, "SLICE_TOKENS", 20)
    out = scoring.difficulty_in_slices(model, made)
    got = [tuple(r) for r in out.collect()]
    assert len(got) == len(whole) == 40 and len(out.inputFiles()) > 4 and all(r == pytest.approx(whole[r[0]]) for r in got)


def test_scores_of_chunks_are_those_of_token_rows(spark):
    """Chunks of whole samples give the scores that joins of token rows give, with unknown words and without an instruction; no window puts token rows in order."""
    toks = spark.createDataFrame([(["a", "b", "a", "c"],), (["b", "c", "d", "b", "a"],), ([],)], "t array<string>")
    rows = [(i, ["a", "zz", "b"][: i % 4], [["b", "a", "b", "yy"], ["yy", "yy", "a"], ["d"]][i % 3]) for i in range(30)]
    made = spark.createDataFrame(rows, "sample_id long, instr array<string>, resp array<string>").coalesce(1)
    for least in (1, 2):
        model = scoring.NGramScorer.of_arrays(toks, least)
        got, want = ({(r.sample_id, r.pos): (r.lp_with, r.lp_without) for r in f(made).collect()} for f in (model.score, model._score_rows))
        assert got.keys() == want.keys() and all(got[k] == pytest.approx(want[k], abs=1e-12) for k in got)
    assert "Window" not in model.score(made)._jdf.queryExecution().executedPlan().toString()


def test_chunks_hold_whole_texts_and_all_of_them(monkeypatch):
    import pyarrow as pa

    monkeypatch.setattr(blocks, "CHUNK", 5)
    texts = [["a", "b"], ["c"], ["a"] * 7, [], ["b", "d"], ["e", "a"], ["f"]]
    batches = [pa.RecordBatch.from_pydict({"id": list(range(i, i + len(t))), "aux": [0] * len(t), "t": t}, pa.schema({"id": pa.int64(), "aux": pa.int64(), "t": pa.list_(pa.string())})) for i, t in ((0, texts[:4]), (4, texts[4:]))]
    made = list(blocks.text_chunks(batches))
    assert len(made) > 2 and [i for m in made for i in m[0]] == list(range(7))
    assert [w for m in made for w in m[5][m[3]]] == [w for t in texts for w in t] and [n for m in made for n in m[2]] == [len(t) for t in texts]


def test_text_of_characters_has_pairs_of_neighbours():
    import pyarrow as pa

    batch = pa.RecordBatch.from_pydict({"id": [1, 2, 3, 4], "aux": [0, 0, 0, 0], "t": ["abca", "", "\U0001f600b", "x"]})
    (_, _, lens, codes, words, _), = blocks.text_chunks([batch])
    assert lens.tolist() == [3, 0, 1, 0] and [chr(w >> 21) + chr(w & 0x1FFFFF) for w in words[codes]] == ["ab", "bc", "ca", "\U0001f600b"]


def test_kmeans_by_batches_is_that_of_rows(spark, monkeypatch):
    v = spark.createDataFrame([(i, [float(i % 7), float(i * i % 5), 1.0]) for i in range(60)] + [(60, [1.0, None, 2.0]), (61, None)], "sample_id long, v array<double>")
    some = [[0.0, 1.0, 1.0], [3.0, 3.0, 1.0], [3.0, 3.0, 1.0]]
    got = sorted(map(tuple, kmeans.assign(v, some).drop("v").collect()))
    whole = kmeans.fit(v.filter("sample_id < 60"), 4, 4)
    monkeypatch.setattr(kmeans, "_regular", lambda *_: False)
    assert got == sorted(map(tuple, kmeans.assign(v, some).drop("v").collect()))
    assert whole == [pytest.approx(c) for c in kmeans.fit(v.filter("sample_id < 60"), 4, 4)]
