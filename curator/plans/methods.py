"""Queries of the methods, variants, baselines and measures."""

from __future__ import annotations

from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from curator.functions.expr import cosine, dot, norm, squared_distance, tokens
from curator.operators import embed, evaluate, kmeans, packing, samples, scoring, select
from curator.plans import oracles as o
from curator.sources.checkpoints import stage
from curator.sources.tables import page_text, read_table

K, ITERS = 10, 10


def six(df: DataFrame) -> DataFrame:
    return df.select(*(F.round(c, 6).alias(c) if t in ("double", "float") else F.col(c) for c, t in df.dtypes))


def text_pairs(spark: SparkSession, d: str, context: str = "last_user") -> DataFrame:
    return samples.build_pairs(read_table(spark, d, "conversations"), context)


def subword_lengths(spark: SparkSession, d: str) -> DataFrame:
    import public_tokenizers

    made = samples.token_pairs(text_pairs(spark, d), "bpe", str(public_tokenizers.path("word_bpe_49k.json")))
    return samples.sample_lengths(made).select("sample_id", "n_instr", "n_resp")


def pairs(spark: SparkSession, d: str, data: str = "pairs") -> DataFrame:
    if data == "documents":
        return samples.build_doc_pairs(read_table(spark, d, "documents"))
    return samples.token_pairs(text_pairs(spark, d))


def logprobs(spark: SparkSession, d: str, data: str = "pairs", mode: str = "word") -> DataFrame:
    return scoring.NGramScorer.fit(read_table(spark, d, "documents")).score(pairs(spark, d, data))


def corpus_model(spark: SparkSession, d: str) -> scoring.NGramScorer:
    return scoring.NGramScorer.fit(read_table(spark, d, "documents"))


def scores(spark: SparkSession, d: str, data: str = "pairs", model: scoring.NGramScorer | None = None) -> DataFrame:
    """Stored scores by ``model``, or by one of the corpus that goes afterwards."""
    samples_ = pairs(spark, d, data)
    own = model or corpus_model(spark, d)
    # Documents are cut into tokens slice by slice; turns would be put in order anew for every slice.
    out = scoring.difficulty_in_slices(own, samples_ if data == "documents" else stage(samples_, "samples"))
    if model is None:
        own.let_go(model=True)
    return out


def vectors(spark: SparkSession, d: str, data: str = "pairs", weight: str = "count", column: str = "instr") -> DataFrame:
    return embed.hashed_vectors(pairs(spark, d, data), weight=weight, column=column)


def clusters(spark: SparkSession, d: str, data: str = "pairs", k: int = K, init: str = "first") -> DataFrame:
    v = stage(vectors(spark, d, data), "vectors")
    return kmeans.assign(v, kmeans.fit(v, k, ITERS, init)).drop("v")


def scored(spark: SparkSession, d: str, data: str = "pairs", k: int = K, model: scoring.NGramScorer | None = None) -> DataFrame:
    """``sample_id, ifd, cluster_id, dist``, stored: every selection and measure behind it reads one narrow table."""
    return stage(scores(spark, d, data, model).select("sample_id", "ifd").join(clusters(spark, d, data, k), "sample_id"), "scored")


def lengths(spark: SparkSession, d: str, data: str = "pairs") -> DataFrame:
    return samples.sample_lengths(pairs(spark, d, data))


def batches(spark: SparkSession, d: str, data: str = "pairs", size: int = 256, order: str = "id") -> DataFrame:
    return packing.form_batches(lengths(spark, d, data), size, order)


def _long(v: DataFrame) -> DataFrame:
    return six(v.select("sample_id", F.posexplode("v").alias("dim", "x")))


def _picked(df: DataFrame) -> DataFrame:
    return six(df.select("sample_id", "cluster_id", "ifd", "rank"))


def _strategy(fn, **kw):
    return lambda s, d: _picked(fn(scored(s, d), **kw))


def _packed(data: str, context: int, fit: str, descending: bool = True, **kw):
    return lambda s, d: packing.segments(packing.dynamic_pack(batches(s, d, data), context, fit, descending, **kw))


def _layouts(data: str, context: int):
    def run(s: SparkSession, d: str) -> DataFrame:
        b = batches(s, d, data)
        if data == "documents":
            b = packing.form_batches(lengths(s, d, data), 256)
        b = b.persist()
        made = {
            "pad_longest": packing.pad_layout(b),
            "pad_model_max": packing.pad_layout(b, context),
            "fixed_pack_stream": packing.fixed_pack(b, 512, "stream"),
            "fixed_pack": packing.fixed_pack(b, 512),
            "next_fit_asc": packing.batch_layout(packing.dynamic_pack(b, context, "next", False)),
            "first_fit_desc": packing.batch_layout(packing.dynamic_pack(b, context, "first")),
            "best_fit_desc": packing.batch_layout(packing.dynamic_pack(b, context, "best")),
        }
        parts = [packing.layout_report(v, k) for k, v in made.items()]
        out = parts[0]
        for p in parts[1:]:
            out = out.unionByName(p)
        return six(out)

    return run


def _one_layout(name: str, data: str, make):
    return lambda s, d: six(packing.layout_report(make(batches(s, d, data)), name))


def _results(s: SparkSession, d: str) -> DataFrame:
    r = read_table(s, d, "labels").join(read_table(s, d, "documents").select("doc_id", "lang"), "doc_id")
    return r.select(F.col("lang").alias("suite"), F.col("doc_id").alias("item_id"), (F.col("quality") == 1).alias("base_pass"), ((F.col("quality") == 1) & (F.col("toxic") == 0)).alias("extended_pass"))


def _benchmark_scores(s: SparkSession, d: str) -> DataFrame:
    return six(_results(s, d).groupBy("suite").agg(F.count(F.lit(1)).alias("n"), F.avg(F.col("base_pass").cast("int")).alias("pass_base"), F.avg(F.col("extended_pass").cast("int")).alias("pass_extended")))


def _vector_ops(s: SparkSession, d: str) -> DataFrame:
    v = read_table(s, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    w = v.select((F.col("vec_id") - 1).alias("vec_id"), F.col("v").alias("w"))
    return six(v.join(w, "vec_id").select("vec_id", dot(F.col("v"), F.col("w")).alias("dot"), norm(F.col("v")).alias("norm"), squared_distance(F.col("v"), F.col("w")).alias("l2sq"), cosine(F.col("v"), F.col("w")).alias("cos")))


def _fit_on_given(s: SparkSession, d: str, **kw) -> tuple[DataFrame, kmeans.Centroids]:
    v = embed.table_vectors(read_table(s, d, "embeddings"))
    return v, kmeans.fit(v, K, ITERS, **kw)


def _centroids(s: SparkSession, d: str) -> DataFrame:
    _, c = _fit_on_given(s, d)
    return six(s.createDataFrame([(i, j, float(x)) for i, row in enumerate(c) for j, x in enumerate(row)], "cluster_id int, dim int, x double"))


def _given_assign(s: SparkSession, d: str, **kw) -> DataFrame:
    v, c = _fit_on_given(s, d, **kw)
    return kmeans.assign(v, c).select("sample_id", "cluster_id")


def _library(s: SparkSession, d: str) -> DataFrame:
    v = embed.table_vectors(read_table(s, d, "embeddings"))
    return six(kmeans.report(kmeans.assign(v, kmeans.library_fit(v, K, ITERS))))


def _consistency(s: SparkSession, d: str) -> DataFrame:
    rows = scored(s, d).persist()
    made = {"combined": select.select_stratified(rows), "difficulty": select.select_difficulty(rows), "random": select.select_random(rows), "kmeans": select.select_cluster(rows)}
    out = None
    for name, sub in made.items():
        picked = rows.join(sub.select("sample_id"), "sample_id", "left_semi")
        part = select.consistency(rows, picked).select(F.lit(name).alias("strategy"), F.lit(40).alias("rate_pct"), "*")
        out = part if out is None else out.unionByName(part)
    return six(out)


def _complexity(s: SparkSession, d: str) -> DataFrame:
    rows = scored(s, d).persist()
    made = {"combined": select.select_stratified(rows), "difficulty": select.select_difficulty(rows), "random": select.select_random(rows), "kmeans": select.select_cluster(rows)}
    full = rows.agg(F.avg("ifd").alias("full_mean_ifd"))
    out = None
    for name, sub in made.items():
        part = sub.agg(F.avg("ifd").alias("mean_ifd")).select(F.lit(name).alias("strategy"), F.lit(40).alias("rate_pct"), "mean_ifd")
        out = part if out is None else out.unionByName(part)
    return six(out.join(full))  # one row beside four


def _render(s: SparkSession, d: str) -> DataFrame:
    p = pairs(s, d)
    rows = packing.dynamic_pack(batches(s, d), 512)
    made = packing.render_rows(rows, p.select("sample_id", F.concat("instr", "resp").alias("toks")))
    return made.select("batch_id", "row_id", F.size("tokens").alias("width"), F.md5(F.array_join("tokens", " ")).alias("digest"))


def _end_to_end(s: SparkSession, d: str) -> DataFrame:
    kept = select.select_stratified(scored(s, d), plan="threshold")
    chosen = stage(lengths(s, d), "lengths").join(kept.select("sample_id"), "sample_id", "left_semi")
    return packing.segments(packing.dynamic_pack(packing.form_batches(chosen), 4096))


QUERIES = {
    "pairs_last_user": text_pairs,
    "pairs_with_system": partial(text_pairs, context="with_system"),
    "pairs_history": partial(text_pairs, context="history"),
    "pairs_documents": lambda s, d: pairs(s, d, "documents").select("sample_id", F.size("instr").alias("n_instr"), F.size("resp").alias("n_resp"), F.md5(F.array_join("instr", " ")).alias("instr_md5")),
    "pairs_rejected": lambda s, d: samples.rejected_pairs(read_table(s, d, "conversations")),
    "token_counts": lambda s, d: lengths(s, d).select("sample_id", "n_instr", "n_resp"),
    "token_counts_space": lambda s, d: read_table(s, d, "documents").select("doc_id", F.size(tokens(F.col("text"), "space")).alias("n")),
    "token_counts_bpe": subword_lengths,
    "token_counts_char": lambda s, d: read_table(s, d, "documents").select("doc_id", F.size(tokens(F.col("text"), "char")).alias("n")),
    "sample_lengths": lengths,
    "vocab_counts": lambda s, d: read_table(s, d, "documents").select(F.explode(tokens(F.col("text"))).alias("tok")).groupBy("tok").agg(F.count(F.lit(1)).alias("n")).filter("n >= 20"),
    "token_logprobs": lambda s, d: six(logprobs(s, d)),
    "ppl_conditional": lambda s, d: six(scoring.perplexity(logprobs(s, d), "lp_with")),
    "ppl_unconditional": lambda s, d: six(scoring.perplexity(logprobs(s, d), "lp_without")),
    "ifd_scores": lambda s, d: six(scores(s, d)),
    "ifd_truncated": lambda s, d: six(scoring.difficulty(logprobs(s, d), 256, lengths(s, d))),
    "ifd_capped": lambda s, d: six(scores(s, d).filter("ifd < 1").select("sample_id", "ifd")),
    "ifd_profile": lambda s, d: six(scoring.difficulty_profile(scored(s, d))),
    "instr_embeddings": lambda s, d: _long(vectors(s, d)),
    "instr_embeddings_tfidf": lambda s, d: _long(vectors(s, d, weight="tfidf")),
    "given_embeddings": lambda s, d: _long(embed.table_vectors(read_table(s, d, "embeddings"))),
    "vector_ops": _vector_ops,
    "kmeans_centroids": _centroids,
    "kmeans_assign": _given_assign,
    "kmeans_assign_summarizer": partial(_given_assign, update="summarizer"),
    "kmeans_assign_hash_init": partial(_given_assign, init="hash"),
    "kmeans_assign_farthest_init": partial(_given_assign, init="farthest"),
    "kmeans_assign_cosine": partial(_given_assign, metric="cosine"),
    "kmeans_assign_pairs": lambda s, d: clusters(s, d).select("sample_id", "cluster_id"),
    "kmeans_report": lambda s, d: six(kmeans.report(clusters(s, d))),
    "kmeans_library": _library,
    "select_full": lambda s, d: six(scored(s, d).select("sample_id", "cluster_id", "ifd")),
    "select_stratified_40": _strategy(select.select_stratified),
    "select_stratified_30": _strategy(select.select_stratified, rate_pct=30),
    "select_threshold": _strategy(select.select_stratified, plan="threshold"),
    "select_easy": _strategy(select.select_stratified, order="asc"),
    "select_top1_cluster": _strategy(select.select_stratified, count=1),
    "select_budget": _strategy(select.select_stratified, budget=50),
    "select_rounding": _strategy(select.select_stratified, rounding="floor"),
    "select_rounding_half": _strategy(select.select_stratified, rounding="round"),
    "select_approx": _strategy(select.select_stratified, plan="approx"),
    "select_gated": lambda s, d: _picked(select.select_stratified(scored(s, d), eligible=lengths(s, d).filter("n_resp >= 50"))),
    "select_ifd_only": _strategy(select.select_difficulty),
    "select_random_40": _strategy(select.select_random),
    "select_kmeans_random": _strategy(select.select_cluster),
    "select_kmeans_central": _strategy(select.select_cluster, pick="central"),
    "rank_profile": lambda s, d: six(select.rank_profile(scored(s, d))),
    "consistency_clusters": _consistency,
    "complexity_gain": _complexity,
    "batches_256": batches,
    "batches_hash_64": lambda s, d: batches(s, d, size=64, order="hash"),
    "batches_length_64": lambda s, d: batches(s, d, size=64, order="length"),
    "pack_first_fit": _packed("pairs", 512, "first"),
    "pack_best_fit": _packed("pairs", 512, "best"),
    "pack_next_fit_asc": _packed("pairs", 512, "next", False),
    "pack_next_fit_desc": _packed("pairs", 512, "next"),
    "pack_documents": _packed("documents", 4096, "first"),
    "pack_oversize": _packed("documents", 1024, "first", oversize="drop"),
    "pack_segments": _packed("documents", 1024, "best"),
    "pack_arrow": _packed("pairs", 512, "first", engine="arrow"),
    "packed_render": _render,
    "loss_spans": lambda s, d: packing.loss_spans(packing.dynamic_pack(batches(s, d), 512), lengths(s, d)),
    "shard_balance": lambda s, d: packing.assign_shards(packing.dynamic_pack(batches(s, d), 512)).groupBy("shard").agg(F.count(F.lit(1)).alias("rows"), F.sum("used").alias("used"), F.sum("width").alias("cells")),
    "pad_longest": _one_layout("pad_longest", "pairs", packing.pad_layout),
    "pad_model_max": _one_layout("pad_model_max", "pairs", partial(packing.pad_layout, context=4096)),
    "pack_fixed_stream": _one_layout("pack_fixed_stream", "documents", partial(packing.fixed_pack, mode="stream")),
    "pack_fixed_cap": _one_layout("pack_fixed_cap", "documents", packing.fixed_pack),
    "padding_rate_pairs": _layouts("pairs", 512),
    "padding_rate_documents": _layouts("documents", 4096),
    "layout_cost": _one_layout("first_fit_desc", "pairs", lambda b: packing.batch_layout(packing.dynamic_pack(b, 512))),
    "layout_peak": _one_layout("first_fit_desc", "documents", lambda b: packing.batch_layout(packing.dynamic_pack(b, 4096))),
    "training_plan": lambda s, d: lengths(s, d).agg(F.count(F.lit(1)).alias("n")).select(F.inline(packing.training_plan(F.col("n")))).select("step", "epoch", F.round("lr", 12).alias("lr")),
    "pass_at_1": lambda s, d: six(evaluate.pass_at_1(_results(s, d))),
    "pass_at_k": lambda s, d: six(evaluate.pass_at_k(_results(s, d).groupBy("suite", F.pmod("item_id", F.lit(20)).alias("item")).agg(F.count(F.lit(1)).alias("n"), F.count_if("base_pass").alias("c")), 2)),
    "macro_average": lambda s, d: six(_benchmark_scores(s, d).select(F.expr("stack(2, 'base', pass_base, 'extended', pass_extended) AS (metric, v)")).groupBy("metric").agg(F.avg("v").alias("value"))),
    "benchmark_scores": _benchmark_scores,
    "page_text": lambda s, d: page_text(read_table(s, d, "pages")),
    "pipeline_end_to_end": _end_to_end,
}

_SEL = {k: v for k, v in o.ALL.items()}
_GIVEN = o.GIVEN | o.kmeans()


def _layout_sql(data: str, context: int) -> str:
    names = {"next_fit_asc": ("next", "ASC"), "first_fit_desc": ("first", "DESC"), "best_fit_desc": ("best", "DESC")}
    parts, outs = dict(o.batched(data)), []
    for name, (fit, direction) in names.items():
        own = o.packed(data, context, fit, direction)
        parts[f"items_{name}"], parts[f"st_{name}"] = own["items"], own["st"].replace("FROM items", f"FROM items_{name}").replace("JOIN items i", f"JOIN items_{name} i").replace("FROM st s", f"FROM st_{name} s")
        parts[f"pk_{name}"] = own["pk"].replace("FROM st", f"FROM st_{name}")
        outs.append(f"SELECT '{name}' AS layout, {o.MEASURES} FROM ({o.PACKED_BATCHES.replace('FROM pk', f'FROM pk_{name}')})")
    outs.append(f"SELECT 'pad_longest' AS layout, {o.MEASURES} FROM ({o.PADDED.format(w='max(n_tokens)', n='n_tokens')})")
    outs.append(f"SELECT 'pad_model_max' AS layout, {o.MEASURES} FROM ({o.PADDED.format(w=context, n=f'least(n_tokens, {context})')})")
    outs.append(f"SELECT 'fixed_pack_stream' AS layout, {o.MEASURES} FROM ({o.STREAMED})")
    parts |= _fixed_parts("fx")
    outs.append(f"SELECT 'fixed_pack' AS layout, {o.MEASURES} FROM ({_FIXED.replace('FXT', 'fx')})")
    return o.sql(parts, "\nUNION ALL\n".join(outs))


_FIXED = "SELECT f.batch_id, f.rows, 512 AS width, t.used, t.truncated FROM (SELECT batch_id, max(rows) AS rows FROM FXT GROUP BY batch_id) f JOIN (SELECT batch_id, sum(least(n_tokens, 512)) AS used, sum(n_tokens - least(n_tokens, 512)) AS truncated FROM ba GROUP BY batch_id) t USING (batch_id)"


def _fixed_parts(name: str) -> dict[str, str]:
    return {
        f"{name}_i": "SELECT batch_id, least(n_tokens, 512)::INTEGER AS n, row_number() OVER (PARTITION BY batch_id ORDER BY sample_id) AS rn FROM ba",
        name: f"""SELECT batch_id, 0::BIGINT AS rn, 0::BIGINT AS rows, 512 AS used FROM (SELECT DISTINCT batch_id FROM {name}_i)
  UNION ALL SELECT s.batch_id, i.rn, CASE WHEN s.used + i.n <= 512 THEN s.rows ELSE s.rows + 1 END, CASE WHEN s.used + i.n <= 512 THEN s.used + i.n ELSE i.n END
  FROM {name} s JOIN {name}_i i ON i.batch_id = s.batch_id AND i.rn = s.rn + 1""",
    }


def _one_sql(name: str, data: str, batches_sql: str, extra: dict[str, str] | None = None) -> str:
    return o.sql(o.batched(data) | (extra or {}), f"SELECT '{name}' AS layout, {o.MEASURES} FROM ({batches_sql})")


def _pack_sql(data: str, context: int, fit: str, direction: str = "DESC", where: str = "true") -> str:
    return o.sql(o.packed(data, context, fit, direction, where=where), 'SELECT batch_id, row_id, sample_id, "offset", length FROM pk')


_LONG = "SELECT sample_id, (generate_subscripts(v, 1) - 1)::INTEGER AS dim, round(unnest(v), 6) AS x FROM vec"
_ASSIGN = "SELECT sample_id, cluster_id FROM cl"


def _unit(vector: str) -> str:
    return f"list_transform({vector}, lambda x: x / greatest(sqrt(list_sum(list_transform({vector}, lambda y: y * y))), 1e-300))"


def _cosine_sql() -> dict[str, str]:
    """Lloyd rounds over unit vectors with centroids brought back to unit length; the last assignment is of the vectors as given."""
    rounds = o.kmeans()
    made = {"raw_vec": o.GIVEN["vec"], "vec": f"SELECT sample_id, {_unit('v')} AS v FROM raw_vec"}
    for name, body in rounds.items():
        if name.startswith("c") and name[1:].isdigit() and name != "c0":
            made[f"u{name}"] = body
            body = f"SELECT cluster_id, {_unit('c')} AS c FROM u{name}"
        made[name] = body.replace("FROM vec CROSS JOIN", "FROM raw_vec CROSS JOIN") if name == "cl" else body
    return made


def _farthest_sql(k: int = 10) -> dict[str, str]:
    """Lloyd rounds from starts that are each the farthest from those before it."""
    gap = "list_sum(list_transform(list_zip(x.v, f.c), lambda p: (p[1] - p[2]) * (p[1] - p[2])))"
    made = {"f1": "SELECT 0 AS cluster_id, v AS c FROM vec ORDER BY sample_id LIMIT 1"}
    for i in range(1, k):
        made[f"f{i + 1}"] = f"SELECT * FROM f{i} UNION ALL SELECT {i}, v FROM (SELECT x.sample_id, any_value(x.v) AS v, min({gap}) AS d FROM vec x CROSS JOIN f{i} f GROUP BY x.sample_id ORDER BY d DESC, x.sample_id LIMIT 1)"
    return made | o.kmeans() | {"c0": f"SELECT cluster_id, c FROM f{k}"}


_PLAIN = "html"
for _from, _to in ((r"(?is)<script\b.*?</script>", " "), (r"(?is)<style\b.*?</style>", " "), (r"(?s)<[^>]*>", " ")):
    _PLAIN = f"regexp_replace({_PLAIN}, '{_from}', '{_to}', 'g')"
for _from, _to in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "''"), ("&nbsp;", " "), ("&amp;", "&")):
    _PLAIN = f"replace({_PLAIN}, '{_from}', '{_to}')"
_RES = {"res": "SELECT lang AS suite, doc_id AS item_id, quality = 1 AS base_pass, quality = 1 AND toxic = 0 AS extended_pass FROM labels JOIN documents USING (doc_id)"}
_STRATEGIES = {
    "pick_c": f"SELECT 'combined' AS strategy, sample_id FROM ({o.chosen(40)})",
    "pick_d": f"SELECT 'difficulty' AS strategy, sample_id FROM ({o.chosen(40, cluster='0')})",
    "pick_r": "SELECT 'random' AS strategy, sample_id FROM (" + o.chosen(40, order="substr(md5('42:' || sample_id), 1, 12), sample_id", cluster="0") + ")",
    "pick_k": "SELECT 'kmeans' AS strategy, sample_id FROM (" + o.chosen(40, order="md5('42:' || sample_id), sample_id") + ")",
    "picks": "SELECT * FROM pick_c UNION ALL SELECT * FROM pick_d UNION ALL SELECT * FROM pick_r UNION ALL SELECT * FROM pick_k",
}
_BUDGET = "SELECT cluster_id, (low + CASE WHEN row_number() OVER (ORDER BY rest DESC, cluster_id) <= 50 - sum(low) OVER () THEN 1 ELSE 0 END)::BIGINT AS quota FROM (SELECT cluster_id, n * 50 // tot AS low, n * 50 % tot AS rest FROM (SELECT cluster_id, count(*) AS n, sum(count(*)) OVER () AS tot FROM scored GROUP BY cluster_id))"

ORACLES = {
    "pairs_last_user": o.sql(o.PAIRS, "SELECT sample_id, instruction, response FROM pairs"),
    "pairs_with_system": """WITH t AS (SELECT conv_id * 1000 + turn AS sample_id, role, text, lead(role) OVER w AS nr, lead(text) OVER w AS response,
  last_value(CASE WHEN role = 'system' THEN text END IGNORE NULLS) OVER (PARTITION BY conv_id ORDER BY turn ROWS UNBOUNDED PRECEDING) AS sys FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn))
SELECT sample_id, concat_ws(chr(10), sys, text) AS instruction, response FROM t WHERE role = 'user' AND nr = 'assistant' AND length(trim(response)) > 0""",
    "pairs_history": """WITH t AS (SELECT conv_id * 1000 + turn AS sample_id, role, lead(role) OVER w AS nr, lead(text) OVER w AS response, list(text) OVER (PARTITION BY conv_id ORDER BY turn ROWS UNBOUNDED PRECEDING) AS past FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn))
SELECT sample_id, array_to_string(past, chr(10)) AS instruction, response FROM t WHERE role = 'user' AND nr = 'assistant' AND length(trim(response)) > 0""",
    "pairs_documents": o.sql(o.DOC_PAIRS, "SELECT sample_id, len(instr)::INTEGER AS n_instr, len(resp)::INTEGER AS n_resp, md5(array_to_string(instr, ' ')) AS instr_md5 FROM dp"),
    "pairs_rejected": o.sql({"turns": o.PAIRS["turns"]}, f"SELECT * FROM (SELECT sample_id, CASE WHEN coalesce(next_role, '') <> 'assistant' THEN 'no_reply' WHEN length(trim(coalesce(next_text, ''))) = 0 THEN 'blank_response' WHEN len({o.toks('text')}) + len({o.toks('next_text')}) > 4096 THEN 'too_long' END AS reason FROM turns WHERE role = 'user') WHERE reason IS NOT NULL"),
    "token_counts": o.sql(o.PAIRS, "SELECT sample_id, len(instr)::INTEGER AS n_instr, len(resp)::INTEGER AS n_resp FROM tp"),
    "token_counts_space": r"SELECT doc_id, len(list_filter(regexp_split_to_array(text, '[ \t\r\n]+'), lambda x: x <> ''))::INTEGER AS n FROM documents",
    "token_counts_char": "SELECT doc_id, length(lower(text))::INTEGER AS n FROM documents",
    "sample_lengths": o.sql(o.PAIRS, "SELECT sample_id, len(instr)::INTEGER AS n_instr, len(resp)::INTEGER AS n_resp, (len(instr) + len(resp))::INTEGER AS n_tokens FROM tp"),
    "vocab_counts": f"SELECT tok, count(*) AS n FROM (SELECT unnest({o.toks('text')}) AS tok FROM documents) GROUP BY tok HAVING count(*) >= 20",
    "token_logprobs": o.sql(o.PAIRS | o.NGRAM, "SELECT sample_id, pos, round(lp_with, 6) AS lp_with, round(lp_without, 6) AS lp_without FROM lp"),
    "ppl_conditional": o.sql(o.PAIRS | o.NGRAM, "SELECT sample_id, n_tokens, round(ppl_with, 6) AS ppl FROM sc"),
    "ppl_unconditional": o.sql(o.PAIRS | o.NGRAM, "SELECT sample_id, n_tokens, round(ppl_without, 6) AS ppl FROM sc"),
    "ifd_scores": o.sql(o.PAIRS | o.NGRAM, "SELECT sample_id, n_tokens, round(ppl_with, 6) AS ppl_with, round(ppl_without, 6) AS ppl_without, round(ifd, 6) AS ifd FROM sc"),
    "ifd_truncated": o.sql(o.PAIRS | o.NGRAM, "SELECT sample_id, count(*) AS n_tokens, round(exp(-avg(lp_with)), 6) AS ppl_with, round(exp(-avg(lp_without)), 6) AS ppl_without, round(exp(avg(lp_without - lp_with)), 6) AS ifd FROM lp JOIN tp USING (sample_id) WHERE len(instr) + pos <= 256 GROUP BY sample_id"),
    "ifd_capped": o.sql(o.PAIRS | o.NGRAM, "SELECT sample_id, round(ifd, 6) AS ifd FROM sc WHERE ifd < 1"),
    "ifd_profile": o.sql(_SEL, "SELECT cluster_id, count(*) AS n, round(avg(ifd), 6) AS mean_ifd, round(coalesce(stddev_samp(ifd), 0), 6) AS sd_ifd, round(quantile_cont(ifd, 0.5), 6) AS median_ifd FROM scored GROUP BY cluster_id"),
    "instr_embeddings": o.sql(o.PAIRS | o.EMBED, _LONG),
    "instr_embeddings_tfidf": o.sql(o.PAIRS | o.EMBED_TFIDF, _LONG),
    "given_embeddings": o.sql(o.GIVEN, _LONG),
    "vector_ops": """WITH v AS (SELECT vec_id, embedding::DOUBLE[] AS v FROM embeddings) SELECT a.vec_id, round(list_dot_product(a.v, b.v), 6) AS dot, round(sqrt(list_dot_product(a.v, a.v)), 6) AS norm,
  round(list_sum(list_transform(list_zip(a.v, b.v), lambda p: (p[1] - p[2]) * (p[1] - p[2]))), 6) AS l2sq, round(list_cosine_similarity(a.v, b.v), 6) AS cos FROM v a JOIN v b ON b.vec_id = a.vec_id + 1""",
    "kmeans_centroids": o.sql(_GIVEN, "SELECT cluster_id, (generate_subscripts(c, 1) - 1)::INTEGER AS dim, round(unnest(c), 6) AS x FROM cen"),
    "kmeans_assign": o.sql(_GIVEN, _ASSIGN),
    "kmeans_assign_summarizer": o.sql(_GIVEN, _ASSIGN),
    "kmeans_assign_summarizer": partial(_given_assign, update="summarizer"),
    "kmeans_assign_cosine": o.sql(_cosine_sql(), _ASSIGN),
    "kmeans_assign_farthest_init": o.sql(o.GIVEN | _farthest_sql(), _ASSIGN),
    "page_text": f"SELECT page_id, trim(regexp_replace({_PLAIN}, '[ \\t\\r\\n]+', ' ', 'g'), ' ') AS text FROM pages",
    "pipeline_end_to_end": o.sql(
        o.ALL | {"kept": o.chosen(40)} | {k: v + " SEMI JOIN kept USING (sample_id)" if k == "ln" else v for k, v in o.packed("pairs", 4096, "first").items() if k not in o.PAIRS},
        'SELECT batch_id, row_id, sample_id, "offset", length FROM pk',
    ),
    "kmeans_assign_hash_init": o.sql(o.GIVEN | o.kmeans(order="md5(sample_id::VARCHAR), sample_id"), _ASSIGN),
    "kmeans_assign_pairs": o.sql(o.PAIRS | o.EMBED | o.kmeans(), _ASSIGN),
    "kmeans_report": o.sql(o.PAIRS | o.EMBED | o.kmeans(), "SELECT cluster_id, count(*) AS n, round(sum(dist * dist), 6) AS sse, round(avg(dist), 6) AS mean_dist FROM cl GROUP BY cluster_id"),
    "select_full": o.sql(_SEL, "SELECT sample_id, cluster_id, round(ifd, 6) AS ifd FROM scored"),
    "select_stratified_40": o.sql(_SEL, o.chosen(40)),
    "select_stratified_30": o.sql(_SEL, o.chosen(30)),
    "select_threshold": o.sql(_SEL, o.chosen(40)),
    "select_easy": o.sql(_SEL, o.chosen(40, order="round(ifd, 9), sample_id")),
    "select_top1_cluster": o.sql(_SEL, o.CHOSEN.format(r=o.ranked(), q="1")),
    "select_budget": o.sql(_SEL | {"qu": _BUDGET}, f"SELECT sample_id, r.cluster_id::INTEGER AS cluster_id, round(ifd, 6) AS ifd, rank FROM ({o.ranked()}) r JOIN qu ON qu.cluster_id = r.cluster_id WHERE rank <= quota"),
    "select_rounding": o.sql(_SEL, o.chosen(40, 0)),
    "select_rounding_half": o.sql(_SEL, o.chosen(40, 50)),
    "select_gated": o.sql(_SEL, o.chosen(40, where="sample_id IN (SELECT sample_id FROM tp WHERE len(resp) >= 50)")),
    "select_ifd_only": o.sql(_SEL, o.chosen(40, cluster="0")),
    "select_random_40": o.sql(_SEL, o.chosen(40, order="substr(md5('42:' || sample_id), 1, 12), sample_id", cluster="0")),
    "select_kmeans_random": o.sql(_SEL, o.chosen(40, order="md5('42:' || sample_id), sample_id")),
    "select_kmeans_central": o.sql(_SEL, o.chosen(40, order="round(dist, 9), sample_id")),
    "rank_profile": o.sql(_SEL, "SELECT sample_id, cluster_id, round(ifd, 6) AS ifd, row_number() OVER w AS rank, count(*) OVER (PARTITION BY cluster_id) AS n, round(percent_rank() OVER w, 6) AS pct_rank FROM scored WINDOW w AS (PARTITION BY cluster_id ORDER BY round(ifd, 9) DESC, sample_id)"),
    "consistency_clusters": o.sql(
        _SEL | _STRATEGIES | {"fullc": "SELECT cluster_id, count(*) / (SELECT count(*) FROM scored) AS p FROM scored GROUP BY cluster_id",
                              "subc": "SELECT strategy, cluster_id, count(*) / sum(count(*)) OVER (PARTITION BY strategy) AS q FROM picks JOIN scored USING (sample_id) GROUP BY strategy, cluster_id",
                              "bothc": "SELECT s.strategy, f.p, coalesce(c.q, 0) AS q FROM (SELECT DISTINCT strategy FROM picks) s CROSS JOIN fullc f LEFT JOIN subc c ON c.strategy = s.strategy AND c.cluster_id = f.cluster_id"},
        "SELECT strategy, 40 AS rate_pct, round(sum(abs(p - q)) / 2, 6) AS tv, round(sum(CASE WHEN q > 0 THEN q * ln(q / p) ELSE 0 END), 6) AS kl, round(sum((q - p) * (q - p) / p), 6) AS chi2 FROM bothc GROUP BY strategy",
    ),
    "complexity_gain": o.sql(_SEL | _STRATEGIES, "SELECT strategy, 40 AS rate_pct, round(avg(ifd), 6) AS mean_ifd, round((SELECT avg(ifd) FROM scored), 6) AS full_mean_ifd FROM picks JOIN scored USING (sample_id) GROUP BY strategy"),
    "batches_256": o.sql(o.batched("pairs"), "SELECT batch_id, sample_id, n_tokens FROM ba"),
    "batches_hash_64": o.sql(o.lengths("pairs"), "SELECT (row_number() OVER (ORDER BY substr(md5('42:' || sample_id), 1, 12), sample_id) - 1) // 64 AS batch_id, sample_id, n_tokens FROM ln"),
    "batches_length_64": o.sql(o.lengths("pairs"), "SELECT (row_number() OVER (ORDER BY n_tokens, sample_id) - 1) // 64 AS batch_id, sample_id, n_tokens FROM ln"),
    "pack_first_fit": _pack_sql("pairs", 512, "first"),
    "pack_best_fit": _pack_sql("pairs", 512, "best"),
    "pack_next_fit_asc": _pack_sql("pairs", 512, "next", "ASC"),
    "pack_next_fit_desc": _pack_sql("pairs", 512, "next"),
    "pack_documents": _pack_sql("documents", 4096, "first"),
    "pack_oversize": _pack_sql("documents", 1024, "first", where="n_tokens <= 1024"),
    "pack_segments": _pack_sql("documents", 1024, "best"),
    "pack_arrow": _pack_sql("pairs", 512, "first"),
    "packed_render": o.sql(
        o.packed("pairs", 512, "first") | {"w": "SELECT batch_id, max(u) AS width FROM (SELECT batch_id, row_id, sum(length) AS u FROM pk GROUP BY ALL) GROUP BY batch_id",
                                          "rt": 'SELECT batch_id, row_id, flatten(list(list_concat(instr, resp) ORDER BY "offset")) AS t FROM pk JOIN tp USING (sample_id) GROUP BY batch_id, row_id'},
        "SELECT batch_id, row_id, width::INTEGER AS width, md5(array_to_string(list_concat(t, list_transform(generate_series(1, (width - len(t))::BIGINT), lambda i: '<pad>')), ' ')) AS digest FROM rt JOIN w USING (batch_id)",
    ),
    "loss_spans": o.sql(o.packed("pairs", 512, "first"), 'SELECT batch_id, row_id, sample_id, ("offset" + len(instr))::INTEGER AS start, ("offset" + length)::INTEGER AS stop FROM pk JOIN tp USING (sample_id)'),
    "shard_balance": o.sql(
        o.packed("pairs", 512, "first") | {"ru": "SELECT batch_id, row_id, sum(length) AS u FROM pk GROUP BY ALL", "rw": "SELECT *, max(u) OVER (PARTITION BY batch_id) AS w FROM ru"},
        "SELECT (row_id % 4)::INTEGER AS shard, count(*) AS rows, sum(u)::BIGINT AS used, sum(w)::BIGINT AS cells FROM rw GROUP BY 1",
    ),
    "pad_longest": _one_sql("pad_longest", "pairs", o.PADDED.format(w="max(n_tokens)", n="n_tokens")),
    "pad_model_max": _one_sql("pad_model_max", "pairs", o.PADDED.format(w=4096, n="least(n_tokens, 4096)")),
    "pack_fixed_stream": _one_sql("pack_fixed_stream", "documents", o.STREAMED),
    "pack_fixed_cap": _one_sql("pack_fixed_cap", "documents", _FIXED.replace("FXT", "fx"), _fixed_parts("fx")),
    "padding_rate_pairs": _layout_sql("pairs", 512),
    "padding_rate_documents": _layout_sql("documents", 4096),
    "layout_cost": o.sql(o.packed("pairs", 512, "first"), f"SELECT 'first_fit_desc' AS layout, {o.MEASURES} FROM ({o.PACKED_BATCHES})"),
    "layout_peak": o.sql(o.packed("documents", 4096, "first"), f"SELECT 'first_fit_desc' AS layout, {o.MEASURES} FROM ({o.PACKED_BATCHES})"),
    "training_plan": o.sql(
        o.PAIRS | {"n": "SELECT ceil(count(*) / 256)::BIGINT AS per FROM pairs", "stp": "SELECT per, unnest(generate_series(1, per * 3)) AS step FROM n"},
        "SELECT step, ((step - 1) // per + 1)::INTEGER AS epoch, round(CASE WHEN step <= 15 THEN 5e-5 * step / 15 ELSE 5e-5 * 0.5 * (1 + cos(pi() * (step - 15) / greatest(per * 3 - 15, 1))) END, 12) AS lr FROM stp",
    ),
    "pass_at_1": o.sql(_RES, "SELECT suite, round(avg(base_pass::INTEGER), 6) AS pass_at_1 FROM res GROUP BY suite"),
    "pass_at_k": o.sql(_RES | {"it": "SELECT suite, item_id % 20 AS item, count(*) AS n, count(*) FILTER (base_pass) AS c FROM res GROUP BY ALL"}, "SELECT suite, round(avg(1 - (n - c) * greatest(n - c - 1, 0) / (n * (n - 1))), 6) AS pass_at_k FROM it WHERE n >= 2 GROUP BY suite"),
    "macro_average": o.sql(_RES | {"bs": "SELECT suite, round(avg(base_pass::INTEGER), 6) AS b, round(avg(extended_pass::INTEGER), 6) AS e FROM res GROUP BY suite"}, "SELECT 'base' AS metric, round(avg(b), 6) AS value FROM bs UNION ALL SELECT 'extended', round(avg(e), 6) FROM bs"),
    "benchmark_scores": o.sql(_RES, "SELECT suite, count(*) AS n, round(avg(base_pass::INTEGER), 6) AS pass_base, round(avg(extended_pass::INTEGER), 6) AS pass_extended FROM res GROUP BY suite"),
}
