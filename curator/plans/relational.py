"""Relational operators around the methods, and streaming flows, each as one query."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from curator.functions.expr import tokens
from curator.sources.tables import read_table
from curator.streaming import flows


def t(s: SparkSession, d: str, name: str) -> DataFrame:
    return read_table(s, d, name)


def asof(s: SparkSession, d: str) -> DataFrame:
    """The last click of the same user before each purchase: one union, one window, no range join."""
    e = t(s, d, "events").select("event_id", "user_id", "ts", "event_type").filter("event_type in ('click', 'purchase')")
    w = Window.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "click", 0).otherwise(1), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    last = F.last(F.when(F.col("event_type") == "click", F.col("event_id")), ignorenulls=True).over(w)
    return e.withColumn("click_id", last).filter("event_type = 'purchase'").select("event_id", "click_id")


def interval_join(s: SparkSession, d: str) -> DataFrame:
    """Events of a user within an hour after one of the user's clicks, met through hour buckets."""
    e = t(s, d, "events").select("event_id", "user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    hour = 3_600_000_000
    a = e.filter("event_type = 'click'").select("user_id", F.col("event_id").alias("click_id"), F.col("us").alias("a"), F.explode(F.array(F.floor(F.col("us") / hour), F.floor(F.col("us") / hour) + 1)).alias("h"))
    b = e.filter("event_type = 'error'").select("user_id", F.col("event_id").alias("error_id"), F.col("us").alias("b"), F.floor(F.col("us") / hour).alias("h"))
    return a.join(b, ["user_id", "h"]).filter((F.col("b") > F.col("a")) & (F.col("b") <= F.col("a") + hour)).select("click_id", "error_id")


def range_join(s: SparkSession, d: str) -> DataFrame:
    docs = t(s, d, "documents").select("doc_id", F.size(tokens(F.col("text"))).alias("n"))
    bands = s.createDataFrame([("short", 0, 100), ("medium", 100, 1000), ("long", 1000, 1 << 30)], "band string, lo int, hi int")
    return docs.join(F.broadcast(bands), (F.col("n") >= F.col("lo")) & (F.col("n") < F.col("hi"))).groupBy("band").agg(F.count(F.lit(1)).alias("n_docs"), F.sum("n").alias("n_tokens"))


def _joined(hint: str):
    def run(s: SparkSession, d: str) -> DataFrame:
        li = t(s, d, "lineitem").select("l_orderkey", "l_quantity")
        od = t(s, d, "orders").select("o_orderkey", "o_orderpriority").hint(hint)
        return li.join(od, F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.sum("l_quantity").alias("qty"))

    return run


_JOIN_SQL = "SELECT o_orderpriority, count(*) AS n, sum(l_quantity) AS qty FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1"


def _cells(s: SparkSession, d: str) -> DataFrame:
    return t(s, d, "documents").join(t(s, d, "labels"), "doc_id").select("lang", "source", "quality", "toxic", "n_chars")


def _cube(kind: str):
    def run(s: SparkSession, d: str) -> DataFrame:
        agg = (F.grouping_id().cast("long").alias("gid"), F.count(F.lit(1)).alias("n"), F.sum("quality").alias("good"))
        c = _cells(s, d)
        if kind == "sets":
            return c.groupingSets([["lang"], ["source"]], "lang", "source").agg(*agg)
        return getattr(c, kind)("lang", "source").agg(*agg)

    return run


def _cube_sql(by: str) -> str:
    return f"SELECT lang, source, (grouping(lang) * 2 + grouping(source))::BIGINT AS gid, count(*) AS n, sum(quality)::BIGINT AS good FROM documents JOIN labels USING (doc_id) GROUP BY {by}"


def _stats(s: SparkSession, d: str) -> DataFrame:
    return t(s, d, "documents").groupBy("lang").agg(
        F.round(F.stddev_samp("n_chars"), 4).alias("sd"), F.round(F.percentile("n_chars", F.lit(0.9)), 4).alias("p90"), F.max_by("doc_id", F.struct("n_chars", "doc_id")).alias("longest"), F.round(F.corr("n_chars", "doc_id"), 6).alias("r")
    )


def _setops(s: SparkSession, d: str) -> DataFrame:
    a, b = t(s, d, "labels").filter("quality = 1").select("doc_id"), t(s, d, "labels").filter("toxic = 1").select("doc_id")
    parts = {"union": a.union(b), "intersect": a.intersect(b), "except": a.exceptAll(b)}
    out = None
    for name, df in parts.items():
        one = df.agg(F.count(F.lit(1)).alias("n")).select(F.lit(name).alias("op"), "n")
        out = one if out is None else out.unionByName(one)
    return out


def _decontaminated(s: SparkSession, d: str) -> DataFrame:
    """Documents that share no run of eight tokens with a benchmark passage; the passages' runs are joined, not broadcast."""

    def grams(df: DataFrame, key: str) -> DataFrame:
        toks = df.select(key, F.explode(F.array(tokens(F.col("text")))).alias("t")).filter(F.size("t") >= 8)
        parts = toks.select(key, F.explode(F.transform(F.sequence(F.lit(1), F.size("t") - 7), lambda i: F.xxhash64(F.slice("t", i, 8)))).alias("g"))
        return parts

    bad = grams(t(s, d, "documents"), "doc_id").join(grams(t(s, d, "benchmark"), "item_id").select("g").distinct(), "g", "left_semi").select("doc_id").distinct()
    return t(s, d, "documents").select("doc_id").join(bad, "doc_id", "left_anti")


_DECON_SQL = r"""WITH dg AS (SELECT doc_id, t, unnest(generate_series(1, len(t) - 7)) AS i FROM (SELECT doc_id, regexp_extract_all(lower(text), '[\p{L}\p{N}]+|[^\s\p{L}\p{N}]') AS t FROM documents) WHERE len(t) >= 8),
bg AS (SELECT DISTINCT array_to_string(t[i:i + 7], ' ') AS g FROM (SELECT t, unnest(generate_series(1, len(t) - 7)) AS i FROM (SELECT regexp_extract_all(lower(text), '[\p{L}\p{N}]+|[^\s\p{L}\p{N}]') AS t FROM benchmark) WHERE len(t) >= 8))
SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM dg JOIN bg ON g = array_to_string(t[i:i + 7], ' '))"""


def _windows(s: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("lang").orderBy(F.desc("n_chars"), "doc_id")
    return t(s, d, "documents").select(
        "doc_id", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.ntile(4).over(w).alias("nt"), F.round(F.cume_dist().over(w), 6).alias("cd"),
        F.sum("n_chars").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("run"), F.lag("doc_id").over(w).alias("prev"), F.lead("doc_id").over(w).alias("next"),
    )


def _stream(kind: str, size: str, slide: str | None = None):
    return lambda s, d: flows.drain(flows.windowed(flows.event_stream(s, f"{d}/events.parquet"), kind, size, slide))


def _stream_dedup(s: SparkSession, d: str) -> DataFrame:
    e = flows.event_stream(s, f"{d}/events.parquet")
    return flows.drain(flows.deduplicated(e, ["event_id"], "60 days").select("event_id"), "append").groupBy().agg(F.count(F.lit(1)).alias("n"), F.sum("event_id").alias("total"))


def _stream_join(s: SparkSession, d: str) -> DataFrame:
    e = lambda kind: flows.event_stream(s, f"{d}/events.parquet").filter(F.col("event_type") == kind)
    return flows.drain(flows.interval_join(e("click"), e("error"), "1 hour", "60 days"), "append").select(F.col("left_id").alias("click_id"), F.col("right_id").alias("error_id"))


_TUMBLE = "SELECT date_trunc('day', ts) AS start_ts, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1, 2"
_SLIDE = "SELECT date_trunc('hour', ts) - INTERVAL (k) HOUR AS start_ts, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events CROSS JOIN (VALUES (0), (1)) AS s(k) GROUP BY 1, 2"
_SESSION = """WITH g AS (SELECT *, CASE WHEN ts >= lag(ts) OVER (PARTITION BY event_type ORDER BY ts) + INTERVAL 10 MINUTE THEN 1 ELSE 0 END AS gap FROM events),
s AS (SELECT *, sum(gap) OVER (PARTITION BY event_type ORDER BY ts ROWS UNBOUNDED PRECEDING) AS sid FROM g) SELECT min(ts) AS start_ts, event_type, count(*) AS n, round(sum(value), 4) AS total FROM s GROUP BY event_type, sid"""

QUERIES = {
    "op_filter_samples": lambda s, d: t(s, d, "documents").filter((F.col("n_chars").between(200, 2000)) & (F.col("lang") == "en")).select("doc_id", F.when(F.col("n_chars") < 1000, "short").otherwise("long").alias("size")),
    "op_join_broadcast": lambda s, d: t(s, d, "customer").join(F.broadcast(t(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count(F.lit(1)).alias("n")),
    "op_join_merge": _joined("merge"),
    "op_join_hash": _joined("shuffle_hash"),
    "op_join_left": lambda s, d: t(s, d, "documents").join(t(s, d, "labels"), "doc_id", "left").groupBy("lang").agg(F.count(F.lit(1)).alias("n"), F.count("quality").alias("labelled")),
    "op_join_full": lambda s, d: t(s, d, "labels").select("doc_id", "quality").join(t(s, d, "embeddings").select(F.col("vec_id").alias("doc_id"), "label"), "doc_id", "full"),
    "op_semi": lambda s, d: t(s, d, "documents").select("doc_id").join(t(s, d, "labels"), "doc_id", "left_semi"),
    "op_anti": _decontaminated,
    "op_cross_rates": lambda s, d: t(s, d, "documents").groupBy("lang").agg(F.count(F.lit(1)).alias("n")).withColumn("rate", F.explode(F.sequence(F.lit(10), F.lit(60), F.lit(10)))).select("lang", "rate", F.expr("(n * rate + 99) div 100").alias("quota")),
    "op_range_join": range_join,
    "op_asof": asof,
    "op_interval_join": interval_join,
    "op_group_agg": lambda s, d: t(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.sum("l_quantity").alias("qty"), F.round(F.avg("l_discount"), 6).alias("disc")),
    "op_distinct_agg": lambda s, d: t(s, d, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"), F.sum_distinct("l_linenumber").cast("long").alias("lines")),
    "op_filter_agg": lambda s, d: _cells(s, d).groupBy("lang").agg(F.count_if(F.col("quality") == 1).alias("good"), F.sum(F.when(F.col("toxic") == 0, F.col("n_chars"))).alias("clean_chars")),
    "op_stats": _stats,
    "op_cube": _cube("cube"),
    "op_rollup": _cube("rollup"),
    "op_grouping_sets": _cube("sets"),
    "op_pivot": lambda s, d: t(s, d, "lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).agg(F.sum("l_quantity")).withColumnsRenamed({"F": "qty_f", "O": "qty_o"}),
    "op_unpivot": lambda s, d: t(s, d, "labels").unpivot("doc_id", ["quality", "toxic"], "metric", "value"),
    "op_win_rank": lambda s, d: _windows(s, d).select("doc_id", "rn", "rk", "dr", "pr", "nt", "cd"),
    "op_win_lead": lambda s, d: _windows(s, d).select("doc_id", "prev", "next"),
    "op_win_frames": lambda s, d: _windows(s, d).select("doc_id", "run"),
    "op_topk": lambda s, d: t(s, d, "documents").orderBy(F.desc("n_chars"), "doc_id").limit(25).select("doc_id", "n_chars"),
    "op_topk_group": lambda s, d: _windows(s, d).filter("rn <= 3").select("doc_id", "rn"),
    "op_setops": _setops,
    "op_dedup": lambda s, d: t(s, d, "documents").groupBy(F.md5("text").alias("h")).agg(F.min("doc_id").alias("doc_id"), F.count(F.lit(1)).alias("copies")).select("doc_id", "copies"),
    "op_subquery": lambda s, d: _windows(s, d).select("doc_id").join(t(s, d, "documents"), "doc_id").withColumn("m", F.avg("n_chars").over(Window.partitionBy("lang"))).filter("n_chars > m").select("doc_id"),
    "op_explode": lambda s, d: t(s, d, "documents").select("doc_id", F.posexplode(F.split("text", "\n")).alias("pos", "line")).groupBy("doc_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("pos", "line"))), lambda x: x["line"]), "|").alias("joined")).select("doc_id", F.md5("joined").alias("h")),
    "op_hash_sample": lambda s, d: t(s, d, "documents").filter(F.conv(F.substring(F.md5(F.col("doc_id").cast("string")), 1, 4), 16, 10).cast("int") < 6554).select("doc_id"),
    "op_json": lambda s, d: t(s, d, "events").groupBy("event_type").agg(F.sum(F.get_json_object("props", "$.k").cast("long")).alias("k")),
    "stream_tumbling": _stream("tumbling", "1 day"),
    "stream_sliding": _stream("sliding", "2 hours", "1 hour"),
    "stream_session": _stream("session", "10 minutes"),
    "stream_dedup": _stream_dedup,
    "stream_interval_join": _stream_join,
}

_WIN = """SELECT doc_id, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, round(percent_rank() OVER w, 6) AS pr, ntile(4) OVER w AS nt, round(cume_dist() OVER w, 6) AS cd,
 sum(n_chars) OVER (w ROWS UNBOUNDED PRECEDING)::BIGINT AS run, lag(doc_id) OVER w AS prev, lead(doc_id) OVER w AS next FROM documents WINDOW w AS (PARTITION BY lang ORDER BY n_chars DESC, doc_id)"""
_HOUR = "SELECT a.event_id AS click_id, b.event_id AS error_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'click' AND b.event_type = 'error'"

ORACLES = {
    "op_filter_samples": "SELECT doc_id, CASE WHEN n_chars < 1000 THEN 'short' ELSE 'long' END AS size FROM documents WHERE n_chars BETWEEN 200 AND 2000 AND lang = 'en'",
    "op_join_broadcast": "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1",
    "op_join_merge": _JOIN_SQL,
    "op_join_hash": _JOIN_SQL,
    "op_join_left": "SELECT lang, count(*) AS n, count(quality) AS labelled FROM documents LEFT JOIN labels USING (doc_id) GROUP BY 1",
    "op_join_full": "SELECT coalesce(l.doc_id, e.vec_id) AS doc_id, quality, label FROM labels l FULL JOIN embeddings e ON l.doc_id = e.vec_id",
    "op_semi": "SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)",
    "op_anti": _DECON_SQL,
    "op_cross_rates": "SELECT lang, rate::INTEGER AS rate, (n * rate + 99) // 100 AS quota FROM (SELECT lang, count(*) AS n FROM documents GROUP BY 1) CROSS JOIN (SELECT unnest([10, 20, 30, 40, 50, 60]) AS rate)",
    "op_range_join": r"WITH n AS (SELECT len(regexp_extract_all(lower(text), '[\p{L}\p{N}]+|[^\s\p{L}\p{N}]')) AS n FROM documents) SELECT CASE WHEN n < 100 THEN 'short' WHEN n < 1000 THEN 'medium' ELSE 'long' END AS band, count(*) AS n_docs, sum(n)::BIGINT AS n_tokens FROM n GROUP BY 1",
    "op_asof": "SELECT p.event_id, (SELECT c.event_id FROM events c WHERE c.event_type = 'click' AND c.user_id = p.user_id AND c.ts <= p.ts ORDER BY c.ts DESC, c.event_id DESC LIMIT 1) AS click_id FROM events p WHERE p.event_type = 'purchase'",
    "op_interval_join": _HOUR,
    "op_group_agg": "SELECT l_returnflag, l_linestatus, count(*) AS n, sum(l_quantity) AS qty, round(avg(l_discount), 6) AS disc FROM lineitem GROUP BY 1, 2",
    "op_distinct_agg": "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, sum(DISTINCT l_linenumber)::BIGINT AS lines FROM lineitem GROUP BY 1",
    "op_filter_agg": "SELECT lang, count(*) FILTER (quality = 1) AS good, sum(n_chars) FILTER (toxic = 0)::BIGINT AS clean_chars FROM documents JOIN labels USING (doc_id) GROUP BY 1",
    "op_stats": "SELECT lang, round(stddev_samp(n_chars), 4) AS sd, round(quantile_cont(n_chars, 0.9), 4) AS p90, first(doc_id ORDER BY n_chars DESC, doc_id DESC) AS longest, round(corr(n_chars, doc_id), 6) AS r FROM documents GROUP BY 1",
    "op_cube": _cube_sql("CUBE (lang, source)"),
    "op_rollup": _cube_sql("ROLLUP (lang, source)"),
    "op_grouping_sets": _cube_sql("GROUPING SETS ((lang), (source))"),
    "op_pivot": "SELECT l_returnflag, sum(l_quantity) FILTER (l_linestatus = 'F') AS qty_f, sum(l_quantity) FILTER (l_linestatus = 'O') AS qty_o FROM lineitem GROUP BY 1",
    "op_unpivot": "SELECT doc_id, 'quality' AS metric, quality AS value FROM labels UNION ALL SELECT doc_id, 'toxic', toxic FROM labels",
    "op_win_rank": f"SELECT doc_id, rn, rk, dr, pr, nt, cd FROM ({_WIN})",
    "op_win_lead": f"SELECT doc_id, prev, next FROM ({_WIN})",
    "op_win_frames": f"SELECT doc_id, run FROM ({_WIN})",
    "op_topk": "SELECT doc_id, n_chars FROM documents ORDER BY n_chars DESC, doc_id LIMIT 25",
    "op_topk_group": f"SELECT doc_id, rn FROM ({_WIN}) WHERE rn <= 3",
    "op_setops": "WITH a AS (SELECT doc_id FROM labels WHERE quality = 1), b AS (SELECT doc_id FROM labels WHERE toxic = 1) SELECT 'union' AS op, count(*) AS n FROM (SELECT * FROM a UNION ALL SELECT * FROM b) UNION ALL SELECT 'intersect', count(*) FROM (SELECT * FROM a INTERSECT SELECT * FROM b) UNION ALL SELECT 'except', count(*) FROM (SELECT * FROM a EXCEPT ALL SELECT * FROM b)",
    "op_dedup": "SELECT min(doc_id) AS doc_id, count(*) AS copies FROM documents GROUP BY md5(text)",
    "op_subquery": "SELECT doc_id FROM documents o WHERE n_chars > (SELECT avg(n_chars) FROM documents i WHERE i.lang = o.lang)",
    "op_explode": "SELECT doc_id, md5(replace(text, chr(10), '|')) AS h FROM documents",
    "op_hash_sample": "SELECT doc_id FROM documents WHERE ('0x' || substr(md5(doc_id::VARCHAR), 1, 4))::INTEGER < 6554",
    "op_json": "SELECT event_type, sum((props ->> '$.k')::BIGINT)::BIGINT AS k FROM events GROUP BY 1",
    "stream_tumbling": _TUMBLE,
    "stream_sliding": _SLIDE,
    "stream_session": _SESSION,
    "stream_dedup": "SELECT count(*) AS n, sum(event_id)::BIGINT AS total FROM (SELECT DISTINCT event_id FROM events)",
    "stream_interval_join": _HOUR,
}
