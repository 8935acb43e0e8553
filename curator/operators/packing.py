"""Batches, dynamic packing, the padding baselines and the measures of a layout."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from curator.operators.ranks import ranked_in_ranges

def global_rank(rows: DataFrame, key: Column, ties: list[Column]) -> DataFrame:
    """``rows`` plus ``rank`` (from 0) in the order of ``key``, then ``ties``, without a single-task sort, whatever the distribution of the key."""
    return ranked_in_ranges(rows, [], [key, *ties]).withColumn("rank", F.col("rank") - 1)


def form_batches(lengths: DataFrame, size: int = 256, order: str = "id", seed: int = 42) -> DataFrame:
    """``batch_id, sample_id, n_tokens`` in order of ``id``, seeded ``hash`` or ``length``."""
    key = {
        "id": F.col("sample_id"),
        "hash": F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), F.col("sample_id"))), 1, 12), 16, 10).cast("double"),
        "length": F.col("n_tokens"),
    }[order]
    ranked = global_rank(lengths.select("sample_id", F.col("n_tokens").cast("int")), key, [F.col("sample_id")])
    return ranked.select(F.expr(f"rank div {size}").alias("batch_id"), "sample_id", "n_tokens")


def _fold(items: Column, context: int, fit: str) -> Column:
    """Rows of a batch as ``array<struct<used, segments>>`` by a fold over its sorted items."""
    empty = F.array().cast("array<struct<used:int,segments:array<struct<sample_id:bigint,offset:int,length:int>>>>")

    def spot(rows: Column, n: Column) -> Column:
        if fit == "next":
            last = F.size(rows)
            return F.when((last > 0) & (F.coalesce(F.try_element_at(rows, last)["used"], F.lit(0)) + n <= context), last).otherwise(0)
        if fit == "first":
            return F.coalesce(F.array_position(F.transform(rows, lambda r: r["used"] + n <= context), True), F.lit(0)).cast("int")
        fullest = F.array_max(F.filter(F.transform(rows, lambda r: r["used"]), lambda u: u + n <= context))
        return F.coalesce(F.array_position(F.transform(rows, lambda r: r["used"]), fullest), F.lit(0)).cast("int")

    def place(rows: Column, item: Column) -> Column:
        n = item["n"]
        segment = lambda at: F.struct(item["id"].alias("sample_id"), at.cast("int").alias("offset"), n.alias("length"))
        fresh = F.array(F.struct(n.alias("used"), F.array(segment(F.lit(0))).alias("segments")))

        def put(at: Column) -> Column:
            grown = F.transform(rows, lambda r, i: F.when(i + 1 == at, F.struct((r["used"] + n).alias("used"), F.concat(r["segments"], F.array(segment(r["used"]))).alias("segments"))).otherwise(r))
            return F.when(at > 0, grown).otherwise(F.concat(rows, fresh))

        return F.transform(F.array(spot(rows, n)), put)[0]

    return F.aggregate(items, empty, place)


def dynamic_pack(batches: DataFrame, context: int = 4096, fit: str = "first", descending: bool = True, oversize: str = "solo", engine: str = "native") -> DataFrame:
    """``batch_id, row_id, width, used, pad, oversize, segments``: whole samples joined into rows of at most ``context`` tokens.

    Samples of a batch are sorted by length and go to the ``next`` (last open), ``first`` or ``best`` (fullest) row that has room; the width is the
    batch's longest row.  A sample longer than the context has a row of its own (``solo``), is left out (``drop``) or fails the job (``fail``).
    """
    rows = batches.select("batch_id", "sample_id", F.col("n_tokens").cast("int").alias("n"))
    if oversize == "drop":
        rows = rows.filter(F.col("n") <= context)
    elif oversize == "fail":
        rows = rows.withColumn("n", F.when(F.col("n") <= context, F.col("n")).otherwise(F.raise_error(F.lit("a sample is longer than the context")).cast("int")))
    if engine == "arrow":
        packed = rows.groupBy("batch_id").applyInPandas(_pandas_pack(context, fit, descending), "batch_id long, row_id int, used int, segments array<struct<sample_id:bigint,offset:int,length:int>>")
    else:
        item = F.struct((-F.col("n") if descending else F.col("n")).alias("key"), F.col("sample_id").alias("id"), "n")
        grouped = rows.groupBy("batch_id").agg(F.sort_array(F.collect_list(item)).alias("items"))
        packed = grouped.select("batch_id", F.posexplode(_fold(F.col("items"), context, fit)).alias("row_id", "r")).select("batch_id", "row_id", "r.used", "r.segments")
    width = F.max("used").over(Window.partitionBy("batch_id"))
    return packed.withColumn("width", width).select("batch_id", "row_id", "width", "used", (F.col("width") - F.col("used")).alias("pad"), (F.col("used") > context).alias("oversize"), "segments")


def _pandas_pack(context: int, fit: str, descending: bool):
    def run(frame):
        import pandas as pd

        rows: list[list] = []
        for n, i in sorted(((n, i) for n, i in zip(frame["n"], frame["sample_id"], strict=True)), key=lambda x: (-x[0] if descending else x[0], x[1])):
            room = [at for at, r in enumerate(rows) if r[0] + n <= context and (fit != "next" or at == len(rows) - 1)]
            at = (max(room, key=lambda a: (rows[a][0], -a)) if fit == "best" else room[0]) if room else len(rows)
            if at == len(rows):
                rows.append([0, []])
            rows[at][1].append({"sample_id": int(i), "offset": int(rows[at][0]), "length": int(n)})
            rows[at][0] += int(n)
        return pd.DataFrame({"batch_id": frame["batch_id"].iloc[0], "row_id": range(len(rows)), "used": [r[0] for r in rows], "segments": [r[1] for r in rows]})

    return run


def segments(packed: DataFrame) -> DataFrame:
    """``batch_id, row_id, sample_id, offset, length``: the long form of packed rows."""
    return packed.select("batch_id", "row_id", F.inline("segments"))


def render_rows(packed: DataFrame, samples: DataFrame, pad: str = "<pad>") -> DataFrame:
    """``batch_id, row_id, tokens``: joined token arrays (``samples``: sample_id, toks) padded to the width."""
    parts = packed.select("batch_id", "row_id", "width", F.inline("segments")).join(samples.select("sample_id", "toks"), "sample_id")
    rows = parts.groupBy("batch_id", "row_id", "width").agg(F.flatten(F.transform(F.array_sort(F.collect_list(F.struct("offset", "toks"))), lambda s: s["toks"])).alias("t"))
    return rows.select("batch_id", "row_id", F.concat("t", F.array_repeat(F.lit(pad), F.col("width") - F.size("t"))).alias("tokens"))


def loss_spans(packed: DataFrame, lengths: DataFrame) -> DataFrame:
    """``batch_id, row_id, sample_id, start, stop``: the response tokens of each segment, which alone are learned."""
    parts = segments(packed).join(lengths.select("sample_id", "n_instr"), "sample_id")
    return parts.select("batch_id", "row_id", "sample_id", (F.col("offset") + F.col("n_instr")).alias("start"), (F.col("offset") + F.col("length")).alias("stop"))


def assign_shards(packed: DataFrame, workers: int = 4) -> DataFrame:
    """Packed rows dealt to data-parallel workers in turn within each batch."""
    return packed.withColumn("shard", F.pmod("row_id", F.lit(workers)).cast("int"))


def batch_layout(packed: DataFrame) -> DataFrame:
    """``batch_id, rows, width, used, truncated`` of packed rows."""
    return packed.groupBy("batch_id").agg(F.count(F.lit(1)).alias("rows"), F.max("width").cast("long").alias("width"), F.sum("used").cast("long").alias("used"), F.lit(0).cast("long").alias("truncated"))


def pad_layout(batches: DataFrame, context: int | None = None) -> DataFrame:
    """One sample a row, padded to ``context`` (longer ones cut there), or to the longest of the batch."""
    n = F.col("n_tokens") if context is None else F.least("n_tokens", F.lit(context))
    width = F.max(n) if context is None else F.lit(context)
    return batches.groupBy("batch_id").agg(F.count(F.lit(1)).alias("rows"), width.cast("long").alias("width"), F.sum(n).cast("long").alias("used"), F.sum(F.col("n_tokens") - n).cast("long").alias("truncated"))


def fixed_pack(batches: DataFrame, cap: int = 512, mode: str = "join") -> DataFrame:
    """The fixed-size pack: samples cut to ``cap`` tokens and joined in arrival order into rows of ``cap``.

    ``join`` opens a row when the next sample does not fit (a fold); ``stream`` lets samples straddle rows (a prefix sum).
    """
    cut = batches.select("batch_id", "sample_id", "n_tokens", F.least("n_tokens", F.lit(cap)).cast("int").alias("n"))
    lost = cut.groupBy("batch_id").agg(F.sum(F.col("n_tokens") - F.col("n")).cast("long").alias("truncated"), F.sum("n").cast("long").alias("used"))
    if mode == "stream":
        return lost.select("batch_id", F.expr(f"(used + {cap - 1}) div {cap}").alias("rows"), F.lit(cap).cast("long").alias("width"), "used", "truncated")
    item = F.struct("sample_id", "n")
    grouped = cut.groupBy("batch_id").agg(F.sort_array(F.collect_list(item)).alias("items"))
    start = F.struct(F.lit(0).cast("long").alias("rows"), F.lit(cap).alias("used"))
    step = lambda s, i: F.when(s["used"] + i["n"] <= cap, F.struct(s["rows"].alias("rows"), (s["used"] + i["n"]).alias("used"))).otherwise(F.struct((s["rows"] + 1).alias("rows"), i["n"].alias("used")))
    folded = grouped.select("batch_id", F.aggregate("items", start, step)["rows"].alias("rows"))
    return folded.join(lost, "batch_id").select("batch_id", "rows", F.lit(cap).cast("long").alias("width"), "used", "truncated")


def layout_report(layout: DataFrame, name: str) -> DataFrame:
    """Measures of a layout (a row per batch): padding rate over all cells, cells, attention cells and peaks, which stand for time and memory."""
    cells = F.col("rows") * F.col("width")
    return layout.agg(
        F.count(F.lit(1)).alias("batches"),
        F.coalesce(F.sum("rows"), F.lit(0)).cast("long").alias("rows"),
        F.coalesce(F.sum(cells), F.lit(0)).cast("long").alias("cells"),
        F.coalesce(F.sum("used"), F.lit(0)).cast("long").alias("used"),
        F.coalesce(1 - F.sum("used") / F.nullif(F.sum(cells), F.lit(0)), F.lit(0.0)).alias("padding_rate"),
        F.coalesce(F.sum(cells * F.col("width")), F.lit(0)).cast("long").alias("attention_cells"),
        F.coalesce(F.max(cells), F.lit(0)).cast("long").alias("peak_cells"),
        F.coalesce(F.max(cells * F.col("width")), F.lit(0)).cast("long").alias("peak_attention"),
        F.coalesce(F.sum("truncated"), F.lit(0)).cast("long").alias("truncated"),
    ).select(F.lit(name).alias("layout"), "*")


def training_plan(n_rows: Column | int, epochs: int = 3, batch: int = 256, peak: float = 5e-5, warmup: int = 15) -> Column:
    """Array of ``(step, epoch, lr)``: linear warm-up, then a cosine to zero."""
    n_rows = F.lit(n_rows) if isinstance(n_rows, int) else n_rows
    per = F.ceil(n_rows / batch)
    total = per * epochs

    def at(s: Column) -> Column:
        decay = peak * 0.5 * (1 + F.cos(F.pi() * (s - warmup) / F.greatest(total - warmup, F.lit(1))))
        return F.struct(s.alias("step"), (F.floor((s - 1) / per) + 1).cast("int").alias("epoch"), F.when(s <= warmup, peak * s / warmup).otherwise(decay).alias("lr"))

    return F.transform(F.sequence(F.lit(1).cast("long"), F.greatest(total, F.lit(1))), at)
