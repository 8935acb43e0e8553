"""Exact top-k inner-product search in tiles (operator 5).

Vectors are packed into blocks of contiguous integers.  Every query block meets every shard block
of its dimension in one tile: a matrix product, a partial selection of ``k + 1`` per query along the tile's rows, and then the
short lists are merged in a tree: shards are numbered, a node of a level merges the lists of FAN_IN nodes that are next to each other on the
level below, and there are as many levels as it takes to come to one list.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .scratch import stored

#: Rows of a shard and of a query block: 8,192 x 2,048 scores of 8 bytes are 128 MB at most, made in strips of QUERY_STRIP.
SHARD_ROWS, QUERY_ROWS, QUERY_STRIP = 8192, 2048, 256
#: Lists that a node of the merging tree takes.
FAN_IN = 16
SCALE = 256

_BLOCK = "dim int, block long, ids binary, vecs binary"
_LIST = "block long, dim int, node long, at int, query_id long, own long, ids array<long>, scores array<long>"


#: Component types of a block, the narrowest that holds it is taken; a block starts with its two letters.
_KINDS = ("<i2", "<i4", "<f8")


def _unpack(blob: bytes, rows: int) -> np.ndarray:
    return np.frombuffer(blob, f"<{blob[:2].decode()}", offset=2).reshape(rows, -1).astype(np.float64) if rows else np.zeros((0, 0))


def _integers(values: np.ndarray) -> np.ndarray:
    return np.floor(SCALE * values.astype(np.float64))


def _pack(rows: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part, serial = TaskContext.get().partitionId(), 0
        held: dict[int, list[tuple[int, np.ndarray]]] = {}

        def block(dim: int) -> pa.RecordBatch:
            nonlocal serial
            own = held.pop(dim)
            serial += 1
            ids = np.array([i for i, _ in own], "<i8").tobytes()
            vecs = np.stack([v for _, v in own]) if dim else np.zeros((len(own), 0))
            kind = next(t for t in _KINDS if t == "<f8" or np.abs(vecs).max(initial=0) < np.iinfo(t).max)
            vecs = kind[1:].encode() + vecs.astype(kind).tobytes()
            return pa.RecordBatch.from_pydict(
                {"dim": pa.array([dim], pa.int32()), "block": pa.array([(part << 33) + serial], pa.int64()), "ids": pa.array([ids], pa.binary()), "vecs": pa.array([vecs], pa.binary())}
            )

        for batch in batches:
            for vec_id, vec in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                values = np.asarray(vec.values.to_numpy(zero_copy_only=False))
                held.setdefault(len(values), []).append((vec_id, _integers(values)))
                if len(held[len(values)]) == rows:
                    yield block(len(values))
        for dim in list(held):
            yield block(dim)

    return run


def _product(queries: np.ndarray, shard: np.ndarray) -> np.ndarray:
    """Exact integer inner products: in floats where every partial sum fits their mantissa, else in integers (modulo 2^64)."""
    bound = float(np.abs(queries).max(initial=0)) * float(np.abs(shard).max(initial=0)) * max(1, queries.shape[1])
    if bound < 2**24:
        return (queries.astype(np.float32) @ shard.astype(np.float32).T).astype(np.int64)
    if bound < 2**53:
        return (queries @ shard.T).astype(np.int64)
    as_int = [[int(x) for x in row] for row in queries], [[int(x) for x in row] for row in shard]
    return np.array([[((sum(a * b for a, b in zip(q, s, strict=True)) + 2**63) % 2**64) - 2**63 for s in as_int[1]] for q in as_int[0]], np.int64).reshape(len(queries), len(shard))


def _best(scores: np.ndarray, ids: np.ndarray, k: int) -> tuple[list[np.ndarray], list[np.ndarray]]:
    """The k first of each row of ``scores`` (one column per id) by falling score, then rising id."""
    rows, n = scores.shape
    if n > k:
        # Everything from a row's k-th score on, ties included.
        at, column = np.nonzero(scores >= np.partition(scores, n - k, axis=1)[:, n - k, None])
    else:
        at, column = np.divmod(np.arange(rows * n), max(1, n))
    found, named = scores[at, column], ids[column]
    # -scores would overflow for the smallest integer; ~ keeps the order reversed.
    order = np.lexsort((named, ~found, at))
    at, found, named = at[order], found[order], named[order]
    place = np.arange(len(at)) - np.searchsorted(at, at)
    first = place < k
    cuts = np.searchsorted(at[first], np.arange(1, rows))
    return np.split(found[first], cuts), np.split(named[first], cuts)


def _tile(k: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in range(batch.num_rows):
                dim, block, node, q_ids, q_vecs, s_ids, s_vecs = (batch.column(i)[row].as_py() for i in range(7))
                q_ids, s_ids = np.frombuffer(q_ids, "<i8"), np.frombuffer(s_ids, "<i8")
                queries, shard = _unpack(q_vecs, len(q_ids)), _unpack(s_vecs, len(s_ids))
                ids, scores, own = [], [], []
                for at in range(0, len(queries), QUERY_STRIP):
                    strip = queries[at : at + QUERY_STRIP]
                    own += [int(_product(q[None, :], q[None, :])[0, 0]) for q in strip]
                    s, i = _best(_product(strip, shard), s_ids, k + 1)
                    scores += s
                    ids += i
                n = len(q_ids)
                yield pa.RecordBatch.from_pydict(
                    {
                        "block": pa.array(np.full(n, block), pa.int64()),
                        "dim": pa.array(np.full(n, dim), pa.int32()),
                        "node": pa.array(np.full(n, node), pa.int64()),
                        "at": pa.array(np.arange(n), pa.int32()),
                        "query_id": pa.array(q_ids, pa.int64()),
                        "own": pa.array(own, pa.int64()),
                        "ids": pa.array(ids, pa.list_(pa.int64())),
                        "scores": pa.array(scores, pa.list_(pa.int64())),
                    }
                )

    return run


def _first(pairs, k: int):
    """First k of an array of (score, id) structs by falling score and rising id."""
    return F.slice(F.array_sort(pairs, lambda a, b: F.when(a["s"] > b["s"], -1).when(a["s"] < b["s"], 1).when(a["i"] < b["i"], -1).when(a["i"] > b["i"], 1).otherwise(0)), 1, k)


def exact_topk(vectors: DataFrame, queries: DataFrame, k: int = 5, id_col: str = "vec_id", vec_col: str = "embedding", shard_rows: int = SHARD_ROWS, query_rows: int = QUERY_ROWS) -> DataFrame:
    """``query_id, rank, vec_id, score``: the ``k`` best rows of ``vectors`` for each row of ``queries``.

    Components become ``floor(256 * x)``; scores are integer inner products (taken modulo 2^64 should they ever leave the range of a long); ties go to the
    smaller id.  A query's own row is left out once: further rows with its id and vector stay candidates.  A row
    with a null id or vector, or with a null or non-finite component, takes no part; vectors meet those of equal length only.
    Repeated query rows give one list each; fewer than ``k`` candidates give shorter lists; empty tables give none.
    Other columns are ignored.
    """
    def blocks(df: DataFrame, rows: int) -> DataFrame:
        ok = df.select(F.col(id_col).cast("long").alias("id"), F.col(vec_col).cast("array<double>").alias("v")).filter(F.col("id").isNotNull() & F.col("v").isNotNull())
        ok = ok.filter(F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf"))))
        return ok.mapInArrow(_pack(rows), _BLOCK)

    shards = stored(blocks(vectors, shard_rows), "shards").select("dim", F.col("block").alias("shard"), F.col("ids").alias("s_ids"), F.col("vecs").alias("s_vecs"))
    asked = blocks(queries, query_rows).select("dim", "block", F.col("ids").alias("q_ids"), F.col("vecs").alias("q_vecs"))
    # The grid of tiles: shards are numbered (one row per SHARD_ROWS vectors), each query block visits every number, and
    # the equi-join on the number deals the tiles out evenly even if all vectors have one dimension.
    numbers = shards.select("shard", (F.row_number().over(Window.orderBy("shard")) - 1).cast("long").alias("node"))
    width = numbers.count()
    shards = shards.join(numbers, "shard")
    asked = asked.withColumn("node", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(max(1, width) - 1).cast("long"))))
    grid = asked.join(shards, ["dim", "node"])
    lists = grid.select("dim", "block", "node", "q_ids", "q_vecs", "s_ids", "s_vecs").mapInArrow(_tile(k), _LIST)
    lists = lists.withColumn("best", F.arrays_zip(F.col("scores").alias("s"), F.col("ids").alias("i"))).drop("ids", "scores")
    key = ["dim", "block", "at", "query_id", "own"]
    while width > 1:
        lists = lists.withColumn("node", F.expr(f"node div {FAN_IN}")).groupBy(*key, "node").agg(_first(F.flatten(F.collect_list("best")), k + 1).alias("best"))
        width = -(-width // FAN_IN)
    me = F.transform("best", lambda b: (b["i"] == F.col("query_id")) & (b["s"] == F.col("own")))
    spot = F.coalesce(F.array_position(me, True), F.lit(0))
    rest = F.filter("best", lambda b, i: i + 1 != F.col("spot"))
    ranked = lists.withColumn("spot", spot).select("query_id", F.posexplode(F.slice(rest, 1, k)).alias("rank", "hit"))
    return ranked.select("query_id", (F.col("rank") + 1).alias("rank"), F.col("hit.i").alias("vec_id"), F.col("hit.s").alias("score"))
