"""SimHash near-duplicates by deletion-variant signatures (operator 2).

A 64-bit fingerprint is cut into two segments.  Two fingerprints that differ in at most three bits have a segment that
differs in at most one, so they share a variant of it with one bit wildcarded.  Distinct fingerprints are
indexed under their 64 variants, equal variants meet by an equality shuffle, and every meeting is verified on all 64 bits.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import LongType

from .components import connected_components
from .scratch import stored
from .text import free_name

MAX_DISTANCE = 3
SHINGLE_WORDS = 3
SEED = 42
#: Shingles whose bits are added at a time, so that a long text needs no more memory than a short one.
CHUNK = 1 << 16
#: Meetings of up to this many fingerprints are compared pair by pair, larger ones by search from one member to the next.
PAIR_RUN = 32
#: Meetings above this are first split by the variants of the other segment.
SPLIT_RUN = 4096


def fingerprint(text: str | None) -> int:
    """SimHash of a text as a signed 64-bit integer; no words: zero."""
    import xxhash

    tokens = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not tokens:
        return 0
    if len(tokens) < SHINGLE_WORDS:
        shingles = iter([b" ".join(tokens)])
        total = 1
    else:
        shingles = map(b" ".join, zip(*(tokens[i:] for i in range(SHINGLE_WORDS)), strict=False))
        total = len(tokens) - SHINGLE_WORDS + 1
    digest = xxhash.xxh64_intdigest
    ones = np.zeros(64, np.int64)
    for at in range(0, total, CHUNK):
        size = min(CHUNK, total - at)
        hashes = np.fromiter((digest(next(shingles), SEED) for _ in range(size)), np.uint64, size)
        ones += np.unpackbits(hashes.astype("<u8").view(np.uint8), bitorder="little").reshape(-1, 64).sum(0, dtype=np.int64)
    return int(np.packbits(2 * ones > total, bitorder="little").view("<i8")[0])


@F.pandas_udf(LongType())
def fingerprint_udf(texts: pd.Series) -> pd.Series:
    return pd.Series([fingerprint(t) for t in texts], dtype="int64")


def _span(prints: np.ndarray, split: int = SPLIT_RUN) -> list[tuple[np.ndarray, np.ndarray]]:
    """Links that connect what is connected among ``prints`` (distinct), without listing all pairs."""
    if len(prints) > split:
        out, cut = [], prints.view(np.uint64)
        # 16-bit quarters: of three differing bits one of the four has none; each value of a quarter is searched by itself.
        for quarter in range(4):
            part = (cut >> np.uint64(16 * quarter)) & np.uint64(0xFFFF)
            order = np.argsort(part, kind="stable")
            for group in np.split(order, np.flatnonzero(np.diff(part[order])) + 1):
                if 1 < len(group) < len(prints):
                    out += _span(prints[group], split)
                elif len(group) == len(prints):
                    out += _span(prints, len(prints))
                    return out
        return out
    left = prints.view(np.uint64)
    rest = np.arange(len(left))
    out = []
    while len(rest):
        queue, rest = [rest[0]], rest[1:]
        while queue and len(rest):
            at = queue.pop()
            near = np.bitwise_count(left[rest] ^ left[at]) <= MAX_DISTANCE
            if near.any():
                out.append((np.full(int(near.sum()), prints[at]), prints[rest[near]]))
                queue += rest[near].tolist()
                rest = rest[~near]
    return out


def _verify(keys: np.ndarray, prints: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Links within runs of equal keys."""
    starts = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]])
    sizes = np.diff(np.r_[starts, len(keys)])
    found = []
    for at, n in zip(starts[sizes > PAIR_RUN], sizes[sizes > PAIR_RUN], strict=True):
        found += _span(prints[at : at + n])
    inside = np.repeat(sizes, sizes) <= PAIR_RUN
    small, small_keys = prints[inside], keys[inside]
    for gap in range(1, int(sizes[sizes <= PAIR_RUN].max(initial=1))):
        same = np.flatnonzero(small_keys[gap:] == small_keys[:-gap])
        a, b = small[same], small[same + gap]
        near = np.bitwise_count(a.view(np.uint64) ^ b.view(np.uint64)) <= MAX_DISTANCE
        found.append((a[near], b[near]))
    if not found:
        return prints[:0], prints[:0]
    return np.concatenate([a for a, _ in found]), np.concatenate([b for _, b in found])


def _links(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Input: ``key, fp`` sorted by key; a run that continues into the next batch is kept back."""
    held: list[tuple[np.ndarray, np.ndarray]] = []

    def out(keys: np.ndarray, prints: np.ndarray) -> pa.RecordBatch:
        a, b = _verify(keys, prints)
        pairs = np.unique(np.stack([np.maximum(a, b), np.minimum(a, b)], 1), axis=0)
        return pa.RecordBatch.from_pydict({"src": pa.array(pairs[:, 0], pa.int64()), "dst": pa.array(pairs[:, 1], pa.int64())})

    for batch in batches:
        if not batch.num_rows:
            continue
        keys, prints = batch.column(0).to_numpy(), batch.column(1).to_numpy()
        last = int(np.searchsorted(keys, keys[-1]))
        if held and (last or held[0][0][0] != keys[0]):
            yield out(np.concatenate([*(k for k, _ in held), keys[:last]]), np.concatenate([*(p for _, p in held), prints[:last]]))
            held, keys, prints = [], keys[last:], prints[last:]
        elif last:
            yield out(keys[:last], prints[:last])
            keys, prints = keys[last:], prints[last:]
        if len(keys):
            held.append((keys, prints))
    if held:
        yield out(np.concatenate([k for k, _ in held]), np.concatenate([p for _, p in held]))


def fingerprint_links(prints: DataFrame) -> DataFrame:
    """``src, dst``: links of at most three differing bits that connect the distinct values of column ``fp``."""
    value = F.col("fp")
    halves = (value.bitwiseAND(F.lit(0xFFFFFFFF)), F.shiftrightunsigned(value, 32))
    keys = F.array(*(F.lit((side << 37) | (bit << 32)).bitwiseOR(halves[side].bitwiseAND(F.lit(0xFFFFFFFF ^ (1 << bit)))) for side in (0, 1) for bit in range(32)))
    variants = prints.select("fp").select(F.explode(keys).alias("key"), "fp")
    met = variants.repartition("key").sortWithinPartitions("key", "fp")
    return met.mapInArrow(_links, "src long, dst long").distinct()


def simhash_components(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id") -> DataFrame:
    """Columns of ``docs`` without the text, plus ``fp`` (signed fingerprint), ``fingerprint`` (16 hex digits) and ``component_id``.

    ``component_id`` is the smallest id that a document reaches over links of at most three differing bits.  Null, empty and
    wordless texts have fingerprint zero and link like any other.  Repeated rows stay and share a component; a null id is never the smallest
    unless all ids of the component are null.  Columns that bear an added column's name are replaced.
    """
    kept = [c for c in docs.columns if c.lower() not in ("fp", "fingerprint", "component_id") and c != text_col]
    rows = stored(docs.select(*kept, fingerprint_udf(F.col(text_col)).alias("fp")), "prints")
    distinct = stored(rows.groupBy("fp").agg(F.min(id_col).alias("low")), "distinct")
    roots = connected_components(fingerprint_links(distinct)).select(F.col("node").alias("fp"), "component")
    rooted = distinct.join(roots, "fp", "left").withColumn("component", F.coalesce("component", "fp"))
    low = rooted.groupBy("component").agg(F.min("low").alias("component_id"))
    labels = stored(rooted.join(low, "component").select(F.col("fp").alias("_fp"), "component_id"), "labels")
    return rows.join(labels, rows["fp"] == labels["_fp"]).select(*kept, "fp", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def one_per_component(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id") -> DataFrame:
    """``docs`` with one row of every component: that of the smallest id (of equal ids the smallest row hash); null ids come last."""
    tie = free_name("row_hash", docs.columns)
    # Equal id and equal text make one document; the hash serves as its key in both shuffles below.
    text_or_null = F.coalesce(F.concat(F.lit("t"), F.col(text_col)), F.lit("n"))
    tagged = docs.withColumn(tie, F.md5(F.concat_ws(":", F.coalesce(F.col(id_col).cast("string"), F.lit("n")), text_or_null)))
    found = simhash_components(tagged.select(id_col, tie, text_col), text_col, id_col)
    order = F.struct(F.col(id_col).isNull().alias("n"), F.col(id_col).alias("d"), F.col(tie).alias("t"))
    # A component of null ids only has a null component_id, so it is named by its fingerprint as well.
    best = found.groupBy("component_id", F.when(F.col("component_id").isNull(), F.col("fp"))).agg(F.min(order).alias("b"))
    ids = best.select(F.col("b.t").alias("_t"))
    return tagged.join(ids, tagged[tie] == ids["_t"], "left_semi").dropDuplicates([tie]).select(*docs.columns)
