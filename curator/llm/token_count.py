"""Token counts without token ids (operator 7).

Three steps.  The distinct pre-tokens of all texts are counted: tasks add up what they see, a shuffle adds up the tasks.  The library says once per distinct
pre-token how many pieces it has; that table is stored.  Then each document's pre-token frequencies are joined to it: up to HEAD of the most
frequent pre-tokens, a table of bounded size that most of a text consists of, inside the tasks that count the frequencies; the others as rows
``(document, pre-token, frequency)`` in a shuffle join, whose sums per document come back by a row number.  So no pre-token is hot in the shuffle.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, StructType

from .pretokens import blocks, strides, tokenizer
from .scratch import stored
from .text import free_name

_OTHERS = ArrayType(StructType().add("part", "binary").add("n", "long"))
#: Pre-tokens of the table that every task holds: some 20 bytes each to send, 150 to hold.
HEAD = 200_000
#: Steps of the frequency per factor of two; the head takes whole steps, of which there are fewer than a thousand.
STEPS = 16
#: Distinct pre-tokens that a task adds up before it passes them on.
FLUSH = 400_000
#: Pre-tokens that the library gets at a time.
ASKED = 4096


def _cut(path: str) -> Callable[[str], Iterable[str]]:
    """How the texts for a model file are cut: into pre-tokens, or for sentencepiece into parts that begin with spaces."""
    if path.endswith(".json"):
        return lambda text: (p for parts, _ in blocks(text) for p in parts)
    from .piece_bpe import parts_of

    return parts_of


def _sizes(path: str) -> Callable[[list[str]], list[int]]:
    """How many pieces the library makes of each of some pre-tokens."""
    if path.endswith(".json"):
        lib = tokenizer(path)
        return lambda parts: [len(e) for e in lib.encode_batch_fast(parts, add_special_tokens=False)]
    from .piece_bpe import META, load

    model = load(path)
    return lambda parts: [len(ids) // 4 for ids in model.encode_parts([p.replace(" ", META) for p in parts])]


def _texts(batch: pa.RecordBatch, at: int) -> Iterator[str]:
    return (t.as_py() or "" for t in batch.column(at))


def piece_table(docs: DataFrame, model_path: str, text_col: str = "text") -> DataFrame:
    """``part, n, pieces``: every distinct pre-token of all texts (UTF-8 bytes), its frequency, and how many pieces the library makes of it; stored."""

    def seen(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cut, held = _cut(model_path), Counter()

        def out() -> pa.RecordBatch:
            made = pa.RecordBatch.from_arrays([pa.array([p.encode("utf-8") for p in held], pa.binary()), pa.array(held.values(), pa.int64())], ["part", "n"])
            held.clear()
            return made

        for batch in batches:
            for text in _texts(batch, 0):
                held.update(cut(text))
                if len(held) > FLUSH:
                    yield out()
        yield out()

    def sized(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ask = _sizes(model_path)
        for batch in batches:
            parts = [p.decode("utf-8") for p in batch.column(0).to_pylist()]
            pieces = [n for at in range(0, len(parts), ASKED) for n in ask(parts[at : at + ASKED])]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(pieces, pa.int64())], ["part", "n", "pieces"])

    distinct = docs.select(text_col).mapInArrow(seen, "part binary, n long").groupBy("part").agg(F.sum("n").alias("n"))
    return stored(distinct.mapInArrow(sized, "part binary, n long, pieces long"), "pieces")


def count_tokens(docs: DataFrame, model_path: str, limit: int = 2048, text_col: str = "text", head: int = HEAD) -> DataFrame:
    """Columns of ``docs`` without the text, plus ``n_bytes``, ``n_tokens`` and ``over_limit``.

    Counts are those of the library for the file: tokenizers for ``.json`` (special strings inside a text count as the library's default has it),
    sentencepiece for ``.model``; no begin, end, truncation or padding.  Null counts as empty: zero bytes and tokens.
    A JSON file must cut texts as the word-BPE file does, a model file must be one that ``piece_bpe`` takes.
    Repeated rows stay; columns that bear an added column's name are replaced; an empty table gives an empty one.
    """
    kept = [c for c in docs.columns if c != text_col and c.lower() not in ("n_bytes", "n_tokens", "over_limit")]
    row, rest = free_name("count_row", kept), free_name("count_rest", kept)
    table = piece_table(docs, model_path, text_col)
    # The head has a proven bound, whatever the corpus; it goes to the driver and from there to the tasks.
    step = F.floor(F.log2("n") * STEPS)
    room, least = head, None
    for r in table.groupBy(step.alias("step")).agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("step")).collect():
        room -= r.n
        if room < 0:
            break
        least = r.step
    common = {bytes(r.part): r.pieces for r in table.filter(step >= least).select("part", "pieces").collect()} if least is not None else {}
    shared = docs.sparkSession.sparkContext.broadcast(common)
    body = docs.select(*kept, F.coalesce(F.col(text_col), F.lit("")).alias("_body"))
    schema = body.drop("_body").schema.add("n_bytes", "long").add("n_tokens", "long").add(row, "long").add(rest, _OTHERS)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        cut, known = _cut(model_path), {p.decode("utf-8"): n for p, n in shared.value.items()}
        at = TaskContext.get().partitionId() << 40
        for batch in batches:
            n_bytes, n_tokens, others = [], [], []
            for texts in strides(_texts(batch, batch.num_columns - 1)):
                for text in texts:
                    frequency = Counter(cut(text))
                    pieces = list(map(known.get, frequency))
                    n_bytes.append(len(text.encode("utf-8")))
                    n_tokens.append(sum(n * k for n, k in zip(pieces, frequency.values(), strict=True) if n is not None))
                    others.append([{"part": p.encode("utf-8"), "n": k} for (p, k), n in zip(frequency.items(), pieces, strict=True) if n is None] if None in pieces else [])
            rows = pa.array(range(at, at + batch.num_rows), pa.int64())
            at += batch.num_rows
            made = [pa.array(n_bytes, pa.int64()), pa.array(n_tokens, pa.int64()), rows, pa.array(others, pa.list_(pa.struct([("part", pa.binary()), ("n", pa.int64())])))]
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], *made], schema.names)

    # Stored, so that row numbers stay what they are.
    made = stored(body.mapInArrow(run, schema), "counted")
    others = made.filter(F.size(rest) > 0).select(F.col(row).alias("_row"), F.explode_outer(rest).alias("_o")).select("_row", F.col("_o.part").alias("part"), F.col("_o.n").alias("k"))
    more = others.join(table.select("part", "pieces").hint("merge"), "part").groupBy("_row").agg(F.sum(F.col("k") * F.col("pieces")).alias("_more"))
    whole = made.join(more.hint("merge"), made[row] == more["_row"], "left").withColumn("n_tokens", F.col("n_tokens") + F.coalesce("_more", F.lit(0)))
    return whole.select(*kept, "n_bytes", "n_tokens", (F.col("n_tokens") > limit).alias("over_limit"))
