"""Fuzzy line deduplication (operator 9), in DataFrame expressions only.

Lines are met exactly by a 128-bit hash first.  Each distinct line gets a MinHash signature of its character shingles, the very set that links are verified
on: a hash orders the shingles, and a band is the run of the next ROWS of them from a fixed place on.  Equal bands meet in an equality shuffle; candidates are
verified by the exact Jaccard similarity of their full character-shingle sets; and components over verified links keep one line, the first by document id and line number.
In between a line is known by the first 64 bits of its hash, not by a place, so rows without an id or with a repeated one cannot be taken for each other.

Every line of a bucket is a candidate with the first of it and with its predecessor, in an order of the lines that is the same in every bucket, so a group of
copies gives each line the same few partners again and again.  A bucket of three lines is so compared in full.  In larger ones that end in several
components every two lines of different components are compared: first by their sizes and by a sketch that tells how many shingles they differ in at least,
then, if these allow the similarity, in full.  So two similar lines of one bucket always end in one component.
tests/llm measures the share of similar pairs that meet in a bucket.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .components import connected_components
from .scratch import discard, free_shuffles, stored
from .text import free_name, let

#: What rounding may take from a product with the similarity.
SIMILARITY, SLACK = 0.8, 1e-6
#: Characters (code points) of a shingle, of verification and signature alike.
SHINGLE = 5
#: Places in each order of the shingles, from which runs of ROWS start: the run of the union of two sets is in both sets, and so theirs, with
#: a probability of about s^ROWS at similarity s.  A pair meets with 1 - (1 - s^6)^16 or more: 0.99 at 0.8.  Unlike lines seldom do, and those that do grow with the
#: square of the lines: runs of 6 from 16 places in place of 5 from 12 make them a third at similarity 0.25, and more of those of 0.8 meet.
STARTS, ROWS = (16, 4, 4, 4), 6
#: Runs of the first order overlap in lines of few shingles, which get runs of the other orders besides (SHORT), and those of fewest, where one shingle
#: that differs is in nearly every run, shorter ones too (FEW).  These come on top: every pair shares the bands of the first order, whatever its sizes.
#: Runs of the other orders stay shorter: in lines of few shingles longer ones find less.
SHORT, FEW, OTHER, PAIR = 100, 10, 5, 2
#: Of the exact pass: 64-bit words of a line's parities (a power of two), and lines of a block; this decides about its cost only.
WORDS, BLOCK = 16, 1000
#: Line numbers per document in the order key.
LINES = 1 << 31


def _order(doc: Column, pos: Column) -> Column:
    """(document id, line number) as one number; a null id comes last."""
    return (F.coalesce(doc.cast("decimal(20,0)"), F.lit(str(2**63)).cast("decimal(20,0)")) * F.lit(str(LINES)).cast("decimal(10,0)") + pos.cast("decimal(10,0)")).cast("decimal(32,0)")


def _hashes(line: Column) -> Column:
    """A hash of every character shingle, with repeats; a line of fewer characters is its own shingle.

    Shingles are cut from four bytes per character, where every place is found without counting from the start.
    """
    width = 4 * SHINGLE
    each = lambda b: F.transform(F.sequence(F.lit(1), F.octet_length(b) - (width - 1), F.lit(4)), lambda i: F.xxhash64(F.substring(b, i, F.lit(width))))
    return F.when(F.length(line) >= SHINGLE, let(F.encode(line, "UTF-32"), each)).otherwise(F.array(F.xxhash64(F.encode(line, "UTF-32"))))


def _places(starts: int) -> list[Column]:
    return [F.lit((start << 64) // starts - (1 << 63)).cast("long") for start in range(starts)]


def _with_keys(lines: DataFrame, order: int, starts: int, rows: int, ordered: str, name: str) -> DataFrame:
    """``lines`` with keys of the runs of ``ordered`` as ``name``, in its place; null where it is null.

    The places are put into the order and looked up there.  Three steps, as what stands beside a function that takes a lambda is not compiled, and one
    method for all would be too large for that.  Runs are taken element by element: a slice would box all of the ring, and one beyond its end is null and hashes to nothing.
    """
    names, places = [c for c in lines.columns if c != ordered], _places(starts)
    out = lines.select(*names, F.concat(ordered, F.slice(ordered, 1, rows)).alias("_ring"), F.sort_array(F.concat(ordered, F.array(*places))).alias("_placed"))
    out = out.select(*names, "_ring", F.array(*(F.array_position("_placed", p).cast("int") - i - 1 for i, p in enumerate(places))).alias("_at"))
    key = lambda a, i: F.xxhash64(F.lit(order), i, F.lit(rows), *(F.get("_ring", a + j) for j in range(rows)))
    # A second use of the array, for which it is not moved into this step.
    return out.select(*names, F.when(F.get("_at", F.lit(0)).isNotNull(), F.transform("_at", key)).alias(name))


def _signed(lines: DataFrame, column: str = "line") -> DataFrame:
    """``lines`` with ``n_shingles``, the size of its shingle set, and ``keys`` in place of ``column``.

    Only lines of few shingles have other orders than the first; these are null in the rest and cost next to nothing there.
    """
    names, none = [c for c in lines.columns if c != column], F.array().cast("array<long>")
    out = lines.select(*names, F.sort_array(F.array_distinct(_hashes(F.col(column)))).alias("_o0"))
    # Order, places and elements of a run.
    more = [(o, STARTS[o], OTHER) for o in range(1, len(STARTS))] + [(o, 1, PAIR) for o in range(len(STARTS))]
    least = {OTHER: SHORT, PAIR: FEW}
    other = lambda o, rows: F.transform(F.when(F.size("_o0") <= least[rows], F.col("_o0")), lambda h: F.xxhash64(h, F.lit(o)))
    out = out.select(*names, F.size("_o0").alias("_n"), "_o0", *(F.sort_array(other(o, rows)).alias(f"_o{rows}_{o}") for o, _, rows in more))
    out = _with_keys(out, 0, STARTS[0], ROWS, "_o0", "_k0")
    for o, starts, rows in more:
        out = _with_keys(out, o, starts, rows, f"_o{rows}_{o}", f"_k{rows}_{o}")
    return out.select(*names, F.col("_n").alias("n_shingles"), F.concat("_k0", *(F.coalesce(f"_k{rows}_{o}", none) for o, _, rows in more)).alias("keys"))


def _occurrences(docs: DataFrame, text_col: str, id_col: str) -> DataFrame:
    # Outer forms of explode here and below: for the plain ones the optimizer adds a filter on the exploded array, which makes the array twice.
    lines = docs.select(F.col(id_col).alias("doc"), F.xxhash64(text_col).alias("text"), F.posexplode_outer(F.split(F.col(text_col), "\n")).alias("pos", "line"))
    lines = lines.filter(F.col("line").rlike(r"[^\x20\x09-\x0D]"))
    return lines.select("doc", "text", _order(F.col("doc"), F.col("pos")).alias("at"), F.xxhash64("line").alias("h1"), F.xxhash64(F.lit(1), "line").alias("h2"), "line")


def _pairs(met: DataFrame) -> DataFrame:
    """``u, v, n_u, n_v``: different pairs of ``id, n`` with ``other.id, other.n`` whose sizes allow the similarity, with their sizes."""
    least, most = F.least("n", F.col("other.n")), F.greatest("n", F.col("other.n"))
    fit = met.filter(least >= SIMILARITY * most - SLACK)
    first = F.col("id") > F.col("other.id")
    a, b = F.struct("id", "n"), F.struct(F.col("other.id").alias("id"), F.col("other.n").alias("n"))
    pair = fit.select(F.when(first, a).otherwise(b).alias("a"), F.when(first, b).otherwise(a).alias("b"))
    return pair.select(F.col("a.id").alias("u"), F.col("b.id").alias("v"), F.col("a.n").alias("n_u"), F.col("b.n").alias("n_v")).distinct()


def _verified(candidates: DataFrame, texts: DataFrame) -> DataFrame:
    """The candidates ``u, v, n_u, n_v`` whose lines have a Jaccard similarity of SIMILARITY or more, as links ``src, dst``."""
    left = candidates.join(texts.withColumnRenamed("line", "a"), candidates["u"] == texts["id"]).drop("id")
    right = texts.select(F.col("id").alias("_v"), F.col("line").alias("b"))
    sets = left.join(right, left["v"] == right["_v"]).select("u", "v", (F.col("n_u") + F.col("n_v")).alias("n"), _hashes(F.col("a")).alias("a"), _hashes(F.col("b")).alias("b"))
    # Stored before it is filtered: a filter would move below the sets and make them twice.
    judged = stored(sets.select("u", "v", "n", F.size(F.array_intersect("a", "b")).alias("both")), "judged")
    return judged.filter(F.col("both") >= SIMILARITY * (F.col("n") - F.col("both")) - SLACK).select(F.col("u").alias("src"), F.col("v").alias("dst"))


def _meeting(bands: DataFrame) -> DataFrame:
    """``key, id, n, n0, n1, crowded``: every line of a bucket but its first, with the first and the one before it; ``crowded`` from the fourth on."""
    inside = Window.partitionBy("key").orderBy("id")
    # Plain columns: what a window takes of a struct would be made before the shuffle and go through it.
    ends = [f(c).over(inside).alias(f"{c}{at}") for at, f in enumerate((F.first, F.lag)) for c in ("id", "n")]
    met = bands.select("key", "id", "n", *ends, (F.row_number().over(inside) > 3).alias("crowded")).filter("id1 is not null")
    return met.select("key", "id", "n", *(F.struct(F.col(f"id{at}").alias("id"), F.col(f"n{at}").alias("n")).alias(f"n{at}") for at in (0, 1)), "crowded")


def _crowds(met: DataFrame) -> DataFrame:
    """``key, id``: all lines of buckets of more than three, stored."""
    keys = met.filter("crowded").select("key").distinct()
    return stored(met.join(keys.hint("merge"), "key", "left_semi").select("key", F.explode(F.array("id", "n0.id")).alias("id")).distinct(), "crowds")


def _undecided(crowds: DataFrame, roots: DataFrame) -> DataFrame:
    """``key, id, comp, lines``: lines of buckets of more than three that are still in several components, with the number of lines of the bucket."""
    inside = crowds.join(roots.hint("merge"), crowds["id"] == roots["node"], "left").select("key", "id", F.coalesce("component", "id").alias("comp"))
    inside = stored(inside, "crowded")
    split = inside.groupBy("key").agg(F.min("comp").alias("low"), F.max("comp").alias("high"), F.count(F.lit(1)).alias("lines")).filter("low != high").select("key", "lines")
    out = stored(inside.join(split.hint("merge"), "key"), "undecided")
    discard(inside)
    return out


def _sketched(lines: DataFrame) -> DataFrame:
    """``id, n, w0, w1, ...``: the size of the shingle set of each of ``lines`` (``id, line``) and its parities: a bit is set if an odd number of shingles fall on it.

    Where two lines differ in a bit, their sets differ in a shingle of its own for it, so they differ in as many shingles at least.
    """
    each = lines.select("id", F.explode_outer(F.array_distinct(_hashes(F.col("line")))).alias("h"))
    each = each.select("id", F.expr(f"shiftright(h, 6) & {WORDS - 1}").alias("at"), F.expr("shiftleft(1L, cast(h & 63 as int))").alias("bit"))
    return each.groupBy("id").agg(F.count(F.lit(1)).alias("n"), *(F.bit_xor(F.when(F.col("at") == i, F.col("bit")).otherwise(F.lit(0).cast("long"))).alias(f"w{i}") for i in range(WORDS)))


def _exact_pairs(undecided: DataFrame, texts: DataFrame) -> DataFrame:
    """``u, v, n_u, n_v``: all pairs of lines of one bucket and different components that may have the similarity by their sizes and parities."""
    ids = undecided.select("id").distinct()
    sketches = stored(_sketched(texts.join(ids.hint("merge"), "id", "left_semi")), "sketches")
    # A large bucket is cut into blocks of lines, every two of which (and each with itself) are a key of their own.
    blocks = F.ceil(F.col("lines") / BLOCK).cast("long")
    dealt = undecided.select("key", "id", "comp", F.pmod("id", blocks).alias("block"), F.explode_outer(F.sequence(F.lit(0).cast("long"), blocks - 1)).alias("other"))
    dealt = dealt.select("key", F.least("block", "other").alias("low"), F.greatest("block", "other").alias("high"), "id", "comp", "block")
    a = dealt.join(sketches.hint("merge"), "id")
    b = a.select("key", "low", "high", *(F.col(c).alias(f"{c}_") for c in a.columns if c not in ("key", "low", "high")))
    differ = sum((F.bit_count(F.col(f"w{i}").bitwiseXOR(F.col(f"w{i}_"))) for i in range(1, WORDS)), F.bit_count(F.col("w0").bitwiseXOR(F.col("w0_"))))
    fit = F.least("n", "n_") >= SIMILARITY * F.greatest("n", "n_") - SLACK
    # Sets of that similarity differ in so many shingles at most.
    near = differ <= (1 - SIMILARITY) / (1 + SIMILARITY) * (F.col("n") + F.col("n_")) + SLACK
    same = [F.col(f"a.{c}") == F.col(f"b.{c}") for c in ("key", "low", "high")]
    met = a.alias("a").join(b.hint("merge").alias("b"), [*same, (F.col("id") < F.col("id_")) & (F.col("comp") != F.col("comp_")) & ((F.col("a.low") == F.col("a.high")) | (F.col("block") != F.col("block_"))) & fit & near])
    out = stored(_pairs(met.select("id", "n", F.struct(F.col("id_").alias("id"), F.col("n_").alias("n")).alias("other"))), "exact")
    discard(sketches)
    return out


def line_classes(lines: DataFrame) -> DataFrame:
    """``h1, h2, id, keep, first``: every distinct line with its number, that of the line its component keeps, and whether it is that line.

    ``lines`` has one row per distinct line, ``h1, h2, id, line``; it is read for the signatures and for the texts of lines that met another.  A
    number is document id times 2^31 plus the zero-based line number of the line's first occurrence.
    """
    keyed = _signed(lines.select(F.col("h1").alias("id"), "line"))
    met = stored(_meeting(keyed.select("id", F.col("n_shingles").alias("n"), F.explode_outer("keys").alias("key"))), "met")
    free_shuffles(met)
    pairs = stored(_pairs(met.select("id", "n", F.explode(F.array_distinct(F.array("n0", "n1"))).alias("other"))), "candidates")
    crowds = _crowds(met)
    discard(met)
    # A line whose size fits neither of the two it met may still be like others of its bucket.
    wanted = pairs.select(F.explode(F.array("u", "v")).alias("id")).union(crowds.select("id")).distinct()
    # Joins ask for a merge: these tables grow with the documents, so none may be broadcast because it happens to be small.
    # Texts of lines that met another.
    texts = stored(lines.select(F.col("h1").alias("id"), "line").join(wanted.hint("merge"), "id", "left_semi").dropDuplicates(["id"]), "texts")
    free_shuffles(texts)
    roots = connected_components(_verified(pairs, texts))
    discard(pairs)
    undecided = _undecided(crowds, roots)
    discard(crowds)
    more = stored(_verified(_exact_pairs(undecided, texts), texts), "links")
    lines_of = undecided.select("id", "comp").distinct()
    ends = [lines_of.select(F.col("id").alias(end), F.col("comp").alias(f"{end}_comp")) for end in ("src", "dst")]
    joined = connected_components(more.join(ends[0].hint("merge"), "src").join(ends[1].hint("merge"), "dst"), "src_comp", "dst_comp")
    joined = joined.select(F.col("node").alias("part"), F.col("component").alias("whole"))
    # Components that the second pass joined take its root; lines that only it links come in from the right.
    roots = roots.join(joined.hint("merge"), roots["component"] == joined["part"], "full").select(F.coalesce("node", "part").alias("node"), F.coalesce("whole", "component").alias("component"))
    # The first line of every component, by number; lines of rows that share an id may have the same number, of which the smaller hash goes first.
    numbers = lines.select("h1", "h2", "id")
    member = numbers.join(roots.hint("merge"), numbers["h1"] == roots["node"]).select("component", "h1", "h2", "id")
    kept = stored(member.groupBy("component").agg(F.min(F.struct("id", "h1", "h2")).alias("kept")), "kept")
    whole = roots.join(kept.hint("merge"), "component").select("node", "kept")
    out = numbers.join(whole.hint("merge"), numbers["h1"] == whole["node"], "left")
    out = out.select("h1", "h2", "id", F.coalesce("kept.id", "id").alias("keep"), F.coalesce((F.col("kept.h1") == F.col("h1")) & (F.col("kept.h2") == F.col("h2")), F.lit(True)).alias("first"))
    out = stored(out, "classes")
    for old in (texts, undecided, more, kept):
        discard(old)
    return out


def distinct_lines(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id") -> DataFrame:
    """``h1, h2, id, line``: every different line that has a word, once, with the number of its first occurrence; stored."""
    seen = _occurrences(docs, text_col, id_col)
    out = stored(seen.groupBy("h1", "h2").agg(F.min("at").alias("id"), F.first("line").alias("line")), "lines")
    free_shuffles(out)
    return out


def dedup_lines(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id") -> DataFrame:
    """Columns of ``docs`` with repeated and near-repeated lines taken out of the text, plus ``n_lines`` and ``n_dropped``.

    Lines are parts between ``\\n``; of all lines of a component the one of the smallest document id, then line number, stays and the others go.
    Lines without a word are neither compared nor dropped (``n_lines`` does not count them).  Null text stays null and an empty one empty.  Rows that share an
    id count as one document: the kept line stays in each that has it at that line number; every row loses lines of its own text only.  Null ids come last.
    Columns that bear an added column's name are replaced.
    """
    names = [c for c in docs.columns if c.lower() not in ("n_lines", "n_dropped")]
    distinct = distinct_lines(docs, text_col, id_col)
    classes = line_classes(distinct)
    discard(distinct)
    at, gone, own = free_name("line_doc", names), free_name("line_gone", names), free_name("line_text", names)
    fate = _occurrences(docs, text_col, id_col).drop("line").join(classes.hint("merge"), ["h1", "h2"]).filter("at != keep or not first")
    # By id and text: rows that share an id, or have none, may differ in their lines.
    drops = fate.groupBy(F.coalesce(F.col("doc").cast("decimal(20,0)"), F.lit(str(2**63)).cast("decimal(20,0)")).alias("_doc"), F.col("text").alias("_text")).agg(
        F.collect_set(F.pmod(F.col("at"), F.lit(str(LINES)).cast("decimal(10,0)")).cast("int")).alias("_gone")
    )
    drops = stored(drops, "drops")
    discard(classes)
    free_shuffles(drops)
    rows = docs.select(*names).withColumns({at: F.coalesce(F.col(id_col).cast("decimal(20,0)"), F.lit(str(2**63)).cast("decimal(20,0)")), own: F.xxhash64(text_col)})
    joined = rows.join(drops.hint("merge"), (rows[at] == drops["_doc"]) & (rows[own] == drops["_text"]), "left").withColumn(gone, F.coalesce("_gone", F.array().cast("array<int>")))

    def rebuild(lines: Column) -> Column:
        stay = F.array_except(F.sequence(F.lit(0), F.size(lines) - 1), F.col(gone))
        return F.array_join(F.transform(stay, lambda i: lines[i]), "\n")

    lines = F.split(F.col(text_col), "\n")
    n_lines = F.coalesce(F.size(F.filter(lines, lambda line: line.rlike(r"[^\x20\x09-\x0D]"))), F.lit(0))
    done = joined.withColumns({"n_lines": F.when(F.col(text_col).isNull(), 0).otherwise(n_lines).cast("long"), "n_dropped": F.size(gone).cast("long")})
    return done.withColumn(text_col, F.when(F.size(gone) > 0, let(lines, rebuild)).otherwise(F.col(text_col))).select(*names, "n_lines", "n_dropped")
