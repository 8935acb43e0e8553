"""Counts of neighbouring tokens, and look-ups of them, over chunks of texts in NumPy.

A chunk is some two million tokens of whole texts with a dictionary of its own.  Only its different pairs leave it, packed as arrays by a hash of the pair, so
a frequent word or pair counts once per chunk and no key is hot.  A word, and in scoring a pair, is known by 64 bits of a hash; two that share them would be taken for one.
"""

from __future__ import annotations

import numpy as np

#: Tokens of a chunk, about; a longer text is a chunk of its own.  This decides about memory and time only.
CHUNK = 2_000_000
START, UNKNOWN = "<s>", "<unk>"
CHUNKS = "chunk long, ids binary, aux binary, lens binary, codes binary, words binary"
PIECES = "bucket int, chunk long, a binary, b binary, c binary"


def hashes(words) -> np.ndarray:
    """64 bits of every word, the same in all processes."""
    from pandas.util import hash_array

    return hash_array(np.asarray(words, dtype=object), categorize=False).view(np.int64) if len(words) else np.zeros(0, np.int64)


START_ID, UNKNOWN_ID = (int(x) for x in hashes([START, UNKNOWN]))
#: First parts of keys that count words, and words that another follows.
WORD_KEY, HEAD_KEY = (int(x) for x in hashes(["\0word", "\0head"]))


def order_of(key: np.ndarray) -> np.ndarray:
    """The stable order of not negative keys."""
    n = len(key)
    if n and int(key.max()) < (1 << 62) // n:
        return np.sort(key * n + np.arange(n)) % n
    return np.argsort(key, kind="stable")


def grouped(key: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The stable order of keys, the starts of equal ones in it, and which of these groups each place of the order is in."""
    order = order_of(key)
    ranked = key[order]
    new = np.ones(len(key), bool)
    new[1:] = ranked[1:] != ranked[:-1]
    return order, np.flatnonzero(new), np.cumsum(new) - 1


def unique(key: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Different keys, the place of each key among them, and their counts."""
    order, first, group = grouped(key)
    inverse = np.empty(len(key), np.int64)
    inverse[order] = group
    return key[order[first]], inverse, np.diff(np.append(first, len(key)))


def _char_pairs(texts: list) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Numbers of pairs, places of all pairs of neighbouring characters among them, pairs of each text."""
    points = np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), np.uint32)
    whole = np.fromiter(map(len, texts), np.int64, len(texts))
    lens = np.maximum(whole - 1, 0)
    if not lens.any():
        return np.zeros(0, np.int64), np.zeros(0, np.int64), lens
    table = np.zeros(int(points.max()) + 1, np.int64)
    table[points] = 1
    alphabet = np.flatnonzero(table)
    table[alphabet] = np.arange(len(alphabet))
    local = table[points]
    keep = np.ones(len(points), bool)
    keep[(np.cumsum(whole) - 1)[whole > 0]] = False
    pair = (local[:-1] * len(alphabet) + local[1:])[keep[:-1]]
    if len(alphabet) ** 2 > 4 * CHUNK:
        used, codes, _ = unique(pair)
    else:
        used = np.flatnonzero(np.bincount(pair, minlength=1))
        names = np.zeros(used[-1] + 1, np.int64)
        names[used] = np.arange(len(used))
        codes = names[pair]
    return (alphabet[used // len(alphabet)] << 21) | alphabet[used % len(alphabet)], codes, lens


def text_chunks(batches):
    """``ids, aux, lens, codes, words, spelled`` of rows ``id, aux, t``: arrays of tokens, or texts, whose tokens are then the pairs of neighbouring
    characters; a pair's number holds the two and is in their order, so they are not spelled out."""
    import pyarrow as pa

    held, size = [], 0

    def flush():
        ids, aux = (np.concatenate([h[i] for h in held]) for i in range(2))
        if isinstance(held[0][2], list):
            words, codes, lens = _char_pairs([x for h in held for x in h[2]])
            return ids, aux, lens, codes, words, None
        flat = pa.chunked_array([h[2] for h in held], pa.string()).combine_chunks()
        flat = (flat.combine_chunks() if isinstance(flat, pa.ChunkedArray) else flat).dictionary_encode()
        spelled = flat.dictionary.to_numpy(zero_copy_only=False)
        return ids, aux, np.concatenate([h[3] for h in held]), flat.indices.to_numpy(zero_copy_only=False).astype(np.int64), hashes(spelled), spelled

    for batch in batches:
        if not batch.num_rows:
            continue
        ids, aux = (batch.column(c).to_numpy(zero_copy_only=False).astype(np.int64) for c in ("id", "aux"))
        t = batch.column("t")
        if pa.types.is_list(t.type) or pa.types.is_large_list(t.type):
            lens, flat = np.nan_to_num(t.value_lengths().to_numpy(zero_copy_only=False)).astype(np.int64), t.flatten()
        else:
            flat = [x or "" for x in t.to_pylist()]
            lens = np.fromiter(map(len, flat), np.int64, len(flat))
        at, ends = 0, np.append(0, np.cumsum(lens))
        while at < len(ids):
            to = max(at + 1, int(np.searchsorted(ends, ends[at] + CHUNK - size, "right")) - 1)
            held.append((ids[at:to], aux[at:to], flat[at:to] if isinstance(flat, list) else flat.slice(int(ends[at]), int(ends[to] - ends[at])), lens[at:to]))
            size += int(ends[to] - ends[at])
            at = to
            if size >= CHUNK or at < len(ids):
                yield flush()
                held, size = [], 0
    if held:
        yield flush()


def _task_chunk() -> int:
    from pyspark import TaskContext

    return TaskContext.get().partitionId() << 33


def _table(rows: list, schema: str):
    import pyarrow as pa

    kinds = {"long": pa.int64(), "int": pa.int32(), "binary": pa.binary()}
    named = [x.split() for x in schema.split(", ")]
    return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], kinds[k]) for i, (_, k) in enumerate(named)], names=[n for n, _ in named])


def write_chunks(batches):
    """A row of ``CHUNKS`` per chunk."""
    base = _task_chunk()
    for i, (ids, aux, lens, codes, words, _) in enumerate(text_chunks(batches)):
        planes = np.ascontiguousarray(codes.astype("<i4").view(np.uint8).reshape(-1, 4).T)  # equal high bytes side by side
        yield _table([(base + i, ids.tobytes(), aux.tobytes(), lens.astype(np.int32).tobytes(), planes.tobytes(), words.tobytes())], CHUNKS)


def read_chunk(row: dict) -> tuple:
    ids, aux, words = (np.frombuffer(row[c], np.int64) for c in ("ids", "aux", "words"))
    lens = np.frombuffer(row["lens"], np.int32).astype(np.int64)
    codes = np.ascontiguousarray(np.frombuffer(row["codes"], np.uint8).reshape(4, -1).T).view("<i4").ravel().astype(np.int64)
    return ids, aux, lens, codes, words


def rows_of(batches):
    for batch in batches:
        for i in range(batch.num_rows):
            yield batch.slice(i, 1).to_pylist()[0]


def before(lens: np.ndarray, codes: np.ndarray, start: int) -> np.ndarray:
    """The predecessor of every token; the first of a text has ``start``."""
    prev = np.empty_like(codes)
    prev[1:] = codes[:-1]
    prev[(np.cumsum(lens) - lens)[lens > 0]] = start
    return prev


def mixed(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """One number of each key."""
    with np.errstate(over="ignore"):
        x = a.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) + b.astype(np.uint64)
        x ^= x >> np.uint64(32)
        x *= np.uint64(0xD6E8FEB86659FD93)
        return x ^ (x >> np.uint64(29))


def dealt(a: np.ndarray, b: np.ndarray, buckets: int) -> tuple[np.ndarray, np.ndarray]:
    """The order of keys by bucket, and the bounds of the buckets in it."""
    return by_bucket(mixed(a, b), buckets)


def by_bucket(k: np.ndarray, buckets: int) -> tuple[np.ndarray, np.ndarray]:
    bucket = (k.view(np.uint64) % np.uint64(buckets)).astype(np.int64)
    return order_of(bucket), np.append(0, np.cumsum(np.bincount(bucket, minlength=buckets)))


def short(x: np.ndarray) -> bytes:
    """Not negative numbers in as few bytes each as they need."""
    most = int(x.max()) if len(x) else 0
    return x.astype(next(f"<i{w}" for w in (1, 2, 4, 8) if most < 1 << (8 * w - 1))).tobytes()


def long(data: bytes, n: int) -> np.ndarray:
    """``n`` numbers written by ``short``."""
    return np.frombuffer(data, f"<i{len(data) // n}").astype(np.int64) if n else np.zeros(0, np.int64)


def pieces(chunk: int, a: np.ndarray, b: np.ndarray, c: np.ndarray | None, buckets: int, numbered: bool = False):
    """Rows of ``PIECES``: keys with their counts, or without for a question; ``numbered``: one number of a key in place of its two parts."""
    if numbered:
        a = mixed(a, b).view(np.int64)
    order, bounds = by_bucket(a, buckets) if numbered else dealt(a, b, buckets)
    a, b, c = a[order], None if numbered else b[order], None if c is None else c[order]
    rows = [(i, chunk, a[x:y].tobytes(), b"" if b is None else b[x:y].tobytes(), b"" if c is None else short(c[x:y])) for i, (x, y) in enumerate(zip(bounds[:-1], bounds[1:], strict=True)) if y > x]
    if rows:
        yield _table(rows, PIECES)


def key_groups(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """``grouped`` for keys of two parts."""
    k = mixed(a, b)
    order = np.argsort(k)
    for _ in range(2):
        x, y, z = a[order], b[order], k[order]
        other = (x[1:] != x[:-1]) | (y[1:] != y[:-1])
        if not (other & (z[1:] == z[:-1])).any():
            break
        order = np.lexsort((b, a))  # two keys share the number
        k = np.arange(len(a))  # not compared again
        k[order] = np.arange(len(a))
    new = np.append(np.ones(min(1, len(a)), bool), other)
    return order, np.flatnonzero(new), np.cumsum(new) - 1


# Counting a corpus and asking for its counts.


def count_keys(buckets: int):
    def run(batches):
        base = _task_chunk()
        for i, (_, _, lens, codes, words, _) in enumerate(text_chunks(batches)):
            start = len(words)
            name = np.append(words, START_ID)
            prev = before(lens, codes, start)
            pair, _, n = unique(prev * (start + 1) + codes)
            heads = np.bincount(prev, minlength=start + 1)
            led = np.flatnonzero(heads)
            a = np.concatenate([name[pair // (start + 1)], np.full(start, WORD_KEY), np.full(len(led), HEAD_KEY)])
            b = np.concatenate([name[pair % (start + 1)], words, name[led]])
            # The last bit tells the counts of words.
            yield from pieces(base + i, a, b, np.concatenate([2 * n, 2 * np.bincount(codes, minlength=start) + 1, 2 * heads[led]]), buckets, True)

    return run


MODEL = PIECES + ", tokens long, known long, odd long"


UNKNOWN_NUMBER = int(mixed(np.array([WORD_KEY]), np.array([UNKNOWN_ID])).view(np.int64)[0])


def _number_sums(k: np.ndarray, n: np.ndarray, marked: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Different numbers, where they begin in their order, their sums, and which are marked."""
    order = np.argsort(k)
    k = k[order]
    first = np.flatnonzero(np.append(np.ones(min(1, len(k)), bool), k[1:] != k[:-1]))
    return k[first], first, np.add.reduceat(n[order], first), np.bitwise_or.reduceat(marked[order], first) == 1


def add_up(min_count: int):
    """A bucket's keys with their sums, and what it adds to the size of the corpus, of the vocabulary, and to the count of ``UNKNOWN`` as a word."""

    def run(table):
        import pyarrow as pa

        rows = table.to_pydict()
        k = np.frombuffer(b"".join(rows["a"]), np.int64)
        c = np.concatenate([long(c, len(a) // 8) for a, c in zip(rows["a"], rows["c"], strict=True)])
        k, _, n, word = _number_sums(k, c >> 1, c & 1)
        out = _table([(rows["bucket"][0], -1, k.tobytes(), b"", short(n))], PIECES)
        extra = (int(n[word].sum()), int((n[word] >= min_count).sum()), int(n[word & (k == UNKNOWN_NUMBER)].sum()))
        return pa.Table.from_arrays([*out.columns, *(pa.array([x], pa.int64()) for x in extra)], names=[x.split()[0] for x in MODEL.split(", ")])

    return run


def score_keys(lens, codes, words) -> tuple:
    """What a chunk asks for: pairs, words, predecessors, and first tokens of responses after the start of a text; with the place of every token among the pairs."""
    start = len(words)
    name = np.append(words, START_ID)
    prev = before(lens, codes, start)
    pair, place, _ = unique(prev * (start + 1) + codes)
    a = np.concatenate([name[pair // (start + 1)], np.full(start, WORD_KEY), np.full(start + 1, HEAD_KEY), np.full(start, START_ID)])
    b = np.concatenate([name[pair % (start + 1)], words, name, words])
    return a, b, prev, place, len(pair)


def ask_keys(buckets: int):
    def run(batches):
        for row in rows_of(batches):
            _, _, lens, codes, words = read_chunk(row)
            a, b, *_ = score_keys(lens, codes, words)
            yield from pieces(row["chunk"], a, b, None, buckets, True)

    return run


ANSWERS = "chunk long, bucket int, n binary"


def answer(table):
    """The counts that a bucket has for the keys of every question; a key that it doesn't have has 0."""
    rows = table.to_pydict()
    known = [i for i, c in enumerate(rows["chunk"]) if c < 0]
    have = np.concatenate([np.zeros(0, np.int64), *(np.frombuffer(rows["a"][i], np.int64) for i in known)])  # one row, in order
    counts = np.concatenate([np.zeros(0, np.int64), *(long(rows["c"][i], len(rows["a"][i]) // 8) for i in known)])
    made = []
    for chunk, bucket, a in zip(rows["chunk"], rows["bucket"], rows["a"], strict=True):
        if chunk >= 0:
            k = np.frombuffer(a, np.int64)
            out = np.zeros(len(k), np.int64)
            if len(have):
                at = np.minimum(np.searchsorted(have, k), len(have) - 1)
                out = np.where(have[at] == k, counts[at], 0)
            made.append((chunk, bucket, short(out)))
    import pyarrow as pa

    return pa.Table.from_batches([_table(made, ANSWERS)])


def collected(table, a: np.ndarray, b: np.ndarray, buckets: int) -> np.ndarray:
    """Answers in the order of the keys that were asked for."""
    order, bounds = dealt(a, b, buckets)
    out = np.zeros(len(a), np.int64)
    rows = table.to_pydict()
    for k, n in zip(rows["bucket"], rows["n"], strict=True):
        mine = order[bounds[k] : bounds[k + 1]]
        out[mine] = long(n, len(mine))
    return out


def places(text: np.ndarray, word: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """How often a word came before in its text; and the order that shows it."""
    order, first, group = grouped(text * size + word)
    seen = np.empty(len(text), np.int64)
    seen[order] = np.arange(len(text)) - first[group]
    return seen, order, first, group


def log_probabilities(buckets: int, total: int, size: int, min_count: int, weights: tuple[float, float, float, float]):
    bigram, unigram, uniform, history = weights

    def run(chunks, answers):
        import pyarrow as pa

        parts = []
        for row in chunks.to_pylist():
            ids, aux, lens, codes, words = read_chunk(row)
            start = len(words)
            a, b, prev, place, n_pairs = score_keys(lens, codes, words)
            n = collected(answers, a, b, buckets)
            pair, word, head, first_of = np.split(n, [n_pairs, n_pairs + start, n_pairs + 2 * start + 1])
            known = np.append(word >= max(1, min_count), True)
            text = np.repeat(np.arange(len(lens)), lens)
            g = np.arange(len(codes)) - np.repeat(np.cumsum(lens) - lens, lens)
            k = g - aux[text]
            out = k >= 0
            mine = known[codes]
            p_uni = np.where(mine, word[codes], 0) / max(1, total)
            led = np.where(prev == start, total > 0, known[prev] & (head[prev] > 0))
            p_big = np.where(mine & known[prev], pair[place], 0) / np.maximum(head[prev], 1)
            follow = np.where(led, p_big, p_uni)
            # Words that the model does not know are one word.
            seen, order, first, group = places(text, np.where(mine, codes, start), start + 1)
            told = np.cumsum(~out[order])
            seen_out = np.empty_like(seen)
            seen_out[order] = seen[order] - (told - (told - ~out[order])[first][group])
            p_start = np.where(mine, first_of[codes], 0) / max(1, head[start])

            def log_p(follows, count, length, p_uni=p_uni):
                share = np.where(length > 0, history * count / np.maximum(length, 1), history * p_uni)
                return np.log(bigram * follows + unigram * p_uni + uniform / (size + 1) + share)

            with_, without = log_p(follow, seen, g), log_p(np.where(k == 0, p_start, follow), seen_out, k)
            cols = [ids[text][out], (k[out] + 1).astype(np.int32), with_[out], without[out]]
            parts.append(pa.Table.from_arrays([pa.array(x) for x in cols], names=["sample_id", "pos", "lp_with", "lp_without"]))
        return pa.concat_tables(parts) if parts else pa.Table.from_arrays([pa.array([], t) for t in (pa.int64(), pa.int32(), pa.float64(), pa.float64())], names=["sample_id", "pos", "lp_with", "lp_without"])

    return run


# Several models as columns of the same keys.

COUNTED = PIECES + ", masks binary, spelled binary"


def count_for_models(buckets: int):
    """Pieces of pairs of tokens with their counts and, as bits, the models that learn from them; ``aux`` holds these bits.  A word is spelled out beside one of its pairs."""

    def run(batches):
        import pickle

        base = _task_chunk()
        for i, (_, aux, lens, codes, words, spelled) in enumerate(text_chunks(batches)):
            start = len(words)
            name = np.append(words, START_ID)
            masks, kind, _ = unique(aux)
            key, _, n = unique((before(lens, codes, start) * (start + 1) + codes) * len(masks) + np.repeat(kind, lens))
            mask, pair = masks[key % len(masks)], key // len(masks)
            tok = pair % (start + 1)
            a, b = name[pair // (start + 1)], name[tok]
            order, bounds = dealt(a, b, buckets)
            a, b, n, mask, tok = a[order], b[order], n[order], mask[order], tok[order]
            told = np.zeros(len(tok), bool)
            if spelled is not None:
                told[np.unique(tok, return_index=True)[1]] = True
            rows = []
            for k, (x, y) in enumerate(zip(bounds[:-1], bounds[1:], strict=True)):
                if y > x:
                    at = np.flatnonzero(told[x:y])
                    said = pickle.dumps((at.astype(np.int32), spelled[tok[x:y][at]].tolist())) if len(at) else b""
                    rows.append((k, base + i, a[x:y].tobytes(), b[x:y].tobytes(), short(n[x:y]), short(mask[x:y]), said))
            if rows:
                yield _table(rows, COUNTED)

    return run


def add_up_models(n_models: int):
    """``prev, tok, word, b0, b1, ...``: a row per pair with its count in each model."""

    def run(table):
        import pickle

        import pyarrow as pa

        rows = table.to_pydict()
        a, b = (np.frombuffer(b"".join(rows[x]), np.int64) for x in "ab")
        c, m = (np.concatenate([long(y, len(x) // 8) for x, y in zip(rows["a"], rows[name], strict=True)]) for name in ("c", "masks"))
        order, first, group = key_groups(a, b)
        c, m = c[order], m[order]
        word, at, place = np.full(len(first), None, object), 0, np.empty(len(a), np.int64)
        place[order] = group
        for x, said in zip(rows["a"], rows["spelled"], strict=True):
            if said:
                where, names = pickle.loads(said)
                word[place[at + where]] = names
            at += len(x) // 8
        sums = [np.add.reduceat(c * ((m >> i) & 1), first) for i in range(n_models)]
        return pa.Table.from_arrays([pa.array(a[order][first]), pa.array(b[order][first]), pa.array(word, pa.string()), *map(pa.array, sums)], names=["prev", "tok", "word", *(f"b{i}" for i in range(n_models))])

    return run


def _pairs_of(lens, codes, words) -> tuple:
    start = len(words)
    name = np.append(words, START_ID)
    pair, place, n = unique(before(lens, codes, start) * (start + 1) + codes)
    return name[pair // (start + 1)], name[pair % (start + 1)], n, place


def pairs_in_chunks(buckets: int):
    """Pieces of the different pairs of stored chunks with their counts."""

    def run(batches):
        for row in rows_of(batches):
            _, _, lens, codes, words = read_chunk(row)
            a, b, n, _ = _pairs_of(lens, codes, words)
            yield from pieces(row["chunk"], a, b, n, buckets)

    return run


DIFFERENT = "bucket int, prev long, tok long, c long"


def different(table):
    """A row per pair of a bucket."""
    import pyarrow as pa

    rows = table.to_pydict()
    a, b = (np.frombuffer(b"".join(rows[x]), np.int64) for x in "ab")
    c = np.concatenate([long(y, len(x) // 8) for x, y in zip(rows["a"], rows["c"], strict=True)])
    order, first, _ = key_groups(a, b)
    return pa.Table.from_arrays([pa.array(np.full(len(first), rows["bucket"][0], np.int32)), pa.array(a[order][first]), pa.array(b[order][first]), pa.array(np.add.reduceat(c[order], first))], names=["bucket", "prev", "tok", "c"])


LOOKED = "chunk long, bucket int, x binary, u binary"


def look_up(n_models: int):
    """What the models make of the pairs of every piece of a bucket: the fixed part of the probability, a row per model, and as bits the models that do not know the word."""

    def run(asked, looked):
        import pyarrow as pa

        rows = asked.to_pydict()
        a, b = (np.frombuffer(b"".join(rows[x]), np.int64) for x in "ab")
        known = [looked.column(c).to_numpy() for c in ("prev", "tok", "u")]
        order, first, group = key_groups(np.append(known[0], a), np.append(known[1], b))
        n = len(known[0])
        owner = np.empty(len(first), np.int64)
        mine = order < n
        owner[group[mine]] = order[mine]
        place = np.empty(len(order), np.int64)
        place[order] = owner[group]
        place = place[n:]
        x = np.stack([looked.column(f"x{i}").to_numpy() for i in range(n_models)])
        at, made = 0, []
        for chunk, bucket, keys in zip(rows["chunk"], rows["bucket"], rows["a"], strict=True):
            mine = place[at : at + len(keys) // 8]
            made.append((chunk, bucket, x[:, mine].tobytes(), known[2][mine].tobytes()))
            at += len(mine)
        return pa.Table.from_batches([_table(made, LOOKED)])

    return run


def add_logs(buckets: int, n_models: int, history: float):
    """``n, s0, s1, ...`` of every chunk: its tokens, and the sums of their log-probabilities under each model."""

    def run(chunks, looked):
        import pyarrow as pa

        made = []
        for row in chunks.to_pylist():
            _, _, lens, codes, words = read_chunk(row)
            a, b, _, place = _pairs_of(lens, codes, words)
            order, bounds = dealt(a, b, buckets)
            x, u = np.empty((n_models, len(a))), np.zeros(len(a), np.int64)
            for part in looked.to_pylist():
                at = order[bounds[part["bucket"]] : bounds[part["bucket"] + 1]]
                x[:, at] = np.frombuffer(part["x"], np.float64).reshape(n_models, -1)
                u[at] = np.frombuffer(part["u"], np.int64)
            text = np.repeat(np.arange(len(lens)), lens)
            first = np.repeat(np.cumsum(lens) - lens, lens)
            g = np.arange(len(codes)) - first
            weight = np.where(g > 0, history / np.maximum(g, 1), 0.0)
            share = places(text, codes, len(words))[0] * weight
            u = u[place]
            sums = []
            for i in range(n_models):
                odd = (u >> i) & 1 == 1
                part = share
                if odd.any():
                    # Words that a model does not know are one word to it.
                    told = np.cumsum(odd)
                    part = np.where(odd, (told - 1 - (told - odd)[first]) * weight, share)
                sums.append(float(np.log(x[i][place] + part).sum()))
            made.append((len(codes), *sums))
        return pa.Table.from_arrays([pa.array([r[0] for r in made], pa.int64()), *(pa.array([r[i + 1] for r in made], pa.float64()) for i in range(n_models))], names=["n", *(f"s{i}" for i in range(n_models))])

    return run
