"""SentencePiece BPE encoding by vectorised merge rounds, and decoding (operator 8).

A text is cut before every run of meta spaces (no piece has one behind another character, which is checked when a model is loaded),
so its parts are encoded independently and each distinct part once per memo.  Parts lie in one flat symbol array; a round finds
the smallest pair rank of every part by a segmented minimum, merges its pairs of that rank from the left, all at once, compacts the array and drops
finished parts, until no pair remains.  A merge may make a pair that has to go before the next of the same rank: a part's merges of a round
end with the first that does.  So merges are those of one after another, and long parts take rounds about as their different ranks.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from functools import lru_cache
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, IntegerType

from .pretokens import Generations, strides

META = "▁"
MEMO_ENTRIES = 200_000
#: Characters of text that are looked through for new parts at a time.
STRIDE = 1 << 19
_SHIFT = np.int64(22)
_NONE = np.int32(2**31 - 1)


class PieceModel:
    """Tables of a sentencepiece BPE model with byte fallback and an identity normalizer."""

    def __init__(self, path: str) -> None:
        import sentencepiece

        self.lib = model = sentencepiece.SentencePieceProcessor(model_file=path)
        size = model.get_piece_size()
        usable = {model.id_to_piece(i): i for i in range(size) if not (model.is_control(i) or model.is_unknown(i) or model.is_byte(i))}
        if any(model.is_unused(i) for i in range(size)) or not all(re.fullmatch(f"{META}*[^{META}]*", p) for p in usable):
            raise ValueError("this model has pieces that parts of a text cannot be encoded by alone")
        self.size, self.end = size, model.eos_id()
        self.decimals = [b"%d" % i for i in range(size)]
        self.byte = np.array([model.piece_to_id(f"<0x{b:02X}>") for b in range(256)])
        # Symbols: piece ids, and size + code point for characters that are no piece.
        self.char = np.arange(size, size + 0x110000, dtype=np.int64)
        for piece, i in usable.items():
            if len(piece) == 1:
                self.char[ord(piece)] = i
        scores = np.array([model.get_score(i) for i in usable.values()])
        rank_of = dict(zip(usable, np.unique(-scores, return_inverse=True)[1].tolist(), strict=True))
        symbol = lambda s: usable.get(s, int(self.char[ord(s)]) if len(s) == 1 else None)
        pairs = {}
        for piece, i in usable.items():
            for at in range(1, len(piece)):
                left, right = symbol(piece[:at]), symbol(piece[at:])
                if left is not None and right is not None:
                    pairs[(left << int(_SHIFT)) | right] = (rank_of[piece], i)
        self.keys = np.array(sorted(pairs), np.int64)
        self.ranks = np.array([pairs[k][0] for k in self.keys.tolist()], np.int32)
        self.merged = np.array([pairs[k][1] for k in self.keys.tolist()], np.int64)

    def packed(self, symbols: np.ndarray) -> bytes:
        """Ids of symbols as 32-bit integers; a character that is no piece becomes its bytes."""
        if not len(symbols) or symbols.max() < self.size:
            return symbols.astype("<i4").tobytes()
        out: list[int] = []
        for s in symbols.tolist():
            out += [s] if s < self.size else self.byte[list(chr(s - self.size).encode("utf-8"))].tolist()
        return np.array(out, "<i4").tobytes()

    def _look(self, left: np.ndarray, right: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        key = (left << _SHIFT) | right
        at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
        hit = self.keys[at] == key
        return np.where(hit, self.ranks[at], _NONE), at

    def _together(self, flat: np.ndarray, rank: np.ndarray, left: np.ndarray, made: np.ndarray, part: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """Of the places ``left`` of each part those up to the first whose merge makes a pair of no higher rank."""
        owner = part[left]
        again = np.r_[False, owner[1:] == owner[:-1]]
        if not again.any():
            return left
        several = np.flatnonzero(again | np.r_[again[1:], False])
        here, own, new = left[several], owner[several], made[several]
        touching = again[several] & (left[several - 1] == here - 2)
        before = np.where(touching, made[several - 1], flat[here - 1])
        first = (here == 0) | (part[here - 1] != own)
        last = here + 2 > ends[own]
        after = flat[np.where(last, here, here + 2)]
        early = ~first & (self._look(before, new)[0] <= rank[here]) | ~last & (self._look(new, after)[0] <= rank[here])
        if not early.any():
            return left
        passed = np.cumsum(early) - early
        starts = np.flatnonzero(~again[several])
        stay = np.ones(len(left), bool)
        stay[several] = passed == np.repeat(passed[starts], np.diff(np.r_[starts, len(several)]))
        return left[stay]

    def encode_parts(self, parts: list[str]) -> list[bytes]:
        """Ids of each part as 32-bit integers."""
        out: list = [b""] * len(parts)
        short = [n for n, part in enumerate(parts) if part]
        if not short:
            return out
        flat = self.char[np.frombuffer("".join([parts[n] for n in short]).encode("utf-32-le"), "<u4")]
        sizes = np.fromiter((len(parts[n]) for n in short), np.int64, len(short))
        names = np.array(short)
        ends = np.cumsum(sizes) - 1
        rank, at = self._look(flat[:-1], flat[1:])
        rank, at = np.append(rank, _NONE), np.append(at, 0)
        rank[ends] = _NONE
        while len(names):
            starts = ends - sizes + 1
            best = np.minimum.reduceat(rank, starts)
            going = best < _NONE
            if not going.all():
                stay = np.repeat(going, sizes)
                done, stops = flat[~stay], np.cumsum(sizes[~going]).tolist()
                plain = self.packed(done) if done.max() < self.size else None
                for n, a, b in zip(names[~going].tolist(), [0, *stops], stops, strict=False):
                    out[n] = self.packed(done[a:b]) if plain is None else plain[4 * a : 4 * b]
                flat, rank, at, names, sizes, best = flat[stay], rank[stay], at[stay], names[going], sizes[going], best[going]
                if not len(names):
                    break
                ends = np.cumsum(sizes) - 1
            part = np.repeat(np.arange(len(names)), sizes)
            hits = np.flatnonzero(rank == best[part])
            # Of pairs that overlap, the leftmost goes, then the next but one: every other hit of a run of neighbours.
            runs = np.flatnonzero(np.r_[True, np.diff(hits) > 1])
            left = hits[(np.arange(len(hits)) - np.repeat(runs, np.diff(np.r_[runs, len(hits)]))) % 2 == 0]
            left = self._together(flat, rank, left, self.merged[at[left]], part, ends)
            flat[left] = self.merged[at[left]]
            # The pair's own rank slot passes to its right neighbour's before that one is dropped.
            rank[left], at[left] = rank[left + 1], at[left + 1]
            keep = np.ones(len(flat), bool)
            keep[left + 1] = False
            flat, rank, at = flat[keep], rank[keep], at[keep]
            sizes = sizes - np.bincount(part[left], minlength=len(names))
            ends = np.cumsum(sizes) - 1
            starts = ends - sizes + 1
            spot, owner = left - np.arange(len(left)), part[left]
            inner = spot[spot < ends[owner]]
            rank[inner], at[inner] = self._look(flat[inner], flat[inner + 1])
            inner = spot[spot > starts[owner]] - 1
            rank[inner], at[inner] = self._look(flat[inner], flat[inner + 1])
        return out


_PARTS = re.compile(" +[^ ]*")


def parts_of(text: str) -> list[str]:
    """The parts of a text with spaces for meta spaces, the leading one added; an empty text has none."""
    return _PARTS.findall(" " + text.replace(META, " ")) if text else []


@lru_cache(maxsize=2)
def load(path: str) -> PieceModel:
    return PieceModel(path)


class Codec:
    """Encodes and decodes whole texts with a bounded memo of distinct parts."""

    def __init__(self, path: str) -> None:
        self.model, self.memo = load(path), Generations(MEMO_ENTRIES)

    def learn(self, lists: list[list[str]]) -> None:
        new = self.memo.missing(chain.from_iterable(lists))
        for part, ids in zip(new, self.model.encode_parts([p.replace(" ", META) for p in new]), strict=True):
            self.memo[part] = ids

    def ids(self, parts: list[str], end: bool = True) -> list[int]:
        found = np.frombuffer(b"".join(map(self.memo.__getitem__, parts)), "<i4").tolist()
        return [*found, self.model.end] if end else found

    def decimal(self, ids: list[int]) -> bytes:
        return b" ".join(map(self.model.decimals.__getitem__, ids))


@lru_cache(maxsize=2)
def shared_codec(path: str) -> Codec:
    return Codec(path)


def encode(texts: list[str], path: str, end: bool = True) -> list[list[int]]:
    codec = Codec(path)
    lists = [parts_of(t) for t in texts]
    codec.learn(lists)
    return [codec.ids(parts, end) for parts in lists]


def encode_documents(docs: DataFrame, model_path: str, text_col: str = "text", with_ids: bool = False) -> DataFrame:
    """Columns of ``docs`` without the text, plus ``n_tokens, ids_sha256, decoded_sha256`` and, if asked for, ``ids`` and ``decoded``.

    Ids are those of the sentencepiece library with its end id alone added; ``decoded`` is what the library's ``decode`` makes of them.  Null
    text is empty and holds the end id only.  Repeated rows stay, an empty table gives an empty one, columns that bear an
    added column's name are replaced.
    """
    added = ["n_tokens", "ids_sha256", "decoded_sha256", *(["ids", "decoded"] if with_ids else [])]
    kept = [c for c in docs.columns if c != text_col and c.lower() not in added]
    body = docs.select(*kept, F.coalesce(F.col(text_col), F.lit("")).alias("_body"))
    schema = body.drop("_body").schema.add("n_tokens", "long").add("ids_sha256", "string").add("decoded_sha256", "string")
    if with_ids:
        schema = schema.add("ids", ArrayType(IntegerType())).add("decoded", "string")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = shared_codec(model_path)
        sha = lambda data: hashlib.sha256(data).hexdigest()
        for batch in batches:
            rows = []
            for texts in strides((t.as_py() for t in batch.column(batch.num_columns - 1)), STRIDE):
                lists = [parts_of(t) for t in texts]
                codec.learn(lists)
                for parts in lists:
                    ids = codec.ids(parts)
                    decoded = codec.model.lib.decode(ids)
                    rows.append((len(ids), sha(codec.decimal(ids)), sha(decoded.encode("utf-8")), *((ids, decoded) if with_ids else ())))
            columns = list(zip(*rows, strict=True)) or [()] * len(added)
            kinds = (pa.int64(), pa.string(), pa.string(), pa.list_(pa.int32()), pa.string())
            made = [pa.array(c, k) for c, k in zip(columns, kinds, strict=False)]
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], *made], [*batch.schema.names[:-1], *added])

    return body.mapInArrow(run, schema)
