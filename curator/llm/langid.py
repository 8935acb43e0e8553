"""Language identification by cross-parsing entropy (operator 10).

Per language a suffix automaton is built of the whole texts of a bounded sample of labelled rows.  A text is parsed greedily against each
automaton: every phrase is the longest match from where the last one ended.  The language that needs the fewest phrases, normalised by the size of
its training text, wins.  Phrases do not run over the border of a letter run, so the parse of a text is the sum of the parses of
its words, and each distinct word is parsed once per memo.  For the same reason a training word that occurs again adds no match, and
the automaton is built of the sample's different words.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: The bounded labelled sample: documents per language (smallest id hashes), each taken whole.
TRAIN_DOCS = 120
FOLDS = 5
UNKNOWN = "und"
#: Letter runs are parsed in pieces of this many letters.
RUN = 64
MEMO_ENTRIES = 400_000
#: Characters of text parsed at a time.
STRIDE = 1 << 19
EDGE = "\n"

_LETTERS = re.compile(r"[^\W\d_]+")


def letter_words(text: str) -> list[str]:
    """Lower-case letter runs of a text, long ones in pieces; none if the text has no letter."""
    found = _LETTERS.findall(text.lower())
    if found and not any(w[0].isalpha() for w in found) and not any(c.isalpha() for w in found for c in w):
        return []
    if any(len(w) > RUN for w in found):
        return [w[i : i + RUN] for w in found for i in range(0, len(w), RUN)]
    return found


def suffix_automaton(text: str) -> list[dict[str, int]]:
    """Transitions of the smallest automaton that accepts every substring of ``text`` from state 0."""
    moves: list[dict[str, int]] = [{}]
    link, length = [-1], [0]
    last = 0
    for c in text:
        here = len(moves)
        moves.append({})
        length.append(length[last] + 1)
        link.append(0)
        p = last
        while p >= 0 and c not in moves[p]:
            moves[p][c] = here
            p = link[p]
        if p >= 0:
            q = moves[p][c]
            if length[p] + 1 == length[q]:
                link[here] = q
            else:
                twin = len(moves)
                moves.append(dict(moves[q]))
                length.append(length[p] + 1)
                link.append(link[q])
                while p >= 0 and moves[p].get(c) == q:
                    moves[p][c] = twin
                    p = link[p]
                link[q] = link[here] = twin
        last = here
    return moves


@dataclass
class CrossParser:
    """One language: its automaton as sorted ``state * base + symbol`` keys, and the weight of a phrase in bits."""

    base: int
    keys: np.ndarray
    nexts: np.ndarray
    bits: float

    @classmethod
    def of(cls, text: str, symbols: dict[str, int]) -> CrossParser:
        moves, base = suffix_automaton(text), len(symbols) + 1
        keys = np.array([s * base + symbols[c] for s, m in enumerate(moves) for c in m], np.int64)
        nexts = np.array([t for m in moves for t in m.values()], np.int64)
        order = np.argsort(keys)
        return cls(base, keys[order], nexts[order], float(np.log2(max(2, len(text)))))

    def _step(self, state: np.ndarray, symbol: np.ndarray) -> np.ndarray:
        key = state * self.base + symbol
        at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
        return np.where(self.keys[at] == key, self.nexts[at], -1)

    def phrases(self, codes: np.ndarray) -> np.ndarray:
        """Phrases of each row of symbols; -1 pads, 0 is a symbol unseen in training."""
        state, count = np.zeros(len(codes), np.int64), np.zeros(len(codes), np.int32)
        for column in codes.T:
            live = np.flatnonzero(column >= 0)
            symbol, at = column[live], state[live]
            to = self._step(at, symbol)
            lost = to < 0
            # A phrase ends before a symbol that does not follow; that symbol then starts the next one.
            count[live[lost & (at > 0)]] += 1
            again = self._step(np.zeros(int(lost.sum()), np.int64), symbol[lost])
            count[live[lost][again < 0]] += 1
            to[lost] = np.maximum(again, 0)
            state[live] = to
        return count + (state > 0)


@dataclass
class LanguageModel:
    languages: list[str]
    symbols: dict[str, int]
    parsers: list[CrossParser]

    @classmethod
    def train(cls, samples: dict[str, list[str]]) -> LanguageModel:
        texts = {}
        for language in sorted(samples):
            words = dict.fromkeys(word for text in samples[language] for word in letter_words(text))
            texts[language] = EDGE + EDGE.join(words) + EDGE
        symbols = {c: i + 1 for i, c in enumerate(sorted(set().union(*texts.values())))} if texts else {}
        return cls(list(texts), symbols, [CrossParser.of(t, symbols) for t in texts.values()])

    def parse_words(self, words: list[str]) -> np.ndarray:
        """Phrases per word (row) and language (column)."""
        framed = [f"{EDGE}{w}{EDGE}" for w in words]
        codes = np.full((len(words), max(map(len, framed), default=0)), -1, np.int64)
        flat = np.array([self.symbols.get(c, 0) for c in "".join(framed)], np.int64)
        sizes = np.fromiter(map(len, framed), np.int64, len(framed))
        codes[np.arange(codes.shape[1])[None, :] < sizes[:, None]] = flat
        return np.stack([p.phrases(codes) for p in self.parsers], 1) if self.parsers else np.zeros((len(words), 0), np.int32)


class Judge:
    """Verdicts of a model, with a memo of the words' phrase counts that is emptied when it is full."""

    def __init__(self, model: LanguageModel) -> None:
        self.model, self.rows, self.counts = model, {}, np.zeros((0, len(model.languages)), np.int32)
        self.bits = np.array([p.bits for p in model.parsers])

    @classmethod
    def of(cls, model: LanguageModel) -> Judge:
        """The judge that goes with a model object, which a worker keeps from task to task."""
        if not hasattr(model, "_judge"):
            model._judge = cls(model)
        return model._judge

    def learn(self, lists: list[list[str]]) -> None:
        if len(self.rows) > MEMO_ENTRIES:
            self.rows, self.counts = {}, self.counts[:0]
        new = list({w for words in lists for w in words if w not in self.rows})
        if new:
            self.rows.update(zip(new, range(len(self.counts), len(self.counts) + len(new)), strict=True))
            self.counts = np.concatenate([self.counts, self.model.parse_words(new)])

    def verdict(self, words: list[str]) -> tuple[str, float]:
        """The language of fewest normalised phrases (ties: first by code point) and its margin over the second, from 0 to 1."""
        if not words or not self.model.languages:
            return UNKNOWN, 0.0
        total = self.counts[np.fromiter(map(self.rows.__getitem__, words), np.int64, len(words))].sum(0) * self.bits
        best = int(np.argmin(total))
        if len(total) == 1:
            return self.model.languages[best], 1.0
        second = float(np.partition(total, 1)[1])
        return self.model.languages[best], (second - float(total[best])) / second if second else 0.0


def training_sample(docs: DataFrame, text_col: str = "text", lang_col: str = "lang", id_col: str = "doc_id") -> dict[str, list[str]]:
    """The ``TRAIN_DOCS`` documents with the smallest id hashes of each language, outside the held-out fold."""
    known = docs.filter(F.col(lang_col).isNotNull() & F.col(text_col).isNotNull() & ~held_out(id_col)).withColumn("_h", F.xxhash64(F.col(id_col)))
    # The smallest hashes of a language lie below a bound that its count gives; twice what is needed passes, whatever the size of the table.
    bound = F.lit(False)
    for row in known.groupBy(F.col(lang_col).alias("lang")).count().collect():
        top = min((1 << 63) - 1, -(1 << 63) + int(min(1.0, 2 * TRAIN_DOCS / row["count"]) * (1 << 64)))
        bound = F.when(F.col(lang_col) == row.lang, F.col("_h") <= top).otherwise(bound)
    rows = known.filter(bound).select(F.col(lang_col).alias("lang"), F.col("_h").alias("h"), F.col(id_col).alias("id"), F.col(text_col).alias("body"))
    ranked = rows.withColumn("n", F.row_number().over(Window.partitionBy("lang").orderBy("h", "id", "body"))).filter(F.col("n") <= TRAIN_DOCS)
    samples: dict[str, list[str]] = {}
    for row in ranked.select("lang", "n", "body").orderBy("lang", "n").collect():
        samples.setdefault(row.lang, []).append(row.body)
    return samples


def held_out(id_col: str = "doc_id"):
    """True for the fold that is never learned from; a null id counts as the text of nothing and is held out."""
    return F.coalesce(F.crc32(F.col(id_col).cast("string").cast("binary")) % FOLDS == 0, F.lit(True))


def identify(docs: DataFrame, model: LanguageModel, text_col: str = "text") -> DataFrame:
    """Columns of ``docs`` without the text, plus ``lang_pred`` and ``score``.

    ``und`` with score 0 where the text is null or has no letter, or nothing was learned.  Only the text is looked at.  Repeated rows
    stay; columns that bear an added column's name are replaced.
    """
    kept = [c for c in docs.columns if c != text_col and c.lower() not in ("lang_pred", "score")]
    body = docs.select(*kept, F.coalesce(F.col(text_col), F.lit("")).alias("_body"))
    schema = body.drop("_body").schema.add("lang_pred", "string").add("score", "double")
    shared = docs.sparkSession.sparkContext.broadcast(model)  # its size is bounded by the texts of TRAIN_DOCS rows per language

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        judge = Judge.of(shared.value)
        for batch in batches:
            names, scores, held, size = [], [], [], 0

            def flush() -> None:
                judge.learn(held)
                for words in held:
                    name, score = judge.verdict(words)
                    names.append(name)
                    scores.append(score)
                held.clear()

            for text in batch.column(batch.num_columns - 1):
                text = text.as_py()
                held.append(letter_words(text))
                size += len(text)
                if size > STRIDE:
                    flush()
                    size = 0
            flush()
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(names, pa.string()), pa.array(scores, pa.float64())], [*batch.schema.names[:-1], "lang_pred", "score"])

    return body.mapInArrow(run, schema)
