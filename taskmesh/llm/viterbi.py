"""Token counts of a unigram tokenizer, by a Viterbi pass that only counts.

An Aho-Corasick automaton over the vocabulary names every piece that ends at each place of a word; dynamic programming
keeps, for each place, the best score and the number of pieces on the path with that score, so no path is stored and no
ids are made. The tie rules are the tokenizer's own: pieces are tried by where they start, and only a better score
replaces a path, so of equal scores the longest last piece stays; a character that no piece covers alone is an unknown
piece, 10 below the least score of the vocabulary, and unknown pieces next to each other are one.

Words are what the tokenizer's pre-tokenizer makes of a text: white space separates, and each word begins with the mark for
a space; a mark inside a word begins another. A word's count does not depend on its neighbours, so counts of words are
kept in a bounded cache.

The vocabulary is given as pieces with scores. ``zipf_unigram`` makes one from the pieces of a public vocabulary: by Zipf's
law, a piece at rank r has a probability in proportion to 1 / (r + 2.7).

Defined cases: null text is an empty text, with no pieces; rows that repeat are each counted; an empty table gives an empty
result; columns of any other name pass through ``count_tokens``.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator

import ahocorasick
import public_tokenizers
import pyarrow as pa
import sentencepiece
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from taskmesh.llm.words import CACHE_ENTRIES, lean, numbered
from taskmesh.sources import load

MARK = "▁"
UNKNOWN_PENALTY = 10.0
#: White space that separates words; the language's own ``split`` also cuts at four control characters.
_WORD = re.compile("[^\\t-\\r \\x85\\xa0\\u1680\\u2000-\\u200a\\u2028\\u2029\\u202f\\u205f\\u3000]+")
_CONTROL = re.compile("[\\x1c-\\x1f]")
_AFTER_MARK = re.compile(f"{MARK}?[^{MARK}]*")


def zipf_unigram(name: str = "piece_bpe_32k.model") -> list[tuple[str, float]]:
    """Pieces of a public vocabulary with scores by rank; the first is the unknown piece. Byte and control pieces are left out."""
    path = name if "/" in name else public_tokenizers.path(name)
    model = sentencepiece.SentencePieceProcessor(model_file=path)
    kept = [model.id_to_piece(i) for i in range(model.get_piece_size()) if not (model.is_unknown(i) or model.is_control(i) or model.is_byte(i) or model.is_unused(i))]
    total = sum(1 / (r + 2.7) for r in range(1, len(kept) + 1))
    return [("<unk>", 0.0), *[(p, math.log(1 / (r + 2.7) / total)) for r, p in enumerate(kept, 1)]]


class Counter:
    """Piece counts of texts."""

    def __init__(self, vocabulary: list[tuple[str, float]]) -> None:
        """vocabulary: pieces and scores; the first is the unknown piece, whose own letters in a text count as unknown too."""
        self.automaton = ahocorasick.Automaton()
        for k, (piece, score) in enumerate(vocabulary):
            self.automaton.add_word(piece, (len(piece), score, k == 0))
        self.automaton.make_automaton()
        self.unknown = min(s for _, s in vocabulary) - UNKNOWN_PENALTY
        self.known: dict[str, tuple[int, int]] = {}

    def count(self, word: str) -> tuple[int, int]:
        """Pieces of one word, and how many of them are unknown."""
        penalty, both = self.unknown, 1 + (1 << 32)
        # For each place: the best score, pieces on its path (unknown ones again from bit 32 on), whether an unknown piece ends there.
        best, counts, open_ = [0.0], [0], [False]
        place, top, count, opened, alone = 1, None, 0, False, False
        for end, (length, score, unknown) in self.automaton.iter(word):  # by end, the longest and so the earliest start first
            while place <= end:  # all pieces that end at ``place`` are seen
                if not alone:
                    s = best[-1] + penalty
                    if top is None or s > top:
                        top, count, opened = s, counts[-1] + both * (not open_[-1]), True
                best.append(top), counts.append(count), open_.append(opened)
                place, top, alone = place + 1, None, False
            start = place - length
            alone |= length == 1
            s = best[start] + score
            if top is None or s > top:
                top, opened = s, unknown
                count = counts[start] + ((both * (not open_[start])) if unknown else 1)
        while place <= len(word):
            if not alone:
                s = best[-1] + penalty
                if top is None or s > top:
                    top, count, opened = s, counts[-1] + both * (not open_[-1]), True
            best.append(top), counts.append(count), open_.append(opened)
            place, top, alone = place + 1, None, False
        return counts[-1] & 0xFFFFFFFF, counts[-1] >> 32

    def _word(self, word: str) -> tuple[int, int]:
        parts = [word] if MARK not in word else [p for p in _AFTER_MARK.findall(word) if p]
        first = parts[0] if parts[0].startswith(MARK) else MARK + parts[0]
        counts = [self.count(p) for p in (first, *parts[1:])]
        return sum(c for c, _ in counts), sum(u for _, u in counts)

    def text(self, text: str) -> tuple[int, int]:
        known, total, unknown = self.known, 0, 0
        for word in _WORD.findall(text) if _CONTROL.search(text) else text.split():
            found = known.get(word)
            if found is None:
                if len(known) >= CACHE_ENTRIES:
                    known.clear()
                found = known[word] = self._word(word)
            total += found[0]
            unknown += found[1]
        return total, unknown


def count_tokens(docs: DataFrame, vocabulary: list[tuple[str, float]], column: str = "n_tokens") -> DataFrame:
    """All columns of ``docs``, the number of pieces of each whole text, and of these the unknown ones (``<column>_unknown``)."""
    plain, names = numbered(docs)
    at = names.index("text")
    shared = docs.sparkSession.sparkContext.broadcast(vocabulary)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = Counter(shared.value)
        for b in batches:
            counts = [counter.text(t) if t else (0, 0) for t in b.column(at).to_pylist()]
            yield pa.RecordBatch.from_arrays(
                [*b.columns, pa.array([c for c, _ in counts], pa.int64()), pa.array([u for _, u in counts], pa.int64())], [*b.schema.names, "tokens", "unknown"]
            )

    schema = T.StructType([*plain.schema.fields, T.StructField("tokens", T.LongType()), T.StructField("unknown", T.LongType())])
    return plain.mapInArrow(lean(run), schema).toDF(*names, column, f"{column}_unknown")


def op8_viterbi(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents", ["doc_id", "text"])
    return count_tokens(docs, zipf_unigram()).select("doc_id", "n_tokens", F.col("n_tokens_unknown").alias("n_unknown"))
