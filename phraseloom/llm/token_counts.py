"""Token counts under a unigram vocabulary, without building the tokens.

An Aho-Corasick automaton enumerates the vocabulary's matches inside each whitespace-delimited word (led by the word
mark), and dynamic programming carries the best score and the piece count to every position. Ties follow the public
tokenizer: among equal scores the match that starts first stays, a position that no one-character piece covers gets an
unknown piece at ten below the lowest score, and neighbouring unknown pieces count once. Scores are added from the
word's start in double precision, as the tokenizer does for each pre-token.

A word's count depends on the word alone, so each task computes a word once; its memory of words has a fixed size.

Defined cases: null and empty texts count 0; texts of any length are counted whole; repeated rows count alike; an empty
table gives no rows; columns besides key and text never enter.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

MARK = "▁"
UNKNOWN_PENALTY = 10.0
REMEMBERED = 400_000


def read_vocabulary(name: str = "piece_bpe_32k.model") -> list[tuple[str, float]]:
    """Pieces and scores of a vocabulary file; control, unknown and byte pieces are left out."""
    import public_tokenizers
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=public_tokenizers.path(name))
    return [(model.id_to_piece(i), float(model.get_score(i))) for i in range(model.get_piece_size()) if not (model.is_control(i) or model.is_unknown(i) or model.is_byte(i))]


class UnigramCounter:
    def __init__(self, vocabulary: list[tuple[str, float]], remembered: int = REMEMBERED) -> None:
        self.automaton = ahocorasick.Automaton()
        for piece, value in vocabulary:
            self.automaton.add_word(piece, (len(piece), value))
        if vocabulary:
            self.automaton.make_automaton()
        self.unknown = min((value for _, value in vocabulary), default=0.0) - UNKNOWN_PENALTY
        self.empty = not vocabulary
        self.memory: dict[str, int] = {}
        self.remembered = remembered

    def word(self, word: str) -> int:
        """Pieces of one marked word on its best path."""
        n = len(word)
        matches: list[list[tuple[int, float]]] = [[] for _ in range(n)]
        if not self.empty:
            for last, (length, value) in self.automaton.iter(word):
                matches[last + 1 - length].append((last + 1, value))
        best: list[float | None] = [None] * (n + 1)
        count, ends_unknown = [0] * (n + 1), [False] * (n + 1)
        best[0] = 0.0
        for start in range(n):
            base = best[start]
            covered = False
            for end, value in matches[start]:
                total = base + value
                if best[end] is None or total > best[end]:
                    best[end], count[end], ends_unknown[end] = total, count[start] + 1, False
                covered |= end == start + 1
            if not covered:
                total, end = base + self.unknown, start + 1
                if best[end] is None or total > best[end]:
                    best[end], count[end], ends_unknown[end] = total, count[start] + (not ends_unknown[start]), True
        return count[n]

    def text(self, text: str) -> int:
        total = 0
        memory = self.memory
        for word, times in Counter(marked_words(text)).items():
            got = memory.get(word)
            if got is None:
                if len(memory) >= self.remembered:
                    memory.clear()
                got = memory[word] = self.word(word)
            total += got * times
        return total


_SPLIT = re.compile(f"{MARK}[^{MARK}]*")


def marked_words(text: str) -> list[str]:
    """The tokenizer's pre-tokens: spaces become marks, the text is led by one, and every mark opens a word."""
    if not text:
        return []
    marked = text.replace(" ", MARK)
    return _SPLIT.findall(marked if marked[0] == MARK else MARK + marked)


def count_tokens(docs: DataFrame, vocabulary: str = "piece_bpe_32k.model", key: str = "doc_id", text: str = "text") -> DataFrame:
    """``(doc_id, n_tokens)`` per row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = UnigramCounter(read_vocabulary(vocabulary))
        for batch in batches:
            yield pa.record_batch([batch.column(0), pa.array([counter.text(t.as_py() or "") for t in batch.column(1)], pa.int64())], names=["doc_id", "n_tokens"])

    return docs.select(F.col(key).cast("long").alias("doc_id"), F.col(text)).mapInArrow(run, "doc_id long, n_tokens long")
