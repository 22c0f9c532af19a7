"""Token counts without tokens: a count-only Viterbi pass over a unigram vocabulary.

For each distinct word an Aho-Corasick automaton lists every vocabulary piece that ends at each character; the dynamic programme
carries only the best score and its number of pieces. Ties go as in the tokenizers library's unigram model: of equal scores the
piece that starts first stays. A character that no piece covers alone is unknown; its score is the lowest score less 10; a run
of unknown characters is one token, or with byte fallback a token for each of its bytes. Words are cut as that library's
metaspace pre-tokenizer does: spaces become U+2581, one is put in front, and a new word begins at each.

The vocabulary file is a parameter; it is read on the driver and its pieces are broadcast (a fixed file, of bounded size).
Defined results: null and empty texts have 0 tokens. A word of any length is worked on whole.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

SPACE = "▁"
UNKNOWN_PENALTY = 10.0  # fixed value of the unigram model
SCHEMA = "doc_id long, n_words long, n_tokens long, n_unknown long"


def load_pieces(path: str) -> list[tuple[str, float, str]]:
    """Pieces of a sentencepiece file: text, score, and kind (normal, byte, unknown or control)."""
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    kind = lambda i: "unknown" if model.is_unknown(i) else "control" if model.is_control(i) else "byte" if model.is_byte(i) else "normal"
    return [(model.id_to_piece(i), model.get_score(i), kind(i)) for i in range(model.get_piece_size())]


class Counter:
    """Counts the tokens of words."""

    def __init__(self, pieces: Iterable[tuple[str, float]], byte_fallback: bool = True, remembered: int = 200_000):
        self.automaton = ahocorasick.Automaton()
        lowest = 0.0
        for piece, score in pieces:
            self.automaton.add_word(piece, (len(piece), score))
            lowest = min(lowest, score)
        self.automaton.make_automaton()
        self.unknown, self.byte_fallback = lowest - UNKNOWN_PENALTY, byte_fallback
        self.memory: dict[str, tuple[int, int]] = {}
        self.remembered = remembered

    def word(self, word: str) -> tuple[int, int]:
        """Number of tokens, and of unknown characters, of one word."""
        score, count, best, pieces, single, at = [0.0], [0], 0.0, 0, False, 0
        for end, (length, value) in self.automaton.iter(word):  # at each end the longest piece comes first
            start = end + 1 - length
            if end == at and pieces:
                total = score[start] + value
                if total > best:
                    best, pieces = total, count[start] + 1
            else:
                if pieces:
                    if not single:
                        return self.word_with_unknown(word)
                    score.append(best)
                    count.append(pieces)
                    at += 1
                if end != at:
                    return self.word_with_unknown(word)
                best, pieces, single = score[start] + value, count[start] + 1, False
            if length == 1:
                single = True
        return (pieces, 0) if single and at == len(word) - 1 else self.word_with_unknown(word)

    def word_with_unknown(self, word: str) -> tuple[int, int]:
        """As word(), for words in which some character is no piece by itself."""
        n = len(word)
        ends: list[list[tuple[int, float]]] = [[] for _ in range(n)]
        for end, match in self.automaton.iter(word):
            ends[end].append(match)
        score = [0.0] * (n + 1)
        count, lost, run = [0] * (n + 1), [0] * (n + 1), [False] * (n + 1)
        for end in range(1, n + 1):
            best, start, known = None, -1, False
            for length, value in ends[end - 1]:
                total = score[end - length] + value
                if best is None or total > best:
                    best, start, known = total, end - length, True
            single = any(length == 1 for length, _ in ends[end - 1])
            if not single and (best is None or score[end - 1] + self.unknown > best):
                best, start, known = score[end - 1] + self.unknown, end - 1, False
            score[end] = best
            if known:
                count[end], lost[end] = count[start] + 1, lost[start]
            else:
                more = len(word[start].encode()) if self.byte_fallback else int(not run[start])
                count[end], lost[end], run[end] = count[start] + more, lost[start] + 1, True
        return count[n], lost[n]

    def text(self, text: str | None) -> tuple[int, int, int]:
        """Words, tokens and unknown characters of a whole text."""
        if not text:
            return 0, 0, 0
        words = text.replace(SPACE, " ").split(" ")
        memory, tokens, lost = self.memory, 0, 0
        for w in words[1:] if not words[0] and len(words) > 1 else words:
            got = memory.get(w)
            if got is None:
                if len(memory) >= self.remembered:
                    memory.clear()
                got = self.word(SPACE + w)
                if len(w) < 64:
                    memory[w] = got
            tokens += got[0]
            lost += got[1]
        return len(words) - (not words[0] and len(words) > 1), tokens, lost


def count_tokens(documents: DataFrame, vocabulary: str, byte_fallback: bool = True) -> DataFrame:
    """doc_id, n_words, n_tokens, n_unknown (characters) of every whole text."""
    pieces = [(piece, score) for piece, score, kind in load_pieces(vocabulary) if kind == "normal"]
    shared = documents.sparkSession.sparkContext.broadcast(pieces)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = Counter(shared.value, byte_fallback)
        for batch in batches:
            got = [counter.text(x.as_py()) for x in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array([g[k] for g in got], pa.int64()) for k in range(3))], names=[x.split()[0] for x in SCHEMA.split(", ")])

    return documents.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(count, SCHEMA)
