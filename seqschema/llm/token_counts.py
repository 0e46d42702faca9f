"""Token counts of a unigram tokenizer without its tokens.

An Aho-Corasick automaton over the vocabulary enumerates all pieces that end at each character of a word; dynamic
programming keeps, for each character, the best score so far and the number of pieces on that path, and nothing else.
Ties go as in the tokenizer: among equal scores the piece that starts first stays. A character without a piece of its own may
be unknown, at the least score less ten; unknown neighbours are fused and count one id for each byte (byte fallback), or
one if the fused string is itself in the vocabulary. Words (cut before each space mark) are independent; common ones are
remembered.

The vocabulary is the piece file's, with the scores it gives. Null and empty texts have no tokens; repeated rows each
get a row.
"""

from __future__ import annotations

import functools

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from seqschema.llm.bpe import Remembered
from seqschema.llm.common import append_columns

#: The space mark, and what an unknown character costs beyond the least score.
MARK, PENALTY = "▁", 10.0


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


def vocabulary(path: str) -> list[tuple[str, float]]:
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    return [(model.id_to_piece(i), model.get_score(i)) for i in range(model.get_piece_size())]


class PieceCounter:
    def __init__(self, pieces: list[tuple[str, float]], unknown: int = 0) -> None:
        self.known = {p for p, _ in pieces}
        self.unknown_score = min(s for _, s in pieces) - PENALTY
        self.matcher = ahocorasick.Automaton()
        for i, (piece, score) in enumerate(pieces):
            if piece:
                self.matcher.add_word(piece, (len(piece), score, i == unknown))
        self.matcher.make_automaton()
        self.cache = Remembered(lambda word: self.word(MARK + word))

    def fused(self, text: str) -> int:
        return 1 if text in self.known else len(text.encode())

    def word(self, text: str) -> int:
        """The number of ids of one word, its mark included."""
        n = len(text)
        matches: list[list] = [[] for _ in range(n + 1)]
        for last, match in self.matcher.iter(text):
            matches[last + 1].append(match)
        score, count, run = [0.0] * (n + 1), [0] * (n + 1), [-1] * (n + 1)
        for end in range(1, n + 1):
            best, start, is_unknown, single = None, 0, False, False
            for size, weight, marks_unknown in sorted(matches[end], reverse=True):
                total = weight + score[end - size]
                if best is None or total > best:
                    best, start, is_unknown = total, end - size, marks_unknown
                single = single or size == 1
            if not single:
                total = self.unknown_score + score[end - 1]
                if best is None or total > best:
                    best, start, is_unknown = total, end - 1, True
            score[end] = best
            if is_unknown:
                run[end] = run[start] if run[start] >= 0 else start
                count[end] = count[start]
            else:
                count[end] = self.closed(text, start, count, run) + 1
        return self.closed(text, n, count, run)

    def closed(self, text: str, at: int, count: list[int], run: list[int]) -> int:
        return count[at] + (self.fused(text[run[at] : at]) if run[at] >= 0 else 0)

    def count(self, text: str) -> int:
        if not text:
            return 0
        marked = text.replace(" ", MARK)
        words = marked.split(MARK)
        return sum(map(self.cache.__getitem__, words[1:] if marked[0] == MARK else words))


@functools.lru_cache(maxsize=2)
def load(path: str) -> PieceCounter:
    return PieceCounter(vocabulary(path))


def count_tokens(docs: DataFrame, text_col: str = "text", path: str | None = None, keep=("doc_id",), out: str = "n_tokens") -> DataFrame:
    path = path or default_path()

    def kernel():
        counter = load(path)
        return lambda texts, _: [pa.array([counter.count(t) for t in texts], pa.int64())]

    return append_columns(docs, text_col, kernel, [(out, T.LongType())], list(keep))
