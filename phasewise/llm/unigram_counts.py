"""Token counts under a unigram vocabulary: count-only Viterbi.

An Aho-Corasick automaton enumerates the vocabulary entries that end at each position; dynamic
programming carries only the best score and its number of pieces (no back pointers, no pieces).
Ties follow the ``tokenizers`` library's unigram model: candidates come in the order of their
start, and a later one wins only if its score is strictly larger.  A character that no entry
covers alone is the unknown piece with the smallest score less ten.

Characters that the vocabulary's pieces hold at their start only (the mark for a blank, line
ends, most punctuation) cut a text into independent chunks; counts of short chunks are
remembered, in two generations of bounded size.  Production vocabulary: the pieces of the public 32,000-piece model
with a Zipf score, -log(place); byte and control pieces are left out.

Defined results: a null or empty text has 0 tokens; repeated rows give repeated rows; extra
columns are ignored.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator
from functools import lru_cache

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame

MARK = "▁"
UNKNOWN_LESS = 10.0
SHORT, REMEMBERED = 48, 500_000


def piece_vocabulary(path: str) -> list[tuple[str, float]]:
    """(piece, score) of a sentencepiece file; the first entry is the unknown piece."""
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    pieces = [model.id_to_piece(i) for i in range(model.vocab_size()) if not (model.is_byte(i) or model.is_control(i) or model.is_unknown(i))]
    return [("<unk>", 0.0)] + [(p, -math.log(i + 2.0)) for i, p in enumerate(pieces)]


class CountViterbi:
    def __init__(self, vocabulary: list[tuple[str, float]]):
        """``vocabulary[0]`` is the unknown piece (matched as any other entry, like the library does)."""
        self.automaton = ahocorasick.Automaton()
        pieces = [p for p, _ in vocabulary if p]
        for piece, score in vocabulary:
            if piece:
                self.automaton.add_word(piece, (len(piece), score))
        self.automaton.make_automaton()
        self.unknown = min(s for _, s in vocabulary) - UNKNOWN_LESS
        self.alone = {p for p in pieces if len(p) == 1}
        self.chunks = re.compile(self._cuts(pieces))
        self.known: dict[str, int] = {}
        self.older: dict[str, int] = {}

    @staticmethod
    def _cuts(pieces: list[str]) -> str:
        """A pattern of chunks that no piece crosses: opening characters are those that every
        piece holds at its start or after other opening characters only."""
        opening = set("\n\t\r" + MARK) | {chr(i) for i in range(33, 127) if not chr(i).isalnum()}
        while True:
            bad = {c for p in pieces for b, c in zip(p, p[1:], strict=False) if c in opening and b not in opening}
            if not bad:
                break
            opening -= bad
        if not opening:
            return "(?s:.+)"
        some = "".join(map(re.escape, sorted(opening)))
        return f"[{some}]+[^{some}]*|[^{some}]+"

    def best(self, s: str) -> int:
        """Four times the pieces, plus 2 if the first and 1 if the last is unknown; a run of
        unknown characters is one piece."""
        n = len(s)
        score, count, state = [0.0] * (n + 1), [0] * (n + 1), [0] * (n + 1)
        alone, unknown, at = self.alone, self.unknown, 0
        low = top = -math.inf
        pick = 0
        for end, (width, value) in self.automaton.iter(s):
            while at < end:  # candidates of the position before are complete
                self._settle(s, at, top, pick, score, count, state)
                at, top = at + 1, low
            total = score[end + 1 - width] + value
            if total > top:  # candidates of one end come with the earliest start first
                top, pick = total, end + 1 - width
        while at < n:
            self._settle(s, at, top, pick, score, count, state)
            at, top = at + 1, low
        return 4 * count[n] + state[n]

    def _settle(self, s: str, at: int, top: float, pick: int, score: list, count: list, state: list) -> None:
        new = 0
        if s[at] not in self.alone and (total := score[at] + self.unknown) > top:
            top, pick, new = total, at, 1
        score[at + 1] = top
        before = state[pick]
        count[at + 1] = count[pick] + 1 - (new and pick > 0 and before & 1)
        state[at + 1] = (new * 2 if pick == 0 else before & 2) | new

    def count(self, text: str) -> int:
        """Pieces of ``text``, blanks given as marks."""
        total, unknown_end, known = 0, 0, self.known
        for chunk in self.chunks.findall(text):
            found = known.get(chunk)
            if found is None:
                found = self._learn(chunk)
                known = self.known
            total += (found >> 2) - (unknown_end & found >> 1)
            unknown_end = found & 1
        return total

    def _learn(self, chunk: str) -> int:
        found = self.older.get(chunk)
        if found is None:
            found = self.best(chunk)
        if len(chunk) <= SHORT:
            if len(self.known) >= REMEMBERED:
                self.known, self.older = {}, self.known
            self.known[chunk] = found
        return found


def marked(text: str) -> str:
    """Blanks as marks, with one before the text (as the vocabulary expects it)."""
    return MARK + text.replace(" ", MARK) if text else ""


@lru_cache(maxsize=2)
def counter(path: str) -> CountViterbi:
    return CountViterbi(piece_vocabulary(path))


def token_counts(docs: DataFrame, path: str) -> DataFrame:
    """Per row of ``docs``: doc_id, n_tokens, n_chars (of the whole text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        viterbi = counter(path)
        for batch in batches:
            texts = [t or "" for t in batch.column(1).to_pylist()]
            counts = [viterbi.count(marked(t)) for t in texts]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(counts, pa.int64()), pa.array([len(t) for t in texts], pa.int64())], ["doc_id", "n_tokens", "n_chars"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_tokens long, n_chars long")
