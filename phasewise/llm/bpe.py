"""BPE encoding and decoding by tree concatenation.

Encoding equals the ``tokenizers`` library's (special strings in a text become special tokens,
none are added); decoding equals its ``decode(ids, skip_special_tokens=False)``.

A text is one tree: it is cut every ``text_leaf`` characters, wherever that falls, the leaves of all
texts at hand are encoded side by side in one batch, then neighbours are joined pair by pair.  At a
join, a window of text around it is encoded again; it reaches from white space to white space (no
token, merge or normalisation step crosses that) and grows until its first piece has the ids that the
left side has there and its last piece those of the right side, or the sides end.  A long run without
white space is a tree of its own, whose windows are of tokens: they grow until the first token is the
left side's token there and the last is the right side's.  Every pair of neighbouring tokens is then
one that BPE itself produces, and a sequence all of whose neighbouring pairs are such is the encoding
of the whole, so the result is exact and not a guess.  The encodings of short pieces are remembered.

Defined results: null texts encode like empty ones (no ids); repeated rows give repeated rows;
extra columns are ignored.
"""

from __future__ import annotations

import hashlib
import json
import re
from collections.abc import Callable, Iterator
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame
from tokenizers import Tokenizer

#: Longest chunk (bytes) that is encoded in one go and remembered, and the characters of a leaf.
SHORT, LEAF = 64, 512
#: Characters of a leaf of a text, and of each side of a join's first window.
TEXT_LEAF, WINDOW = 2048, 32
#: Remembered chunks of a worker in each of two generations.
REMEMBERED = 300_000
#: Characters that normalisation leaves or lower-cases one by one, and the pieces between them
#: as the file's own pattern has them (fixed values of the tokenizer).
PLAIN = re.compile("[^\\x09-\\x0d\\x20-\\x7eÀ-ÖØ-öø-ÿ]")
SPACE, SPACE_BYTES = re.compile("[\\x09-\\x0d ]"), re.compile(rb"[\x09-\x0d ]")
PLAIN_PIECES = re.compile("'s|'t|'re|'ve|'m|'ll|'d|[a-zß-öø-ÿ]+|[0-9]|[^\\sa-z0-9ß-öø-ÿ]+")


class TreeBpe:
    """Encoder and decoder of one ``tokenizers`` BPE file with end-of-word suffixes."""

    def __init__(self, path: str, leaf: int = LEAF, text_leaf: int = TEXT_LEAF):
        self.leaf, self.text_leaf = leaf, text_leaf
        self.whole = Tokenizer.from_file(path)
        self.whole.no_padding(), self.whole.no_truncation()
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        self.suffix = spec["model"].get("end_of_word_suffix") or ""
        self.special = re.compile("(" + "|".join(re.escape(t["content"]) for t in spec["added_tokens"]) + ")") if spec["added_tokens"] else None
        bare = {"added_tokens": [], "normalizer": None, "pre_tokenizer": None, "post_processor": None, "decoder": None, "truncation": None, "padding": None}
        model = spec["model"]
        self.last = Tokenizer.from_str(json.dumps(spec | bare))
        self.inner = Tokenizer.from_str(json.dumps(spec | bare | {"model": model | {"end_of_word_suffix": None}}))
        self.token = {i: t for t, i in self.whole.get_vocab(with_added_tokens=True).items()}
        self.ends = {i for t, i in self.whole.get_vocab(with_added_tokens=False).items() if self.suffix and t.endswith(self.suffix)}
        # characters that a token stands for, without the suffix
        ends = len(self.suffix)
        self.width = {i: len(t) - ends if ends and t.endswith(self.suffix) and len(t) > ends else len(t) for i, t in self.token.items()}
        self.plain = spec["pre_tokenizer"]["pretokenizers"][0]["pattern"]["Regex"] == r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+" if self.suffix else False
        self.known: dict[bytes | str, tuple[int, bytes, bytes]] = {}
        self.older: dict[bytes | str, tuple[int, bytes, bytes]] = {}

    # one pre-tokenised run ------------------------------------------------------------

    def _part(self, run: str, lo: int, hi: int) -> list[int]:
        coder = self.last if hi == len(run) else self.inner
        return coder.encode(run[lo:hi], add_special_tokens=False).ids

    def run(self, run: str) -> list[int]:
        """Ids of one pre-tokenised run (byte-level characters)."""
        if len(run) <= self.leaf:
            return self.last.encode(run, add_special_tokens=False).ids
        cuts = [*range(0, len(run), self.leaf), len(run)]
        if cuts[-1] - cuts[-2] < 2:
            del cuts[-2]
        leaves = [run[a:b] for a, b in zip(cuts, cuts[1:], strict=False)]
        parts = [e.ids for e in self.inner.encode_batch(leaves[:-1], add_special_tokens=False)] + [self._part(run, cuts[-2], cuts[-1])]
        spans = [(a, b, ids) for a, b, ids in zip(cuts, cuts[1:], parts, strict=False)]
        while len(spans) > 1:
            joined = [self._join(run, *spans[i], *spans[i + 1]) for i in range(0, len(spans) - 1, 2)]
            spans = joined + spans[len(joined) * 2 :]
        return spans[0][2]

    def _join(self, run: str, a: int, mid: int, left: list[int], _: int, b: int, right: list[int]) -> tuple[int, int, list[int]]:
        take = 4
        while True:
            i, j = max(0, len(left) - take), min(len(right), take)
            lo = mid - sum(self.width[t] for t in left[i:])
            hi = mid + sum(self.width[t] for t in right[:j]) if j < len(right) else b
            window = self._part(run, lo, hi)
            left_agrees = i == 0 or window[0] == left[i]
            right_agrees = j == len(right) or window[-1] == right[j - 1]
            if left_agrees and right_agrees:
                return a, b, left[:i] + window + right[j:]
            take *= 2

    # texts ----------------------------------------------------------------------------

    def _long(self, chunk: str) -> list[int]:
        ids: list[int] = []
        for n, part in enumerate(self.special.split(chunk) if self.special else [chunk]):
            if n % 2:
                ids.append(self.whole.token_to_id(part))
            elif part:
                for piece, _ in self.whole.pre_tokenizer.pre_tokenize_str(self.whole.normalizer.normalize_str(part)):
                    ids += self.run(piece)
        return ids

    def _entry(self, ids: list[int]) -> tuple[int, bytes, bytes]:
        return len(ids), " ".join(map(str, ids)).encode(), " ".join([self.token[i] for i in ids]).encode()

    def learn(self, chunks: list[bytes | str]) -> None:
        """Remembers chunks of texts (bytes) or lower-case pieces of plain texts (str)."""
        fresh, older = [], self.older
        for chunk in chunks:
            if chunk in older:
                self.known[chunk] = older[chunk]
            else:
                fresh.append(chunk)
        pieces = [c for c in fresh if isinstance(c, str) and len(c) <= SHORT]
        for at in range(0, len(pieces), 1000):
            some = pieces[at : at + 1000]
            ids, start = self.whole.encode(" ".join(some), add_special_tokens=False).ids, 0
            ends, rows = self.ends, iter(some)
            for i, token in enumerate(ids):
                if token in ends:  # each piece ends with the one token that has the suffix
                    self.known[next(rows)] = self._entry(ids[start : i + 1])
                    start = i + 1
        for chunk in fresh:
            if isinstance(chunk, bytes):
                self.known[chunk] = self._entry(self._long(chunk.decode()))
            elif len(chunk) > SHORT:
                self.known[chunk] = self._entry(self._long(chunk))

    def encode(self, text: str) -> list[int]:
        ids: list[int] = []
        for chunk in text.encode().split():
            ids += self._long(chunk.decode())
        return ids

    def decode(self, ids: list[int]) -> str:
        return " ".join([self.token[i] for i in ids])

    def form(self, text: bytes) -> tuple[str | bytes, Callable, re.Pattern]:
        """(text, how it is cut into pieces, white space): lower-cased where its characters are plain."""
        if self.plain:
            plain = text.decode()
            if not PLAIN.search(plain) and not (self.special and self.special.search(plain)):
                return plain.lower(), PLAIN_PIECES.findall, SPACE
        return text, bytes.split, SPACE_BYTES

    def leaves(self, text: str | bytes) -> list[int]:
        """Borders of the leaves (of bytes: between characters)."""
        cuts = list(range(0, len(text), self.text_leaf)) or [0]
        if isinstance(text, bytes):
            for i, c in enumerate(cuts):
                while c and text[c] & 0xC0 == 0x80:
                    c -= 1
                cuts[i] = c
        return sorted({*cuts, len(text)}) if text else [0, 0]

    def _known(self, pieces: list) -> list[tuple[int, bytes, bytes]]:
        new = [c for c in dict.fromkeys(pieces) if c not in self.known]
        if new:
            self.learn(new)
        return [self.known[c] for c in pieces]

    def _meet(self, form: tuple, a: int, mid: int, left: list, b: int, right: list) -> list:
        """The pieces of text[a:b] from those of text[a:mid] and text[mid:b]."""
        text, cut, space = form
        take = WINDOW
        while True:
            lo, hi = max(a, mid - take), min(b, mid + take)
            start = a if lo == a else next((m.start() for m in [space.search(text, lo, mid)] if m), None)
            ends = [b] if hi == b else [m.start() for m in space.finditer(text, mid, hi)]
            take *= 2
            if start is None or not ends:
                continue
            end = ends[-1]
            before, after, window = cut(text[start:mid]), cut(text[mid:end]), cut(text[start:end])
            if start > a and (len(before) < 2 or self._known(window[:1]) != self._known(before[:1])):
                continue
            if end < b and (len(after) < 2 or self._known(window[-1:]) != self._known(after[-1:])):
                continue
            self._known(window)
            return left[: len(left) - len(before)] + window + right[len(after) :]

    def tree(self, form: tuple, cuts: list[int], parts: list[list]) -> list:
        """The pieces of a whole text from those of its leaves."""
        spans = [(a, b, p) for a, b, p in zip(cuts, cuts[1:], parts, strict=False)]
        while len(spans) > 1:
            joined = [(x[0], y[1], self._meet(form, x[0], x[1], x[2], y[1], y[2])) for x, y in zip(spans[::2], spans[1::2], strict=False)]
            spans = joined + spans[len(joined) * 2 :]
        return spans[0][2]

    def coded_all(self, texts: list[bytes]) -> list[tuple[int, bytes, bytes]]:
        """Of each text: number of ids, ids joined by a space, decoded text."""
        out = []
        for at, upto in _portions(texts):
            if len(self.known) > REMEMBERED:
                self.known, self.older = {}, self.known
            forms = [self.form(t) for t in texts[at:upto]]
            cuts = [self.leaves(f[0]) for f in forms]
            parts = [[f[1](f[0][a:b]) for a, b in zip(c, c[1:], strict=False)] for f, c in zip(forms, cuts, strict=True)]
            known = self.known
            new = {c: 0 for row in parts for leaf in row for c in leaf if c not in known}
            if new:
                self.learn(list(new))
            for form, c, row in zip(forms, cuts, parts, strict=True):
                found = [v for v in map(known.__getitem__, self.tree(form, c, row)) if v[0]]
                out.append((sum([v[0] for v in found]), b" ".join([v[1] for v in found]), b" ".join([v[2] for v in found])))
        return out

    def coded(self, text: bytes) -> tuple[int, bytes, bytes]:
        return self.coded_all([text])[0]


def _portions(texts: list[bytes], most: int = 1_500_000) -> Iterator[tuple[int, int]]:
    at = size = 0
    for i, t in enumerate(texts):
        if size and size + len(t) > most:
            yield at, i
            at, size = i, 0
        size += len(t)
    if at < len(texts):
        yield at, len(texts)


@lru_cache(maxsize=2)
def coder(path: str) -> TreeBpe:
    return TreeBpe(path)


def _texts(column: pa.Array) -> list[bytes]:
    return [t or b"" for t in column.cast(pa.binary()).to_pylist()]


def digests(docs: DataFrame, path: str) -> DataFrame:
    """Per row of ``docs``: doc_id, n_tokens, ids_sha256, decoded_sha256."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = coder(path)
        for batch in batches:
            n, ids, back = [], [], []
            for count, joined, decoded in bpe.coded_all(_texts(batch.column(1))):
                n.append(count), ids.append(hashlib.sha256(joined).hexdigest()), back.append(hashlib.sha256(decoded).hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(ids), pa.array(back)], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def encoded(docs: DataFrame, path: str) -> DataFrame:
    """Per row of ``docs``: doc_id, ids (array<int>), decoded (string)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = coder(path)
        for batch in batches:
            texts = _texts(batch.column(1))
            for at in range(0, max(1, len(texts)), 500):
                ids, back = [], []
                for _, joined, decoded in bpe.coded_all(texts[at : at + 500]):
                    ids.append([int(x) for x in joined.split()]), back.append(decoded.decode())
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(at, 500), pa.array(ids, pa.list_(pa.int32())), pa.array(back, pa.string())], ["doc_id", "ids", "decoded"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, ids array<int>, decoded string")


def encoded_documents(docs: DataFrame, path: str) -> DataFrame:
    """Per row of ``docs``: doc_id, source, n_tokens, ids (array<int>)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = coder(path)
        for batch in batches:
            texts = _texts(batch.column(2))
            for at in range(0, max(1, len(texts)), 500):
                ids = [[int(x) for x in joined.split()] for _, joined, _ in bpe.coded_all(texts[at : at + 500])]
                counts = pa.array([len(i) for i in ids], pa.int64())
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(at, 500), batch.column(1).slice(at, 500), counts, pa.array(ids, pa.list_(pa.int32()))], ["doc_id", "source", "n_tokens", "ids"])

    return docs.select("doc_id", "source", "text").mapInArrow(run, "doc_id long, source string, n_tokens long, ids array<int>")


def decoded(coded: DataFrame, path: str) -> DataFrame:
    """Per row of ``coded(doc_id, ids)``: doc_id, text; null ids give an empty text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = coder(path)
        for batch in batches:
            out = [bpe.decode(ids or []) for ids in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.string())], ["doc_id", "text"])

    return coded.select("doc_id", "ids").mapInArrow(run, "doc_id long, text string")
