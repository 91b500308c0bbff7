"""Whole-text token ids from a public tokenizer file, one Arrow batch at a time.

The vocabulary drops white space and never merges over it, so a batch is split at ASCII
white space in Arrow, every distinct word is encoded once by the ``tokenizers`` library, and
the ids of the texts are gathered with numpy. Words that the batch trick could not keep
apart go through the library one by one, so the ids always equal those of the whole text.
"""

from __future__ import annotations

import os
from itertools import chain

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from patchspace.shared import trim

MARK = "\x01"  # between two words of a joined text; encodes to one id of its own
GROUP = 64
CACHE_WORDS = 400_000  # words whose ids a worker keeps; a memory bound, results do not depend on it
_encoders: dict[str, WordEncoder] = {}
# byte-level alphabet: a byte stands for itself where it prints in Latin-1, the others follow from 256
_UNSEEN = [b for b in range(256) if not (33 <= b <= 126 or 161 <= b <= 172 or b >= 174)]
BYTE_LEVEL = {b: 256 + n for n, b in enumerate(_UNSEEN)}


def default_tokenizer() -> str:
    """The file of the word-level vocabulary, where this machine keeps it."""
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


class WordEncoder:
    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        mark = self.tok.encode(MARK, add_special_tokens=False).ids
        if len(mark) != 1:
            raise ValueError("the tokenizer has no single id for the mark between words")
        self.mark = mark[0]
        self.model = self.tok.model
        self.letters = frozenset("abcdefghijklmnopqrstuvwxyz")
        single = {c: self.tok.encode(c, add_special_tokens=False).ids for c in ",."}
        self.ends = {c: i[0] for c, i in single.items() if len(i) == 1}
        self._forget()

    def _forget(self) -> None:
        self.known: dict[str, int] = {}
        self.flat, self.off = np.empty(1 << 16, np.uint32), np.zeros(1 << 16, np.int64)

    def places(self, words: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(all known ids, start of each word's ids in them, their number)."""
        if len(self.known) > CACHE_WORDS:
            self._forget()
        known, ends, last = self.known, self.ends, self.letters
        new = [w for w in words if w not in known]
        if new:
            # a comma or stop after a letter is a piece of its own: such words share their stem's ids
            tailed = [w for w in new if w[-1:] in ends and w[-2:-1] in last]
            if tailed:
                stems = {w[:-1] for w in tailed}
                stems.update(w for w in new if not (w[-1:] in ends and w[-2:-1] in last))
                new = [w for w in stems if w not in known]
            self._remember(new, *self.words(new))
            if tailed:
                at = np.fromiter((known[w[:-1]] for w in tailed), np.int64, len(tailed))
                sizes = self.off[at + 1] - self.off[at] + 1
                off = np.zeros(len(tailed) + 1, np.int64)
                np.cumsum(sizes, out=off[1:])
                source = np.repeat(self.off[at] - off[:-1], sizes) + np.arange(off[-1])
                ids = self.flat[np.minimum(source, len(self.flat) - 1)]
                ids[off[1:] - 1] = [ends[w[-1]] for w in tailed]
                self._remember(tailed, ids, off)
        at = np.fromiter(map(known.__getitem__, words), np.int64, len(words))
        starts = self.off[at]
        return self.flat, starts, self.off[at + 1] - starts

    def _remember(self, words: list[str], ids: np.ndarray, off: np.ndarray) -> None:
        n, end = len(self.known), int(self.off[len(self.known)])
        while n + len(words) + 1 > len(self.off):
            self.off = np.concatenate([self.off, np.zeros_like(self.off)])
        while end + len(ids) > len(self.flat):
            self.flat = np.concatenate([self.flat, np.empty_like(self.flat)])
        self.flat[end : end + len(ids)] = ids
        self.off[n + 1 : n + 1 + len(words)] = off[1:] + end
        self.known.update(zip(words, range(n, n + len(words)), strict=True))

    @staticmethod
    def one_piece(w: str) -> str | None:
        """The model's form of a word of lower-case Latin letters, which no earlier step changes
        or splits: normalised already, and one run of letters."""
        if w.isalpha():
            if w.isascii():
                return w  # lower case, as A-Z were lowered
            if max(w) < "\u0250" and w == w.lower():
                return w.encode().decode("latin-1").translate(BYTE_LEVEL)
        return None

    def words(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all words one after another, offsets of length n+1)."""
        tokenize, direct, rest = self.model.tokenize, [None] * len(words), []
        for i, w in enumerate(words):
            p = self.one_piece(w)
            if p is None:
                rest.append(i)
            else:
                direct[i] = [t.id for t in tokenize(p)]
        if rest:
            ids, off = self._joined([words[i] for i in rest])
            ids, off = ids.tolist(), off.tolist()
            for n, i in enumerate(rest):
                direct[i] = ids[off[n] : off[n + 1]]
        offsets = np.zeros(len(words) + 1, np.int64)
        np.cumsum(np.fromiter(map(len, direct), np.int64, len(direct)), out=offsets[1:])
        return np.fromiter(chain.from_iterable(direct), np.uint32, int(offsets[-1])), offsets

    def _joined(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """The same through the whole tokenizer, many words to a text."""
        odd = [i for i, w in enumerate(words) if MARK in w]
        safe = words
        if odd:
            safe = list(words)
            for i in odd:
                safe[i] = ""
        joined = [f" {MARK} ".join(safe[i : i + GROUP]) for i in range(0, len(safe), GROUP)]
        parts = []
        for e in self.tok.encode_batch_fast(joined, add_special_tokens=False):
            parts.append(np.asarray(e.ids, dtype=np.uint32))
            parts.append(np.array([self.mark], dtype=np.uint32))
        flat = np.concatenate(parts) if parts else np.empty(0, np.uint32)
        ends = np.flatnonzero(flat == self.mark)
        if len(ends) != len(words):  # a word holds the mark's id in another spelling
            each = [np.asarray(self.tok.encode(w, add_special_tokens=False).ids, np.uint32) for w in words]
            offsets = np.zeros(len(words) + 1, np.int64)
            np.cumsum([len(x) for x in each], out=offsets[1:])
            return (np.concatenate(each) if each else flat), offsets
        lengths = np.diff(np.concatenate(([-1], ends))) - 1
        offsets = np.zeros(len(words) + 1, np.int64)
        np.cumsum(lengths, out=offsets[1:])
        flat = flat[flat != self.mark]
        if odd:
            pieces, at = [], 0
            for i in odd:
                pieces += [flat[at : offsets[i]], np.asarray(self.tok.encode(words[i], add_special_tokens=False).ids, np.uint32)]
                lengths[i] = len(pieces[-1])
                at = offsets[i]
            flat = np.concatenate([*pieces, flat[at:]])
            np.cumsum(lengths, out=offsets[1:])
        return flat, offsets

    def batch(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all texts one after another, offsets of length n+1); null is empty."""
        # the cast comes last: ascii_lower misreads the offsets of a slice that was cast
        texts = pc.ascii_lower(pc.fill_null(texts, "")).cast(pa.large_string())
        split = pc.ascii_split_whitespace(texts)
        at = np.asarray(split.offsets, dtype=np.int64)
        coded = pc.dictionary_encode(split.flatten())
        at = at - at[0]
        ids, starts, sizes = self.places(coded.dictionary.to_pylist())
        index = np.asarray(coded.indices, dtype=np.int64)
        n = sizes[index]
        ends = np.zeros(len(index) + 1, np.int64)
        np.cumsum(n, out=ends[1:])
        # position of each output id: start of its word in ids, plus its place in the word
        source = np.repeat(starts[index] - ends[:-1], n)
        source += np.arange(ends[-1], dtype=np.int64)
        return ids[source], ends[at]


def encoder(path: str) -> WordEncoder:
    if path not in _encoders:
        _encoders[path] = WordEncoder(path)
    return _encoders[path]


def slices(batch: pa.RecordBatch, column: str = "text", max_bytes: int = 4 << 20):
    """A batch cut into row ranges of about ``max_bytes`` of text, one row at least."""
    lengths = np.asarray(pc.fill_null(pc.binary_length(batch.column(column).cast(pa.large_string())), 0), dtype=np.int64)
    start, total = 0, 0
    for i, n in enumerate(lengths):
        if i > start and total + n > max_bytes:
            yield batch.slice(start, i - start)
            start, total = i, 0
        total += int(n)
    if start < batch.num_rows:
        yield batch.slice(start)
    trim()
