"""Texts to ids of a word-end BPE vocabulary, fast, with results equal to the library's.

The library's normaliser and its small word cache dominate its running time. Words
of texts made only of plain Latin-1 characters are therefore split here, and each
distinct word is encoded once by the library. Every other text (other characters,
unusual white space, strings of special tokens) goes to the library whole.
"""

from __future__ import annotations

import os
import re

import numpy as np

#: Bytes of Latin-1 on which the splitting here and the library's agree by construction.
_PLAIN = bytes([9, 10, 13, *range(0x20, 0x7F), *range(0xA1, 0x100)])
_LETTERS = "a-zªµºß-öø-ÿ"
_NUMBERS = "0-9²³¹¼½¾"
_WORD = re.compile(rf"'s|'t|'re|'ve|'m|'ll|'d|[{_LETTERS}]+|[{_NUMBERS}]|[^ \t\n\r{_LETTERS}{_NUMBERS}]+")


class _Numbers(dict):
    """Gives each new word the next number and keeps it in ``fresh``."""

    def __init__(self):
        super().__init__()
        self.fresh: list[str] = []

    def __missing__(self, word: str) -> int:
        self[word] = n = len(self)
        self.fresh.append(word)
        return n


class WordIds:
    """Encoder with a bounded cache of words: when over ``cache_words``, the half that was used most stays."""

    def __init__(self, path: str, cache_words: int = 300_000):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.cache_words = cache_words
        self._reset()

    def _reset(self) -> None:
        self.numbers = _Numbers()
        self.starts = np.zeros(0, np.int64)
        self.lengths = np.zeros(0, np.int64)
        self.flat = np.zeros(0, np.uint32)
        self.used = np.zeros(0, np.int64)

    def _trim(self) -> None:
        """Keeps the words used most, and only those used more than once."""
        count = min(self.cache_words // 2, int((self.used > 1).sum()))
        kept = np.sort(np.argsort(-self.used, kind="stable")[:count])
        words = list(self.numbers)
        numbers = _Numbers()
        for i, k in enumerate(kept.tolist()):
            numbers[words[k]] = i
        lengths = self.lengths[kept]
        total = np.cumsum(lengths) - lengths
        self.flat = self.flat[np.repeat(self.starts[kept] - total, lengths) + np.arange(lengths.sum())]
        self.numbers, self.starts, self.lengths, self.used = numbers, total, lengths, self.used[kept] // 2

    def _learn(self, at_once: int = 4096) -> None:
        """Encodes new words, many in one text: each is one pre-token, so the library tells their ids apart."""
        all_ids, all_lengths = [], []
        for i in range(0, len(self.numbers.fresh), at_once):
            words = self.numbers.fresh[i : i + at_once]
            found = self.tokenizer.encode(" ".join(words), add_special_tokens=False)
            lengths = np.bincount(np.array(found.word_ids, np.int64), minlength=len(words))
            ids = found.ids
            if len(lengths) != len(words):  # the library splits one of them otherwise: one by one
                single = [x.ids for x in self.tokenizer.encode_batch_fast(words, add_special_tokens=False)]
                lengths = np.fromiter(map(len, single), np.int64, len(single))
                ids = [k for x in single for k in x]
            all_ids.append(np.array(ids, np.uint32))
            all_lengths.append(lengths)
        lengths, flat = np.concatenate(all_lengths), np.concatenate(all_ids)
        self.starts = np.concatenate([self.starts, len(self.flat) + np.cumsum(lengths) - lengths])
        self.lengths = np.concatenate([self.lengths, lengths])
        self.flat = np.concatenate([self.flat, flat])
        self.numbers.fresh = []

    def encode(self, texts: list[str], end_id: int | None) -> tuple[np.ndarray, np.ndarray]:
        """Returns all ids as uint32 and the bounds by text (length texts + 1)."""
        if len(self.numbers) > self.cache_words:
            self._trim()
        counts, words, odd = np.zeros(len(texts), np.int64), [], []
        for i, text in enumerate(texts):
            try:
                plain = not text.encode("latin-1").translate(None, _PLAIN) and "<|" not in text
            except UnicodeEncodeError:
                plain = False
            if plain:
                own = _WORD.findall(text.lower())
                counts[i] = len(own)
                words += own
            else:
                odd.append(i)
        numbers = np.fromiter(map(self.numbers.__getitem__, words), np.int64, len(words))
        if self.numbers.fresh:
            self._learn()
        self.used = np.pad(self.used, (0, len(self.numbers) - len(self.used)))
        self.used += np.bincount(numbers, minlength=len(self.used))
        lengths = self.lengths[numbers]
        total = np.zeros(len(numbers) + 1, np.int64)
        np.cumsum(lengths, out=total[1:])
        flat = self.flat[np.repeat(self.starts[numbers] - total[:-1], lengths) + np.arange(total[-1])]
        bounds = np.zeros(len(texts) + 1, np.int64)
        np.cumsum(counts, out=bounds[1:])
        bounds = total[bounds]
        if not odd and end_id is None:
            return flat, bounds
        sizes = np.diff(bounds)
        library = {i: np.array(self.tokenizer.encode(texts[i], add_special_tokens=False).ids, np.uint32) for i in odd}
        for i, ids in library.items():
            sizes[i] = len(ids)
        if end_id is not None:
            sizes += 1
        out_bounds = np.zeros(len(texts) + 1, np.int64)
        np.cumsum(sizes, out=out_bounds[1:])
        out = np.empty(out_bounds[-1], np.uint32)
        own = np.diff(bounds)
        out[np.repeat(out_bounds[:-1] - bounds[:-1], own) + np.arange(len(flat))] = flat
        for i, ids in library.items():
            out[out_bounds[i] : out_bounds[i] + len(ids)] = ids
        if end_id is not None:
            out[out_bounds[1:] - 1] = end_id
        return out, out_bounds


_ENCODERS: dict[str, WordIds] = {}


def encoder(path: str) -> WordIds:
    """One encoder for each worker process and vocabulary."""
    if path not in _ENCODERS:
        _ENCODERS[path] = WordIds(path)
    return _ENCODERS[path]


def text_lists(batch, bytes_at_once: int = 2 << 20):
    """(first row, texts) in pieces of about ``bytes_at_once``; null texts are empty."""
    column = batch.column(batch.schema.get_field_index("text"))
    first, size, own = 0, 0, []
    for i in range(len(column)):
        value = column[i].as_py() or ""
        own.append(value)
        size += len(value)
        if size >= bytes_at_once:
            yield first, own
            first, size, own = i + 1, 0, []
    if own:
        yield first, own
