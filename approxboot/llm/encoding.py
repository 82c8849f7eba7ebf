"""Token ids of whole texts through a word cache.

A tokenizer's pre-tokenization never joins what a single space separates (byte-level BPE: the space opens
the next token; BPE with word ends: white space is dropped), so ids of a text are those of its words, and
each distinct word is encoded once. Texts where that does not hold (runs of spaces) go to the tokenizer whole.
Where a text holds what a special token looks like, it is that token, as it is for the tokenizer.
"""

from __future__ import annotations

import os
import re
from functools import lru_cache

import numpy as np


#: A word that begins with its only white space, a blank.
LED = re.compile(r" \S+").fullmatch


def ragged(flat: np.ndarray, starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Concatenate flat[s : s + n] for all pairs of starts and lengths."""
    total = int(lengths.sum())
    if not total:
        return flat[:0]
    ends = np.cumsum(lengths)
    at = np.repeat(starts - (ends - lengths), lengths)
    at += np.arange(total)
    return flat[at]


class _Words(dict):
    """Word -> number, in order of first lookup; new words wait in fresh until they are encoded."""

    def __init__(self):
        self.fresh = []
        self.count = 0

    def __missing__(self, word):
        self[word] = n = self.count
        self.count = n + 1
        self.fresh.append(word)
        return n


class WordEncoder:
    """Encodes lists of texts with the tokenizer in a file of the tokenizers library.

    lead: what stands before every word but the first (" " for byte-level BPE, "" where white space is
    dropped). max_ids and max_words bound the cache: beyond them only words that were met again stay, the most
    frequent ones, in half the room at most.
    """

    def __init__(self, path: str, lead: str, max_ids: int = 6_000_000, max_words: int = 2_000_000):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        #: special tokens of the vocabulary: words that hold one are encoded alone, other words are joined by one
        self.marks = [t.content for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.mark = next(m for m in self.marks if m.startswith("<|"))
        self.mark_id = self.tokenizer.token_to_id(self.mark)
        self.opens = np.zeros(self.tokenizer.get_vocab_size(), bool)
        self.opens[[i for t, i in self.tokenizer.get_vocab().items() if t.startswith("\u0120")]] = True  # how byte-level vocabularies write a blank
        self.lead, self.max_ids, self.max_words = lead, max_ids, max_words
        self._reset()

    def _reset(self) -> None:
        self.words = _Words()
        self.flat = np.zeros(0, np.uint32)
        self.starts = np.zeros(0, np.int64)
        self.lengths = np.zeros(0, np.int64)
        self.met = np.zeros(0, np.int64)

    def _thin(self) -> None:
        """Forget words that were met once and, of the others, all that do not fit half the bounds."""
        order = np.argsort(-self.met, kind="stable")
        fits = (np.cumsum(self.lengths[order]) <= self.max_ids // 2) & (np.arange(len(order)) < self.max_words // 2) & (self.met[order] > 1)
        keep = np.sort(order[fits])
        flat, lengths, met = ragged(self.flat, self.starts[keep], self.lengths[keep]), self.lengths[keep], self.met[keep]
        names = list(self.words)
        names = [names[i] for i in keep.tolist()]
        self._reset()
        for w in names:
            self.words[w]
        self.words.fresh = []
        # halves, so that what was frequent long ago makes room in time
        self.flat, self.starts, self.lengths, self.met = flat, np.cumsum(lengths) - lengths, lengths, met // 2 + 1

    def _ids(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of texts that stand alone, and their numbers."""
        got = [e.ids for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]
        lengths = np.fromiter(map(len, got), np.int64, len(got))
        return np.array([i for ids in got for i in ids], np.uint32), lengths

    def _joined_ids(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """The same for texts without special tokens: many are sent as one, with the special token between them, which parts them before anything else."""
        joined = [self.mark.join(texts[i : i + 400]) for i in range(0, len(texts), 400)]
        got = [e.ids for e in self.tokenizer.encode_batch_fast(joined, add_special_tokens=False)]
        ids = np.array([i for x in got for i in (*x, self.mark_id)], np.uint32)
        at = np.flatnonzero(ids == self.mark_id)
        lengths = np.diff(np.concatenate([[-1], at])) - 1
        return ids[ids != self.mark_id], lengths

    def _led_ids(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """The same for words that begin with the only blank in them: joined as they are, each begins where an id begins with a blank."""
        joined = ["".join(texts[i : i + 400]) for i in range(0, len(texts), 400)]
        got = [e.ids for e in self.tokenizer.encode_batch_fast(joined, add_special_tokens=False)]
        ids = np.array([i for x in got for i in x], np.uint32)
        at = np.flatnonzero(self.opens[ids])
        return ids, np.diff(np.concatenate([at, [len(ids)]]))

    def _add(self, flat: np.ndarray, lengths: np.ndarray, numbers: np.ndarray) -> None:
        self.starts[numbers] = len(self.flat) + np.cumsum(lengths) - lengths
        self.lengths[numbers] = lengths
        self.flat = np.concatenate([self.flat, flat])

    def _learn(self) -> None:
        fresh, self.words.fresh = self.words.fresh, []
        first = len(self.starts)
        self.starts = np.concatenate([self.starts, np.zeros(len(fresh), np.int64)])
        self.lengths = np.concatenate([self.lengths, np.zeros(len(fresh), np.int64)])
        self.met = np.concatenate([self.met, np.zeros(len(fresh), np.int64)])
        alone, joined, led = [], [], []
        for i, w in enumerate(fresh):
            (alone if any(m in w for m in self.marks) else led if self.lead and LED(w) else joined).append(i)
        for numbers, ids in ((alone, self._ids), (joined, self._joined_ids), (led, self._led_ids)):
            for lo in range(0, len(numbers), 100_000):
                part = numbers[lo : lo + 100_000]
                self._add(*ids([fresh[i] for i in part]), first + np.array(part, np.int64))

    def encode(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """All ids of texts one after another, and the number of ids of each."""
        words, lead = self.words, self.lead
        # texts are cut in one go, at the byte 0; those that hold it, or runs of blanks, stay whole
        odd = [i for i, t in enumerate(texts) if "\0" in t or (lead and "  " in t)]
        if lead:
            cut = lambda part: "\0".join(part).replace(lead, "\0" + lead).split("\0")
            counts = [t.count(lead) + 1 for t in texts]
        else:
            cut = lambda part: "\0".join(part).replace("\n", " ").replace(" ", "\0").split("\0")
            counts = [t.count(" ") + t.count("\n") + 1 for t in texts]
        numbers: list[int] = []
        lo = 0
        for i in [*odd, len(texts)]:
            if i > lo:
                numbers += map(words.__getitem__, cut(texts[lo:i]))
            if i < len(texts):
                numbers.append(words[texts[i]])
                counts[i] = 1
            lo = i + 1
        self._learn()
        numbers = np.array(numbers, np.int64)
        self.met += np.bincount(numbers, minlength=len(self.met))
        lengths = self.lengths[numbers]
        ids = ragged(self.flat, self.starts[numbers], lengths)
        ends = np.concatenate([[0], np.cumsum(lengths)])
        at = np.concatenate([[0], np.cumsum(np.array(counts, np.int64))])
        if len(self.flat) > self.max_ids or len(self.starts) > self.max_words:
            self._thin()
        return ids, np.diff(ends[at])


@lru_cache(maxsize=2)
def encoder(path: str, lead: str, max_ids: int = 6_000_000, max_words: int = 2_000_000) -> WordEncoder:
    """One encoder for each worker process, so that its cache serves all tasks there."""
    return WordEncoder(path, lead, max_ids, max_words)


def slices(texts: list[str], limit: int = 2_000_000):
    """Ranges of texts whose characters stay under limit, one text at least."""
    lo = size = 0
    for i, t in enumerate(texts):
        if size and size + len(t) > limit:
            yield lo, i
            lo, size = i, 0
        size += len(t)
    if lo < len(texts):
        yield lo, len(texts)
