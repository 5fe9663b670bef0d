"""Token ids of whole texts by a public vocabulary file.

White space never takes part in a token of the word vocabularies used here, so
a text's ids are those of its words one after another; a vocabulary of another
kind is refused. Each worker keeps a bounded memo of words by 64-bit hash; the
library encodes only words not in it. A worker draws its hash at random and
leaves very long words out, so no text can be made to collide. Tests hold the
result against the library's ids of the whole text.
"""

from __future__ import annotations

import os
import re
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa

from .words import mix, text_slices, word_hashes, word_spans

#: The memo starts anew beyond so many words or ids.
MEMO_WORDS, MEMO_IDS = 600_000, 4_000_000
_SLOT_BITS = 21
#: Words looked up at once; with those in the memo they leave the table under half full.
_PIECE = 200_000
#: Longer words are never looked up.
MEMO_BYTES = 512
#: White space of every kind that separates words, between and around pieces that could join.
_PROBE = " The quick\tbrown  fox\n\njumps\x0bover\x0c 12 34\r\n5 'll s ! ? x "
#: Letters that normalisation only lower-cases, then common closing punctuation.
#: Such a word is one or two pre-tokens, so the library's model can take them directly.
_PLAIN = re.compile("([A-Za-z\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u00ff]+)([.,;:!?]*)")


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


class WordTokenizer:
    """Ids of texts, with a memo of the ids of words in an open-addressed table."""

    def __init__(self, path: str):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self._library = Tokenizer.from_file(path)
        self._model = self._library.model
        byte_level = self._library.pre_tokenizer
        spell = lambda c: "".join(t for t, _ in byte_level.pre_tokenize_str(c.lower()))
        self._spelling = {i: spell(chr(i)) for i in (*range(65, 91), *range(0xC0, 0x100)) if chr(i).isalpha()}
        self._closing = {"": []}
        whole = self._library.encode(_PROBE, add_special_tokens=False).ids
        if whole != [i for word in _PROBE.split() for i in self._library.encode(word, add_special_tokens=False).ids]:
            raise ValueError(f"{path} does not split at white space: ids of texts are not those of their words")
        self._letters = np.frombuffer(os.urandom(256 * 8), np.uint64) | np.uint64(1)
        self._unseen = 0
        self._forget()

    def _direct(self, word: str) -> list[int] | None:
        """Ids of a plain word from the model, None if the word needs the whole library."""
        if not (match := _PLAIN.fullmatch(word)):
            return None
        core, closing = match.groups()
        if closing not in self._closing:
            self._closing[closing] = self._library.encode(closing, add_special_tokens=False).ids
        return [t.id for t in self._model.tokenize(core.translate(self._spelling))] + self._closing[closing]

    def _forget(self) -> None:
        self._keys = np.zeros(1 << _SLOT_BITS, np.uint64)
        self._codes = np.zeros(1 << _SLOT_BITS, np.int32)
        self._ids = np.zeros(1 << 16, np.uint32)
        self._starts = np.zeros(1 << 14, np.int32)
        self._words = self._used = 0

    def _find(self, keys: np.ndarray) -> np.ndarray:
        """Codes of word hashes, -1 for those not in the memo."""
        out = np.full(len(keys), -1, np.int32)
        slots = (keys >> np.uint64(64 - _SLOT_BITS)).astype(np.int64)
        left = np.arange(len(keys))
        while len(left):
            there = self._keys[slots]
            hit = there == keys[left]
            out[left[hit]] = self._codes[slots[hit]]
            on = ~hit & (there != 0)
            left, slots = left[on], (slots[on] + 1) & ((1 << _SLOT_BITS) - 1)
        return out

    def _learn(self, keys: np.ndarray, words: list[str]) -> None:
        lists = list(map(self._direct, words))
        odd = [i for i, ids in enumerate(lists) if ids is None]
        for i, encoded in zip(odd, self._library.encode_batch_fast([words[i] for i in odd], add_special_tokens=False)):
            lists[i] = encoded.ids
        flat = np.fromiter(chain.from_iterable(lists), np.uint32)
        lengths = np.fromiter(map(len, lists), np.int32, len(lists))
        first = self._words
        while self._used + len(flat) > len(self._ids):
            self._ids = np.concatenate((self._ids, np.zeros_like(self._ids)))
        while first + len(words) + 1 > len(self._starts):
            self._starts = np.concatenate((self._starts, np.zeros_like(self._starts)))
        self._ids[self._used : self._used + len(flat)] = flat
        self._starts[first + 1 : first + 1 + len(words)] = self._used + np.cumsum(lengths)
        self._used += len(flat)
        self._words += len(words)
        codes = np.arange(first, self._words, dtype=np.int32)
        slots = (keys >> np.uint64(64 - _SLOT_BITS)).astype(np.int64)
        left = np.arange(len(keys))
        while len(left):
            free = self._keys[slots] == 0
            self._keys[slots[free]] = keys[left[free]]
            held = free & (self._keys[slots] == keys[left])
            self._codes[slots[held]] = codes[left[held]]
            left, slots = left[~held], (slots[~held] + 1) & ((1 << _SLOT_BITS) - 1)

    def encode_texts(self, column: pa.Array, end_id: int | None = None) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
        """Yield (first row, end row, ids, offsets in them), some texts at a time.

        A null text has no ids; ``end_id``, if given, follows each text's ids.
        """
        for row, end, data, offsets in text_slices(column):
            starts, ends, first = word_spans(data, offsets)
            parts, sizes = [np.zeros(0, np.uint32)], [np.zeros(0, np.int32)]
            for at in range(0, len(starts), _PIECE):
                ids, lengths = self._encode_words(data, starts[at : at + _PIECE], ends[at : at + _PIECE])
                parts.append(ids)
                sizes.append(lengths)
            ids = np.concatenate(parts)
            place = np.concatenate(([0], np.cumsum(np.concatenate(sizes), dtype=np.int64)))[first]
            if end_id is not None:
                ids = np.insert(ids, place[1:], np.uint32(end_id))
                place = place + np.arange(len(place))
            yield row, end, ids, place

    def _encode_words(self, data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(ids, number of ids of each word)."""
        keys = word_hashes(data, starts, ends, letters=self._letters) | np.uint64(1)
        long = np.flatnonzero(ends - starts > MEMO_BYTES)
        if len(long):  # each is new
            keys[long] = mix(np.arange(self._unseen + 1, self._unseen + 1 + len(long), dtype=np.uint64) ^ self._letters[0]) | np.uint64(1)
            self._unseen += len(long)
        if self._words > MEMO_WORDS or self._used > MEMO_IDS:
            self._forget()
        codes = self._find(keys)
        new = np.flatnonzero(codes < 0)
        if len(new):
            fresh, at = np.unique(keys[new], return_index=True)
            self._learn(fresh, [data[a:b].tobytes().decode() for a, b in zip(starts[new[at]].tolist(), ends[new[at]].tolist())])
            codes[new] = self._find(keys[new])
        begin = self._starts[codes].astype(np.int64)
        lengths = self._starts[codes + 1] - self._starts[codes]
        total = np.cumsum(lengths, dtype=np.int64)
        return self._ids[np.arange(total[-1]) + np.repeat(begin - total + lengths, lengths)], lengths

    def encode(self, text: str | None, end_id: int | None = None) -> np.ndarray:
        """The ids of one text."""
        return next(self.encode_texts(pa.array([text], pa.large_string()), end_id))[2]


_made: dict[str, WordTokenizer] = {}


def tokenizer(path: str) -> WordTokenizer:
    """One tokenizer per worker process and vocabulary."""
    if path not in _made:
        _made[path] = WordTokenizer(path)
    return _made[path]
