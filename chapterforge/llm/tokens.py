"""Exact token ids of a public tokenizer, by white-space word with a bounded cache."""

from __future__ import annotations

import re
from array import array
from collections.abc import Iterator
from itertools import chain

import numpy as np

_NOT_BY_WORD = re.compile("[\x1c-\x1f]")
_SPACE = re.compile(r"\s")
# Latin letters that no normal form changes, then marks other than the apostrophe
_LETTERS_MARKS = re.compile(r"([a-z\xdf-\xf6\xf8-\xff]+)([!-&(-/:-@\[-`{-~]*)").fullmatch

# the letters above, and as the characters that stand for their UTF-8 bytes in byte-level vocabularies
_LETTERS = "".join(map(chr, [*range(0x61, 0x7B), *range(0xDF, 0xF7), *range(0xF8, 0x100)]))
_PRINTED = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
_OTHERS = [b for b in range(256) if b not in _PRINTED]
_AS_BYTES = {ord(c): "".join(chr(b if b in _PRINTED else 256 + _OTHERS.index(b)) for b in c.encode()) for c in _LETTERS}

_SHARED: dict[str, WordIds] = {}


def tokenizer_path(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


class WordIds:
    """Ids of whole texts as little-endian unsigned 32-bit bytes.

    For tokenizers whose own split never joins characters over white space: ids of a text are those of its
    white-space words, one after the other. Words come from a dictionary that is held to about ``most_bytes``; new
    ones go through the tokenizer itself, many at a time. Most words of a corpus stand in it once, so a word is held
    lastingly only when it is learnt a second time; the others leave whenever the dictionary is full. Which words
    came before is held as one bit each, in a fixed field that starts anew when a quarter of its bits may be set: a wrong
    bit costs space or time, never a wrong id. Texts are taken ``stretch`` characters at a time, so that what is held besides the dictionary
    doesn't grow with a text or a batch. Texts with the four separator controls, which
    Python takes for white space and the tokenizer doesn't, go through it whole. ``split_marks`` is for
    tokenizers that lower-case and part letters from marks: a new word then shares its letters' entry. Where normal form
    and split leave letters as they are (``_letters_alone``), these go to the model alone, many as one text.
    """

    #: bytes of an entry besides its word and ids: two objects and their place in the dictionary
    ENTRY = 140
    #: longer words are not kept
    KEPT = 256
    #: bits of the field of words that came before
    BITS = 1 << 25

    def __init__(self, path: str, most_bytes: int = 96 << 20, split_marks: bool = True, stretch: int = 1 << 18):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.most_bytes, self.split_marks, self.stretch = most_bytes, split_marks, stretch
        self.known: dict[str, bytes] = {}
        self.held = 0
        self.young: list[str] = []
        self.came, self.marked = bytearray(self.BITS >> 3), 0
        self.alone, self.last = (split_marks and self._letters_alone()) or (None, None)

    def _letters_alone(self) -> tuple | None:
        """The model behind a split by white space, and which ids end a word; None where that can't give the ids of words of
        ``_LETTERS``. Ends are told by the suffix that the vocabulary has for them."""
        from tokenizers import Tokenizer, models, pre_tokenizers

        t = self.tokenizer
        if not isinstance(t.model, models.BPE) or t.model.dropout or not t.model.end_of_word_suffix or t.model.continuing_subword_prefix:
            return None
        if t.normalizer is not None and t.normalizer.normalize_str(_LETTERS) != _LETTERS:
            return None
        if t.pre_tokenizer is None or [x for x, _ in t.pre_tokenizer.pre_tokenize_str(_LETTERS)] != [_LETTERS.translate(_AS_BYTES)]:
            return None
        if any(set(x.content.lower()) <= set(_LETTERS) for x in t.get_added_tokens_decoder().values()):
            return None
        alone = Tokenizer(t.model)
        alone.pre_tokenizer = pre_tokenizers.WhitespaceSplit()
        vocabulary = t.get_vocab()
        last = np.zeros(max(vocabulary.values()) + 1, dtype=bool)
        last[[i for x, i in vocabulary.items() if x.endswith(t.model.end_of_word_suffix)]] = True
        return alone, last

    @classmethod
    def shared(cls, path: str) -> WordIds:
        """One for each Python worker, which may run many tasks."""
        if path not in _SHARED:
            _SHARED[path] = cls(path)
        return _SHARED[path]

    def _whole(self, text: str) -> bytes:
        return array("I", self.tokenizer.encode(text, add_special_tokens=False).ids).tobytes()

    def _encode(self, words: list[str]) -> dict[str, bytes]:
        out = {}
        for at in range(0, len(words), 2000):
            some = words[at : at + 2000]
            found = self.tokenizer.encode(some, is_pretokenized=True, add_special_tokens=False)
            ids = np.array(found.ids, dtype="<u4").tobytes()
            ends = (4 * np.cumsum(np.bincount(np.array(found.word_ids, dtype=np.int64), minlength=len(some)))).tolist()
            start = 0
            for w, end in zip(some, ends):
                out[w] = ids[start:end]
                start = end
        return out

    def _encode_letters(self, words: list[str]) -> dict[str, bytes]:
        """``_encode`` of words of ``_LETTERS``."""
        if self.alone is None:
            return self._encode(words)
        out = {}
        for at in range(0, len(words), 4000):
            some = words[at : at + 4000]
            found = np.array(self.alone.encode_batch_fast([" ".join(some).translate(_AS_BYTES)], add_special_tokens=False)[0].ids, dtype="<u4")
            ends = (4 * np.flatnonzero(self.last[found]) + 4).tolist()
            if len(ends) != len(some):  # a letter that the vocabulary lacks
                out |= self._encode(some)
                continue
            ids, start = found.tobytes(), 0
            for w, end in zip(some, ends):
                out[w] = ids[start:end]
                start = end
        return out

    def _learn(self, words: set[str]) -> dict[str, bytes]:
        """Ids of words that the dictionary lacks, and of their letters and marks where it lacks them too."""
        known, parts, whole = self.known, {}, []
        for w in words:
            if self.split_marks and (m := _LETTERS_MARKS(w.lower())):
                parts[w] = m.groups()
            else:
                whole.append(w)
        fresh = self._encode_letters(list({letters for letters, _ in parts.values() if letters not in known}))
        fresh |= self._encode(list({marks for _, marks in parts.values() if marks and marks not in known}.union(whole)))
        ids = lambda part: fresh[part] if part in fresh else known[part]
        for w, (letters, marks) in parts.items():
            if w not in fresh:
                fresh[w] = ids(letters) + ids(marks) if marks else ids(letters)
        return fresh

    def _keep(self, fresh: dict[str, bytes]) -> None:
        known, young, came, last = self.known, self.young, self.came, self.BITS - 1
        for w, ids in fresh.items():
            if len(w) > self.KEPT:
                continue
            known[w] = ids
            self.held += self._size(w, ids)
            place, bit = (at := hash(w) & last) >> 3, 1 << (at & 7)
            if not came[place] & bit:
                came[place] |= bit
                self.marked += 1
                young.append(w)
        if self.held > self.most_bytes:
            self._shrink()
        if self.marked > self.BITS >> 2:
            self.came, self.marked = bytearray(self.BITS >> 3), 0

    def _size(self, word: str, ids: bytes) -> int:
        return self.ENTRY + len(word) + len(ids)

    def _shrink(self) -> None:
        """The words that came once leave; if the others still take three quarters of the bytes, the latest of them leave too: by
        Zipf's law the earliest are the frequent ones."""
        for w in self.young:
            self.held -= self._size(w, self.known.pop(w))
        self.young = []
        if self.held > self.most_bytes * 3 // 4:
            kept, self.held = {}, 0
            for w, ids in self.known.items():
                size = self._size(w, ids)
                if self.held + size > self.most_bytes // 2:
                    break
                kept[w] = ids
                self.held += size
            self.known = kept

    def _joined(self, texts: list[str]) -> list[bytes]:
        split = [t.split() for t in texts]
        words = list(chain.from_iterable(split))
        found = list(map(self.known.get, words))
        absent = [i for i, ids in enumerate(found) if ids is None]
        if absent:
            fresh = self._learn({words[i] for i in absent})
            for i in absent:
                found[i] = fresh[words[i]]
            self._keep(fresh)
        out, at = [], 0
        for s in split:
            out.append(b"".join(found[at : at + len(s)]))
            at += len(s)
        return out

    def _stretches(self, text: str) -> Iterator[str]:
        """The text in parts that begin and end between words."""
        at = 0
        while len(text) - at > self.stretch:
            gap = _SPACE.search(text, at + self.stretch)
            if gap is None:
                break
            yield text[at : gap.start()]
            at = gap.start()
        yield text[at:]

    def each(self, texts: list[str]) -> Iterator[bytes]:
        """Ids of one text after the other."""
        few, size = [], 0
        for t in texts:
            if few and size + len(t) > self.stretch:
                yield from self._joined(few)
                few, size = [], 0
            if _NOT_BY_WORD.search(t):
                if few:
                    yield from self._joined(few)
                    few, size = [], 0
                yield self._whole(t)
            elif len(t) > self.stretch:
                yield b"".join(self._joined([part])[0] for part in self._stretches(t))
            else:
                few.append(t)
                size += len(t)
        if few:
            yield from self._joined(few)

    def batch(self, texts: list[str]) -> list[bytes]:
        return list(self.each(texts))
