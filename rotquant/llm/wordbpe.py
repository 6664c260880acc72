"""Whole-text encoding with a public word-level BPE file, through a bounded cache of words.

The vocabulary's own pre-tokenizer never joins characters across white space, so a text's
ids are those of its white-space chunks in a row. Chunks that are not known go to the
``tokenizers`` library together, with a mark between them whose one id nothing else has, and
are remembered as little-endian 32-bit ids in two generations of bounded size. A text with
characters whose case or class the fast path does not cover goes to the library whole.
"""

from __future__ import annotations

import re
from array import array

import numpy as np

from .common import claim

#: Characters on which Python's lower() and split() agree with the tokenizer's normaliser.
_PLAIN = re.compile(r"[^\x20-\x7e\n\t\rÀ-ÖØ-öø-ÿ]")
#: Words of one generation. At most two generations are held, about 200 bytes a word.
GENERATION = 200_000
#: Words that go to the library as one text, and the mark between them; it is not among the plain characters.
JOINED, BETWEEN = 256, "\u20ac"
_MARKS = "!\"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~"


def public_path(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


class Words(dict):
    """Ids by word. A word not known yet gets a place that is filled once it is encoded.

    Words that were used since the last turn are the young generation; those of the turn
    before are kept until the next, so words that come again stay and others go.
    """

    def __init__(self):
        self.old: dict[str, bytes] = {}
        self.waiting: dict[str, bytearray] = {}

    def __missing__(self, word: str) -> bytes | bytearray:
        ids = self.old.get(word)
        if ids is None:
            stem = word.rstrip(_MARKS)
            if len(stem) < len(word) and stem.isalpha():  # letters and the marks after them are encoded apart
                a, b = self[stem], self[word[len(stem) :]]
                ids = a + b if type(a) is bytes and type(b) is bytes else None
        if ids is not None:
            self[word] = ids
            return ids
        if word not in self.waiting:
            self.waiting[word] = bytearray()
        return self.waiting[word]

    def learn(self, ids: list[bytes]) -> None:
        """Fills the places of the words that waited, and turns generations."""
        for (word, place), x in zip(self.waiting.items(), ids):
            place[:] = x
            self[word] = x
        self.waiting = {}
        if len(self) > GENERATION:
            self.old = dict(self)
            self.clear()

    def forget(self) -> None:
        self.clear()
        self.old = {}


class WordEncoder:
    def __init__(self, path: str):
        import os

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        self.tok.encode_special_tokens = True
        self.batch = getattr(self.tok, "encode_batch_fast", self.tok.encode_batch)
        self.words = Words()
        between = self.batch([BETWEEN], add_special_tokens=False)[0].ids
        self.between = between[0] if len(between) == 1 else None
        self.normaliser = self.tok.normalizer

    def _ids(self, texts: list[str]) -> list[bytes]:
        return [array("I", e.ids).tobytes() for e in self.batch(texts, add_special_tokens=False)]

    def _word_ids(self, words: list[str]) -> list[bytes]:
        """Ids of single words, which are normal already. Marks are set off from other marks by a blank."""
        out: list[bytes] = []
        self.tok.normalizer = None
        for at in range(0, len(words), JOINED):
            part = words[at : at + JOINED]
            if self.between is not None:
                text = [part[0]]
                for a, b in zip(part, part[1:]):
                    text.append((BETWEEN if a[-1].isalnum() else " " + BETWEEN) + (b if b[0].isalnum() else " " + b))
                ids = np.array(self.batch(["".join(text)], add_special_tokens=False)[0].ids, dtype="<u4")
                cuts = np.flatnonzero(ids == self.between)
                if len(cuts) == len(part) - 1:
                    data, ends = ids.tobytes(), [*(4 * cuts).tolist(), 4 * len(ids)]
                    out += [data[a:b] for a, b in zip([0, *(e + 4 for e in ends)], ends)]
                    continue
            out += self._ids(part)
        self.tok.normalizer = self.normaliser
        return out

    def encode(self, texts: list[str | None]) -> list[bytes]:
        """Little-endian unsigned 32-bit ids of each text; null is the empty text."""
        words = self.words
        look = words.__getitem__
        found = [list(map(look, t.lower().split())) if t and not _PLAIN.search(t) else None for t in texts]
        words.learn(self._word_ids(list(words.waiting)))
        odd = [i for i, x in enumerate(found) if x is None and texts[i]]
        whole = {i: self._ids([texts[i]])[0] for i in odd}
        return [whole.get(i, b"") if x is None else b"".join(x) for i, x in enumerate(found)]


_encoders: dict[str, WordEncoder] = {}


def encoder(path: str) -> WordEncoder:
    """One encoder for each worker process; its cache outlives the task."""
    if path not in _encoders:
        _encoders[path] = WordEncoder(path)
    claim("encoder", lambda: [e.words.forget() for e in _encoders.values()])
    return _encoders[path]
