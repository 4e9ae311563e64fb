"""Token ids of whole texts, word by word with a cache.

The vocabulary drops white space and never merges over it, so a text's ids are those of its ASCII
space-separated words one after another; a word seen before costs a dictionary lookup. Words are
looked up in lower case, as the vocabulary lowers letters itself, except where that could differ:
texts with combining marks, which are composed before letters are lowered, keep their case, and
texts that may hold special tokens are encoded as they stand.
"""

from __future__ import annotations

from array import array
from collections import Counter

import numpy as np

#: The byte-level alphabet writes these bytes (as Latin-1 characters) as other letters.
_BYTES = {b: 256 + i for i, b in enumerate([*range(33), *range(127, 161), 173])}
#: Words remembered per worker process; once it is full, further words are encoded anew each time.
CACHE = 500_000
#: Ids are stored in two bytes each while the vocabulary allows it.
END = 1
#: Words of the table of frequent words, and how many words are counted before it is made.
HOT, HOT_AFTER = 20_000, 400_000
_SEPARATOR = "~"
#: Marks that never begin a token with letters (an apostrophe can), cut off the end of words of letters.
_MARKS = b",.!?;:*#$%&"

_encoders: dict[str, "Encoder"] = {}


class _Known(dict):
    """word -> ids as bytes; a word not known yet gets a buffer that is filled once its text's run is encoded."""

    def __init__(self):
        super().__init__()
        self.pending: dict[bytes, bytearray] = {}

    def __missing__(self, word: bytes) -> bytearray:
        slot = self.pending.get(word)
        if slot is None:
            slot = self.pending[word] = bytearray()
        return slot


def _stays_letters(t: str) -> bool:
    """Whether a word is nothing but letters of alphabets whose lower case is letters again."""
    return t.isalpha() and max(t) < "\u0250" and t.lower().isalpha()


class Encoder:
    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.kind = np.dtype("<u2" if self.tokenizer.get_vocab_size() < 1 << 16 else "<u4")
        self.code = "H" if self.kind.itemsize == 2 else "I"
        self.known = _Known()
        self.hot, self.seen = None, Counter()
        self.model = self.tokenizer.model
        alone = self._plain(_SEPARATOR)
        self.separator = int(alone[0]) if len(alone) == 1 else None
        self.marks: dict[bytes, bytes] = {}
        probe = ["hello", "straße", "école", "niño", "x", "Hello", "a,", "~"]
        apart = np.concatenate([self._plain(w) for w in probe])
        folded = np.concatenate([self._plain(w) for w in ("hello", "straße", "école", "niño", "x", "hello", "a", ",", "~")])
        #: Whether texts may be taken apart into words at all; otherwise they are encoded as they stand.
        self.by_word = self.separator is not None and len(apart) == len(folded) and bool((apart == folded).all()) and bool((self._plain("  ".join(probe)) == apart).all())
        #: Whether words of lower-case letters may go to the model as they are, bytes in its alphabet.
        self.fast = self.by_word and all(self._letters(w.encode()) == self._plain(w).tobytes() for w in probe[:5])

    def _heat(self) -> None:
        """Put the most frequent words into a small table of their own, close together in memory; it falls back to the large one."""
        top = [w for w, _ in self.seen.most_common(HOT) if w in self.known]
        table = type("_Hot", (dict,), {"__missing__": self.known.__getitem__})
        self.hot = table({bytes(bytearray(w)): bytes(bytearray(self.known[w])) for w in top})
        self.seen = None

    def _plain(self, text: str) -> np.ndarray:
        return np.array(self.tokenizer.encode_batch_fast([text], add_special_tokens=False)[0].ids, self.kind)

    def _letters(self, word: bytes) -> bytes:
        text = word.decode() if word.isascii() else word.decode("latin-1").translate(_BYTES)
        return array(self.code, [t.id for t in self.model.tokenize(text)]).tobytes()

    def _encode_new(self, words: list[bytes]) -> dict[bytes, bytes]:
        """Ids of words not known; a run of marks after letters is a token stretch of its own."""
        known, out, marked, joined, fast, letters = self.known, {}, [], [], self.fast, self._letters
        for w in words:
            core = w.rstrip(_MARKS) if w[-1] in _MARKS else w
            if fast and core is not w and core and (core.isalpha() or (core[-1] > 127 and _stays_letters(core.decode()))):
                marked.append((w, core))
                if core in known or core in out:
                    continue
                w = core
            if fast and w.isalpha():
                out[w] = letters(w) if w.islower() else self._plain(w.decode()).tobytes()
                continue
            if w in out:
                continue
            t = w.decode()
            if fast and _stays_letters(t):
                out[w] = letters(t.lower().encode())
            elif _SEPARATOR in t:
                out[w] = self._plain(t).tobytes()
            else:
                out[w] = b""
                joined.append(w)
        size, between = self.kind.itemsize, f" {_SEPARATOR} ".encode()
        for at in range(0, len(joined), 1000):
            part = joined[at : at + 1000]
            ids = self._plain(between.join(part).decode())
            raw, first = ids.tobytes(), 0
            for w, end in zip(part, [*np.flatnonzero(ids == self.separator).tolist(), len(ids)]):
                out[w] = raw[first * size : end * size]
                first = end + 1
        for w, core in marked:
            mark = w[len(core) :]
            if mark not in self.marks:
                if len(self.marks) > 10_000:
                    self.marks.clear()
                self.marks[mark] = self._plain(mark.decode()).tobytes()
            out[w] = (out[core] if core in out else known[core]) + self.marks[mark]
        return out

    def ids(self, texts: list[bytes | None]) -> list[np.ndarray]:
        """Ids (uint32) of each text, END appended; null is empty."""
        split: list = []
        for t in texts:
            t = t or b""
            if not self.by_word or b"<|" in t:
                split.append(None)
            else:
                split.append((t if b"\xcc" in t or b"\xcd" in t else t.lower()).split())
        known = self.known
        if self.hot is None:
            for words in split:
                self.seen.update(words or ())
            if self.seen.total() > HOT_AFTER and len(known) > HOT:
                self._heat()
        get = (known if self.hot is None else self.hot).__getitem__
        found = [words and list(map(get, words)) for words in split]
        if known.pending:
            pending, known.pending = known.pending, {}
            new = self._encode_new(list(pending))
            for w, slot in pending.items():
                slot += new[w]
            if len(known) < CACHE:
                known.update(new)
        end = np.array([END], self.kind).tobytes()
        out = []
        for t, got in zip(texts, found):
            raw = self._plain(t.decode()).tobytes() if got is None else b"".join(got)
            out.append(np.frombuffer(raw + end, self.kind).astype("<u4"))
        return out


def forget() -> None:
    """Give back a worker's encoders, for steps of other operators that run in the same process later."""
    _encoders.clear()


def encoder(path: str) -> Encoder:
    """The worker's encoder for a vocabulary file."""
    import os

    os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
    if path not in _encoders:
        _encoders[path] = Encoder(path)
    return _encoders[path]


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def encode_batches(path: str, texts: list[bytes | None], most: int = 1 << 22):
    """(position, ids) of each text, encoded in runs of bounded size."""
    enc, run, size, first = encoder(path), [], 0, 0
    for i, t in enumerate(texts):
        run.append(t)
        size += len(t or b"")
        if size > most or len(run) >= 256:
            yield from zip(range(first, i + 1), enc.ids(run))
            run, size, first = [], 0, i + 1
    yield from zip(range(first, first + len(run)), enc.ids(run))
