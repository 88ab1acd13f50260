"""Token ids of whole texts, with a memory of the words met.

The tokenizer splits at white space, and letters from punctuation, and never looks
across such a place, so the ids of a text are those of its parts between spaces or line
feeds. ASCII capitals are lowered first, as the tokenizer does itself. Arrow finds the
different parts of a batch of texts; a worker keeps the ids of those it has met, up to
``KEPT`` of them, and asks the tokenizer only for new ones. Of a new part, a closing run of
ASCII punctuation behind an ASCII letter is a part of its own. What is then words of
small Latin letters alone needs no normalising and goes straight to the tokenizer's model.
The tokenizer's special strings, as written, are one id each; texts are divided at them before all else.
"""

from __future__ import annotations

import os
import re
from array import array
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

KEPT = 800_000
TOKENIZER = "word_bpe_49k.json"
_CLOSING = re.compile(rb"(?s)(.*[a-z])([!-/:-@\[-`{-~]+)")
#: Small letters of ASCII and of Latin-1 (all NFC).
_PLAIN = re.compile("[a-zß-öø-ÿ]+")


def tokenizer_path(name: str = TOKENIZER) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def byte_characters() -> dict[int, str]:
    """The printable character that stands for each byte in a byte-level vocabulary: itself, or the next free one from 256 on."""
    shown = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    hidden = [b for b in range(256) if b not in shown]
    return {b: chr(b) for b in shown} | {b: chr(256 + i) for i, b in enumerate(hidden)}


class WordIds:
    """Ids as little-endian unsigned 32-bit integers."""

    def __init__(self, path: str) -> None:
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        # Special strings count as they are written, before any normalising: texts are divided at them first. What
        # becomes one only by lowering is plain text, and is kept so in the parts.
        special = {a.content: i for i, a in self.tokenizer.get_added_tokens_decoder().items() if a.special}
        self.special = {t.encode(): np.array([i], "<u4").tobytes() for t, i in special.items()}
        self.divide = re.compile(b"(" + b"|".join(re.escape(t) for t in sorted(self.special, key=len, reverse=True)) + b")") if special else None
        self.tokenizer.encode_special_tokens = True
        self.model = self.tokenizer.model
        self.shown = byte_characters()
        self.known: dict[bytes, bytes] = {b"": b""}

    def learn(self, new: list[bytes]) -> None:
        known, closing, is_plain = self.known, _CLOSING.fullmatch, _PLAIN.fullmatch
        pairs, need = [], set()
        for w in new:
            m = closing(w)
            if m:
                pairs.append((w, *m.groups()))
                need.update(m.groups())
            else:
                need.add(w)
        other, tokenize, shown = [], self.model.tokenize, self.shown
        for w in need - known.keys():
            s = w.decode("utf-8", "replace")
            if is_plain(s):
                known[w] = array("I", [t.id for t in tokenize(w.decode("latin-1").translate(shown))]).tobytes()
            else:
                other.append((w, s))
        for a in range(0, len(other), 4096):
            part = other[a : a + 4096]
            for (w, _), e in zip(part, self.tokenizer.encode_batch_fast([s for _, s in part], add_special_tokens=False), strict=True):
                known[w] = np.array(e.ids, "<u4").tobytes()
        for w, letters, marks in pairs:
            known[w] = known[letters] + known[marks]

    def __call__(self, bodies: list[bytes]) -> list[bytes]:
        """The ids of each text."""
        if self.divide is None or not any(map(self.divide.search, bodies)):
            return self.plain(bodies)
        divided = [self.divide.split(t) for t in bodies]
        ids = iter(self.plain([t for d in divided for t in d[::2]]))
        return [b"".join(self.special[t] if i % 2 else next(ids) for i, t in enumerate(d)) for d in divided]

    def plain(self, bodies: list[bytes]) -> list[bytes]:
        """The ids of texts without special strings."""
        lowered = pa.array([t.lower().replace(b"\n", b" ") for t in bodies], pa.large_binary())
        parts = pc.split_pattern(lowered, b" ")
        coded = parts.values.dictionary_encode()
        met = coded.dictionary.to_pylist()
        new = [w for w in met if w not in self.known]
        if new:
            if len(self.known) + len(new) > KEPT:
                self.known = {b"": b""}
                new = met
            self.learn(new)
        ids = [self.known[w] for w in met]
        size = np.fromiter(map(len, ids), np.int64, len(ids)) // 4
        flat, first = np.frombuffer(b"".join(ids), "<u4"), np.cumsum(size) - size
        index = coded.indices.to_numpy()
        n = size[index]
        ends = np.cumsum(n)
        out = flat[np.repeat(first[index] - (ends - n), n) + np.arange(ends[-1] if len(ends) else 0)]
        at = np.r_[0, ends][parts.offsets.to_numpy()].tolist()
        whole = out.tobytes()
        return [whole[4 * a : 4 * b] for a, b in zip(at[:-1], at[1:], strict=True)]


@lru_cache(maxsize=2)
def word_ids(path: str) -> WordIds:
    """One for each worker and file."""
    return WordIds(path)
