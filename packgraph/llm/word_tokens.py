"""Token ids of whole texts by a tokenizers file whose pre-tokenizer never joins across white space.

Such a tokenizer gives a text the ids of its white-space-free chunks one after another, so each
worker keeps the ids of chunks it has seen (a bounded table) and asks the library for new ones.
"""

from __future__ import annotations

import os
import re
from array import array

import numpy as np

CACHE_CHUNKS = 600_000
#: Characters whose lower case and NFC form are the same in every library: Latin without the dotted capital I.
_PLAIN = re.compile("[\x00-\u012f\u0131-\u024f]*")
# The byte-level alphabet: printable bytes stand for themselves, others for characters from 256 on.
_PRINTABLE = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
_BYTE_ALPHABET = {b: chr(256 + k) for k, b in enumerate(b for b in range(256) if b not in _PRINTABLE)}


class _Known(dict):
    """Ids of chunks. A new chunk gets an empty bytearray at once, filled in later; ``old`` is the generation before."""

    def __init__(self, old: dict):
        self.old, self.new = old, []

    def __missing__(self, chunk: str):
        found = self.old.get(chunk)
        if found is None:
            found = bytearray()
            self.new.append(chunk)
        self[chunk] = found
        return found


class ChunkEncoder:
    """Chunks end at spaces and line feeds only: whatever else the library splits at stays inside a chunk.

    letters: the tokenizer puts texts in NFC and lower case, makes a run of letters one word of its
    byte-level BPE model, and a full stop or comma between a letter and white space a word of its own; chunks of plain
    Latin letters then skip everything but the model.
    """

    def __init__(self, path: str, cache: int = CACHE_CHUNKS, letters: bool = True):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        added = sorted((t.content for t in self.tokenizer.get_added_tokens_decoder().values()), key=len, reverse=True)
        # chunks that hold an added token's text go to the library as they are; such texts must hold no white space
        self.added = re.compile("|".join(map(re.escape, added)), re.IGNORECASE) if added else None
        if any(re.search(r"\s", x) for x in added):
            raise ValueError("an added token holds white space")
        self.known, self.cache, self.letters = _Known({}), cache, letters
        self.ends = {c: self._one(c) for c in ".,"}

    def _one(self, chunk: str) -> bytes:
        """The ids of a chunk; one of plain letters is a single word for the library's model."""
        if self.letters and chunk.isalpha() and _PLAIN.fullmatch(chunk) and not (self.added and self.added.search(chunk)):
            if not chunk.isascii():
                chunk = chunk.encode().decode("latin-1").translate(_BYTE_ALPHABET)
            ids = [t.id for t in self.tokenizer.model.tokenize(chunk)]
        else:
            ids = self.tokenizer.encode(chunk, add_special_tokens=False).ids
        return array("I", ids).tobytes()

    def _fill(self) -> None:
        """Finds the ids of new chunks, from their plain forms where those give them."""
        known, old = self.known, self.known.old
        for c in known.new:
            base, end = c, None
            if self.letters and (c.isascii() or _PLAIN.fullmatch(c)) and not (self.added and self.added.search(c)):
                base = c.lower()
                if base[-1:] in (".", ",") and base[-2:-1].isalpha():
                    base, end = base[:-1], base[-1]
            if base == c:
                ids = self._one(c)
            else:
                ids = known.get(base) or old.get(base)
                if not ids:
                    ids = self._one(base)
                    if base not in known:  # a new one that comes later in the list fills its own place
                        known[base] = ids
            ids = bytes(ids)
            if end:
                ids += self.ends[end]
            known[c] += ids  # in place: rows hold it
            known[c] = ids
        known.new = []

    def __call__(self, texts: list[str | None]) -> list[np.ndarray]:
        """The ids of each text; null has none."""
        out: list[np.ndarray] = []
        for i in range(0, len(texts), 64):
            if len(self.known) > self.cache:
                self.known.old = {}
                self.known = _Known(self.known)
            ids = self.known.__getitem__
            rows = [list(map(ids, (t or "").replace("\n", " ").split(" "))) for t in texts[i : i + 64]]
            if self.known.new:
                self._fill()
            out += [np.frombuffer(b"".join(r), "<u4") for r in rows]
        return out


_encoders: dict[str, ChunkEncoder] = {}


def encoder(path: str) -> ChunkEncoder:
    """This worker's encoder for ``path``."""
    if path not in _encoders:
        _encoders[path] = ChunkEncoder(path)
    return _encoders[path]


def slices(lengths: np.ndarray, most: int) -> list[tuple[int, int]]:
    """Ranges of rows of at most ``most`` in all, or of one row."""
    out, i = [], 0
    total = np.cumsum(lengths)
    while i < len(lengths):
        j = max(i + 1, int(np.searchsorted(total, (total[i - 1] if i else 0) + most, "right")))
        out.append((i, j))
        i = j
    return out
