"""Words of UTF-8 texts as hashes, for whole Arrow columns at a time.

A word is a run of ASCII letters, digits and non-ASCII characters; A-Z count as a-z. All bytes of a
non-ASCII character are 0x80 or more, so words can be found in the bytes themselves.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

from factorclust.llm.shared import FORGET

#: Bytes looked at together; bounds the memory of the arrays below.
CHUNK = 1 << 20
_BASE = 0x9E3779B97F4A7C15
_powers: list[np.ndarray] = []
FORGET.append(_powers.clear)


def _table() -> np.ndarray:
    t = np.zeros(256, np.uint8)
    for lo, hi in ((0x30, 0x3A), (0x61, 0x7B), (0x80, 0x100)):
        t[lo:hi] = np.arange(lo, hi)
    t[0x41:0x5B] = np.arange(0x61, 0x7B)
    return t


FOLD = _table()
#: The same for bytes.translate: what belongs to no word becomes a space.
FOLD_BYTES = bytes(int(x) or 0x20 for x in FOLD)


def split_words(text: bytes) -> list[bytes]:
    return text.translate(FOLD_BYTES).split()


def mix(h: np.ndarray) -> np.ndarray:
    """A finaliser that spreads all 64 bits."""
    h = h ^ (h >> np.uint64(30))
    h = h * np.uint64(0xBF58476D1CE4E5B9)
    h ^= h >> np.uint64(27)
    h *= np.uint64(0x94D049BB133111EB)
    h ^= h >> np.uint64(31)
    return h


def _power(n: int) -> tuple[np.ndarray, np.ndarray]:
    if not _powers or len(_powers[0]) < n:
        inverse = pow(_BASE, -1, 1 << 64)
        for base in (_BASE, inverse):
            p = np.full(n, base, np.uint64)
            p[0] = 1
            _powers.append(np.cumprod(p))
        del _powers[:-2]
    return _powers[0], _powers[1]


@dataclass
class Chunk:
    """Words of some texts: ``word[i]`` is the hash of a word, ``doc[j]:doc[j+1]`` the words of text j.

    ``first`` is the number of the first text here; ``more`` says that the last text goes on in the
    next chunk, whose first text it then is.
    """

    first: int
    word: np.ndarray
    doc: np.ndarray
    more: bool


def hash_words(flat: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(hashes, where each text's words begin and end) of the texts flat[bounds[j]:bounds[j+1]]."""
    n = len(flat)
    if not n:
        return np.zeros(0, np.uint64), np.zeros(len(bounds), np.int64)
    folded = FOLD[flat]
    inside = folded != 0
    fence = np.zeros(n + 1, bool)
    fence[bounds] = True
    start = inside.copy()
    start[1:] &= ~inside[:-1] | fence[1:-1]
    end = inside.copy()
    end[:-1] &= ~inside[1:] | fence[1:-1]
    s, e = np.flatnonzero(start), np.flatnonzero(end)
    up, down = _power(max(n, CHUNK + 4096))
    sums = np.zeros(n + 1, np.uint64)
    np.cumsum(folded.astype(np.uint64) * up[:n], out=sums[1:])
    h = (sums[e + 1] - sums[s]) * down[s]
    return mix(h + (e - s).astype(np.uint64)), np.searchsorted(s, bounds)


def chunks(texts: pa.Array) -> Iterator[Chunk]:
    """The words of a string column in chunks of about CHUNK bytes; a longer text is cut between words."""
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
    if not pa.types.is_large_string(texts.type):
        texts = texts.cast(pa.large_string())
    if texts.null_count:
        texts = texts.fill_null("")
    n = len(texts)
    if not n:
        return
    buffers = texts.buffers()
    at = np.frombuffer(buffers[1], np.int64)[texts.offset : texts.offset + n + 1]
    data = np.frombuffer(buffers[2], np.uint8) if buffers[2] is not None else np.zeros(0, np.uint8)
    j = 0
    while j < n:
        k = max(j + 1, int(np.searchsorted(at, at[j] + CHUNK, "right")) - 1)
        lo, hi = int(at[j]), int(at[k])
        if hi - lo <= CHUNK or k > j + 1:
            h, d = hash_words(data[lo:hi], (at[j : k + 1] - lo).astype(np.int64))
            yield Chunk(j, h, d, False)
        else:  # one long text
            while lo < hi:
                to = min(hi, lo + CHUNK)
                while to < hi and FOLD[data[to]] and FOLD[data[to - 1]]:
                    to += 1
                h, d = hash_words(data[lo:to], np.array([0, to - lo]))
                lo = to
                yield Chunk(j, h, d, lo < hi)
        j = k


def whole(texts: pa.Array) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """As ``chunks``, but each text is whole: (first text, hashes, bounds). A long text takes 8 bytes a word."""
    held: list[np.ndarray] = []
    for c in chunks(texts):
        if c.more:
            held.append(c.word)
        elif held:
            words = np.concatenate([*held, c.word])
            held = []
            yield c.first, words, np.array([0, len(words)])
        else:
            yield c.first, c.word, c.doc


def grams(word: np.ndarray, doc: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(hash of the k words from each word on, whether all k lie in its text)."""
    n = len(word)
    h = np.zeros(n, np.uint64)
    factor = np.uint64(1)
    with np.errstate(over="ignore"):
        for i in range(k):
            factor = factor * np.uint64(0xD6E8FEB86659FD93)
            h[: n - i] += word[i:] * factor if i < n else np.uint64(0)
    ok = np.zeros(n, bool)
    size = np.diff(doc)
    last = np.repeat(doc[1:], size)
    ok[:] = np.arange(n) + k <= last if n else ok
    return mix(h), ok


def hash_one(words: list[bytes]) -> np.ndarray:
    """Hashes of single words, as in the chunks."""
    flat = b" ".join(words)
    h, _ = hash_words(np.frombuffer(flat, np.uint8), np.array([0, len(flat)]))
    return h
