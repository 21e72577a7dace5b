"""Byte-level BPE ids of whole texts, with a compact memory of the ids of words.

A single space between two other characters that aren't white space always starts a pre-token, and so does
a line's end between such characters. So a text may be cut there without changing an id: its pieces are
hashed in NumPy, known pieces are looked up in one sorted table, and only new ones go to the library, many
in one string. Texts with other white space, white space in a row, or the string of a special token, go to
the library as they are: it makes one id of such a string, as the library does by default.
"""

from __future__ import annotations

import os
import re
from collections.abc import Iterable, Iterator

import numpy as np

from factorclust.llm.shared import FORGET
from factorclust.llm.words import _power, mix

#: Pieces a task remembers, some 30 bytes each, and the ids of all of them.
REMEMBERED, HELD = 4_000_000, 1 << 25
#: Characters encoded at once; longer texts are cut where the pre-tokenizer cuts anyway.
LONGEST = 200_000
#: Unknown pieces encoded in one string; characters of texts looked at together.
TOGETHER, BATCH = 256, 1 << 18
#: Such strings encoded in one call; what the library returns takes some 40 times the ids.
STRINGS = 32
END_ID = 0

_DOUBLE = re.compile(r"\s\s")
_SAFE = re.compile(r"(?<=\S) (?=\S)")
_loaded: dict[str, Encoder] = {}
FORGET.append(_loaded.clear)  # an encoder takes a hundred MB, which the tasks of other stages may need


def _plainly_spaced(text: str) -> bool:
    """True if no white space stands beside other white space or at an end; a quick look that settles most texts."""
    if text[0].isspace() or text[-1].isspace():
        return False
    flat = text.replace("\n", "_") if "\n" in text else text
    if flat.isprintable() and "  " not in text and "\n\n" not in text and " \n" not in text and "\n " not in text:
        return True
    return "\0" not in text and not _DOUBLE.search(text)


class Memory:
    """A sorted table of hashes with, for each, where its ids stand in a pool; new rows are merged in by and by."""

    def __init__(self, dtype: np.dtype):
        self.dtype = dtype
        self.clear()

    def clear(self) -> None:
        self.runs: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        self.pool = np.zeros(1 << 16, self.dtype)
        self.used = 0

    def __len__(self) -> int:
        return sum(len(r[0]) for r in self.runs)

    def find(self, h: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(known, start, length) of each hash."""
        known = np.zeros(len(h), bool)
        start, length = np.zeros(len(h), np.int64), np.zeros(len(h), np.int64)
        for keys, starts, lengths in self.runs:
            at = np.minimum(np.searchsorted(keys, h), len(keys) - 1)
            hit = keys[at] == h
            start[hit], length[hit] = starts[at[hit]], lengths[at[hit]]
            known |= hit
        return known, start, length

    def add(self, h: np.ndarray, ids: list[bytes]) -> None:
        """Rows for sorted hashes that aren't there yet."""
        if len(self) + len(h) > REMEMBERED or self.used > HELD:
            self.clear()
        flat = np.frombuffer(b"".join(ids), self.dtype)
        length = np.array([len(x) for x in ids], np.int64) // self.dtype.itemsize
        if self.used + len(flat) > len(self.pool):
            self.pool = np.concatenate([self.pool, np.zeros(max(len(flat), len(self.pool) // 2), self.dtype)])
        self.pool[self.used : self.used + len(flat)] = flat
        run = (h, (self.used + np.cumsum(length) - length).astype(np.uint32), length.astype(np.uint32))
        self.used += len(flat)
        while self.runs and len(self.runs[-1][0]) <= 2 * len(run[0]):
            old = self.runs.pop()
            keys = np.concatenate([old[0], run[0]])
            order = np.argsort(keys, kind="stable")
            run = tuple(np.concatenate([a, b])[order] for a, b in zip(old, run, strict=True))
        self.runs.append(run)


class Encoder:
    """Ids of texts, each followed by END_ID, as integers of ``dtype``."""

    def __init__(self, path: str):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")  # tasks are parallel already; threads would each keep memory
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        vocab = self.tokenizer.get_vocab(with_added_tokens=True)
        most = max(vocab.values())
        self.dtype = np.dtype(np.uint16 if most < 1 << 16 else np.uint32)
        self.end = np.array([END_ID], self.dtype)
        # ids of tokens that begin with a space, and with a line's end
        self.spaced, self.broken = np.zeros(most + 1, bool), np.zeros(most + 1, bool)
        self.spaced[[i for token, i in vocab.items() if token.startswith("Ġ")]] = True
        self.broken[[i for token, i in vocab.items() if token.startswith("Ċ")]] = True
        self.memory = Memory(self.dtype)
        added = [re.escape(t.content) for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.special = re.compile("|".join(added)) if added else None

    def _has_special(self, text: str) -> bool:
        return self.special is not None and self.special.search(text) is not None

    def _plain(self, text: str) -> np.ndarray:
        cuts = [text] if self._has_special(text) else self._pieces(text)  # a special token may take the white space beside it
        parts = [np.array(self.tokenizer.encode(p, add_special_tokens=False).ids, self.dtype) for p in cuts if p]
        return np.concatenate([*parts, self.end])

    def _pieces(self, text: str) -> Iterator[str]:
        at = 0
        while len(text) - at > LONGEST:
            cut = _SAFE.search(text, at + LONGEST)
            if not cut:
                break
            yield text[at : cut.start()]
            at = cut.start()
        yield text[at:]

    def _learn(self, words: list[str]) -> list[bytes]:
        """The ids of new pieces: of " word", or of "\\nword" as it is."""
        out: dict[str, bytes] = {}
        self._encode([w for w in words if w[0] != "\n"], " ", self.spaced, out)
        self._encode([w for w in words if w[0] == "\n"], "", self.broken, out)
        return [out[w] for w in words]

    def _encode(self, words: list[str], before: str, begins: np.ndarray, out: dict[str, bytes]) -> None:
        """Many pieces in one string; each begins with a token that ``begins`` tells from all others in it."""
        step = self.dtype.itemsize
        rows = [words[i : i + TOGETHER] for i in range(0, len(words), TOGETHER)]
        for k in range(0, len(rows), STRINGS):
            some = rows[k : k + STRINGS]
            for row, found in zip(some, self.tokenizer.encode_batch_fast([before + before.join(row) for row in some], add_special_tokens=False), strict=True):
                ids = np.array(found.ids, self.dtype)
                packed = ids.tobytes()
                edges = (np.flatnonzero(begins[ids]) * step).tolist()
                edges.append(len(packed))
                for word, lo, hi in zip(row, edges[:-1], edges[1:], strict=True):
                    out[word] = packed[lo:hi]

    def _together(self, texts: list[str]) -> list[np.ndarray]:
        """Ids of plainly spaced texts; the first word of each is looked up as that of a line."""
        flat = b"\0".join([b"\n" + t.encode("utf-8", "surrogatepass") for t in texts])
        data = np.frombuffer(flat, np.uint8)
        gap = (data == 0x20) | (data == 0)
        line = data == 0x0A
        start = ~gap
        start[1:] &= gap[:-1] | line[1:]
        last = ~gap
        last[:-1] &= gap[1:] | line[1:]
        s, e = np.flatnonzero(start), np.flatnonzero(last)
        up, down = _power(max(len(data), BATCH + (1 << 17)))
        sums = np.zeros(len(data) + 1, np.uint64)
        np.cumsum((data.astype(np.uint64) + np.uint64(1)) * up[: len(data)], out=sums[1:])
        h = mix((sums[e + 1] - sums[s]) * down[s] + (e - s).astype(np.uint64))
        distinct, first, which = np.unique(h, return_index=True, return_inverse=True)
        known, at, length = self.memory.find(distinct)
        for again in (False, True):
            if known.all():
                break
            if again:  # rows went for want of room
                self.memory.clear()
                known[:] = False
            new = np.flatnonzero(~known)
            lo, hi = s[first[new]].tolist(), (e[first[new]] + 1).tolist()
            self.memory.add(distinct[new], self._learn([flat[a:b].decode("utf-8", "surrogatepass") for a, b in zip(lo, hi, strict=True)]))
            known, at, length = self.memory.find(distinct)
        begin = np.flatnonzero(np.concatenate([[True], data[s[1:] - 1] == 0]))  # each text's first piece
        at, length = at[which], length[which]
        at[begin] += 1  # without the line's end
        length[begin] -= 1
        ends = np.cumsum(length)
        ids = self.memory.pool[np.repeat(at - ends + length, length) + np.arange(ends[-1])]
        cuts = np.concatenate([ends[begin] - length[begin], ends[-1:]]).tolist()
        return [np.concatenate([ids[a:b], self.end]) for a, b in zip(cuts[:-1], cuts[1:], strict=True)]

    def encode_many(self, texts: Iterable[str | None]) -> Iterator[np.ndarray]:
        """Ids of each text in turn; about BATCH characters are held at once."""
        held: list[str | None] = []
        size = 0
        for text in texts:
            held.append(text)
            size += len(text or "")
            if size >= BATCH:
                yield from self._lot(held)
                held, size = [], 0
        yield from self._lot(held)

    def _lot(self, texts: list[str | None]) -> Iterator[np.ndarray]:
        easy = [bool(t) and len(t) <= 2 * BATCH and _plainly_spaced(t) and not self._has_special(t) for t in texts]
        ready = iter(self._together([t for t, plain in zip(texts, easy, strict=True) if plain]) if any(easy) else ())
        for t, plain in zip(texts, easy, strict=True):
            yield next(ready) if plain else self._plain(t) if t else self.end

    def encode(self, text: str | None) -> np.ndarray:
        return next(self._lot([text]))


def encoder(path: str) -> Encoder:
    """One encoder a task and file."""
    if path not in _loaded:
        _loaded[path] = Encoder(path)
    return _loaded[path]
