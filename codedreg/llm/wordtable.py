"""A bounded table of words and their token ids, looked up for whole buffers of texts at once.

A buffer holds texts, each after a byte 255 (which UTF-8 never has).  Its words tile it; they begin at that byte, at
spaces, at line feeds that follow another character, at A-Z or a-z after a single line feed, and at a mark between such
a letter and white space or the end, where no pre-token of the published pattern crosses.  Words are found by 64-bit hashes with open addressing,
and every word found is compared byte by byte with what the table holds, so that equal hashes of different words
cost time and never a wrong id.  A full table is emptied; what it holds never changes a result.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np

from codedreg.llm.common import mix64

ENTRIES = 1 << 20
#: Longer words are coded anew each time.
LONGEST = 64
TEXT, SPACE, FEED = 255, 32, 10
#: Letters, and marks that are a pre-token of their own between a letter and white space.
LETTER = np.isin(np.arange(256), [*range(65, 91), *range(97, 123)])
MARK = np.isin(np.arange(256), list(b".,;:!?"))

_SCATTER = mix64(np.arange(1, 257, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))
_BASE = 0xD6E8FEB86659FD93
_INVERSE = pow(_BASE, -1, 1 << 64)


def powers(base: int, n: int) -> np.ndarray:
    return np.cumprod(np.concatenate([[np.uint64(1)], np.full(n - 1, base, np.uint64)]))


class Pool:
    """An array that grows."""

    def __init__(self, kind):
        self.data, self.size = np.zeros(1024, kind), 0

    def add(self, values: np.ndarray) -> None:
        need = self.size + len(values)
        if need > len(self.data):
            self.data = np.concatenate([self.data[: self.size], np.zeros(2 * need - self.size, self.data.dtype)])
        self.data[self.size : need] = values
        self.size = need


def spread(starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """The places start, start + 1, ... of each run, one run after the other."""
    ends = np.cumsum(sizes)
    return np.repeat(starts - (ends - sizes), sizes) + np.arange(ends[-1] if len(ends) else 0)


class WordTable:
    def __init__(self, learn: Callable[[list[bytes]], list[bytes]], entries: int = ENTRIES):
        self.learn, self.entries = learn, entries
        self.bits = int(2 * entries - 1).bit_length()
        self.powers = self.inverses = np.ones(1, np.uint64)
        self.clear()

    def clear(self) -> None:
        self.slot_hash = np.zeros(1 << self.bits, np.uint64)
        self.slot_entry = np.zeros(1 << self.bits, np.int32)
        self.text, self.ids = Pool(np.uint8), Pool(np.uint32)
        self.text_at, self.text_n = Pool(np.int64), Pool(np.int32)
        self.ids_at, self.ids_n = Pool(np.int64), Pool(np.int32)

    def hashes(self, b: np.ndarray, starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
        if len(self.powers) < len(b):
            n = max(len(b), 1 << 20)
            self.powers, self.inverses = powers(_BASE, n), powers(_INVERSE, n)
        sums = np.concatenate([[np.uint64(0)], np.cumsum(_SCATTER[b] * self.powers[: len(b)])])
        h = mix64((sums[starts + sizes] - sums[starts]) * self.inverses[starts] + sizes.astype(np.uint64))
        return np.maximum(h, np.uint64(1))

    def find(self, h: np.ndarray) -> np.ndarray:
        """Entry of each hash, or -1."""
        out = np.full(len(h), -1, np.int64)
        open_, slot = np.arange(len(h)), (h >> np.uint64(64 - self.bits)).astype(np.int64)
        while len(open_):
            there = self.slot_hash[slot]
            hit = there == h[open_]
            out[open_[hit]] = self.slot_entry[slot[hit]]
            on = ~hit & (there != 0)
            open_, slot = open_[on], (slot[on] + 1) & ((1 << self.bits) - 1)
        return out

    def _name(self, h: np.ndarray, entry: np.ndarray) -> None:
        """Give distinct new hashes their slots."""
        open_, slot = np.arange(len(h)), (h >> np.uint64(64 - self.bits)).astype(np.int64)
        while len(open_):
            free = np.flatnonzero(self.slot_hash[slot] == 0)
            self.slot_hash[slot[free]] = h[open_[free]]
            won = free[self.slot_hash[slot[free]] == h[open_[free]]]
            self.slot_entry[slot[won]] = entry[open_[won]]
            on = np.ones(len(open_), bool)
            on[won] = False
            open_, slot = open_[on], (slot[on] + 1) & ((1 << self.bits) - 1)

    def _append(self, words: list[bytes]) -> np.ndarray:
        """New entries of these words."""
        first = self.text_at.size
        coded = self.learn(words)
        for text, at, n, parts, kind in ((self.text, self.text_at, self.text_n, words, np.uint8), (self.ids, self.ids_at, self.ids_n, coded, np.uint32)):
            size = np.array([len(x) for x in parts], np.int64) // np.dtype(kind).itemsize
            at.add(text.size + np.cumsum(size) - size)
            n.add(size)
            text.add(np.frombuffer(b"".join(parts), kind))
        return np.arange(first, self.text_at.size)

    def encode(self, buffer: bytes) -> list[bytes]:
        """Little-endian ids of each text of the buffer."""
        if not buffer:
            return []
        with np.errstate(over="ignore"):
            return self._encode(buffer)

    def _encode(self, buffer: bytes) -> list[bytes]:
        b = np.frombuffer(buffer, np.uint8)
        first, feed, letter = b == TEXT, b == FEED, LETTER[b]
        begin = first | (b == SPACE)
        after = np.append(begin[1:] | feed[1:], True)
        begin[1:] |= feed[1:] & ~feed[:-1] | MARK[b[1:]] & letter[:-1] & after[1:]
        begin[2:] |= letter[2:] & feed[1:-1] & ~feed[:-2]
        starts = np.flatnonzero(begin)
        sizes = np.diff(starts, append=len(b))
        h = self.hashes(b, starts, sizes)
        short = sizes <= LONGEST
        entry = self.find(h)
        missing = np.flatnonzero((entry < 0) & short)
        if len(missing):
            fresh, at = np.unique(h[missing], return_index=True)
            if self.text_at.size + len(fresh) > self.entries:
                self.clear()
                missing = np.flatnonzero(short)
                fresh, at = np.unique(h[missing], return_index=True)
                if 2 * len(fresh) > 1 << self.bits:
                    raise ValueError("the buffer holds more words than the table")
            at = missing[at]
            self._name(fresh, self._append([buffer[s : s + n] for s, n in zip(starts[at].tolist(), sizes[at].tolist())]))
            entry = self.find(h)
        # what the table says of each word, laid along the buffer
        known = entry >= 0
        held = np.where(known, entry, 0)
        same = known & short & (self.text_n.data[held] == sizes)
        place = np.repeat(np.where(same, self.text_at.data[held], 0) - starts, np.where(same, sizes, 0))
        inside = np.repeat(same, sizes)
        own = np.flatnonzero(inside) if not same.all() else np.arange(len(b))
        differs = self.text.data[place + own] != b[own]
        if differs.any():
            same[np.searchsorted(starts, own[differs], side="right") - 1] = False
        marks = [p.size for p in (self.text, self.ids, self.text_at, self.text_n, self.ids_at, self.ids_n)]
        rest = np.flatnonzero(~same)
        if len(rest):
            words = [buffer[s : s + n] for s, n in zip(starts[rest].tolist(), sizes[rest].tolist())]
            entry[rest] = self._append(words)
        n = self.ids_n.data[entry].astype(np.int64)
        ids = self.ids.data[spread(self.ids_at.data[entry], n)]
        for pool, size in zip((self.text, self.ids, self.text_at, self.text_n, self.ids_at, self.ids_n), marks):
            pool.size = size
        raw = ids.astype("<u4", copy=False).tobytes()
        ends = np.concatenate([[0], np.cumsum(n)])
        cuts = [*(4 * ends[np.flatnonzero(first[starts])]).tolist(), len(raw)]
        return [raw[a:z] for a, z in zip(cuts[:-1], cuts[1:])]
