"""Hashes of words and of runs of words, for whole batches of texts at a time."""

from __future__ import annotations

from itertools import chain

import numpy as np
import xxhash

MULTIPLIER = np.uint64(0x9E3779B97F4A7C15)


def mix(x: np.ndarray) -> np.ndarray:
    """Finaliser that spreads every bit of 64-bit integers over all others."""
    with np.errstate(over="ignore"):
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def words_of(text: str | None) -> list[bytes]:
    """Runs of characters other than space and the five ASCII controls after tab, as UTF-8."""
    return (text or "").encode("utf-8", "surrogatepass").split()


class WordHasher:
    """64-bit hashes of words; those of words met before are kept."""

    def __init__(self, seed: int = 0, most_words: int = 250_000) -> None:
        self.seed, self.most, self.known = seed, most_words, {}

    def clear(self) -> None:
        self.known = {}

    def __call__(self, split: list[list[bytes]]) -> np.ndarray:
        """Hashes of all words of all texts, one after the other."""
        words = set(chain.from_iterable(split))
        if len(self.known) + len(words) > self.most:
            self.known = {}
        known, digest, seed = self.known, xxhash.xxh3_64_intdigest, self.seed
        for w in words:
            if w not in known:
                known[w] = digest(w, seed)
        return np.fromiter(map(known.__getitem__, chain.from_iterable(split)), np.uint64, sum(map(len, split)))


#: Bytes that part words: space and the five controls after tab; and masks of the first bytes of eight.
_PARTS = np.isin(np.arange(256), [9, 10, 11, 12, 13, 32])
_FIRST = np.array([(1 << 8 * n) - 1 for n in range(9)], np.uint64)
_LONG = 256  # words of more bytes are hashed one by one


class Words:
    """The words of several texts (UTF-8), found and hashed as arrays, without an object for each."""

    def __init__(self, texts: list[bytes]) -> None:
        self.buffer = b" ".join([*texts, bytes(8)])  # room for eight bytes from any place
        self.bytes = np.frombuffer(self.buffer, np.uint8)
        begin = np.cumsum([0, *(len(t) + 1 for t in texts)])
        edge = np.flatnonzero(np.diff(_PARTS[self.bytes[: begin[-1]]], prepend=True, append=True))
        self.starts, self.ends = edge[::2], edge[1::2]
        self.first = np.searchsorted(self.starts, begin)  # number of each text's first word
        self.sizes = np.diff(self.first).tolist()

    def hashes(self) -> tuple[np.ndarray, np.ndarray]:
        """Two independent 64-bit hashes of each word, made of its length and its bytes, eight at a time."""
        size = self.ends - self.starts
        eight = np.ndarray((len(self.buffer) - 7,), "<u8", self.buffer, 0, (1,))
        with np.errstate(over="ignore"):
            one = size.astype(np.uint64) * np.uint64(0xC2B2AE3D27D4EB4F)
            two = size.astype(np.uint64) * np.uint64(0x165667B19E3779F9) + np.uint64(0x27D4EB2F165667C5)
            at, rest, done = slice(None), size, 0
            while len(rest):
                part = eight[self.starts[at] + done] & _FIRST[np.minimum(rest, 8)]
                one[at], two[at] = mix(one[at] ^ part), mix(two[at] + part * MULTIPLIER)
                done += 8
                at = np.flatnonzero((size > done) & (size <= _LONG))
                rest = size[at] - done
        for i in np.flatnonzero(size > _LONG).tolist():
            one[i], two[i] = np.frombuffer(xxhash.xxh3_128_digest(self.buffer[self.starts[i] : self.ends[i]], 7), np.uint64)
        return one, two

    def joined(self) -> list[bytes]:
        """The words of each text joined by one space."""
        out = self.bytes.copy()
        keep = ~_PARTS[out]
        keep[self.ends] = True
        out[self.ends] = 32
        keep[self.ends[-1] + 1 if len(self.ends) else 0 :] = False
        kept = out[keep].tobytes()
        places = np.concatenate([[0], np.cumsum(self.ends - self.starts + 1)])[self.first].tolist()
        return [kept[a : max(a, b - 1)] for a, b in zip(places, places[1:])]


def runs(hashes: np.ndarray, n: int) -> np.ndarray:
    """A hash for each place of the n words that begin there; the last n - 1 places are meaningless."""
    with np.errstate(over="ignore"):
        out, power = hashes.copy(), MULTIPLIER
        for j in range(1, min(n, len(out))):
            out[: len(out) - j] += hashes[j:] * power
            power = power * MULTIPLIER
    return mix(out)


def window_minima(values: np.ndarray, n: int) -> np.ndarray:
    """For each place the place of the least value among the n from there (the first one, if equal)."""
    at = np.arange(len(values))
    least, span = values.copy(), 1
    while span < n:
        step = min(span, n - span)
        if step >= len(values):
            break
        other = least[step:]
        better = other < least[:-step]
        least[:-step] = np.where(better, other, least[:-step])
        at[:-step] = np.where(better, at[step:], at[:-step])
        span += step
    return at
