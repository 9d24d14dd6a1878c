"""Byte-pair encoding of whole corpora with the vocabulary file of a tokenizers model.

The merges of the file are run by a ranked byte-pair encoder, several times as fast as the library's own;
ids are the same (tests compare them on whole tables), and texts that hold the string of a special token, or a run of white
space so long that the split pattern could run out of stack, go through the library itself.  Two kinds of files are read: byte-level ones with the usual split of words, numbers and signs,
and ones whose tokens carry an end-of-word suffix, where white space is dropped: there each distinct word
(a part between spaces) is encoded once in a while and its ids are kept.
"""

from __future__ import annotations

import json
import re
import unicodedata
from itertools import compress, repeat
from operator import is_

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from .base import slices

# How the two kinds of models split texts.
BYTE_LEVEL = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
END_OF_WORD = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}\x00]+|\x00"
_MARK = "\0"  # stands for the end-of-word suffix; texts that hold it go through the library
_LONG_SPACE = re.compile(r"\s{4096}")
_CODECS: dict[str, BpeCodec] = {}


def byte_alphabet() -> dict[str, int]:
    """Characters by which byte-level vocabularies write bytes: printable ones stand for themselves, the others follow from 256 on."""
    printable = [*range(33, 127), *range(161, 173), *range(174, 256)]
    out, spare = {chr(b): b for b in printable}, 256
    for b in range(256):
        if b not in printable:
            out[chr(spare)], spare = b, spare + 1
    return out


class BpeCodec:
    def __init__(self, path: str, most_words: int = 400_000) -> None:
        import os

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        import tiktoken

        self.path, self._library = path, None
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        self.special = [t["content"] for t in spec["added_tokens"]]
        suffix, alphabet = spec["model"].get("end_of_word_suffix") or "", byte_alphabet()
        self.by_word, ranks, ends = bool(suffix), {}, []
        for token, i in spec["model"]["vocab"].items():
            if token in self.special:
                continue
            whole = bool(suffix) and token.endswith(suffix)
            ranks[bytes(alphabet[c] for c in (token[: -len(suffix)] if whole else token)) + _MARK.encode() * whole] = i
            if whole:
                ends.append(i)
        self.ranked = tiktoken.Encoding("ranked", pat_str="[^\\x00]+\\x00" if suffix else BYTE_LEVEL, mergeable_ranks=ranks, special_tokens={})
        self.ends = np.zeros(max(ranks.values()) + 1, bool)
        self.ends[ends] = True
        self.most, self.known = most_words, {}
        import regex

        self.split = regex.compile(END_OF_WORD).findall

    @property
    def library(self):
        """The library's own tokenizer, loaded where it is needed."""
        if self._library is None:
            from tokenizers import Tokenizer

            self._library = Tokenizer.from_file(self.path)
        return self._library

    def by_library(self, text: str) -> bytes:
        return np.array(self.library.encode(text, add_special_tokens=False).ids, "<u4").tobytes()

    def _ranked(self, text: str) -> np.ndarray:
        return self.ranked.encode_to_numpy(text, disallowed_special=())

    def _unusual(self, text: str) -> bool:
        return any(s in text for s in self.special) or len(text) > 4096 and _LONG_SPACE.search(text) is not None

    def encode(self, texts: list[str | None]) -> list[bytes]:
        """Ids of each text as little-endian unsigned 32-bit integers."""
        texts = [t or "" for t in texts]
        if not self.by_word:
            return [self.by_library(t) if self._unusual(t) else self._ranked(t).astype("<u4").tobytes() for t in texts]
        out: list[bytes] = []
        for i, j in slices(texts, 2_000_000):
            parts = pc.split_pattern(pa.array(texts[i:j], pa.string()), " ")
            words = parts.flatten().dictionary_encode()
            ids = self._known(words.dictionary.to_numpy(zero_copy_only=False).tolist())
            size = np.fromiter(map(len, ids), np.int64, len(ids)) // 4
            flat = np.frombuffer(b"".join(ids), "<u4")
            # Ids of each occurrence, one after the other: where its word's are, and their number.
            at = words.indices.to_numpy()
            many = size[at]
            ends = np.concatenate([[0], np.cumsum(many)])
            raw = flat[np.arange(ends[-1]) + np.repeat((np.cumsum(size) - size)[at] - ends[:-1], many)].tobytes()
            cuts = (4 * ends[parts.offsets.to_numpy()]).tolist()
            out += [raw[a:b] for a, b in zip(cuts, cuts[1:])]
        return out

    def _known(self, words: list[str]) -> list[bytes]:
        """Ids of distinct words."""
        found = list(map(self.known.get, words))
        new = list(compress(words, map(is_, found, repeat(None))))
        if not new:
            return found
        self._learn(words, new)
        learnt = map(self.known.__getitem__, new)
        return [next(learnt) if x is None else x for x in found]

    def _learn(self, words: list[str], new: list[str]) -> None:
        known = self.known
        if len(known) + len(new) > self.most:  # words of this slice stay, so frequent ones do
            self.known = known = {w: known[w] for w in words if w in known}
        joined = _MARK.join(new)
        if joined.count(_MARK) >= len(new) or len(joined) > 4096 and _LONG_SPACE.search(joined):  # some word holds the mark, or long white space: one by one
            known.update((w, self.by_library(w)) for w in new)
            return
        # Cases in which lower-casing depends on context, or a special token is in the way, are the library's.
        odd = [w for w in new if "\u03a3" in w or "<|" in w] if "\u03a3" in joined or "<|" in joined else []
        low = (joined if joined.isascii() else unicodedata.normalize("NFC", joined)).lower().split(_MARK)
        counts = np.ones(len(new), np.int64)
        mixed = [i for i, w in enumerate(low) if not w.isalpha()]
        at, done = 0, 0
        some = self.split(_MARK.join([low[i] for i in mixed]))  # all of them at once; a mark is a part of its own
        for i in mixed:
            try:
                at = some.index(_MARK, done)
            except ValueError:
                at = len(some)
            low[i], counts[i] = _MARK.join(some[done:at]), at - done
            done = at + 1
        low.append("")
        ids = self._ranked(_MARK.join(low))
        cuts = np.concatenate([[0], np.flatnonzero(self.ends[ids]) + 1])
        at = (cuts[np.concatenate([[0], np.cumsum(counts)])] * 4).tolist()
        raw = ids.astype("<u4").tobytes()
        known.update(zip(new, [raw[a:b] for a, b in zip(at, at[1:])], strict=True))
        known.update((w, self.by_library(w)) for w in odd)


def codec(path: str) -> BpeCodec:
    """One codec for each file in a worker process."""
    if path not in _CODECS:
        _CODECS[path] = BpeCodec(path)
    return _CODECS[path]
