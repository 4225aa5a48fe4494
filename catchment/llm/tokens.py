"""Whole-text encoding with a public tokenizer file, word by word.

The vocabulary file cuts texts at white space before anything else, so the ids of a text are those of
its space-separated words in a row. Each distinct word goes through the tokenizers library once in a
worker; a flat hash table of bounded size keeps the results across tasks. ``encode`` equals the
library's encoding of the whole text (tests compare them).
"""

from __future__ import annotations

import os
import re

import numpy as np

from .common import U, _powers, column_bytes, mix, slices, worker_store

_SIMPLE = re.compile("[!-~À-ÖØ-öø-ÿ]+")
_PARTS = re.compile("'s|'t|'re|'ve|'m|'ll|'d|[a-zß-öø-ÿ]+|[0-9]|[^a-zß-öø-ÿ0-9]+")
_BLANK = bytes.maketrans(b"\t\n\r", b"   ")


class WordEncoder:
    """Encodes batches of UTF-8 texts; ``slots`` bounds the table (a power of two), ``parts`` the dictionary of word parts."""

    def __init__(self, path: str, slots: int = 1 << 20, parts: int = 150_000):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.lib = Tokenizer.from_file(path)
        vocabulary = self.lib.get_vocab()
        self.ends = np.zeros(max(vocabulary.values()) + 1, bool)
        for text, i in vocabulary.items():
            self.ends[i] = text.endswith("</w>")
        self.mask = slots - 1
        self.room = slots * 6 // 10
        self.keys = np.zeros(slots, np.uint64)
        self.checks = np.zeros(slots, np.uint64)
        self.words = np.zeros(slots, np.int32)
        self.starts = np.zeros(1 << 16, np.int64)
        self.lens = np.zeros(1 << 16, np.int32)
        self.pool = np.zeros(1 << 18, np.uint32)
        self.n_words = self.n_pool = 0
        self.parts: dict[str, int] = {}
        self.part_room = parts

    def _find(self, h, c):
        """The word number of each hash, -1 where the table has none."""
        out = np.full(len(h), -1, np.int64)
        at = (h & U(self.mask)).astype(np.int64)
        left = np.arange(len(h))
        while len(left):
            slot = at[left]
            key = self.keys[slot]
            hit = (key == h[left]) & (self.checks[slot] == c[left])
            out[left[hit]] = self.words[slot[hit]]
            left = left[~hit & (key != 0)]
            at[left] = (at[left] + 1) & self.mask
        return out

    def _keep(self, h, c, numbers):
        at = (h & U(self.mask)).astype(np.int64)
        left = np.arange(len(h))
        while len(left):
            free = left[self.keys[at[left]] == 0]
            slots, first = np.unique(at[free], return_index=True)
            won = free[first]
            self.keys[slots], self.checks[slots], self.words[slots] = h[won], c[won], numbers[won]
            left = np.setdiff1d(left, won, assume_unique=True)
            at[left] = (at[left] + 1) & self.mask

    def _add(self, flat: np.ndarray, lens: np.ndarray) -> np.ndarray:
        """Put id lists that stand in a row into the pool; their numbers."""
        while self.n_pool + len(flat) > len(self.pool):
            self.pool = np.concatenate((self.pool, np.zeros_like(self.pool)))
        while self.n_words + len(lens) > len(self.starts):
            self.starts = np.concatenate((self.starts, np.zeros_like(self.starts)))
            self.lens = np.concatenate((self.lens, np.zeros_like(self.lens)))
        numbers = np.arange(self.n_words, self.n_words + len(lens))
        self.pool[self.n_pool : self.n_pool + len(flat)] = flat
        self.starts[numbers] = self.n_pool + np.cumsum(lens) - lens
        self.lens[numbers] = lens
        self.n_words += len(lens)
        self.n_pool += len(flat)
        return numbers

    def _gather(self, numbers: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        lens = self.lens[numbers].astype(np.int64)
        stops = np.cumsum(lens)
        shift = self.starts[numbers] - (stops - lens)
        return self.pool[np.repeat(shift, lens) + np.arange(stops[-1] if len(stops) else 0)], lens

    def _by_library(self, words: list[str]) -> np.ndarray:
        """Numbers of words that the library encodes one by one."""
        found = [e.ids for e in self.lib.encode_batch_fast(words, add_special_tokens=False)]
        lens = np.fromiter(map(len, found), np.int64, len(found))
        return self._add(np.fromiter((i for f in found for i in f), np.uint32, int(lens.sum())), lens)

    def _resolve(self, words: list[str]) -> np.ndarray:
        """The numbers of distinct new words, by the library: plain words through their parts, any others whole."""
        known = self.parts
        plain = [_SIMPLE.fullmatch(w) is not None and "<|" not in w for w in words]
        cut = [_PARTS.findall(w.lower()) for w, p in zip(words, plain) if p]
        parts = [p for found in cut for p in found]
        self.fresh = fresh = [p for p in dict.fromkeys(parts) if p not in known]
        for lo in range(0, len(fresh), 8192):
            some = fresh[lo : lo + 8192]
            ids = np.array(self.lib.encode_batch_fast([" ".join(some)], add_special_tokens=False)[0].ids, np.uint32)
            ends = np.flatnonzero(self.ends[ids])
            numbers = self._add(ids, np.diff(ends, prepend=-1)) if len(ends) == len(some) else self._by_library(some)
            known.update(zip(some, numbers.tolist()))
        out = np.empty(len(words), np.int64)
        plain = np.array(plain, bool)
        if cut:
            flat, lens = self._gather(np.fromiter(map(known.__getitem__, parts), np.int64, len(parts)))
            at = np.cumsum([0] + [len(found) for found in cut])
            sums = np.concatenate(([0], np.cumsum(lens)))[at]
            out[plain] = self._add(flat, np.diff(sums))
        if not plain.all():
            out[~plain] = self._by_library([w for w, p in zip(words, plain) if not p])
        return out

    def encode(self, texts: list, end_id: int | None = None) -> tuple[np.ndarray, np.ndarray]:
        """All ids of the texts in a row (null as empty), and how many each has, an end id included."""
        all_ids, all_sizes = [], []
        for lo, hi in slices([len(t or b"") + 1 for t in texts], 1 << 20):
            ids, sizes = self._some([t or b"" for t in texts[lo:hi]], end_id)
            all_ids.append(ids)
            all_sizes.append(sizes)
        if not all_ids:
            return np.empty(0, np.uint32), np.empty(0, np.int64)
        return np.concatenate(all_ids), np.concatenate(all_sizes)

    def _some(self, texts, end_id):
        big = b" ".join(texts).translate(_BLANK)
        b = np.frombuffer(big, np.uint8)
        gaps = np.flatnonzero(b == 32)
        starts = np.concatenate(([0], gaps + 1))
        ends = np.concatenate((gaps, [len(b)]))
        real = ends > starts
        starts, ends = starts[real], ends[real]
        begins = np.cumsum([0] + [len(t) + 1 for t in texts])[:-1]
        first = np.searchsorted(starts, begins)
        lens = np.empty(0, np.int64)
        flat = np.empty(0, np.uint32)
        if len(starts):
            p, q = _powers(len(b) + 1)
            sums = np.empty(len(b) + 1, np.uint64)
            sums[0] = 0
            np.cumsum((b.astype(np.uint64) + U(1)) * p[: len(b)], out=sums[1:])
            raw = (sums[ends] - sums[starts]) * q[starts]
            size = (ends - starts).astype(np.uint64)
            h = mix(raw + size)
            h[h == 0] = U(1)
            wide = np.concatenate((b, np.zeros(8, np.uint8)))
            window = np.lib.stride_tricks.sliding_window_view(wide, 8)
            short = np.minimum(ends - starts, 8)
            head = np.ascontiguousarray(window[starts]).view("<u8").ravel() & (U(0xFFFFFFFFFFFFFFFF) >> (U(64) - short.astype(np.uint64) * U(8)))
            c = head ^ (size << U(56)) ^ (raw >> U(9))
            numbers = self._find(h, c)
            kept = self.n_words, self.n_pool
            miss = np.flatnonzero(numbers < 0)
            full = False
            if len(miss):
                _, at, back = np.unique(h[miss], return_index=True, return_inverse=True)
                new = miss[at]
                words = [big[s:e].decode() for s, e in zip(starts[new].tolist(), ends[new].tolist())]
                added = self._resolve(words)
                numbers[miss] = added[back]
                full = self.n_words > self.room or len(self.parts) > self.part_room
                if not full:
                    self._keep(h[new], c[new], added)
            flat, lens = self._gather(numbers)
            if full:
                self.n_words, self.n_pool = kept
                for p in self.fresh:
                    del self.parts[p]
        sums = np.concatenate(([0], np.cumsum(lens)))
        edges = np.append(first, len(starts))
        cuts = sums[edges]
        sizes = np.diff(cuts)
        if end_id is not None:
            flat = np.insert(flat, cuts[1:], end_id)
            sizes = sizes + 1
        return flat, sizes


def encoder(path: str) -> WordEncoder:
    """The worker's encoder of this file; made once a worker."""
    store = worker_store("encoders")
    if path not in store:
        store[path] = WordEncoder(path)
    return store[path]


def encoded(batch_column, path: str, end_id: int | None):
    return encoder(path).encode(column_bytes(batch_column), end_id)
