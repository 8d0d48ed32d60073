"""Exact, fast encoding with a public BPE vocabulary.

Both vocabularies used here merge only inside pre-tokens, so a text's ids are those of its
pre-tokens one after the other.  Texts made of plain Latin characters are split into
pre-tokens with array arithmetic, equal pre-tokens of a slice are found by hash, and only
the distinct ones are looked up or given to the tokenizers library.  Any text with other
characters (apostrophes, marks, other scripts, special-token strings) goes to the library
whole, so the result always equals the library's.
"""

from __future__ import annotations

import gc
import os
import re

import numpy as np

os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")

#: Characters that the array path understands; every other one sends a text to the library.
_OTHER = re.compile(r"[^\t\n\r -&(-~À-ÖØ-öø-įı-ſ]")
_LETTER, _DIGIT, _MARK, _SPACE = 1, 2, 3, 4
_MEMO_LIMIT, _FRESH_LIMIT = 1_500_000, 200_000
#: Byte-level vocabularies show each byte as a visible character: printable bytes stand for
#: themselves, the others follow from U+0100 on in their order.
_PRINTED = [*range(33, 127), *range(161, 173), *range(174, 256)]
_HIDDEN = [b for b in range(256) if b not in _PRINTED]
_VISIBLE = [chr(256 + _HIDDEN.index(b)) if b in _HIDDEN else chr(b) for b in range(256)]
_B1, _B2 = 0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F


def _classes() -> np.ndarray:
    lut = np.full(0x180, _MARK, np.uint8)
    for c in range(0x180):
        if chr(c).isalpha():
            lut[c] = _LETTER
        elif chr(c).isdigit():
            lut[c] = _DIGIT
    lut[[9, 10, 13, 32]] = _SPACE
    return lut


class _Powers:
    """Powers of an odd base and of its inverse modulo 2**64, grown on demand."""

    def __init__(self, base: int):
        self.base, self.inv = base, pow(base, -1, 1 << 64)
        self.up = self.down = np.ones(1, np.uint64)

    def get(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(self.up) < n:
            size = max(n, 2 * len(self.up), 1 << 16)
            self.up, self.down = np.full(size, self.base, np.uint64), np.full(size, self.inv, np.uint64)
            self.up[0] = self.down[0] = 1
            np.cumprod(self.up, out=self.up)
            np.cumprod(self.down, out=self.down)
        return self.up[:n], self.down[:n]


def _span_hash(codes: np.ndarray, starts: np.ndarray, ends: np.ndarray, powers: _Powers) -> np.ndarray:
    up, down = powers.get(len(codes) + 1)
    total = np.zeros(len(codes) + 1, np.uint64)
    np.cumsum((codes.astype(np.uint64) + np.uint64(1)) * up[:-1], out=total[1:])
    h = (total[ends] - total[starts]) * down[starts]
    h ^= h >> np.uint64(32)
    h *= np.uint64(0xD6E8FEB86659FD93)
    h ^= h >> np.uint64(29)
    return h + (ends - starts).astype(np.uint64)


class _Memo:
    """Ids of known pre-tokens, found by two hashes in sorted arrays; emptied when full."""

    def __init__(self):
        self.reset()

    def reset(self) -> None:
        none = np.zeros(0, np.uint64)
        self.levels = [[none, none, none.astype(np.int64), none.astype(np.int64)] for _ in range(2)]
        self.pool, self.used = np.zeros(1 << 16, np.uint32), 0

    def find(self, h: np.ndarray, second: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        if sum(len(x[0]) for x in self.levels) > _MEMO_LIMIT:
            self.reset()
        start, size, known = np.zeros(len(h), np.int64), np.zeros(len(h), np.int64), np.zeros(len(h), bool)
        for keys, others, at, n in self.levels:
            if len(keys):
                p = np.minimum(np.searchsorted(keys, h), len(keys) - 1)
                hit = (keys[p] == h) & (others[p] == second)
                start[hit], size[hit] = at[p[hit]], n[p[hit]]
                known |= hit
        return start, size, known

    def add(self, h: np.ndarray, second: np.ndarray, lens: np.ndarray, ids: np.ndarray) -> np.ndarray:
        while self.used + len(ids) > len(self.pool):
            self.pool = np.concatenate([self.pool, np.zeros(len(self.pool), np.uint32)])
        self.pool[self.used : self.used + len(ids)] = ids
        start = self.used + np.cumsum(lens) - lens
        self.used += len(ids)
        self._merge(1, [h, second, start, lens])
        if len(self.levels[1][0]) > _FRESH_LIMIT:
            self._merge(0, self.levels[1])
            self.levels[1] = [x[:0] for x in self.levels[1]]
        return start

    def _merge(self, level: int, more: list[np.ndarray]) -> None:
        both = [np.concatenate(x) for x in zip(self.levels[level], more)]
        order = np.argsort(both[0], kind="stable")
        self.levels[level] = [x[order] for x in both]


class Encoder:
    """``kind`` 'byte': byte-level BPE with leading-space pre-tokens; 'word': lower-cased
    BPE whose pre-tokens hold no white space and end in a word mark."""

    def __init__(self, path: str, kind: str):
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        self.tok.no_truncation()
        self.tok.no_padding()
        self.kind, self.lut, self.memo = kind, _classes(), _Memo()
        self.p1, self.p2 = _Powers(_B1), _Powers(_B2)

    def library(self, texts: list[str]) -> list[np.ndarray]:
        return [np.array(e.ids, np.uint32) for e in self.tok.encode_batch(texts, add_special_tokens=False)]

    def encode(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """All ids one text after the other, and the number of ids of each text."""
        collecting = gc.isenabled()
        gc.disable()  # many short-lived tuples and no cycles
        try:
            return self._encode(texts)
        finally:
            if collecting:
                gc.enable()

    def _encode(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        odd = [i for i, t in enumerate(texts) if _OTHER.search(t) or "<|" in t]
        if not odd:
            return self._plain(texts)
        if len(odd) == len(texts):
            out = self.library(texts)
            return np.concatenate(out), np.array([len(x) for x in out], np.int64)
        plain = sorted(set(range(len(texts))) - set(odd))
        ids, lens = self._plain([texts[i] for i in plain])
        out: list = [None] * len(texts)
        for i, x in zip(plain, np.split(ids, np.cumsum(lens)[:-1])):
            out[i] = x
        for i, x in zip(odd, self.library([texts[i] for i in odd])):
            out[i] = x
        return np.concatenate(out).astype(np.uint32), np.array([len(x) for x in out], np.int64)

    def _spans(self, codes: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        n = len(codes)
        cls = self.lut[codes]
        prev, nxt = np.empty(n, np.uint8), np.empty(n, np.uint8)
        prev[1:], nxt[:-1] = cls[:-1], cls[1:]
        prev[offs[:-1][offs[:-1] < n]] = 0
        nxt[offs[1:][offs[1:] > 0] - 1] = 0
        space = cls == _SPACE
        if self.kind == "word":
            alone = cls == _DIGIT
            first = ~space & ((prev != cls) | alone)
            last = ~space & ((nxt != cls) | alone)
            return np.flatnonzero(first), np.flatnonzero(last) + 1
        blank = np.zeros(n, bool)
        blank[1:] = codes[:-1] == 32
        blank[prev == 0] = False
        first = np.where(space, (prev != _SPACE) | ((nxt != _SPACE) & (nxt != 0)), (prev != cls) & ~blank)
        starts = np.flatnonzero(first)
        return starts, np.append(starts[1:], n)

    def _plain(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        if self.kind == "word":
            texts = [t.lower() for t in texts]
        big = "".join(texts)
        offs = np.zeros(len(texts) + 1, np.int64)
        np.cumsum([len(t) for t in texts], out=offs[1:])
        if not big:
            return np.zeros(0, np.uint32), np.zeros(len(texts), np.int64)
        codes = np.frombuffer(big.encode("utf-32-le"), np.uint32)
        starts, ends = self._spans(codes, offs)
        if not len(starts):
            return np.zeros(0, np.uint32), np.zeros(len(texts), np.int64)
        h = _span_hash(codes, starts, ends, self.p1)
        _, where, back = np.unique(h, return_index=True, return_inverse=True)
        second = _span_hash(codes, starts, ends, self.p2)
        if not np.array_equal(second, second[where][back]):  # two words with one hash: no reuse
            out = self.library(texts)
            return np.concatenate(out), np.array([len(x) for x in out], np.int64)
        h, second = h[where], second[where]
        ustart, ulen, known = self.memo.find(h, second)
        new = np.flatnonzero(~known)
        if len(new):
            merge, blank, visible = self.tok.model.tokenize, _VISIBLE[32], _VISIBLE.__getitem__
            at, ids = where[new], []
            lens = np.empty(len(new), np.int64)
            for i, (s, e) in enumerate(zip(starts[at].tolist(), ends[at].tolist())):
                w = big[s:e]
                got = merge(w.replace(" ", blank) if w.isascii() and w[-1] > " " else "".join(map(visible, w.encode())))
                ids += [k.id for k in got]
                lens[i] = len(got)
            ustart[new] = self.memo.add(h[new], second[new], lens, np.array(ids, np.uint32))
            ulen[new] = lens
        pool = self.memo.pool
        k = ulen[back]
        ends_at = np.cumsum(k)
        ids = pool[np.repeat(ustart[back] - (ends_at - k), k) + np.arange(int(ends_at[-1]))]
        upto = np.concatenate([[0], ends_at])[np.searchsorted(starts, offs)]
        return ids, np.diff(upto)


_LOADED: dict[tuple[str, str], Encoder] = {}


def encoder(path: str, kind: str) -> Encoder:
    """One encoder for a worker process."""
    key = (path, kind)
    if key not in _LOADED:
        _LOADED[key] = Encoder(path, kind)
    return _LOADED[key]
