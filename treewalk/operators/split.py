"""The phased sampler for bipartite graphs with a small side, on classes of vertices with equal neighbours.

Vertices of the large side with the same row of weights are alike: a derived graph has one weight for all pairs of two
classes, so its powers are kept for classes only, and a class is drawn before its member.  Returns to the same vertex
stay in the walk (they change neither which vertices it visits, nor in what order, nor the edges it enters by); only so
do members of a class remain alike.  Phases, goals, lengths and middles are those of ``kernels.phased``.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from . import params

SMALL = 64


@dataclass
class Split:
    """``rows``: weights of each class to the small side; ``kind``: class of each vertex of the large side.  Vertices
    are numbered, large side first."""

    rows: np.ndarray
    kind: np.ndarray

    @property
    def n(self) -> int:
        return len(self.kind) + self.rows.shape[1]

    @classmethod
    def of(cls, at: np.ndarray, to: np.ndarray, w: np.ndarray, large: int, small: int) -> Split:
        full = np.zeros((large, small))
        full[at, to] = w
        rows, kind = np.unique(full, axis=0, return_inverse=True)
        return cls(rows, kind.reshape(-1))


class _Derived:
    """Weights between the kept vertices, by class, and what the entry edges need."""

    def __init__(self, s: Split, kept: np.ndarray):
        large, self.c = len(s.kind), s.rows.shape[1]
        self.s, self.large, m = s, large, len(s.rows)
        self.members = [np.flatnonzero(kept[:large] & (s.kind == k)) for k in range(m)] if m <= 64 else self._members(s, kept[:large], m)
        total = np.bincount(s.kind, minlength=m)
        here = np.array([len(x) for x in self.members])
        self.gone_count = total - here
        d_row, self.d_small = s.rows.sum(1), total @ s.rows
        self.t = s.rows.T @ (s.rows * (self.gone_count / d_row)[:, None])
        small = kept[large:]
        self.gone = np.flatnonzero(~small)
        g = self.gone
        self.m = np.linalg.inv(np.diag(self.d_small[g]) - self.t[np.ix_(g, g)]) if len(g) else np.zeros((0, 0))
        self.classes, self.smalls = np.flatnonzero(here), np.flatnonzero(small)
        b, t = s.rows[self.classes], self.t
        uu = b[:, g] @ self.m @ b[:, g].T
        ut = b[:, self.smalls] + b[:, g] @ self.m @ t[np.ix_(g, self.smalls)]
        tt = t[np.ix_(self.smalls, self.smalls)] + t[np.ix_(self.smalls, g)] @ self.m @ t[np.ix_(g, self.smalls)]
        self.weight = np.maximum(np.block([[uu, ut], [ut.T, tt]]), 0)
        self.size = np.concatenate([here[self.classes], np.ones(len(self.smalls), np.int64)])
        self.state = np.full(s.n, -1)
        for k, c in enumerate(self.classes):
            self.state[self.members[c]] = k
        self.state[large + self.smalls] = len(self.classes) + np.arange(len(self.smalls))

    @staticmethod
    def _members(s: Split, kept: np.ndarray, m: int) -> list[np.ndarray]:
        at = np.flatnonzero(kept)
        order = at[np.argsort(s.kind[at], kind="stable")]
        return np.split(order, np.cumsum(np.bincount(s.kind[at], minlength=m))[:-1])

    def ladder(self, levels: int) -> list[np.ndarray]:
        p = self.weight / (self.weight @ self.size)[:, None]
        out = [p]
        for _ in range(levels):
            q = (out[-1] * self.size) @ out[-1]
            out.append(q / (q @ self.size)[:, None])
        return out

    def draw(self, law: np.ndarray, count: int, r: np.random.Generator) -> np.ndarray:
        """Vertices by a law over one member of each state."""
        high = np.cumsum(law * self.size)
        if not high[-1] > 0:
            raise FloatingPointError("a middle has no weight at this precision")
        found = np.searchsorted(high, r.random(count) * high[-1], side="right")
        out = np.empty(count, np.int64)
        for k in np.unique(found):
            at = np.flatnonzero(found == k)
            if k < len(self.classes):
                mine = self.members[self.classes[k]]
                out[at] = mine[r.integers(0, len(mine), len(at))]
            else:
                out[at] = self.large + self.smalls[k - len(self.classes)]
        return out

    def entry(self, a: int, b: int, visited: np.ndarray, r: np.random.Generator) -> int:
        """The neighbour by which a step of the derived graph from ``a`` came into ``b``."""
        s, g, large = self.s, self.gone, self.large
        row = lambda v: s.rows[s.kind[v]]
        first = row(a)[g] / row(a).sum() if a < large else self.t[a - large, g] / self.d_small[a - large]
        stay = first @ self.m  # visits of each small vertex outside, over its degree
        direct = 0.0
        if (a < large) != (b < large):
            direct = row(a)[b - large] / row(a).sum() if a < large else row(b)[a - large] / self.d_small[a - large]
        if b < large:
            law, names = np.append(np.maximum(stay * row(b)[g], 0), direct), [*(large + g).tolist(), a]
            return names[int(np.searchsorted(np.cumsum(law), r.random() * law.sum(), side="right"))]
        visits = s.rows[:, g] @ stay + (s.rows[:, a - large] / self.d_small[a - large] if a >= large else 0)
        law = np.append(np.maximum(visits, 0) * s.rows[:, b - large] / s.rows.sum(1) * self.gone_count, direct)
        k = int(np.searchsorted(np.cumsum(law), r.random() * law.sum(), side="right"))
        if k == len(s.rows):
            return a
        mine = np.flatnonzero(visited[:large] & (s.kind == k) & (self.state[:large] < 0))
        return int(mine[r.integers(len(mine))])


def _walk(d: _Derived, ladder: list[np.ndarray], start: int, goal: int, r: np.random.Generator, shuffle: bool) -> np.ndarray:
    """Vertices of a walk of 2^levels steps cut at its ``goal``-th distinct vertex."""
    top = len(ladder) - 1
    walk = np.concatenate([[start], d.draw(ladder[top][d.state[start]], 1, r)])
    whole = True  # until a cut the last place is an end, not a middle
    for level in range(top, 0, -1):
        half, s = ladder[level - 1], len(d.size)
        a, b = d.state[walk[:-1]], d.state[walk[1:]]
        code, at = np.unique(a * s + b, return_inverse=True)
        mids = np.empty(len(a), np.int64)
        for k, c in enumerate(code.tolist()):
            mine = np.flatnonzero(at == k)
            mids[mine] = d.draw(half[c // s] * half[:, c % s], len(mine), r)
        filled = np.empty(2 * len(a) + 1, np.int64)
        filled[::2], filled[1::2] = walk, mids
        first = np.sort(np.unique(filled, return_index=True)[1])
        if len(first) >= goal:
            filled = filled[: first[goal - 1] + 1]
        if shuffle:  # middles of one pair change places; a last middle stays
            n = (len(filled) - 1) // 2
            pair = walk[:n] * d.s.n + walk[1 : n + 1]
            new = filled[1 : 2 * n : 2].copy()
            filled[1 : 2 * n : 2][np.argsort(pair, kind="stable")] = new[np.lexsort((r.random(n), pair))]
        walk = filled
    return walk


def phased(s: Split, r: np.random.Generator, eps: float = 0.01, exact: bool = False, length: int = 0, facts: dict | None = None, start: int = 0, on_short: str = "arbitrary") -> list[tuple[int, int]]:
    """A tree as (child, parent), by the phased sampler."""
    n, large = s.n, len(s.kind)
    goal = params.rho(n, "cbrt" if exact else "sqrt")
    edges = int(((s.rows > 0).sum(1)[s.kind]).sum())
    size = length or params.target_length(n, edges, eps, weight=int(max(1, s.rows.max())))
    seen, end, out, phases = np.zeros(n, bool), start, [], 0
    seen[start] = True
    while not seen.all():
        phases += 1
        kept = ~seen
        kept[end] = True
        k = int(kept.sum())
        d, want = _Derived(s, kept), min(goal, k)
        if k == 2:
            walk = np.array([end, int(np.flatnonzero(~seen)[0])])
        else:
            ladder = d.ladder(size.bit_length() - 1)
            walk = _walk(d, ladder, end, want, r, exact)
            while exact and len(np.unique(walk)) < want:
                walk = np.concatenate([walk, _walk(d, ladder, int(walk[-1]), want, r, exact)[1:]])
            first = np.sort(np.unique(walk, return_index=True)[1])
            walk = walk[: first[want - 1] + 1] if len(first) >= want else walk
        distinct = len(np.unique(walk))
        if distinct < want:
            if facts is not None:
                facts["short"] = True
            if on_short != "fail":
                raise NotImplementedError("a phase fell short; ask for on_short='fail' or a longer walk")
            raise RuntimeError(f"a phase saw {distinct} of {want} vertices in {size} steps")
        first = np.sort(np.unique(walk, return_index=True)[1])[1:]
        for i in first.tolist():
            out.append((int(walk[i]), d.entry(int(walk[i - 1]), int(walk[i]), seen, r)))
        seen[walk] = True
        end = int(walk[-1])
        if facts is not None:
            facts.setdefault("distinct", []).append(distinct)
            facts.setdefault("length", []).append(len(walk) - 1)
    if facts is not None:
        facts["phases"] = phases
    return out
