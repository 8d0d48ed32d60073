"""The phased sampler for graphs above the dense bound: rows of powers are made when a middle asks for them.

A walk of 2^k steps is made of stretches of equal, shorter length, each filled from the top down, and ends with the one
in which it meets its goal: later ones would be cut off.  A stretch asks for few rows of powers, those of its own
vertices, by products of the derived graph with vectors.  Phases, goals and lengths are those of ``kernels.phased``.

Of a derived graph two forms are held.  A vertex outside with no kept neighbour is forgotten: no step meets it again.
Until more than the kept ones are remembered: rows of neighbours and the inverse of the outside's Laplacian; then returns to the same vertex stay in the walk (they change neither which vertices it
visits, nor in what order, nor the edges it enters by).  After that: the weights between the kept vertices, and where a
walk from each outside vertex first meets them.  Neither takes more than half of n^2 numbers.
"""

from __future__ import annotations

import numpy as np

from . import params
from .sparse import Rows

LIMIT = 12_000  # vertices; the forms of a derived graph and their copies then take some 900 MB in a task


class _Derived:
    def __init__(self, g: Rows):
        self.g, self.w = g, g.weight.astype(float)
        self.total = np.add.reduceat(self.w, g.ptr[:-1])
        self.place = np.full(g.n, -1)  # among those outside; -1: kept, -2: forgotten
        self.dropped = 0
        self.names = self.at = np.arange(g.n)  # vertex of each state, state of each vertex
        self.gone = np.zeros(0, np.int64)
        self.inverse = np.zeros((0, 0))
        self.weight: np.ndarray | None = None  # second form: between states
        self.meets: np.ndarray | None = None  # and chance, for each state, that it is the first met from each place
        self._arcs()

    def _near(self, v: int) -> tuple[np.ndarray, np.ndarray]:
        s = slice(self.g.ptr[v], self.g.ptr[v + 1])
        return self.g.near[s], self.w[s]

    def _outside(self, v: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Neighbours of ``v`` outside: their places, weights and names."""
        near, w = self._near(v)
        p = self.place[near]
        return p[p >= 0], w[p >= 0], near[p >= 0]

    def drop(self, out: np.ndarray) -> None:
        """Take vertices out of the kept ones."""
        if not len(out):
            return
        if self.weight is None:
            self._grow(out)
        else:
            self._shrink(out)
        self.dropped += len(out)
        self._forget()
        if self.weight is None and len(self.gone) > self.g.n - self.dropped:
            self._turn()
        elif self.weight is None:
            self._arcs()

    def _forget(self) -> None:
        """Leave out those outside whose neighbours are all outside."""
        some = np.add.reduceat(self.place[self.g.near] == -1, self.g.ptr[:-1], dtype=np.int64)[self.gone] > 0
        if some.all():
            return
        self.place[self.gone[~some]] = -2
        self.gone = self.gone[some]
        self.place[self.gone] = np.arange(len(self.gone))
        if self.weight is None:
            self.inverse = self.inverse[np.ix_(some, some)]
        else:
            self.meets = self.meets[:, some]

    def _grow(self, out: np.ndarray) -> None:
        v, t, m = len(self.gone), len(out), self.inverse
        cross, a = np.zeros((v, t)), np.diag(self.total[out])
        column = np.full(self.g.n, -1)
        column[out] = np.arange(t)
        for k, x in enumerate(out.tolist()):
            p, w, _ = self._outside(x)
            cross[p, k] = w
            near, w = self._near(x)
            c = column[near]
            a[k, c[c >= 0]] -= w[c >= 0]
        x = m @ cross
        a = np.linalg.inv(a - cross.T @ x)
        a = (a + a.T) / 2
        xa = x @ a
        self.inverse = np.empty((v + t, v + t))
        self.inverse[:v, v:], self.inverse[v:, v:] = xa, a
        self.inverse[v:, :v] = xa.T
        for lo in range(0, v, 512):
            self.inverse[lo : min(v, lo + 512), :v] = m[lo : lo + 512] + xa[lo : lo + 512] @ x.T
        self.place[out] = v + np.arange(t)
        self.gone = np.append(self.gone, out)

    def _turn(self) -> None:
        """From the first form to the second."""
        self.names = np.flatnonzero(self.place == -1)
        s = len(self.names)
        self.at = np.full(self.g.n, -1)
        self.at[self.names] = np.arange(s)
        self.meets = np.zeros((s, len(self.gone)))
        for k, x in enumerate(self.names.tolist()):
            p, w, _ = self._outside(x)
            self.meets[k] = w @ self.inverse[p]
        self.inverse = np.zeros((0, 0))
        self.weight = np.zeros((s, s))
        for k, x in enumerate(self.names.tolist()):
            p, w, _ = self._outside(x)
            self.weight[k] = self.meets[:, p] @ w
            near, w = self._near(x)
            c = self.at[near]
            self.weight[k, c[c >= 0]] += w[c >= 0]
        self._settle()

    def _settle(self) -> None:
        np.fill_diagonal(self.weight, 0)
        self.total = self.weight.sum(1)

    def _shrink(self, out: np.ndarray) -> None:
        t = self.at[out]
        left = np.ones(len(self.names), bool)
        left[t] = False
        keep, v = np.flatnonzero(left), len(self.gone)
        to = self.weight[np.ix_(t, keep)]
        first = np.linalg.solve(np.diag(self.total[t]) - self.weight[np.ix_(t, t)], to)
        meets, weight = np.empty((len(keep), v + len(t))), np.empty((len(keep), len(keep)))
        for lo in range(0, len(keep), 512):
            k = keep[lo : lo + 512]
            meets[lo : lo + 512, :v] = self.meets[k] + first[:, lo : lo + 512].T @ self.meets[t]
        meets[:, v:] = first.T
        self.meets = meets
        for lo in range(0, len(keep), 512):
            weight[lo : lo + 512] = self.weight[np.ix_(keep[lo : lo + 512], keep)] + to[:, lo : lo + 512].T @ first
        self.weight = weight
        self.place[out] = v + np.arange(len(t))
        self.gone = np.append(self.gone, out)
        self.names = self.names[keep]
        self.at = np.full(self.g.n, -1)
        self.at[self.names] = np.arange(len(keep))
        self._settle()

    def _part(self, chosen: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Chosen arcs: their ends and weights, the vertices that have any, and where each one's begin."""
        k = np.flatnonzero(chosen)
        count = np.add.reduceat(chosen, self.g.ptr[:-1], dtype=np.int64)
        rows = np.flatnonzero(count)
        return self.g.near[k], self.w[k], rows, np.concatenate([[0], np.cumsum(count[rows])])

    def _arcs(self) -> None:
        """Arcs that a step of the first form uses: to kept vertices, and from them to those outside."""
        kept, near = self.place == -1, self.g.near
        self.inner = self._part(kept[near])
        self.outer = self._part(np.repeat(kept, self.g.degree) & (self.place[near] >= 0))

    def _times(self, part: tuple, x: np.ndarray) -> np.ndarray:
        near, w, rows, ptr = part
        out = np.zeros(x.shape)
        if not len(rows):
            return out
        if x.shape[1] == 1:
            out[rows, 0] = np.add.reduceat(w * x[near, 0], ptr[:-1])
            return out
        cuts = np.unique(np.append(np.searchsorted(ptr, np.arange(0, len(near), 1 << 14)), [0, len(rows)]))
        cuts = cuts[cuts <= len(rows)]
        for lo, hi in zip(cuts[:-1].tolist(), cuts[1:].tolist()):
            s = slice(ptr[lo], ptr[hi])
            out[rows[lo:hi]] = np.add.reduceat(w[s, None] * x[near[s]], ptr[lo:hi] - ptr[lo], axis=0)
        return out

    def step(self, x: np.ndarray) -> np.ndarray:
        """Laws after one more step, a column each."""
        x = x / self.total[:, None]
        if self.weight is not None:
            return self.weight @ x
        y = self._times(self.inner, x)
        if len(self.gone):
            back = np.zeros_like(x)
            back[self.gone] = self.inverse @ y[self.gone]
            y[self.gone] = 0
            y += self._times(self.outer, back)
        return y

    def entry(self, a: int, b: int, r: np.random.Generator) -> int:
        """The neighbour by which a step from ``a`` came into ``b``."""
        near, w = self._near(b)
        p, law, names = self._outside(b)
        if self.weight is None:
            q, from_a, _ = self._outside(a)
            law = law * (self.inverse[np.ix_(p, q)] @ from_a)
        else:
            law = law * self.meets[self.at[a], p]
        law, names = np.append(np.maximum(law, 0), w[near == a].sum()), np.append(names, a)
        return int(names[_draw(law, r)])


def _draw(law: np.ndarray, r: np.random.Generator) -> int:
    high = np.cumsum(law)
    if not high[-1] > 0:
        raise FloatingPointError("a middle has no weight at this precision")
    return int(np.searchsorted(high, r.random() * high[-1], side="right"))


def _stretch(d: _Derived, start: int, levels: int, before: set[int], want: int, r: np.random.Generator, rows: dict[int, list[np.ndarray]]) -> list[int]:
    """States of a walk of 2^levels steps, cut where those in ``before`` and its own are ``want`` distinct ones.
    ``rows``: of the powers 1, 2, 4, ... of a step, as far as this graph's states were asked for."""

    def ask(states: list[int], level: int) -> None:
        short: dict[int, list[int]] = {}
        for s in dict.fromkeys(states):
            have = len(rows.setdefault(s, []))
            if have <= level:
                short.setdefault(have, []).append(s)
        for have, new in short.items():
            if have:
                x = np.stack([rows[s][-1] for s in new], 1)
            else:
                x = np.zeros((len(d.names), len(new)))
                x[new, np.arange(len(new))] = 1
            for k in range((1 << have >> 1) + 1, (1 << level) + 1):
                x = d.step(x)
                if k & (k - 1) == 0:
                    for j, s in enumerate(new):
                        rows[s].append(x[:, j].copy())

    ask([start], levels)
    walk = [start, _draw(rows[start][levels], r)]
    for level in range(levels, 0, -1):
        ask(walk, level - 1)
        filled = []
        for a, b in zip(walk, walk[1:]):
            filled += [a, _draw(rows[a][level - 1] * rows[b][level - 1] / d.total, r)]
        filled.append(walk[-1])
        seen = set(before)
        for i, s in enumerate(filled):
            seen.add(s)
            if len(seen) == want:
                filled = filled[: i + 1]
                break
        walk = filled
    return walk


def phased(g: Rows, r: np.random.Generator, eps: float = 0.01, length: int = 0, facts: dict | None = None, start: int = 0, on_short: str = "fail") -> list[tuple[int, int]]:
    """A tree as (child, parent), by the phased sampler."""
    if on_short != "fail":
        raise NotImplementedError("a phase that falls short raises here; ask for on_short='fail'")
    n = g.n
    goal = params.rho(n)
    size = length or params.target_length(n, len(g.near) // 2, eps, weight=int(max(1, g.weight.max(initial=1))))
    d, seen, end, out = _Derived(g), np.zeros(n, bool), start, []
    seen[start] = True
    while not seen.all():
        left = seen & (d.place == -1)
        left[end] = False
        d.drop(np.flatnonzero(left))
        want = min(goal, n - d.dropped)
        levels = min(size, want).bit_length() - 1
        if want == n - d.dropped == 2:  # the only step there is; even powers would never leave the start
            walk = [int(d.at[end]), int(d.at[int(np.flatnonzero(~seen)[0])])]
        else:
            walk, steps, rows = [int(d.at[end])], 0, {}
            while len(set(walk)) < want and steps < size:
                walk += _stretch(d, walk[-1], levels, set(walk), want, r, rows)[1:]
                steps += 1 << levels
        distinct = len(set(walk))
        if facts is not None:
            facts.setdefault("distinct", []).append(distinct)
            facts.setdefault("length", []).append(len(walk) - 1)
        if distinct < want:
            if facts is not None:
                facts["short"] = True
            raise RuntimeError(f"a phase saw {distinct} of {want} vertices in {size} steps")
        first = {walk[0]}
        for a, b in zip(walk, walk[1:]):
            if b not in first:
                first.add(b)
                out.append((int(d.names[b]), d.entry(int(d.names[a]), int(d.names[b]), r)))
        seen[d.names[list(first)]] = True
        end = int(d.names[walk[-1]])
    if facts is not None:
        facts["phases"] = len(facts.get("length", []))
    return out
