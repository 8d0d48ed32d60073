"""Samplers of one tree of a small graph in numpy, run many at a time inside Spark tasks.

A graph is a symmetric weight matrix; a tree is a list of (child, parent).
"""

from __future__ import annotations

import functools
import math

import numpy as np

from . import derived, matching, params


def _step(p: np.ndarray, v: int, r: np.random.Generator) -> int:
    """``p``: rows of cumulative chances."""
    return int(np.searchsorted(p[v], r.random() * p[v, -1], side="right"))


def _cumulative(w: np.ndarray) -> np.ndarray:
    return np.cumsum(w, axis=1)


def cover_walk(w: np.ndarray, r: np.random.Generator, start: int = 0) -> list[tuple[int, int]]:
    """Walk until every vertex is seen."""
    c, seen, v, out = _cumulative(w), {start}, start, []
    while len(seen) < len(w):
        x = _step(c, v, r)
        if x not in seen:
            seen.add(x)
            out.append((x, v))
        v = x
    return out


def cover_steps(w: np.ndarray, r: np.random.Generator, start: int = 0) -> int:
    c, seen, v, n = _cumulative(w), {start}, start, 0
    while len(seen) < len(w):
        v = _step(c, v, r)
        seen.add(v)
        n += 1
    return n


def hitting_steps(w: np.ndarray, r: np.random.Generator, start: int, goal: int) -> int:
    c, v, n = _cumulative(w), start, 0
    while v != goal:
        v = _step(c, v, r)
        n += 1
    return n


def loop_erased(w: np.ndarray, r: np.random.Generator, root: int = 0) -> list[tuple[int, int]]:
    """From each vertex outside the tree, walk to the tree; keep the last exits."""
    c, inside, exit_ = _cumulative(w), {root}, {}
    out = []
    for s in range(len(w)):
        v = s
        while v not in inside:
            exit_[v] = _step(c, v, r)
            v = exit_[v]
        v = s
        while v not in inside:
            inside.add(v)
            out.append((v, exit_[v]))
            v = exit_[v]
    return out


def _sides(n: int, edges: list[tuple[int, int]]) -> np.ndarray:
    label = list(range(n))

    def root(x):
        while label[x] != x:
            label[x] = label[label[x]]
            x = label[x]
        return x

    for a, b in edges:
        label[root(a)] = root(b)
    return np.array([root(x) for x in range(n)])


def exchange_chain(w: np.ndarray, r: np.random.Generator, steps: int | None = None) -> list[tuple[int, int]]:
    """Drop a uniform tree edge, add an edge across the split by weight; approximate."""
    n = len(w)
    tree = cover_tree_bfs(w)
    for _ in range(steps if steps is not None else 4 * n * max(1, math.ceil(math.log(n + 1)))):
        tree.pop(int(r.integers(len(tree))))
        side = _sides(n, tree)
        a, b = np.nonzero(np.triu((w > 0) & (side[:, None] != side[None, :]), 1))
        p = w[a, b]
        i = int(r.choice(len(a), p=p / p.sum()))
        tree.append((int(a[i]), int(b[i])))
    return tree


def cover_tree_bfs(w: np.ndarray, root: int = 0) -> list[tuple[int, int]]:
    """Breadth-first tree: an arbitrary valid answer."""
    seen, queue, out = {root}, [root], []
    for v in queue:
        for x in np.flatnonzero(w[v]).tolist():
            if x not in seen:
                seen.add(x)
                queue.append(x)
                out.append((x, v))
    return out


def conditional_marginals(w: np.ndarray, r: np.random.Generator) -> list[tuple[int, int]]:
    """Edge by edge: keep with chance weight times effective resistance given earlier choices."""
    n = len(w)
    cur, names = w.astype(float).copy(), list(range(n))
    out: list[tuple[int, int]] = []
    label = np.arange(n)  # contracted vertex of each
    for a, b in [(int(a), int(b)) for a, b in zip(*np.nonzero(np.triu(w, 1)))]:
        x, y = label[a], label[b]
        if x == y or len(out) == n - 1:
            continue
        live = np.unique(label)
        lap = np.diag(cur.sum(1)) - cur
        lap = lap[np.ix_(live, live)]
        i, j = int(np.searchsorted(live, x)), int(np.searchsorted(live, y))
        inv = np.linalg.pinv(lap)
        chance = w[a, b] * (inv[i, i] + inv[j, j] - 2 * inv[i, j])
        cur[x, y] -= w[a, b]
        cur[y, x] -= w[a, b]
        if r.random() < chance:
            out.append((a, b))
            cur[x] += cur[y]
            cur[:, x] += cur[:, y]
            cur[y] = cur[:, y] = 0
            cur[x, x] = 0
            label[label == y] = x
    return out


def random_weight_mst(w: np.ndarray, r: np.random.Generator) -> list[tuple[int, int]]:
    """Minimum spanning tree under random weights: a tree, but not a uniform one."""
    a, b = np.nonzero(np.triu(w, 1))
    order = np.argsort(r.random(len(a)))
    label = np.arange(len(w))
    out = []
    for i in order:
        x, y = label[a[i]], label[b[i]]
        if x != y:
            label[label == y] = x
            out.append((int(a[i]), int(b[i])))
    return out


def _ladder(p: np.ndarray, levels: int, bits: int | None) -> list[np.ndarray]:
    out = [p]
    for _ in range(levels):
        m = out[-1] @ out[-1]
        out.append(np.floor(m * 2.0**bits) / 2.0**bits if bits else m)
    return out


def topdown_walk(ladder: list[np.ndarray], start: int, rho: int, r: np.random.Generator, place: str = "order", goal_only: bool = False) -> list[tuple[int, int]]:
    """Filled places (pos, vertex) of a walk cut at its ``rho``-th distinct vertex."""
    top = len(ladder) - 1
    row = ladder[top][start]
    walk = [(0, start), (1 << top, int(r.choice(len(row), p=row / row.sum())))]
    for level in range(top, 0, -1):
        half, step = ladder[level - 1], 1 << (level - 1)
        pairs: dict[tuple[int, int], list[int]] = {}
        for k in range(len(walk) - 1):
            pairs.setdefault((walk[k][1], walk[k + 1][1]), []).append(k)
        mids = {}
        for (p, q), at in pairs.items():
            law = half[p] * half[:, q]
            if law.sum() <= 0:
                raise FloatingPointError("a middle has no weight at this precision")
            for k, v in zip(at, r.choice(len(law), size=len(at), p=law / law.sum())):
                mids[k] = int(v)
        filled = []
        for k in range(len(walk) - 1):
            filled += [(*walk[k], None), (walk[k][0] + step, mids[k], k)]
        filled.append((*walk[-1], None))
        seen: set[int] = set()
        for i, (_, v, _k) in enumerate(filled):
            seen.add(v)
            if len(seen) == rho:
                filled = filled[: i + 1]
                break
        if place != "order":
            filled = _replace(filled, walk, half, r, place)
        walk = [(pos, v) for pos, v, _ in filled]
    return walk


def _replace(filled, walk, half, r, place):
    """Put the middles back by a drawn matching; the last one stays where it is."""
    slots = [i for i, x in enumerate(filled) if x[2] is not None]
    if slots and slots[-1] == len(filled) - 1:
        slots = slots[:-1]
    if len(slots) < 2:
        return filled
    ends = [(walk[filled[i][2]][1], walk[filled[i][2] + 1][1]) for i in slots]
    items = np.array([filled[i][1] for i in slots])
    if place == "per_pair":
        new = items.copy()
        for pair in set(ends):
            at = [k for k, e in enumerate(ends) if e == pair]
            new[at] = r.permutation(items[at])
    else:
        w = np.array([half[p, items] * half[items, q] for p, q in ends])
        names = {e: k for k, e in enumerate(sorted(set(ends)))}
        m = matching.draw(w / w.max(), place, r, np.array([names[e] for e in ends]), items, np.arange(len(items)))
        new = items[m]
    out = list(filled)
    for i, v in zip(slots, new.tolist()):
        out[i] = (filled[i][0], v, filled[i][2])
    return out


def phased(w: np.ndarray, r: np.random.Generator, eps: float = 0.01, place: str = "order", rho: str = "sqrt", bits: int | None = None, exact: bool = False, length: int = 0, facts: dict | None = None, start: int = 0, on_short: str = "arbitrary") -> list[tuple[int, int]]:
    """The phased sampler: short walks by the top-down method on ever smaller derived graphs.

    ``exact``: cube-root phases, shuffles inside pairs, and walks that go on until the phase's
    goal is met, so that nothing is cut off (a reconstruction of the announced variant).
    """
    n = len(w)
    if exact:
        place, rho = "per_pair", "cbrt"
    goal = params.rho(n, rho)
    size = length or params.target_length(n, int((w > 0).sum() // 2), eps, weight=int(max(1, w.max())))
    levels = size.bit_length() - 1
    seen, end, out, phases = {start}, start, [], 0
    while len(seen) < n:
        phases += 1
        keep = sorted({end} | (set(range(n)) - seen))
        m = w if len(keep) == n else derived.schur_dense(w, keep)
        p = m / m.sum(1, keepdims=True)
        ladder = _ladder(p, levels, bits) if len(keep) > 2 else []
        here, want, walk = keep.index(end), min(goal, len(keep)), []
        if len(keep) == 2:  # the only step there is; even powers would never leave the start
            walk = [here, 1 - here]
        while len(set(walk)) < want:
            part = topdown_walk(ladder, walk[-1] if walk else here, want, r, place)
            part = [v for _, v in part]
            walk = part if not walk else walk + part[1:]
            if len(set(walk)) >= want or not exact:
                break
        if exact and len(set(walk)) > want:
            got: set[int] = set()
            for i, v in enumerate(walk):
                got.add(v)
                if len(got) == want:
                    walk = walk[: i + 1]
                    break
        if len(set(walk)) < want:
            if facts is not None:
                facts["short"] = True
            if on_short == "fail":
                raise RuntimeError(f"a phase saw {len(set(walk))} of {want} vertices in {size} steps")
            return cover_tree_bfs(w)
        q = derived.shortcut_dense(w, keep) if len(keep) < n else None
        mass = w[:, keep].sum(1)
        first: set[int] = {walk[0]}
        for a, b in zip(walk, walk[1:]):
            if b in first:
                continue
            first.add(b)
            u, v = keep[a], keep[b]
            if q is None:
                out.append((v, u))
            else:
                law = np.where(w[:, v] > 0, q[u] * w[:, v] / np.maximum(mass, 1e-300), 0)
                out.append((v, int(r.choice(n, p=law / law.sum()))))
        seen |= {keep[x] for x in walk}
        end = keep[walk[-1]]
        if facts is not None:
            facts.setdefault("distinct", []).append(len(set(walk)))
            facts.setdefault("length", []).append(len(walk) - 1)
    if facts is not None:
        facts["phases"] = phases
    return out


def _active_phases(w: np.ndarray, r: np.random.Generator, steps: int, start: int = 0) -> list[tuple[int, int]]:
    """Plain walks of a number of steps on the derived graph, phase by phase."""
    n, seen, end, out = len(w), {start}, start, []
    while len(seen) < n:
        keep = sorted({end} | (set(range(n)) - seen))
        m = w if len(keep) == n else derived.schur_dense(w, keep)
        q, mass, c = derived.shortcut_dense(w, keep), w[:, keep].sum(1), _cumulative(m)
        v, first = keep.index(end), {keep.index(end)}
        for _ in range(steps):
            x = _step(c, v, r)
            if x not in first:
                first.add(x)
                law = np.where(w[:, keep[x]] > 0, q[keep[v]] * w[:, keep[x]] / np.maximum(mass, 1e-300), 0)
                out.append((keep[x], int(r.choice(n, p=law / law.sum()))))
            v = x
        seen |= {keep[x] for x in first}
        end = keep[v]
    return out


def linear_phases(w: np.ndarray, r: np.random.Generator) -> list[tuple[int, int]]:
    """Phases of n steps each."""
    return _active_phases(w, r, len(w))


def shortcut_walk(w: np.ndarray, r: np.random.Generator) -> list[tuple[int, int]]:
    """One step a phase: every return to the visited region is skipped at once."""
    return _active_phases(w, r, 1)


def doubled_walk(w: np.ndarray, r: np.random.Generator, tau: int, start: int = 0) -> np.ndarray:
    """Walk of ``start`` by index-paired doubling of stubs of all vertices."""
    n, k = len(w), 1 << max(0, math.ceil(math.log2(max(tau, 1))))
    c = _cumulative(w)
    u = r.random((n, k)) * c[:, -1:]
    paths = np.stack([np.stack([np.full(k, v), np.searchsorted(c[v], u[v], side="right")], 1) for v in range(n)])
    while k > 1:
        pre, need = paths[:, : k // 2], k - 1 - np.arange(k // 2)
        suf = paths[pre[:, :, -1], need[None, :]]
        paths = np.concatenate([pre, suf[:, :, 1:]], 2)
        k //= 2
    return paths[start, 0]


def by_doubling(w: np.ndarray, r: np.random.Generator, tau: int | None = None, start: int = 0) -> list[tuple[int, int]]:
    """First-visit tree of doubled walks, continued from the end until all is covered."""
    n = len(w)
    tau = tau or 2 * n * max(1, math.ceil(math.log(n + 1)))
    seen, end, out = {start}, start, []
    while len(seen) < n:
        walk = doubled_walk(w, r, tau, end).tolist()
        for a, b in zip(walk, walk[1:]):
            if b not in seen:
                seen.add(b)
                out.append((b, a))
        end = walk[-1]
    return out


METHODS = {
    "cover_walk": cover_walk,
    "loop_erased": loop_erased,
    "exchange_chain": exchange_chain,
    "conditional_marginals": conditional_marginals,
    "random_weight_mst": random_weight_mst,
    "phased": phased,
    "phased_matching": functools.partial(phased, place="auto"),
    "phased_swap": functools.partial(phased, place="swap"),
    "phased_per_pair": functools.partial(phased, place="per_pair"),
    "phased_exact": functools.partial(phased, exact=True),
    "linear_phases": linear_phases,
    "shortcut_walk": shortcut_walk,
    "doubling": by_doubling,
}
#: Methods whose law is not the uniform (or weighted) one.
NOT_UNIFORM = {"random_weight_mst"}
