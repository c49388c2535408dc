"""Best-first search on a resident graph."""

from __future__ import annotations

from bisect import bisect_left

import numpy as np

from ..core.metric import sq_l2_pairs, sq_l2_rows


def beam(x: np.ndarray, graph: list[np.ndarray], q: np.ndarray, k: int, pool: int, entries, width: int = 1, ids=None):
    """(row numbers, squared distances) of the k nearest found, every row number whose distance was computed, and how many were expanded.

    The pool holds the ``pool`` nearest seen; each step expands its ``width`` nearest unexpanded members."""
    ids = np.arange(len(x)) if ids is None else ids
    entries = list(dict.fromkeys(int(e) for e in entries))
    d = sq_l2_rows(x[entries], q)
    top = sorted(zip(d.tolist(), ids[entries].tolist(), entries, strict=True))[:pool]
    seen = np.zeros(len(x), bool)
    seen[entries] = True
    log, done, first = list(entries), set(), 0  # nothing unexpanded stands before ``first``
    while True:
        go: list[int] = []
        while first < len(top) and top[first][2] in done:
            first += 1
        for t in top[first:]:
            if len(go) == width:
                break
            if t[2] not in done:
                go.append(t[2])
        if not go:
            break
        done.update(go)
        new: list[int] = []
        for u in go:
            near = np.asarray(graph[u], np.int64)
            near = near[near >= 0]
            near = near[~seen[near]]
            seen[near] = True
            new += dict.fromkeys(near.tolist())
        if new:
            log += new
            d = sq_l2_rows(x[new], q)
            if len(top) == pool:
                some = np.flatnonzero(d <= top[-1][0]).tolist()
                offers = [(float(d[i]), int(ids[new[i]]), new[i]) for i in some]
            else:
                offers = list(zip(d.tolist(), ids[new].tolist(), new, strict=True))
            for t in offers:
                at = bisect_left(top, t)
                if at < pool:
                    top.insert(at, t)
                    first = min(first, at)
            del top[pool:]
    best = top[:k]
    return np.array([t[2] for t in best], np.int64), np.array([t[0] for t in best]), log, len(done)


def beams(x: np.ndarray, to: np.ndarray, rows: np.ndarray, pool: int, entry: int, ids: np.ndarray) -> np.ndarray:
    """(len(rows), n) what a search of width 1 for each of the given rows visits from the entry: the same as ``beam``'s, a step of all of
    them at a time. ``to``: lists of one width, -1 where empty, no node twice in a list."""
    n, none = len(rows), np.iinfo(np.int64).max
    seen = np.zeros((n, len(x)), bool)
    seen[:, entry] = True
    d = np.full((n, pool), np.inf)
    at = np.full((n, pool), -1, np.int64)
    open_ = np.zeros((n, pool), bool)
    d[:, 0], at[:, 0], open_[:, 0] = sq_l2_rows(x[entry], x[rows]), entry, True
    live = np.arange(n)
    while len(live):
        slot = open_[live].argmax(1)
        open_[live, slot] = False
        near = to[at[live, slot]]
        r, c = np.nonzero((near >= 0) & ~seen[live[:, None], near])
        w, q = near[r, c], live[r]
        seen[q, w] = True
        far = np.full(near.shape, np.inf)
        far[r, c] = sq_l2_pairs(x, w, rows[q])
        far[far > d[live, -1][:, None]] = np.inf
        some = np.flatnonzero(np.isfinite(far).any(1))
        if len(some):
            mine, most = live[some], int(np.isfinite(far[some]).sum(1).max())
            pick = np.argsort(far[some], axis=1, kind="stable")[:, :most]
            new, dn = np.take_along_axis(near[some], pick, 1), np.take_along_axis(far[some], pick, 1)
            new[np.isinf(dn)] = -1
            dd, aa, oo = np.hstack([d[mine], dn]), np.hstack([at[mine], new]), np.hstack([open_[mine], new >= 0])
            order = np.argsort(dd, axis=1, kind="stable")
            s = np.take_along_axis(dd, order, 1)
            tie = np.flatnonzero(((s[:, 1:] == s[:, :-1]) & np.isfinite(s[:, 1:])).any(1))
            if len(tie):
                order[tie] = np.lexsort((np.where(aa[tie] >= 0, ids[aa[tie]], none), dd[tie]), axis=1)
            order = order[:, :pool]
            d[mine], at[mine], open_[mine] = (np.take_along_axis(z, order, 1) for z in (dd, aa, oo))
        live = live[open_[live].any(1)]
    return seen


def entry_point(x: np.ndarray, ids=None) -> int:
    """Row nearest the centroid, ties by id."""
    ids = np.arange(len(x)) if ids is None else ids
    d = sq_l2_rows(x, x.mean(0))
    return int(np.lexsort((ids, d))[0])


def path_candidates(x: np.ndarray, graph: list[np.ndarray], size: int, pool: int, entry: int, own: list[np.ndarray] | None = None, log: str = "seen", ids=None) -> list[np.ndarray]:
    """For every node, the nearest ``size`` of what a search for it visits from the entry, joined with its own list."""
    ids = np.arange(len(x)) if ids is None else ids
    width = max(map(len, graph), default=0)
    to = np.full((len(x), max(1, width)), -1, np.int64)
    for v, g in enumerate(graph):
        to[v, : len(g)] = g
    to.sort(axis=1)  # a list that names a node twice offers it once
    to[:, 1:][to[:, 1:] == to[:, :-1]] = -1
    out, block = [], max(1, min(512, 32_000_000 // max(1, len(x))))
    for s in range(0, len(x), block):
        rows = np.arange(s, min(len(x), s + block))
        seen = beams(x, to, rows, pool, entry, ids)
        for v, met in zip(rows.tolist(), seen, strict=True):
            if own is not None:
                w = np.asarray(own[v], np.int64)
                met[w[w >= 0]] = True
            met[v] = False
            c = np.flatnonzero(met)
            d = sq_l2_rows(x[c], x[v])
            out.append(c[np.lexsort((ids[c], d))[:size]])
    return out


def two_hop(x: np.ndarray, to: np.ndarray, size: int, ids=None) -> list[np.ndarray]:
    ids = np.arange(len(x)) if ids is None else ids
    out = []
    for v in range(len(x)):
        own = to[v][to[v] >= 0]
        c = np.unique(np.concatenate([own, to[own].ravel()]))
        c = c[(c >= 0) & (c != v)]
        d = sq_l2_rows(x[c], x[v])
        out.append(c[np.lexsort((ids[c], d))[:size]])
    return out
