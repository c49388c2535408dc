"""Neighbour descent on a resident matrix. Rows are numbered 0..n-1; ``ids`` are what the portable mix sees."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

from ..core.metric import sq_l2_pairs, sq_l2_rows
from ..core.mix import mix_np

NONE = -1


@dataclass
class Lists:
    """Fixed-width neighbour lists: row numbers (-1: empty slot), squared distances, flags; each row sorted by (d2, id)."""

    to: np.ndarray
    d2: np.ndarray
    fresh: np.ndarray
    visited: np.ndarray
    seen: list[set] = field(default_factory=list)
    evaluations: int = 0

    @property
    def k(self) -> int:
        return self.to.shape[1]

    def copy(self) -> Lists:
        return Lists(self.to.copy(), self.d2.copy(), self.fresh.copy(), self.visited.copy(), [set(s) for s in self.seen], self.evaluations)


def _sorted(n: int, k: int, src, to, d2, fresh, visited, ids) -> Lists:
    """Lists from flat entries: per source the first k by (d2, id), one entry a target (an old one wins over an offer)."""
    order = np.lexsort((fresh, ids[to], d2, src))
    src, to, d2, fresh, visited = (x[order] for x in (src, to, d2, fresh, visited))
    # the same target at the same distance stands side by side
    keep = np.ones(len(src), bool)
    keep[1:] = (src[1:] != src[:-1]) | (to[1:] != to[:-1])
    src, to, d2, fresh, visited = (x[keep] for x in (src, to, d2, fresh, visited))
    first = np.searchsorted(src, np.arange(n))
    rank = np.arange(len(src)) - first[src]
    ok = rank < k
    out = Lists(np.full((n, k), NONE, np.int64), np.full((n, k), np.inf), np.zeros((n, k), bool), np.zeros((n, k), bool))
    out.to[src[ok], rank[ok]], out.d2[src[ok], rank[ok]] = to[ok], d2[ok]
    out.fresh[src[ok], rank[ok]], out.visited[src[ok], rank[ok]] = fresh[ok], visited[ok]
    return out


def random_lists(x: np.ndarray, k: int, seed: int = 42, ids: np.ndarray | None = None) -> Lists:
    n = len(x)
    ids = np.arange(n) if ids is None else ids
    k = min(k, n - 1)
    v = np.arange(n)[:, None]
    if n - 1 <= k:
        to = (v + 1 + np.arange(n - 1)[None, :]) % n if n > 1 else np.zeros((n, 0), np.int64)
    else:
        slots = (v + 1 + mix_np(v, np.arange(2 * k)[None, :], seed) % (n - 1)) % n
        slots = np.hstack([slots, (v + 1 + np.arange(k)[None, :]) % n])  # enough when the slots repeat
        order = np.argsort(slots, axis=1, kind="stable")
        s = np.take_along_axis(slots, order, 1)
        dup = np.zeros_like(s, bool)
        dup[:, 1:] = s[:, 1:] == s[:, :-1]
        first = np.zeros_like(dup)
        np.put_along_axis(first, order, ~dup, 1)
        at = np.where(first, np.cumsum(first, 1) - 1, 10**9)
        pick = np.argsort(at, axis=1, kind="stable")[:, :k]
        to = np.take_along_axis(slots, pick, 1)
    src = np.repeat(np.arange(n), to.shape[1])
    to = to.ravel()
    d = sq_l2_pairs(x, src, to)
    out = _sorted(n, k, src, to, d, np.ones(len(to), bool), np.zeros(len(to), bool), ids)
    out.seen = [set() for _ in range(n)]
    out.evaluations = len(to)
    return out


def _least(key: np.ndarray, ok: np.ndarray, s: int) -> np.ndarray:
    """Per row, the mask of the ``s`` usable entries of smallest key."""
    key = np.where(ok, key, np.inf)
    rank = np.argsort(np.argsort(key, axis=1, kind="stable"), axis=1, kind="stable")
    return ok & (rank < s)


def _reverse(n: int, src: np.ndarray, to: np.ndarray, s: int, seed: int, it: int, ids: np.ndarray):
    """Owners that sampled each node, at most s of them by mix."""
    m = mix_np(seed, it, ids[to], ids[src])
    order = np.lexsort((ids[src], m, to))
    src, to = src[order], to[order]
    rank = np.arange(len(to)) - np.searchsorted(to, np.arange(n))[to]
    ok = rank < s
    return to[ok], src[ok]


def _padded(n: int, at: np.ndarray, member: np.ndarray, ids: np.ndarray) -> np.ndarray:
    """(n, width) members of each anchor without repeats, in id order, -1 behind."""
    if not len(at):
        return np.full((n, 0), NONE, np.int64)
    order = np.lexsort((ids[member], at))
    at, member = at[order], member[order]
    keep = np.ones(len(at), bool)
    keep[1:] = (at[1:] != at[:-1]) | (member[1:] != member[:-1])
    at, member = at[keep], member[keep]
    rank = np.arange(len(at)) - np.searchsorted(at, np.arange(n))[at]
    out = np.full((n, int(rank.max()) + 1), NONE, np.int64)
    out[at, rank] = member
    return out


def groups(g: Lists, s: int, it: int, seed: int, reverse: bool, ids: np.ndarray):
    """Anchors' fresh and old parts, and which list entries were sampled as fresh."""
    n = len(g.to)
    v = np.arange(n)[:, None]
    m = mix_np(seed, it, ids[v], ids[np.where(g.to >= 0, g.to, 0)]).astype(float) + ids[np.where(g.to >= 0, g.to, 0)] / (ids.max() + 2.0)
    f, o = _least(m, (g.to >= 0) & g.fresh, s), _least(m, (g.to >= 0) & ~g.fresh, s)
    parts = []
    for pick in (f, o):
        src, slot = np.nonzero(pick)
        to = g.to[src, slot]
        at, member = src, to
        if reverse:
            ra, rm = _reverse(n, src, to, s, seed, it, ids)
            at, member = np.concatenate([at, ra]), np.concatenate([member, rm])
        parts.append(_padded(n, at, member, ids))
    fresh, old = parts
    if fresh.shape[1] and old.shape[1]:
        both = (old[:, :, None] == fresh[:, None, :]).any(2)
        old = np.where(both, NONE, old)
        order = np.argsort(old < 0, axis=1, kind="stable")
        old = np.take_along_axis(old, order, 1)
    return fresh, old, f


def _last(g: Lists) -> np.ndarray:
    """What an offer must be nearer than: each list's greatest distance, infinite while a slot is empty."""
    return np.where(g.to[:, -1] >= 0, g.d2[:, -1], np.inf)


def _listed(to: np.ndarray, t: np.ndarray, p: np.ndarray, size: int = 1 << 16) -> np.ndarray:
    """Whether p[i] stands in the list of t[i]; so many lists are laid out at once."""
    out = np.empty(len(t), bool)
    for at in range(0, len(t), size):
        out[at : at + size] = (to[t[at : at + size]] == p[at : at + size, None]).any(1)
    return out


def local_join(x: np.ndarray, fresh: np.ndarray, old: np.ndarray, keep: str, tile: int, ids: np.ndarray, block: int = 0, last: np.ndarray | None = None):
    """Offers (target, partner, d2) of one shared join; members of an anchor meet in one batched product.

    ``keep``: 'all'; 'tile' (the nearest of each run of ``tile`` partners of an anchor); 'one' (the nearest of the iteration). Offers not
    nearer than ``last`` of their target, which no update would admit, go as soon as they are chosen."""
    n, a, b = len(fresh), fresh.shape[1], old.shape[1]
    if a == 0:
        z = np.zeros(0, np.int64)
        return z, z, np.zeros(0), 0
    block = block or max(1, 6_000_000 // max(1, a * (a + b) * x.shape[1]))
    out, count = [], 0

    def nearest(t, p, d):
        order = np.lexsort((ids[p], d, t))
        t, p, d = t[order], p[order], d[order]
        first = np.append(True, t[1:] != t[:-1]) if len(t) else np.zeros(0, bool)
        return t[first], p[first], d[first]

    def offer(t, p, d):
        ok = slice(None) if last is None else d < last[t]
        out.append(nearest(t[ok], p[ok], d[ok]) if keep == "one" else (t[ok], p[ok], d[ok]))

    for at in range(0, n, block):
        f, o = fresh[at : at + block], old[at : at + block]
        mem = np.hstack([f, o])
        pos = np.hstack([np.tile(np.arange(a), (len(f), 1)), (f >= 0).sum(1)[:, None] + np.arange(b)[None, :]])
        ok = (f >= 0)[:, :, None] & (mem >= 0)[:, None, :]
        ok[:, np.arange(a), np.arange(a)] = False
        d = sq_l2_rows(x[f][:, :, None, :], x[mem][:, None, :, :])
        count += int(ok.sum()) - int((ok[:, :, :a]).sum()) // 2
        if keep == "all" or keep == "one":
            r, i, j = np.nonzero(ok)
            t, p, dd = f[r, i], mem[r, j], d[r, i, j]
            into_old = j >= a
            t2, p2, dd2 = p[into_old], t[into_old], dd[into_old]
            offer(np.concatenate([t, t2]), np.concatenate([p, p2]), np.concatenate([dd, dd2]))
            continue
        big = np.where(ok, d, np.inf)
        for c in range((a + b - 1) // tile + 1):
            w = np.where((pos // tile == c)[:, None, :], big, np.inf)  # offers to the fresh
            m = w.min(2)
            who = np.where(w == m[:, :, None], ids[mem][:, None, :], np.iinfo(np.int64).max).argmin(2)
            r, i = np.nonzero(np.isfinite(m))
            offer(f[r, i], mem[r, who[r, i]], m[r, i])
        if b:
            for c in range((a - 1) // tile + 1):
                rows = slice(c * tile, (c + 1) * tile)
                w = big[:, rows, a:]
                if w.shape[1] == 0:
                    continue
                m = w.min(1)
                who = np.where(w == m[:, None, :], ids[f[:, rows]][:, :, None], np.iinfo(np.int64).max).argmin(1) + c * tile
                r, j = np.nonzero(np.isfinite(m))
                offer(o[r, j], f[r, who[r, j]], m[r, j])
    t, p, d = (np.concatenate(z) for z in zip(*out, strict=True))
    if keep == "one":
        t, p, d = nearest(t, p, d)
    return t, p, d, count


def update(g: Lists, t, p, d, ids: np.ndarray, fresh: bool = True) -> tuple[Lists, int]:
    """Lists after offers: viable ones (nearer than the list's last, not in it) merged in; how many were admitted."""
    n, k = g.to.shape
    ok = d < _last(g)[t]
    t, p, d = t[ok], p[ok], d[ok]
    if len(t):
        own = _listed(g.to, t, p)
        t, p, d = t[~own], p[~own], d[~own]
    src, slot = np.nonzero(g.to >= 0)
    vis = np.array([p_ in g.seen[t_] for t_, p_ in zip(t.tolist(), p.tolist(), strict=True)], bool) if g.seen and not fresh else np.zeros(len(t), bool)
    out = _sorted(n, k, np.concatenate([src, t]), np.concatenate([g.to[src, slot], p]), np.concatenate([g.d2[src, slot], d]), np.concatenate([g.fresh[src, slot], np.full(len(t), fresh)]), np.concatenate([g.visited[src, slot], vis]), ids)
    out.seen, out.evaluations = g.seen, g.evaluations
    s2, z2 = np.nonzero(out.to >= 0)
    return out, int((~np.isin(s2 * n + out.to[s2, z2], src * n + g.to[src, slot])).sum())


def shared_round(x, g: Lists, s: int, it: int, seed: int = 42, keep: str = "tile", tile: int = 4, reverse: bool = True, ids=None) -> tuple[Lists, int]:
    ids = np.arange(len(x)) if ids is None else ids
    fresh, old, sampled = groups(g, s, it, seed, reverse, ids)
    t, p, d, count = local_join(x, fresh, old, keep, tile, ids, last=_last(g))
    g2 = g.copy()
    g2.fresh = g.fresh & ~sampled
    out, new = update(g2, t, p, d, ids)
    out.evaluations += count
    return out, new


def fine_round(x, g: Lists, m: int, take: int | None = None, ids=None, prefilter: str | None = None) -> tuple[Lists, int]:
    """Each node expands its m nearest unvisited neighbours and compares their lists with itself only.

    ``prefilter='triangle'`` skips candidates w of a neighbour u with |d(v,u) - d(u,w)| >= d(v, last): they cannot enter."""
    n, k = g.to.shape
    ids = np.arange(n) if ids is None else ids
    g = g.copy()
    open_ = (g.to >= 0) & ~g.visited
    pick = open_ & (np.cumsum(open_, 1) <= m)
    src, slot = np.nonzero(pick)
    mid = g.to[src, slot]
    g.visited |= pick
    for a, b in zip(src.tolist(), mid.tolist(), strict=True):
        g.seen[a].add(b)
    lists = g.to[mid][:, : take or k]
    far = g.d2[mid][:, : take or k]
    v = np.repeat(src, lists.shape[1])
    w = lists.ravel()
    ok = (w >= 0) & (w != v)
    if prefilter == "triangle":
        kth = np.where(g.to[:, -1] >= 0, np.sqrt(np.where(np.isfinite(g.d2[:, -1]), g.d2[:, -1], 0)), np.inf)
        gap = np.abs(np.repeat(np.sqrt(g.d2[src, slot]), lists.shape[1]) - np.sqrt(np.where(np.isfinite(far), far, 0)).ravel())
        ok &= gap < kth[v]
    v, w = v[ok], w[ok]
    key = np.unique(v * n + w)
    v, w = key // n, key % n
    if len(v):
        own = _listed(g.to, v, w)
        v, w = v[~own], w[~own]
    d = sq_l2_pairs(x, v, w)
    out, new = update(g, v, w, d, ids, fresh=False)
    out.evaluations += len(v)
    return out, new


def two_phase(x, k: int, it1: int, it2: int, sample: int, m: int = 2, tile: int = 4, keep: str = "tile", seed: int = 42, reverse: bool = True, delta: float = 0.0, take: int | None = None, prefilter: str | None = None, ids=None, trace=None) -> Lists:
    """Shared rounds, then fine rounds; stops early when fewer than ``delta`` * n * k entries change, or where ``trace(it, lists)``, which
    sees each round, returns True (``until_recall`` makes such a trace)."""
    x = np.asarray(x, np.float64)
    g = random_lists(x, k, seed, ids)
    if trace:
        trace(0, g)
    for it in range(1, it1 + it2 + 1):
        if it <= it1:
            g, new = shared_round(x, g, sample, it, seed, keep, tile, reverse, ids)
        else:
            g, new = fine_round(x, g, m, take, ids, prefilter)
        if trace and trace(it, g) is True:
            break
        settled = new < delta * g.to.size
        if it > it1 and (settled or new == 0):
            break
        if settled:
            it1 = it  # the shared phase is over: the fine one follows
    return g


def until_recall(x: np.ndarray, k: int, target: float, rows: int = 64, seed: int = 42, ids=None):
    """A trace that ends a descent once the mean recall of ``rows`` sampled rows, whose true lists are computed, reaches ``target``."""
    ids = np.arange(len(x)) if ids is None else ids
    some = np.argsort(mix_np(seed, ids), kind="stable")[:rows]
    d = (x[some] ** 2).sum(1)[:, None] + (x**2).sum(1)[None, :] - 2 * x[some] @ x.T
    d[np.arange(len(some)), some] = np.inf
    truth = np.argsort(d, axis=1, kind="stable")[:, : min(k, len(x) - 1)]
    return lambda it, g: bool(recall(g.to[some], truth) >= target)


def exact_lists(x: np.ndarray, k: int, ids=None) -> Lists:
    """The true lists of a shard small enough for its own square."""
    n = len(x)
    ids = np.arange(n) if ids is None else ids
    k = min(k, n - 1)
    to, d2 = np.full((n, k), NONE, np.int64), np.full((n, k), np.inf)
    for at in range(0, n, 256):
        q = x[at : at + 256]
        d = (q**2).sum(1)[:, None] + (x**2).sum(1)[None, :] - 2 * q @ x.T
        d[np.arange(len(q)), at + np.arange(len(q))] = np.inf
        near = np.argpartition(d, min(k + 8, n - 1), 1)[:, : k + 9]
        real = sq_l2_rows(q[:, None, :], x[near])
        real[near == (at + np.arange(len(q)))[:, None]] = np.inf
        order = np.lexsort((ids[near], real), axis=1)[:, :k]
        to[at : at + 256], d2[at : at + 256] = np.take_along_axis(near, order, 1), np.take_along_axis(real, order, 1)
    return Lists(to, d2, np.ones((n, k), bool), np.zeros((n, k), bool), [set() for _ in range(n)], n * (n - 1) // 2)


def recall(g: np.ndarray, truth: np.ndarray) -> float:
    """Mean share of each row's true neighbours that its list holds."""
    k = truth.shape[1]
    return float(np.mean([len(np.intersect1d(a[a >= 0], b[b >= 0])) / k for a, b in zip(g, truth, strict=True)])) if k else 1.0
