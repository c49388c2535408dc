"""Pruning on resident vectors: one owner's candidates at a time, serial or in waves."""

from __future__ import annotations

import numpy as np

from ..core.metric import apex_angle_np, sq_l2_rows


def conflict_pairs(metric: str, thres: float, dkept: np.ndarray, dp: np.ndarray, dij: np.ndarray) -> np.ndarray:
    """Whether kept ones forbid candidates, pair by pair, from their squared distances to the owner and to each other."""
    if metric == "dist":
        return np.broadcast_to(dp, dij.shape) >= thres * thres * dij
    return apex_angle_np(dkept, dp, dij) <= thres


def serial(v: np.ndarray, dp: np.ndarray, metric: str, thres: float, degree: int) -> tuple[list[int], int]:
    """Candidates one by one against the kept list, leaving a comparison early at the first conflict. Kept positions, distances computed."""
    kept: list[int] = []
    tests, own, far = 0, np.empty((min(degree, len(dp)), v.shape[1])), np.empty(min(degree, len(dp)))
    for j in range(len(dp)):
        m = len(kept)
        if m == degree:
            break
        if m:  # kept ones behind the first conflict do not count
            hit = conflict_pairs(metric, thres, far[:m], dp[j], sq_l2_rows(own[:m], v[j]))
            first = int(hit.argmax())
            if hit[first]:
                tests += first + 1
                continue
            tests += m
        own[m], far[m] = v[j], dp[j]
        kept.append(j)
    return kept, tests


def wavefront(v: np.ndarray, dp: np.ndarray, metric: str, thres: float, degree: int, pick: str = "nearest") -> tuple[list[int], int]:
    """Each wave keeps one survivor and tests all others against it alone."""
    at = np.arange(len(dp))  # candidates that are still looked at; the forbidden ones go once they are half of them
    alive = np.ones(len(dp), bool)
    kept: list[int] = []
    tests, left = 0, len(dp)
    while left and len(kept) < degree:
        if 2 * left <= len(at):
            v, dp, at, alive = v[alive], dp[alive], at[alive], np.ones(left, bool)
        x = int(alive.argmax()) if pick == "nearest" else int(np.flatnonzero(alive)[left // 2])
        kept.append(int(at[x]))
        alive[x] = False
        tests += left - 1
        alive &= ~conflict_pairs(metric, thres, dp[x], dp, sq_l2_rows(v[x], v))
        left = int(np.count_nonzero(alive))
    return sorted(kept) if pick != "nearest" else kept, tests


def dispersion(v: np.ndarray, dp: np.ndarray, degree: int) -> tuple[list[int], float]:
    """The nearest, then always the candidate of greatest angle sum to the kept; kept positions in order of choice, and the objective."""
    n = len(dp)
    if n == 0:
        return [], 0.0
    kept, total = [0], 0.0
    s = apex_angle_np(np.full(n, dp[0]), dp, sq_l2_rows(v[0], v))
    s[0] = -np.inf
    while len(kept) < min(degree, n):
        x = int(np.flatnonzero(s >= s.max() - 1e-9)[0])
        total += float(s[x])
        kept.append(x)
        s = s + apex_angle_np(np.full(n, dp[x]), dp, sq_l2_rows(v[x], v))
        s[x] = -np.inf
    return kept, total


def dispersion_anew(v: np.ndarray, dp: np.ndarray, degree: int) -> list[int]:
    """The same choice with every candidate's angle sum added up anew in each step: the original form, of which ``dispersion`` keeps the sums."""
    kept = [0] if len(dp) else []
    while kept and len(kept) < min(degree, len(dp)):
        s = apex_angle_np(dp[kept][:, None], dp, sq_l2_rows(v[kept][:, None], v)).sum(0)
        s[kept] = -np.inf
        kept.append(int(np.flatnonzero(s >= s.max() - 1e-9)[0]))
    return kept


def dispersion_lists(x: np.ndarray, cand: list[np.ndarray], degree: int, running: bool = True) -> list[np.ndarray]:
    out = []
    for p, c in enumerate(cand):
        dp = sq_l2_rows(x[p], x[c]) if len(c) else np.zeros(0)
        out.append(c[dispersion(x[c], dp, degree)[0] if running else dispersion_anew(x[c], dp, degree)])
    return out


def detours(to: np.ndarray, hop: str = "forward") -> np.ndarray:
    """(n, k) detour counts of every edge of fixed-width lists, from ranks alone: no vector is read."""
    n, k = to.shape
    out = np.zeros((n, k), np.int64)
    for i in range(n):
        row = to[i]
        ok = row >= 0
        mids = row[ok]
        if hop == "forward":  # rank of j in the middle's list
            hit = to[mids][:, :, None] == row[None, None, :]  # middle, its slot, target slot
            rank = np.where(hit.any(1), hit.argmax(1), k)  # 0-based
        else:  # rank of the middle in the target's list
            hit = to[np.where(ok, row, 0)][None, :, :] == mids[:, None, None]
            rank = np.where(hit.any(2), hit.argmax(2), k)
        at = np.arange(k)[None, :]
        mid_at = np.flatnonzero(ok)[:, None]
        out[i] = ((mid_at < at) & (rank < at)).sum(0)
        out[i, ~ok] = 0
    return out


def detour_prune(to: np.ndarray, degree: int, hop: str = "forward") -> np.ndarray:
    """(n, degree) lists by fewest detours, ties by rank."""
    c = detours(to, hop)
    c[to < 0] = np.iinfo(np.int64).max
    order = np.argsort(c, axis=1, kind="stable")[:, :degree]
    return np.take_along_axis(to, order, 1)


def detour_prune_rows(to: np.ndarray, degree: int) -> list[np.ndarray]:
    """``detour_prune`` with each edge's detours counted one by one: the original form."""
    place = [{int(w): r for r, w in enumerate(row) if w >= 0} for row in to]
    out = []
    for row in to:
        own = [int(w) for w in row if w >= 0]
        count = [sum(place[m].get(w, len(row)) < r for m in own[:r]) for r, w in enumerate(own)]
        order = sorted(range(len(own)), key=lambda r: (count[r], r))[:degree]
        out.append(np.array([own[r] for r in order], to.dtype))
    return out


def work(k: int, kernel: str) -> list[int]:
    """List positions scanned by each work unit of the detour count over a list of k: one unit a candidate (r - 1 scans), or pairs of
    candidates whose positions sum to k + 2, so that each unit scans k (half of it for a middle position alone)."""
    if kernel == "per_candidate":
        return [r - 1 for r in range(1, k + 1)]
    units: dict[int, int] = {}
    for r in range(2, k + 1):
        units[min(r, k + 2 - r)] = units.get(min(r, k + 2 - r), 0) + r - 1
    return [units[u] for u in sorted(units)]


def prune_lists(x: np.ndarray, cand: list[np.ndarray], metric: str, thres: float, degree: int, fill: bool = False, kernel: str = "wavefront", pick: str = "nearest") -> tuple[list[np.ndarray], int]:
    """Kept row numbers of each owner's candidates (nearest first). ``fill`` tops lists up with the nearest pruned ones."""
    out, tests = [], 0
    for p, c in enumerate(cand):
        c = np.asarray(c)
        dp = sq_l2_rows(x[p], x[c]) if len(c) else np.zeros(0)
        if metric == "angle" and thres == 0:
            kept, _ = dispersion(x[c], dp, degree)
            tests += len(kept) * len(c)
        else:
            kept, n = (serial if kernel == "serial" else lambda *a: wavefront(*a, pick=pick))(x[c], dp, metric, thres, degree)
            tests += n
        if fill and len(kept) < min(degree, len(c)):
            have = set(kept)
            kept = kept + [j for j in range(len(c)) if j not in have][: degree - len(kept)]
        out.append(c[kept] if len(kept) else np.zeros(0, np.int64))
    return out, tests
