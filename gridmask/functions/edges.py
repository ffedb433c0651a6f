"""Bin edges: equi-depth, weighted, v-optimal, and the reduction of a node's child bounds to few bins.

Edges e_0 < ... < e_B delimit B bins [e_k, e_k+1), the last one closed. Everything here works on one chunk's or one
node's numbers, which are few; the DataFrame side calls it once for each group.
"""

from __future__ import annotations

import heapq
from bisect import bisect_left

import numpy as np


def equi_depth(values: np.ndarray, bins: int) -> tuple[np.ndarray, np.ndarray]:
    """Edges at order statistics of the sorted values, equal values never apart; and the bins' counts."""
    n = len(values)
    starts = values[(np.arange(bins) * n) // bins]
    edges = np.unique(np.concatenate([starts, values[-1:]]))
    return edges, bin_counts(values, edges)


def equi_width(values: np.ndarray, bins: int) -> tuple[np.ndarray, np.ndarray]:
    edges = np.unique(np.linspace(values[0], values[-1], bins + 1))
    return edges, bin_counts(values, edges)


def weighted_equi_depth(values: np.ndarray, weights: np.ndarray, bins: int) -> tuple[np.ndarray, np.ndarray]:
    """Edges at equal shares of the weight, for instance of how often queries ask for a value."""
    total = np.cumsum(weights)
    at = np.searchsorted(total, np.arange(bins) * total[-1] / bins, side="right")
    edges = np.unique(np.concatenate([values[np.minimum(at, len(values) - 1)], values[:1], values[-1:]]))
    return edges, bin_counts(values, edges)


def bin_counts(values: np.ndarray, edges: np.ndarray) -> np.ndarray:
    """Values in each bin; with one edge there is one bin, of that value."""
    bins = max(1, len(edges) - 1)
    at = np.clip(np.searchsorted(edges, values, side="right") - 1, 0, bins - 1)
    return np.bincount(at, minlength=bins).astype(float)


def v_optimal(values: np.ndarray, freq: np.ndarray, bins: int) -> tuple[np.ndarray, float]:
    """Edges over distinct values that make the frequencies within bins vary least, and that variance."""
    k, bins = len(values), min(bins, len(values))
    s = np.concatenate([[0], np.cumsum(freq)])
    q = np.concatenate([[0], np.cumsum(np.square(freq, dtype=float))])

    at = np.arange(k + 1)
    best = np.full((bins + 1, k + 1), np.inf)  # of bins 1.. over the first j frequencies
    best[1, 1:] = q[1:] - s[1:] ** 2 / at[1:]
    back = np.zeros((bins + 1, k + 1), int)
    for first in range(2, k + 1, 64):  # ends of the last bin, some at a time; its beginnings are all before them
        j, i = at[first : first + 64, None], at[None, : min(first + 64, k + 1) - 1]
        # summed squared deviations of freq[i:j]
        spread = np.where(i < j, q[j] - q[i] - (s[j] - s[i]) ** 2 / np.maximum(j - i, 1), np.inf)
        for b in range(2, bins + 1):
            last = slice(None) if b < bins else slice(-1, None) if j[-1, 0] == k else slice(0)  # of all bins only the whole is asked for
            cost = best[b - 1, i] + spread[last]
            if len(cost):
                m = np.argmin(cost, axis=1)
                back[b, j[last, 0]], best[b, j[last, 0]] = m, cost[np.arange(len(m)), m]
    cuts, j = [], k
    for b in range(bins, 1, -1):
        j = back[b, j]
        cuts.append(j)
    return np.unique(np.concatenate([values[:1], values[sorted(cuts)], values[-1:]])), float(best[bins, k])


def v_optimal_within(edges: np.ndarray, weights: np.ndarray, bins: int, model: str = "uniform", points: int = 8) -> np.ndarray:
    """V-optimal edges when only child bins are known: their mass is spread evenly or bell-shaped over `points` places."""
    t = (np.arange(points) + 0.5) / points
    share = np.full(points, 1 / points) if model == "uniform" else np.exp(-0.5 * ((t - 0.5) / 0.2) ** 2)
    share = share / share.sum()
    freq = np.outer(weights, share).ravel()
    where = (edges[:-1, None] + np.diff(edges)[:, None] * t).ravel()
    cuts, _ = v_optimal(where, freq, bins)
    inner = edges[np.clip(np.searchsorted(edges, cuts[1:-1]), 0, len(edges) - 1)]
    return np.unique(np.concatenate([edges[:1], inner, edges[-1:]]))


# ---- reduction of edges in a parent node ------------------------------------------------------------------------


def spread_mass(edges: np.ndarray, children: list[tuple[np.ndarray, np.ndarray]]) -> np.ndarray:
    """Mass of all children in each interval between edges: a child's bin gives each interval its share of overlap."""
    if len(edges) < 2:
        return np.array([sum(float(w.sum()) for _, w in children)])
    out = np.zeros(len(edges) - 1)
    for e, w in children:
        if len(e) < 2:  # all mass at one value
            out[min(int(np.searchsorted(edges, e[0], side="right")) - 1, len(out) - 1)] += w.sum()
        else:
            out += np.diff(np.interp(edges, e, np.concatenate([[0], np.cumsum(w)])))
    return out


def merged_mass(edges: np.ndarray, mass: np.ndarray, kept: np.ndarray) -> np.ndarray:
    at = np.searchsorted(edges, kept)
    total = np.concatenate([[0], np.cumsum(mass)])
    return np.diff(total[at]) if len(at) > 1 else np.array([total[-1]])


def wsse(mass: np.ndarray, bins: int) -> float:
    """Summed squared deviation of the bins' mass from an equal share."""
    return float(((mass - mass.sum() / bins) ** 2).sum())


def reduce_equi_width(edges: np.ndarray, bins: int) -> np.ndarray:
    """At most `bins` bins: evenly spaced cuts, each moved to the nearest edge; edges stay a subset."""
    if len(edges) <= bins + 1:
        return edges
    ideal = np.linspace(edges[0], edges[-1], bins + 1)[1:-1]
    right = np.clip(np.searchsorted(edges, ideal), 1, len(edges) - 1)
    left = right - 1
    near = np.where(ideal - edges[left] <= edges[right] - ideal, left, right)
    return edges[np.unique(np.concatenate([[0], near, [len(edges) - 1]]))]


def _middle(total: list[float], a: int, b: int) -> int:
    """The inner edge that parts the bin from a to b most evenly, the first of several: totals ascend."""
    half = (total[a] + total[b]) / 2
    i = bisect_left(total, half, a + 1, b)
    if i == b or i > a + 1 and half - total[i - 1] <= total[i] - half:
        i = bisect_left(total, total[i - 1], a + 1, i - 1)
    return i


def _fill(total: list[float], kept: list[int], bins: int) -> list[int]:
    """Split the heaviest splittable bins until there are `bins` of them."""
    kept = sorted(kept)
    while len(kept) < bins + 1:
        options = [(total[a] - total[b], k) for k, (a, b) in enumerate(zip(kept, kept[1:])) if b - a > 1]
        if not options:
            break
        k = min(options)[1]
        kept.insert(k + 1, _middle(total, kept[k], kept[k + 1]))
    return kept


class _Exchange:
    """Bins over numbered edges, with a queue of splits by what they gain and one of merges by what they cost.

    Queue entries name the bins they change; an entry whose bins are gone is dropped when it comes up.
    """

    def __init__(self, total: list[float], kept: list[int], bins: int) -> None:
        self.total, self.share = total, total[-1] / bins
        self.after = dict(zip(kept, kept[1:]))
        self.before = dict(zip(kept[1:], kept))
        self.splits: list[tuple[float, int, int, int]] = []
        self.merges: list[tuple[float, int, int, int]] = []
        for a in kept[:-1]:
            self.offer_split(a)
        for m in kept[1:-1]:
            self.offer_merge(m)

    def error(self, i, j):
        return (self.total[j] - self.total[i] - self.share) ** 2

    def offer_split(self, a: int) -> None:
        b = self.after[a]
        if b - a > 1:
            m = _middle(self.total, a, b)  # both squares together are least where both masses are most alike
            heapq.heappush(self.splits, (self.error(a, m) + self.error(m, b) - self.error(a, b), a, m, b))

    def offer_merge(self, m: int) -> None:
        a, b = self.before.get(m), self.after.get(m)
        if a is not None and b is not None:
            heapq.heappush(self.merges, (self.error(a, b) - self.error(a, m) - self.error(m, b), a, m, b))

    def best(self, queue: list, ok) -> tuple | None:
        """The first entry of a queue that still holds and is ok; others that hold stay in it."""
        aside, found = [], None
        while queue:
            entry = heapq.heappop(queue)
            _, a, m, b = entry
            holds = self.after.get(a) == b if queue is self.splits else self.after.get(a) == m and self.after.get(m) == b
            if not holds:
                continue
            aside.append(entry)
            if ok(entry):
                found = entry
                break
        for entry in aside:
            heapq.heappush(queue, entry)
        return found

    def step(self) -> bool:
        """Make the split and the merge, on bins apart from each other, that together lower the error most."""
        any_ = lambda e: True
        apart = lambda s, m: s[1] not in (m[1], m[2])
        s, m = self.best(self.splits, any_), self.best(self.merges, any_)
        if s is None or m is None:
            return False
        pairs = [(s, m)] if apart(s, m) else [(s, self.best(self.merges, lambda e: apart(s, e))), (self.best(self.splits, lambda e: apart(e, m)), m)]
        pairs = [p for p in pairs if None not in p]
        if not pairs:
            return False
        s, m = min(pairs, key=lambda p: p[0][0] + p[1][0])
        if s[0] + m[0] >= -1e-9 * (1 + self.share**2):
            return False
        _, a, e, b = s
        self.after |= {a: e, e: b}
        self.before |= {e: a, b: e}
        _, left, gone, right = m
        del self.after[gone], self.before[gone]
        self.after[left], self.before[right] = right, left
        for x in {a, e, left}:
            self.offer_split(x)
        for x in {a, e, b, left, right}:
            self.offer_merge(x)
        return True


def _begin(edges: np.ndarray, total: list[float], bins: int) -> list[int]:
    """Numbers of the edges that the exchange begins with: the equi-width cuts, heaviest bins split until all are used."""
    return _fill(total, np.searchsorted(edges, reduce_equi_width(edges, bins)).tolist(), bins)


def begin_equi_depth(edges: np.ndarray, mass: np.ndarray, bins: int) -> np.ndarray:
    """The edges that reduce_equi_depth begins its exchange with."""
    return edges[_begin(edges, [0.0, *np.cumsum(mass).tolist()], bins)]


def reduce_equi_depth(edges: np.ndarray, mass: np.ndarray, bins: int) -> np.ndarray:
    """Nearly equi-depth bins by local exchange: from the equi-width bins on, the split that helps most and the merge
    that hurts least are made together as long as the total error falls. The error falls each time, so this ends."""
    if len(edges) <= bins + 1:
        return edges
    total = [0.0, *np.cumsum(mass).tolist()]
    work = _Exchange(total, _begin(edges, total, bins), bins)
    while work.step():
        pass
    return edges[sorted({0, *work.after, *work.after.values()})]


def reduce_equi_depth_many(edges: np.ndarray, n_edges: np.ndarray, mass: np.ndarray, bins: int) -> np.ndarray:
    """reduce_equi_depth for many rows at once, each of more than bins + 1 edges: rows of edges are filled up with infinity,
    those of masses with 0. All rows take their exchanges side by side; each ends as it would alone."""
    rows, last = np.arange(len(edges))[:, None], n_edges[:, None] - 1
    total = np.concatenate([np.zeros((len(edges), 1)), np.cumsum(mass, axis=1)], axis=1)
    share = total[:, -1:] / bins

    def place(of: np.ndarray, table: np.ndarray, x: np.ndarray) -> np.ndarray:
        """bisect_left of each row's numbers in its row of the table."""
        return (table[of[:, 0]][:, None, :] < x[:, :, None]).sum(axis=2)

    def middle(of: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        half = (total[of, a] + total[of, b]) / 2
        i = np.maximum(np.minimum(place(of, total, half), b), a + 1)
        back = (i >= b) | (i > a + 1) & (half - total[of, i - 1] <= total[of, np.minimum(i, last[of[:, 0]])] - half)
        return np.where(back, np.maximum(np.minimum(place(of, total, total[of, i - 1]), i - 1), a + 1), i)

    def error(of: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
        return (total[of, j] - total[of, i] - share[of[:, 0]]) ** 2

    # evenly spaced cuts at the nearest edges; what falls together is split again where most mass lies
    ideal = np.linspace(edges[:, 0], edges[rows[:, 0], last[:, 0]], bins + 1, axis=1)[:, 1:-1]
    right = np.clip(place(rows, edges, ideal), 1, last)
    near = np.where(ideal - edges[rows, right - 1] <= edges[rows, right] - ideal, right - 1, right)
    kept = np.sort(np.concatenate([np.zeros_like(last), near, last], axis=1), axis=1)
    kept = np.sort(np.where(np.diff(kept, axis=1, prepend=-1) == 0, last, kept), axis=1)
    while len(of := np.flatnonzero(kept[:, -2] == last[:, 0])):
        of = of[:, None]
        a, b = kept[of[:, 0], :-1], kept[of[:, 0], 1:]
        k = np.argmin(np.where(b - a > 1, total[of, a] - total[of, b], np.inf), axis=1)[:, None]
        kept[of[:, 0], -2] = middle(of, np.take_along_axis(a, k, 1), np.take_along_axis(b, k, 1))[:, 0]
        kept[of[:, 0]] = np.sort(kept[of[:, 0]], axis=1)
    of = rows
    while len(of):
        k = kept[of[:, 0]]
        a, b = k[:, :-1], k[:, 1:]
        wide = b - a > 1
        m = np.where(wide, middle(of, a, np.where(wide, b, a + 1)), a)
        gain = np.where(wide, error(of, a, m) + error(of, m, b) - error(of, a, b), np.inf)
        cost = error(of, k[:, :-2], k[:, 2:]) - error(of, k[:, :-2], k[:, 1:-1]) - error(of, k[:, 1:-1], k[:, 2:])
        s, j = np.argmin(gain, axis=1)[:, None], np.argmin(cost, axis=1)[:, None]
        best = lambda table, at: np.take_along_axis(table, at, 1)
        # a split and a merge of the same bin exclude each other: the better of either with the best that goes with it
        bins_, merges = np.arange(bins)[None], np.arange(bins - 1)[None]
        other_cost = np.where((merges == s) | (merges == s - 1), np.inf, cost)
        other_gain = np.where((bins_ == j) | (bins_ == j + 1), np.inf, gain)
        j2, s2 = np.argmin(other_cost, axis=1)[:, None], np.argmin(other_gain, axis=1)[:, None]
        clash = (s == j) | (s == j + 1)
        first, second = best(gain, s) + best(other_cost, j2), best(other_gain, s2) + best(cost, j)
        s, j = np.where(clash & (second < first), s2, s), np.where(clash & (first <= second), j2, j)
        change = np.where(clash, np.minimum(first, second), best(gain, s) + best(cost, j))
        go = (change < -1e-9 * (1 + share[of[:, 0]] ** 2))[:, 0]
        of, k = of[go], k[go]
        np.put_along_axis(k, j[go] + 1, best(m, s)[go], 1)
        kept[of[:, 0]] = np.sort(k, axis=1)
    return kept


def reduce_optimal(edges: np.ndarray, mass: np.ndarray, bins: int) -> np.ndarray:
    """The least error with exactly min(bins, all) bins, by dynamic programming; the yardstick for the exchange."""
    k = len(edges) - 1
    if k <= bins:
        return edges
    total = np.concatenate([[0], np.cumsum(mass)])
    share = total[-1] / bins
    best = (total - share) ** 2
    best[0] = np.inf
    back = np.zeros((bins + 1, k + 1), int)
    for b in range(2, bins + 1):
        nxt = np.full(k + 1, np.inf)
        for j in range(b, k + 1):
            cost = best[b - 1 : j] + (total[j] - total[b - 1 : j] - share) ** 2
            m = int(np.argmin(cost))
            nxt[j], back[b, j] = cost[m], b - 1 + m
        best = nxt
    kept, j = [k], k
    for b in range(bins, 1, -1):
        j = back[b, j]
        kept.append(j)
    return edges[sorted([0, *kept])]


def reduce_by_sign(starts: np.ndarray, ends: np.ndarray, edges: np.ndarray, mass: np.ndarray, bins: int) -> np.ndarray:
    """Starts and ends of children reduced apart, half the bins each, and put together."""
    out = [edges[:1], edges[-1:]]
    for own in (np.unique(starts), np.unique(ends)):
        own = np.unique(np.concatenate([edges[:1], own, edges[-1:]]))
        out.append(reduce_equi_depth(own, merged_mass(edges, mass, own), max(1, bins // 2)))
    return np.unique(np.concatenate(out))


REDUCE = {
    "equi_width": lambda e, m, b: reduce_equi_width(e, b),
    "equi_depth": reduce_equi_depth,
    "optimal": reduce_optimal,
    "v_uniform": lambda e, m, b: v_optimal_within(e, m, b) if len(e) > b + 1 else e,
    "v_normal": lambda e, m, b: v_optimal_within(e, m, b, "normal") if len(e) > b + 1 else e,
}
