"""The sampled loop on arrays: for samples within a checked bound, on the driver or, for many runs, in a task each.

Everything here works on the sample, whose size does not depend on the data's. The same steps on DataFrames are in
graph.py; tests hold both to the same states.
"""

from __future__ import annotations

import hashlib
import math
import time
from collections.abc import Iterator
from dataclasses import dataclass, field, replace

import numpy as np

from densereps.operators.stability import StopPolicy
from densereps.operators.testsize import test_size
from densereps.params import SsdcParams

BLOCK = 1 << 20
#: Ordered near pairs of vectors, or numbers and near pairs in the plane, that the arrays may hold; beyond it the sample is grown on DataFrames.
MAX_PAIRS = 1 << 26
#: Places of a table of counts by place; in the plane, where more are spanned, counts come from pairs.
MAX_TABLE = 1 << 25


def permutation(ids: np.ndarray, seed: int) -> np.ndarray:
    """Order of the ids by md5 of "seed:id", as in sampling.py."""
    return _by_md5(str(seed), ids)


def _by_md5(prefix: str, ids: np.ndarray) -> np.ndarray:
    """Order of the ids by md5 of "prefix:id", of which 16 bytes an id are held."""
    keys, step = np.empty((len(ids), 2), ">u8"), 1 << 16
    for s in range(0, len(ids), step):
        found = b"".join(hashlib.md5(f"{prefix}:{i}".encode()).digest() for i in ids[s : s + step].tolist())
        keys[s : s + step] = np.frombuffer(found, ">u8").reshape(-1, 2)
    return np.lexsort((keys[:, 1], keys[:, 0]))


def squares(a: np.ndarray, b: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Squared distances of rows i of a from rows j of b."""
    out = np.empty(len(i))
    step = max(1, BLOCK // a.shape[1])
    for k in range(0, len(i), step):
        out[k : k + step] = ((a[i[k : k + step]] - b[j[k : k + step]]) ** 2).sum(axis=1)
    return out


def all_near(a: np.ndarray, b: np.ndarray, eps: float) -> tuple[np.ndarray, np.ndarray]:
    """near_pairs() in any dimension, by blocks of all pairs."""
    out_i, out_j = [], []
    step = max(1, BLOCK // len(b))
    norm = (b * b).sum(axis=1)
    for s in range(0, len(a), step):
        part = a[s : s + step]
        size = (part * part).sum(axis=1)
        slack = 1e-9 * (size.max() + norm.max())  # products round; what they leave open is measured by differences
        i, j = np.nonzero(size[:, None] + norm[None, :] - 2 * part @ b.T <= eps * eps + slack)
        ok = squares(part, b, i, j) <= eps * eps
        out_i.append(i[ok] + s)
        out_j.append(j[ok])
    return np.concatenate(out_i), np.concatenate(out_j)


def near_pairs(a: np.ndarray, b: np.ndarray, eps: float) -> tuple[np.ndarray, np.ndarray]:
    """Rows (i of a, j of b) at most eps apart: by grid cells in up to 3 dimensions, else in blocks."""
    none = np.zeros(0, np.int64)
    if not len(a) or not len(b):
        return none, none
    if a.shape[1] > 3:
        return all_near(a, b, eps)
    parts = list(near_chunks(a, b, eps))
    return np.concatenate([none, *[i for i, _ in parts]]), np.concatenate([none, *[j for _, j in parts]])


def near_chunks(a: np.ndarray, b: np.ndarray, eps: float) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """near_pairs() in up to 3 dimensions, in pieces of bounded size."""
    if not len(a) or not len(b):
        return
    low = np.minimum(a.min(axis=0), b.min(axis=0))
    ca, cb = np.floor((a - low) / eps).astype(np.int64), np.floor((b - low) / eps).astype(np.int64)
    span = np.maximum(ca.max(axis=0), cb.max(axis=0)) + 3
    weight = np.concatenate([[1], np.cumprod(span[:-1])])
    key_b = (cb + 1) @ weight
    order = np.argsort(key_b, kind="stable")
    sorted_b = key_b[order]
    for shift in np.ndindex(*([3] * a.shape[1])):
        key = (ca + np.array(shift)) @ weight
        first, last = np.searchsorted(sorted_b, key, "left"), np.searchsorted(sorted_b, key, "right")
        sizes = last - first
        at = 0
        ends = np.cumsum(sizes)
        while at < len(a):
            stop = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + BLOCK)))
            k = sizes[at:stop]
            i = np.repeat(np.arange(at, min(stop, len(a))), k)
            j = order[np.repeat(first[at:stop], k) + np.arange(int(k.sum())) - np.repeat(np.cumsum(k) - k, k)]
            ok = ((a[i] - b[j]) ** 2).sum(axis=1) <= eps * eps
            if ok.any():
                yield i[ok], j[ok]
            at = stop


def near_counts(xs: np.ndarray, eps: float, weight: np.ndarray | None = None, at: np.ndarray | None = None) -> np.ndarray:
    """Weight of the rows at most eps from each of the rows at (all by default), which count themselves.

    Whole numbers in the plane: running sums over a table's lines give what lies within eps by two values a line, so that work
    goes with eps and not with the pairs. Rows too far apart for a table are halved until each part fits one, or has few pairs.
    Other points, and those of an eps that no table holds, go by pairs.
    """
    at = np.arange(len(xs)) if at is None else at
    weight = np.ones(len(xs), np.int64) if weight is None else weight
    out = np.zeros(len(at), np.int64)
    whole, reach = xs.shape[1] == 2 and np.issubdtype(xs.dtype, np.integer), math.floor(eps)
    parts = [(np.arange(len(at)), np.arange(len(xs)))] if len(at) else []
    while parts:
        rows, near = parts.pop()
        mine = xs[at[rows]]
        low, high = mine.min(axis=0), mine.max(axis=0)
        near = near[((xs[near] >= low - eps) & (xs[near] <= high + eps)).all(axis=1)]
        few = len(rows) < len(at) and len(rows) * len(near) <= BLOCK
        if whole and not few:
            width, height = (int(v) + 1 for v in xs[near].max(axis=0) - xs[near].min(axis=0))
            if (width + 1) * height <= MAX_TABLE:
                out[rows] = _table_counts(mine, xs[near], weight[near], eps)
                continue
            side = int((high - low).max()) + 1
            if side > reach:
                line = int((high - low).argmax())
                left = mine[:, line] < low[line] + side // 2
                parts += [(rows[left], near), (rows[~left], near)]
                continue
        for i, j in near_chunks(mine, xs[near], eps):
            out[rows] += np.bincount(i, weights=weight[near[j]], minlength=len(rows)).astype(np.int64)
    return out


def _table_counts(mine: np.ndarray, near: np.ndarray, weight: np.ndarray, eps: float) -> np.ndarray:
    """near_counts() of the rows mine, which are among those near, by one table that holds these."""
    low, square = near.min(axis=0), math.floor(eps * eps)
    width, height = (int(v) + 1 for v in near.max(axis=0) - low)
    reach, up = min(math.isqrt(square), width), min(math.isqrt(square), height - 1)
    apart = (width + reach) * height + reach <= MAX_TABLE  # lines so far apart that no part of one reaches the next
    gap = reach if apart else 0
    stride = width + gap
    flat = np.zeros(gap + height * stride + 1, np.int32 if weight.sum() < 1 << 31 else np.int64)
    np.add.at(flat, (near[:, 1] - low[1]) * stride + near[:, 0] - low[0] + gap + 1, weight.astype(flat.dtype))
    np.cumsum(flat, out=flat)
    by = np.lexsort((mine[:, 0], mine[:, 1]))  # neighbours in the table follow one another
    x, y = (mine[by] - low).T
    place, sums, step = y * stride + x + gap, np.zeros(len(by), flat.dtype), 1 << 12
    for s in range(0, len(by), step):
        lines, kept, held = y[s : s + step], None, place[:0]
        for dy in range(-up, up + 1):
            half = min(math.isqrt(square - dy * dy), width)
            a, b = (s + int(v) for v in np.searchsorted(lines, (-dy, height - dy)))  # those whose line is in the table
            if a == b:
                continue
            if apart:
                if kept != (a, b):
                    kept, held = (a, b), place[a:b] - place[a]
                first = int(place[a]) + dy * stride
                sums[a:b] += flat[first + half + 1 :].take(held, mode="clip")
                sums[a:b] -= flat[first - half :].take(held, mode="clip")
            else:
                line = (y[a:b] + dy) * stride
                sums[a:b] += flat[line + np.minimum(x[a:b] + half + 1, width)] - flat[line + np.maximum(x[a:b] - half, 0)]
    out = np.empty(len(by), np.int64)
    out[by] = sums
    return out


def _small_cells(xs: np.ndarray, eps: float) -> tuple[np.ndarray, np.ndarray, int]:
    """Cells in the plane whose rows are at most eps apart: their numbers, each row's, and the numbers' step for one in x."""
    whole = np.issubdtype(xs.dtype, np.integer)
    side = math.isqrt(math.floor(eps * eps / 2)) + 1 if whole else eps / math.sqrt(2) * (1 - 1e-9)
    c = ((xs - xs.min(axis=0)) // side).astype(np.int64)
    stride = int(c[:, 1].max()) + 5
    cells, home = np.unique(c[:, 0] * stride + c[:, 1] + 2, return_inverse=True)
    return cells, home, stride


def cell_weights(xs: np.ndarray, eps: float, weight: np.ndarray) -> np.ndarray:
    """A lower bound of near_counts(): the weight of each row's small cell."""
    cells, home, _ = _small_cells(xs, eps)
    total = np.zeros(len(cells), np.int64)
    np.add.at(total, home, weight)
    return total[home]


def linked(xs: np.ndarray, eps: float) -> np.ndarray:
    """Least row of each row's component in the plane, where rows at most eps apart are linked; without their pairs.

    Rows of one cell of side eps / sqrt(2) are linked. Of two cells side by side only the outermost row on each line can be
    the closest, so those alone meet; cells that are linked already don't.
    """
    if not len(xs):
        return np.zeros(0, np.int64)
    cells, home, stride = _small_cells(xs, eps)
    node = np.arange(len(cells))

    def outer(line: int) -> tuple:
        """Rows with the least and the greatest value on each line of a cell, by cell, and where each cell's begin."""
        by = np.lexsort((xs[:, 1 - line], xs[:, line], home))
        new = (np.diff(home[by]) != 0) | (np.diff(xs[by, line]) != 0)
        first, last = by[np.concatenate([[True], new])], by[np.concatenate([new, [True]])]
        return first, last, np.searchsorted(home[first], np.arange(len(cells) + 1))

    sides = {line: outer(line) for line in (0, 1)}
    for dx, dy in [(0, 1), (0, 2), *((dx, dy) for dx in (1, 2) for dy in (0, -1, 1, -2, 2))]:
        want = cells + dx * stride + dy
        to = np.minimum(np.searchsorted(cells, want), len(cells) - 1)
        u = np.flatnonzero((cells[to] == want) & (node != node[to]))
        first, last, begin = sides[1 if dx else 0]
        if len(u):  # where the two outermost rows this way are near, no others need to meet
            p, q = _foremost(last, xs[last] @ [dx, dy], begin)[u], _foremost(first, xs[first] @ [-dx, -dy], begin)[to[u]]
            ok = ((xs[p] - xs[q]) ** 2).sum(axis=1) <= eps * eps
            node = components(node, u[ok], to[u[ok]])
            u = u[node[u] != node[to[u]]]
        sizes = begin[u + 1] - begin[u]
        a = last[np.repeat(begin[u], sizes) + np.arange(int(sizes.sum())) - np.repeat(np.cumsum(sizes) - sizes, sizes)]
        v = np.repeat(to[u], sizes)
        counts = begin[v + 1] - begin[v]
        ends, k = np.cumsum(counts), 0
        while k < len(a):
            stop = max(k + 1, int(np.searchsorted(ends, (ends[k - 1] if k else 0) + BLOCK)))
            n = counts[k:stop]
            i = np.repeat(a[k:stop], n)
            j = first[np.repeat(begin[v[k:stop]], n) + np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)]
            ok = ((xs[i] - xs[j]) ** 2).sum(axis=1) <= eps * eps
            met = np.unique(home[i[ok]] * len(cells) + home[j[ok]])
            node = components(node, met // len(cells), met % len(cells))
            k = stop
    least = np.full(len(cells), len(xs))
    np.minimum.at(least, node[home], np.arange(len(xs)))
    return least[node[home]]


def _foremost(rows: np.ndarray, score: np.ndarray, begin: np.ndarray) -> np.ndarray:
    """The row of the greatest score in each group; groups begin at begin[:-1], and none is empty."""
    best = np.flatnonzero(score == np.repeat(np.maximum.reduceat(score, begin[:-1]), np.diff(begin)))
    return rows[best[np.searchsorted(best, begin[:-1])]]


def components(label: np.ndarray, u: np.ndarray, v: np.ndarray) -> np.ndarray:
    """Least label of each row's component under the links u-v. A label is the number of its component's least row."""
    label = label.copy()
    while True:
        a, b = label[u], label[v]
        apart = a != b
        if not apart.any():
            return label
        u, v, a, b = u[apart], v[apart], a[apart], b[apart]
        np.minimum.at(label, np.maximum(a, b), np.minimum(a, b))
        while True:
            up = label[label]
            if (up == label).all():
                break
            label = up


def canonical(ids: np.ndarray, label: np.ndarray, core: np.ndarray) -> np.ndarray:
    """Cluster of each labelled row: the least core id with the same label; -1 for label -1."""
    out = np.full(len(ids), -1, np.int64)
    real = label >= 0
    own = np.flatnonzero(core & real)
    kinds, place = np.unique(label[own], return_inverse=True)
    least = np.full(len(kinds), np.iinfo(np.int64).max)
    np.minimum.at(least, place, ids[own])
    if len(kinds):
        out[real] = least[np.searchsorted(kinds, label[real])]
    return out


def _attached(ids: np.ndarray, xs: np.ndarray, core: np.ndarray, cluster: np.ndarray, i: np.ndarray, j: np.ndarray, rule: str) -> np.ndarray:
    """cluster, known of cores, with that of borders by the rule."""
    cluster = np.where(core, cluster, -1)
    edge = ~core[i] & core[j]
    bi, bj = i[edge], j[edge]
    if rule == "nearest_core":
        key = [ids[bj], ((xs[bi] - xs[bj]) ** 2).sum(axis=1), bi]
    elif rule == "lowest_core_id":
        key = [ids[bj], bi]
    else:
        key = [cluster[bj], bi]
    by = np.lexsort(key)
    one, first = np.unique(bi[by], return_index=True)
    cluster[one] = cluster[bj[by][first]]
    return cluster


def _weakly(ids: np.ndarray, core: np.ndarray, label: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Clusters over links with one core at least; label is that of the cores, i, j the near pairs with no core at i."""
    edge = core[j]
    label = components(label, i[edge], j[edge])
    label[~core & (np.bincount(i, weights=edge, minlength=len(ids)) == 0)] = -1
    return canonical(ids, label, core)


def _named(core: np.ndarray, cluster: np.ndarray) -> np.ndarray:
    return np.where(core, "core", np.where(cluster >= 0, "border", "noise"))


class Sample:
    """A growing sample's graph: counts are added to, components of cores merged.

    In the plane no pair of cores is held: counts and components come from tables and cells, and only the few near pairs of
    rows that are no cores are sought. For vectors, near pairs are appended. Counts only grow, so while the threshold stays
    cores stay, and only links of new cores can join components; a raised threshold builds them anew.
    """

    def __init__(self, p: SsdcParams):
        self.p, self.eta, self.size, self.held = p, 0, 0, 0
        self.ids, self.xs = np.zeros(0, np.int64), None
        self.i = self.j = np.zeros(0, np.int32)
        self.n = self.label = self.cluster = np.zeros(0, np.int64)
        self.core = np.zeros(0, bool)
        self.state = np.zeros(0, "U6")

    @property
    def planar(self) -> bool:
        return self.xs.shape[1] == 2

    def _append(self, i: np.ndarray, j: np.ndarray) -> None:
        need = self.held + len(i)
        if need > MAX_PAIRS:
            raise OverflowError("the sample's near pairs outgrow the arrays")
        if need > len(self.i):
            spare = np.empty(min(MAX_PAIRS, max(need, 2 * len(self.i))) - self.held, np.int32)
            self.i, self.j = np.concatenate([self.i[: self.held], spare]), np.concatenate([self.j[: self.held], spare])
        self.i[self.held : need], self.j[self.held : need] = i, j
        self.held = need

    def add(self, ids: np.ndarray, xs: np.ndarray) -> None:
        """Points that join the sample; settle() must follow."""
        m, k = len(self.ids), len(ids)
        before = self.xs
        self.ids, self.xs = np.concatenate([self.ids, ids]), xs if before is None else np.concatenate([before, xs])
        self.n = np.concatenate([self.n, np.zeros(k, np.int64)])
        self.label = np.concatenate([self.label, np.arange(m, m + k)])
        self.core = np.concatenate([self.core, np.zeros(k, bool)])
        self.cluster = np.concatenate([self.cluster, np.full(k, -1)])
        if self.planar:
            self.n[m:] = near_counts(self.xs, self.p.eps, at=np.arange(m, m + k))
            if m and k and self.n[m:].sum() < m:  # pairs are fewer than what a table costs
                for _, j in near_chunks(xs, before, self.p.eps):
                    self.n[:m] += np.bincount(j, minlength=m)
            elif m and k:
                new = (np.arange(m + k) >= m).astype(np.int64)
                self.n[:m] += near_counts(self.xs, self.p.eps, new, np.arange(m))
        else:
            c, d = near_pairs(xs, xs, self.p.eps)
            gained = [(c + m, d + m)]
            if m:
                a, b = near_pairs(xs, before, self.p.eps)
                gained += [(a + m, b), (b, a + m)]
            for i, j in gained:
                self._append(i, j)
                self.n += np.bincount(i, minlength=m + k)
        self.size = int(self.n.sum())

    def _loose(self, core: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Near pairs (i, j) with no core at i; each i has fewer than the threshold."""
        if self.planar:
            rows = np.flatnonzero(~core)
            i, j = near_pairs(self.xs[rows], self.xs, self.p.eps)
            return rows[i], j
        i, j = self.i[: self.held], self.j[: self.held]
        loose = ~core[i]
        return i[loose], j[loose]

    def _components(self, core: np.ndarray, fresh: np.ndarray) -> np.ndarray:
        """Least row of each core's component."""
        if self.planar:
            label, rows = np.arange(len(core)), np.flatnonzero(core)
            label[rows] = rows[linked(self.xs[rows], self.p.eps)]
            return label
        i, j = self.i[: self.held], self.j[: self.held]
        anew = bool((self.core & ~core).any())
        touched = (core if anew else fresh)[i] & core[j]
        return components(np.arange(len(core)) if anew else self.label, i[touched], j[touched])

    def settle(self, eta: int) -> None:
        """States and clusters at this threshold."""
        p, core = self.p, self.n >= eta
        fresh = core & ~self.core
        self.label = self._components(core, fresh)
        i, j = self._loose(core)
        if self.planar and 3 * len(core) + len(i) > MAX_PAIRS:
            raise OverflowError("the sample outgrows the arrays")
        before, inserted = self.cluster, eta == self.eta
        self.core, self.eta = core, eta
        if p.weak_edges == "connect":
            self.cluster = _weakly(self.ids, core, self.label, i, j)
        else:
            cluster = canonical(self.ids, np.where(core, self.label, -1), core)
            if p.keeps_merges:
                cluster = _only_merges(before, cluster, core)
            self.cluster = _attached(self.ids, self.xs, core, cluster, i, j, p.border_rule)
            if p.merge_on == "any" and inserted:
                met = fresh[j] & (self.cluster[i] >= 0)
                self.cluster = _joined(self.cluster, self.cluster[j[met]], self.cluster[i[met]])
        self.state = _named(core, self.cluster)


def _joined(cluster: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """cluster with the clusters a and b, pair by pair, made one; the least id stays."""
    kinds, place = np.unique(cluster, return_inverse=True)
    label = components(np.arange(len(kinds)), np.searchsorted(kinds, a), np.searchsorted(kinds, b))
    return kinds[label][place]


def next_eta(ids: np.ndarray, n: np.ndarray, eta: int, p: SsdcParams) -> int:
    """The threshold for a sample with these neighbour counts."""
    if p.eta_rule == "fixed":
        return p.min_pts
    if p.eta_rule == "plus_one":
        return min(p.min_pts, eta + 1)
    order = _by_md5("eta", ids)
    mean = float(np.mean(n[order[: max(1, math.ceil(p.eim_fraction * len(ids)))]]))
    guess = math.floor(mean + 0.5)
    if p.eta_rule == "printed":
        return guess if mean <= p.min_pts else eta + 1
    return min(p.min_pts, max(eta + 1, guess)) if mean <= p.min_pts else min(p.min_pts, eta + 1)


def select_representatives(cluster: np.ndarray, state: np.ndarray, n: np.ndarray, tau: float, selector: str = "rim_and_center") -> np.ndarray:
    """Rows of the representatives: cores at most tau as dense as their cluster's densest, and the densest."""
    core = np.flatnonzero(state == "core")
    kinds, place = np.unique(cluster[core], return_inverse=True)
    top = np.zeros(len(kinds), np.int64)
    np.maximum.at(top, place, n[core])
    ratio = n[core] / top[place]
    center, rim = n[core] == top[place], ratio <= tau
    keep = {"all_core": np.ones(len(core), bool), "center_only": center, "rim_only": rim, "rim_and_center": center | rim}[selector]
    return core[keep]


def nearest(
    xs: np.ndarray, reps: np.ndarray, rep_ids: np.ndarray, cluster: np.ndarray, max_distance: float | None = None, reach: float | None = None
) -> np.ndarray:
    """Cluster of the nearest representative; ties go to the smaller id; -1 without any or beyond max_distance.

    reach: a distance at which most points have a representative. In up to 3 dimensions cells of at most that side find it,
    and are doubled for the points without any.
    """
    if not len(reps):
        return np.full(len(xs), -1, np.int64)
    order = np.argsort(rep_ids, kind="stable")
    if reach and xs.shape[1] == 2 and len(xs) and len(reps) > 64 and all(np.issubdtype(v.dtype, np.integer) for v in (xs, reps)):
        found = _nearest_by_lines(xs, reps[order])
        if found is not None:
            label = cluster[order][found[0]]
            return label if max_distance is None else np.where(found[1] <= max_distance**2, label, -1)
    reps, cluster = reps[order].astype(np.float64), cluster[order]
    out, far = np.full(len(xs), -1, np.int64), np.arange(len(xs))
    if reach and reps.shape[1] <= 3 and len(reps) > 64:
        spread = np.prod(np.maximum(reps.max(axis=0) - reps.min(axis=0), 1.0)) / len(reps)
        side, step = min(float(reach), 2 * spread ** (1 / reps.shape[1])), 1 << 16
        while len(far):
            for s in range(0, len(far), step):
                at = far[s : s + step]
                part = xs[at].astype(np.float64)
                i, j = near_pairs(part, reps, side)
                by = np.lexsort((j, squares(part, reps, i, j), i))
                one, first = np.unique(i[by], return_index=True)
                out[at[one]] = j[by][first]
            far, side = far[out[far] < 0], 2 * side
    step = max(1, BLOCK // len(reps))
    for s in range(0, len(far), step):
        part = xs[far[s : s + step]].astype(np.float64)
        if part.shape[1] <= 3:
            best = sum((part[:, k, None] - reps[None, :, k]) ** 2 for k in range(part.shape[1])).argmin(axis=1)
        else:
            size, norm = (part * part).sum(axis=1), (reps * reps).sum(axis=1)
            d2 = size[:, None] + norm[None, :] - 2 * part @ reps.T
            slack = 2e-9 * (size.max() + norm.max())  # products round; what they leave open is measured by differences
            i, j = np.nonzero(d2 <= d2.min(axis=1)[:, None] + slack)
            by = np.lexsort((j, squares(part, reps, i, j), i))
            best = j[by][np.unique(i[by], return_index=True)[1]]
        out[far[s : s + step]] = best
    if max_distance is None:
        return cluster[out]
    d2 = squares(xs.astype(np.float64), reps, np.arange(len(xs)), out)
    return np.where(d2 <= max_distance**2, cluster[out], -1)


def _nearest_by_lines(xs: np.ndarray, reps: np.ndarray) -> tuple[np.ndarray, np.ndarray] | None:
    """The nearest of reps to each row, the first of equals, and its squared distance; whole numbers in the plane.

    On a line of equal x only the rep above a row and the one below can be the nearest. Lines are visited outwards from the
    row's own, until the next is farther than what is found; so work goes with the lines up to there, and not with the pairs.
    A squared distance and a rep are one number, the least of which is sought; None where 63 bits don't hold it.
    """
    low, high = np.minimum(xs.min(axis=0), reps.min(axis=0)), np.maximum(xs.max(axis=0), reps.max(axis=0))
    shift, stride = len(reps).bit_length(), int(high[1] - low[1]) + 1
    if sum(int(v) ** 2 for v in high - low) >> (62 - shift):
        return None
    by = np.lexsort((np.arange(len(reps)), reps[:, 1], reps[:, 0]))
    by = by[np.concatenate([[True], (np.diff(reps[by], axis=0) != 0).any(axis=1)])]  # the first on each place
    lines, home = np.unique(reps[by, 0], return_inverse=True)
    heights = reps[by, 1] - low[1]
    key, begin = home * stride + heights, np.searchsorted(home, np.arange(len(lines) + 1))

    def either(above: np.ndarray, line: np.ndarray, y: np.ndarray) -> np.ndarray:
        """The lesser number of the rep at above or the next, and the one before it, where they are on the line."""
        up, down = np.minimum(above, begin[line + 1] - 1), np.maximum(above - 1, begin[line])  # another of the line is no nearer
        return np.minimum(((heights[up] - y) ** 2 << shift) + by[up], ((heights[down] - y) ** 2 << shift) + by[down])

    table = None
    if len(lines) * stride <= min(MAX_TABLE, 64 * len(xs)):  # many rows: the numbers of all places of the lines
        table, every = np.empty(len(lines) * stride, np.int64), np.arange(stride)
        for i in range(len(lines)):
            own = heights[begin[i] : begin[i + 1]]
            above = begin[i] + np.repeat(np.arange(len(own) + 1), np.diff(np.concatenate([[-1], own, [stride - 1]])))
            table[i * stride : (i + 1) * stride] = either(above, np.full(1, i), every)
    out = np.full(len(xs), np.iinfo(np.int64).max)
    order, step = np.lexsort((xs[:, 1], xs[:, 0])), 1 << 14
    for s in range(0, len(xs), step):
        rows = order[s : s + step]
        x, y, best = xs[rows, 0], xs[rows, 1] - low[1], out[rows]
        mid = np.searchsorted(lines, x)
        for first, last in ((0, 8), (8, 32), (32, 128), (128, len(lines))):  # both ways in turn: what one finds ends the other
            for way in (1, -1):
                at, line = np.arange(len(rows)), mid + first if way > 0 else mid - 1 - first
                px, py, least = x, y, best.copy()
                for _ in range(first, last):
                    real = (line >= 0) & (line < len(lines))
                    off = (lines[np.clip(line, 0, len(lines) - 1)] - px) ** 2 << shift
                    real &= off <= least  # as far can be an equal that comes first
                    if not real.all():
                        best[at] = least
                        at, line, px, py, least, off = (v[real] for v in (at, line, px, py, least, off))
                        if not len(at):
                            break
                    met = table.take(line * stride + py) if table is not None else either(np.searchsorted(key, line * stride + py), line, py)
                    np.minimum(least, met + off, out=least)
                    line = line + way
                best[at] = least
        out[rows] = best
    return out & ((1 << shift) - 1), out >> shift


def disagreement(a: np.ndarray, b: np.ndarray) -> float:
    """Share of pairs that one labelling joins and the other parts."""
    m = len(a)
    if m < 2:
        return 0.0
    pairs = lambda x: float(sum(c * (c - 1) // 2 for c in np.unique(x, return_counts=True)[1].tolist()))
    _, ca = np.unique(a, return_inverse=True)
    _, cb = np.unique(b, return_inverse=True)
    return (pairs(ca) + pairs(cb) - 2 * pairs(ca.astype(np.int64) * m + cb)) / (m * (m - 1) / 2)


@dataclass
class Fit:
    """What a run leaves: the sample in order of drawing with its states, the test ids, and the trace."""

    ids: np.ndarray
    xs: np.ndarray
    n: np.ndarray
    state: np.ndarray
    cluster: np.ndarray
    reps: np.ndarray
    test_ids: np.ndarray
    eta: int
    reason: str
    trace: list[dict] = field(default_factory=list)
    history: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = field(default_factory=list)


def run(draw, n_total: int, p: SsdcParams, keep_history: bool = False) -> Fit:
    """The sampled loop. draw(a, b): (ids, points) at the places a to b - 1 of the permutation."""
    p.validate()
    began = time.time()
    gamma = min(p.gamma, n_total)
    sample = Sample(p)
    sample.add(*draw(0, gamma))
    used = queries = gamma
    eta = next_eta(sample.ids, sample.n, 1, p)
    sample.settle(eta)
    history = [(sample.ids, sample.state, sample.cluster)] if keep_history else []

    def reps() -> np.ndarray:
        return select_representatives(sample.cluster, sample.state, sample.n, p.tau, p.selector)

    def label(points: np.ndarray) -> np.ndarray:
        r = reps()
        return nearest(points, sample.xs[r], sample.ids[r], sample.cluster[r], p.max_distance, p.eps)

    def size(k: int) -> int:
        return test_size(n_total, max(1, k), rectify_n=p.rectify_n, rectify_k=p.rectify_k)

    def clusters() -> int:
        return len(np.unique(sample.cluster[sample.cluster >= 0]))

    k = clusters()
    t_ids, t_xs = draw(used, min(n_total, used + size(k)))
    used += len(t_ids)
    before = label(t_xs)
    trace: list[dict] = []

    def log(iteration: int, delta: float | None) -> None:
        counts = {s: int((sample.state == s).sum()) for s in ("core", "border", "noise")}
        trace.append(
            {"iteration": iteration, "eta": eta, "n_sample": len(sample.ids), "n_test": len(t_ids), "k": k, "n_reps": len(reps()), "delta": delta,
             "n_core": counts["core"], "n_border": counts["border"], "n_noise": counts["noise"], "n_range_queries": queries,
             "n_pairs": sample.size, "seconds": time.time() - began}
        )

    log(0, None)
    iteration, reason = 0, "exhausted"
    policy = StopPolicy(p.min_pts, force_full_minpts=p.force_full_minpts, max_iterations=p.max_iterations)
    while used < n_total and iteration < p.max_iterations:
        iteration += 1
        new_ids, new_xs = draw(used, min(n_total, used + p.beta))
        used += len(new_ids)
        if eta < p.min_pts:
            eta = next_eta(sample.ids, sample.n, eta, p)
            if p.keeps_merges and eta != sample.eta:
                sample.settle(eta)
        sample.add(new_ids, new_xs)
        queries += len(new_ids)
        sample.settle(eta)
        if keep_history:
            history.append((sample.ids, sample.state, sample.cluster))
        k = clusters()
        after = label(t_xs)
        delta = disagreement(before, after)
        more = size(k) - len(t_ids)
        if 0 < more <= n_total - used:
            grown, grown_xs = draw(used, used + more)
            used += more
            t_ids, t_xs = np.concatenate([t_ids, grown]), np.concatenate([t_xs, grown_xs])
            after = np.concatenate([after, label(grown_xs)])
        before = after
        log(iteration, delta)
        why, raised = policy.after(iteration, delta if k >= p.min_clusters else 1.0, eta, n_total - used)
        if raised != eta:
            eta = raised
            sample.settle(eta)
        if why:
            reason = "all_noise" if why == "stable" and not k else why
            break
    else:
        reason = "max_iterations" if used < n_total else "exhausted"
    if p.finalize_eta and eta < p.min_pts:
        eta = p.min_pts
        sample.settle(eta)
    return Fit(sample.ids, sample.xs, sample.n, sample.state, sample.cluster, reps(), t_ids, eta, reason, trace, history)


def _only_merges(old: np.ndarray, new: np.ndarray, core: np.ndarray) -> np.ndarray:
    """Clusters of cores, coarsened so that no old cluster's surviving cores part."""
    live = np.flatnonzero((old >= 0) & core)
    by = live[np.argsort(old[live], kind="stable")]
    same = old[by][1:] == old[by][:-1]
    return _joined(new, new[by[:-1][same]], new[by[1:][same]])


def exact(ids: np.ndarray, xs: np.ndarray, p: SsdcParams) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(counts, state, cluster) of all points at min_pts."""
    sample = Sample(replace(p, relabel="graph", merge_on="core"))
    sample.add(ids, xs)
    sample.settle(p.min_pts)
    return sample.n, sample.state, sample.cluster


def mutual_information(a: np.ndarray, b: np.ndarray, average: str = "geometric") -> float:
    """Normalised mutual information of two labellings; noise is one class."""
    n = len(a)
    _, ca = np.unique(a, return_inverse=True)
    _, cb = np.unique(b, return_inverse=True)
    entropy = lambda c: -float(sum(x / n * math.log(x / n) for x in np.bincount(c) if x))
    ha, hb = entropy(ca), entropy(cb)
    hab = entropy(np.unique(ca.astype(np.int64) * (cb.max() + 1) + cb, return_inverse=True)[1])
    scale = {"geometric": math.sqrt(ha * hb), "arithmetic": (ha + hb) / 2, "max": max(ha, hb), "min": min(ha, hb)}[average]
    return (ha + hb - hab) / scale if scale else float(ha == hb)
