"""Tree building and searching on arrays; no Spark here.

A tree is built over an array of points (n x D, doubles). Splits send x < value to the left. Every node keeps the tight box
of its points. Answers are the k smallest by (squared distance, id); distances are summed dimension by dimension, from
left to right, and so are the lower bounds of boxes, so that rounding never lifts a bound above a distance inside its box.
"""

from __future__ import annotations

import heapq
from dataclasses import dataclass

import numpy as np

NO_ID = np.iinfo(np.int64).max
DIM_RULES, VALUE_RULES = ("variance", "variance_full", "range", "cycle"), ("hist", "exact", "first100", "midrange", "sketch")


@dataclass(frozen=True)
class SplitPolicy:
    """How a node chooses its dimension and its value; sample sizes of the whole tree and of a cell's own."""

    dim_rule: str = "variance"
    value_rule: str = "hist"
    sample_per_part: int = 256
    local_sample: int = 1024
    two_level: bool = False  # numpy's binary search is the faster of the two lookups (exp_bin_lookups)
    min_balance: float = 0.3
    stride: int = 32

    def __post_init__(self) -> None:
        if self.dim_rule not in DIM_RULES or self.value_rule not in VALUE_RULES:
            raise ValueError(f"unknown rule: {self.dim_rule}, {self.value_rule}")

    @classmethod
    def vfm(cls) -> SplitPolicy:
        """Variance for the dimension, mean of the first hundred values."""
        return cls("variance", "first100")

    @classmethod
    def brm(cls) -> SplitPolicy:
        """Extent for the dimension, middle of the range."""
        return cls("range", "midrange")


# ---- bins ----------------------------------------------------------------------------------------------------------


def bin_binary(values: np.ndarray, edges: np.ndarray) -> np.ndarray:
    """Number of sorted edges that are at most the value, by binary search."""
    return np.searchsorted(edges, values, side="right")


def bin_two_level(values: np.ndarray, edges: np.ndarray, stride: int = 32) -> np.ndarray:
    """The same number: first by a coarse array of every stride-th edge, then inside one run of stride edges."""
    coarse = edges[::stride]
    run = np.maximum(np.searchsorted(coarse, values, side="right") - 1, 0)
    padded = np.concatenate([edges, np.full(-len(edges) % stride, np.inf)]).reshape(-1, stride)
    out = np.empty(len(values), dtype=np.int64)
    for at in range(0, len(values), 1 << 15):
        r = run[at : at + (1 << 15)]
        out[at : at + len(r)] = r * stride + (padded[r] <= values[at : at + len(r), None]).sum(axis=1)
    return out


def histogram(values: np.ndarray, edges: np.ndarray, two_level: bool = True, stride: int = 32) -> np.ndarray:
    """Counts of values in the len(edges) + 1 bins that the edges bound."""
    at = bin_two_level(values, edges, stride) if two_level and len(edges) > 2 * stride else bin_binary(values, edges)
    return np.bincount(at, minlength=len(edges) + 1)


def edge_nearest(edges: np.ndarray, counts: np.ndarray, share: float = 0.5) -> tuple[float, float] | None:
    """(edge, share of the values below it) nearest to the wanted share; ties go to the smaller edge, empty sides are out."""
    below = np.cumsum(counts)[:-1]
    total = int(counts.sum())
    ok = np.flatnonzero((below > 0) & (below < total))
    if not len(ok):
        return None
    k = ok[np.argmin(np.abs(below[ok] / total - share))]
    return float(edges[k]), float(below[k] / total)


# ---- split rules on arrays -----------------------------------------------------------------------------------------


def dimension_order(x: np.ndarray, policy: SplitPolicy, level: int, extent: np.ndarray | None = None) -> np.ndarray:
    """Dimensions from the best on, without those in which all points coincide."""
    extent = x.max(axis=0) - x.min(axis=0) if extent is None else extent
    if policy.dim_rule == "cycle":
        order = (np.arange(x.shape[1]) + level) % x.shape[1]
    elif policy.dim_rule == "range":
        order = np.argsort(-extent, kind="stable")
    else:
        part = x if policy.dim_rule == "variance_full" else x[: policy.local_sample]
        order = np.argsort(-part.var(axis=0), kind="stable")
    return order[extent[order] > 0]


def split_value(v: np.ndarray, policy: SplitPolicy) -> float | None:
    """A value with points on both sides, or None."""
    if policy.value_rule == "midrange":
        low, high = float(v.min()), float(v.max())
        mid = low + (high - low) / 2
        return (mid if mid > low else high) if low < high else None
    if policy.value_rule == "first100":
        mean = float(v[:100].mean())
        return mean if v.min() < mean <= v.max() else None
    if policy.value_rule in ("exact", "sketch") or len(v) <= policy.local_sample:
        return median_edge(np.sort(v))
    edges = np.unique(v[: policy.local_sample])
    found = edge_nearest(edges, histogram(v, edges, policy.two_level, policy.stride))
    return found and found[0]


def median_edge(v: np.ndarray) -> float | None:
    """Of sorted values the one whose share of smaller values is nearest to a half, and not none: as edge_nearest over all of them."""
    n = len(v)
    first, after = np.searchsorted(v, v[n // 2], side="left"), np.searchsorted(v, v[n // 2], side="right")
    if first == 0 and after == n:
        return None
    if first == 0 or after < n and 2 * after - n < n - 2 * first:
        return float(v[after])
    return float(v[first])


@dataclass
class Tree:
    points: np.ndarray
    ids: np.ndarray
    dim: np.ndarray
    split: np.ndarray
    left: np.ndarray
    right: np.ndarray
    start: np.ndarray
    end: np.ndarray
    lo: np.ndarray
    hi: np.ndarray
    depth: np.ndarray

    @property
    def leaves(self) -> np.ndarray:
        return np.flatnonzero(self.left < 0)


def build(points: np.ndarray, ids: np.ndarray, bucket_size: int = 32, policy: SplitPolicy = SplitPolicy(), seed: int = 42) -> Tree:
    """Depth-first over an index array; points are moved once, in the end, so that buckets are contiguous."""
    n, d = points.shape
    # in hashed order the head of any node's index range is a random sample of it
    index = np.random.default_rng(seed).permutation(n)
    rows: list[list] = []
    boxes: list[tuple[np.ndarray, np.ndarray]] = []

    def new(s: int, e: int, level: int) -> int:
        x = points[index[s:e]]
        rows.append([-1, 0.0, -1, -1, s, e, level])
        boxes.append((x.min(axis=0), x.max(axis=0)) if e > s else (np.full(d, np.inf), np.full(d, -np.inf)))
        return len(rows) - 1

    stack = [new(0, n, 0)]
    while stack:
        node = stack.pop()
        s, e, level = rows[node][4:7]
        if e - s <= bucket_size:
            continue
        x = points[index[s:e]]
        best = None
        for dim in dimension_order(x, policy, level, boxes[node][1] - boxes[node][0]):
            value = split_value(x[:, dim], policy)
            if value is None:
                continue
            left = x[:, dim] < value
            share = np.count_nonzero(left) / len(left)
            balance = min(share, 1 - share)
            if best is None or balance > best[0]:
                best = (balance, dim, value, left)
            if balance >= policy.min_balance or policy.value_rule in ("first100", "midrange"):
                break
        if best is None and len(dims := np.flatnonzero(boxes[node][1] > boxes[node][0])):
            # the rule found nothing: the largest value goes right
            dim = dims[0]
            best = (0, dim, float(x[:, dim].max()), x[:, dim] < x[:, dim].max())
        if best is None:  # all points coincide
            continue
        _, dim, value, left = best
        own = index[s:e]
        mid = s + int(left.sum())
        index[s:e] = np.concatenate([own[left], own[~left]])
        rows[node][:4] = [int(dim), value, new(s, mid, level + 1), new(mid, e, level + 1)]
        stack += [rows[node][3], rows[node][2]]
    for r in rows:
        if r[2] < 0:  # in a bucket by id
            own = index[r[4] : r[5]]
            index[r[4] : r[5]] = own[np.argsort(ids[own], kind="stable")]
    cols = list(zip(*rows, strict=True))
    return Tree(
        points[index], ids[index], np.array(cols[0]), np.array(cols[1]), np.array(cols[2]), np.array(cols[3]), np.array(cols[4]), np.array(cols[5]),
        np.array([b[0] for b in boxes]), np.array([b[1] for b in boxes]), np.array(cols[6]),
    )


# ---- distances -----------------------------------------------------------------------------------------------------


#: How the distance grows by a dimension's gap: squared Euclidean, Manhattan, maximum.
METRICS = {"l2": lambda total, gap: total + gap * gap, "l1": lambda total, gap: total + np.abs(gap), "linf": lambda total, gap: np.maximum(total, np.abs(gap))}


def distance(a: np.ndarray, b: np.ndarray, metric: str = "l2") -> np.ndarray:
    """Distances along the last axis (squared for l2), summed from left to right."""
    grow, total = METRICS[metric], 0.0
    for k in range(a.shape[-1]):
        total = grow(total, a[..., k] - b[..., k])
    return total


def squared(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return distance(a, b)


def box_distance(q: np.ndarray, lo: np.ndarray, hi: np.ndarray, metric: str = "l2") -> np.ndarray:
    """Distance of points to boxes, as distance measures it."""
    grow, total = METRICS[metric], 0.0
    for k in range(q.shape[-1]):
        total = grow(total, np.maximum(np.maximum(lo[..., k] - q[..., k], q[..., k] - hi[..., k]), 0.0))
    return total


# ---- search --------------------------------------------------------------------------------------------------------


@dataclass
class Found:
    """Per query: squared distances and ids, padded by infinity and NO_ID; nodes visited, points compared."""

    d2: np.ndarray
    ids: np.ndarray
    visited: np.ndarray
    compared: np.ndarray


def top_k(d2: np.ndarray, ids: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """The k first of each row by (d2, id)."""
    order = np.lexsort((ids, d2), axis=-1)[:, :k]
    return np.take_along_axis(d2, order, 1), np.take_along_axis(ids, order, 1)


#: Pairs of a query and a point that a step of a search holds at most.
SCAN = 1 << 19
#: Queries that show whether boxes prune; the share of a tree's points beyond which all of them are compared, block by block.
PROBE, DENSE = 64, 0.1
#: Smaller trees are searched by their boxes anyway.
DENSE_POINTS = 16_384


def search(tree: Tree, q: np.ndarray, k: int, r2: np.ndarray | float = np.inf, own: np.ndarray | None = None, order: str = "near_first", chunk: int = 2048, metric: str = "l2") -> Found:
    """The k nearest of every query within the radius r2 (squared for l2), bound by bound, for many queries at a time.

    Each query first looks into the bucket it falls in, which gives a radius; then it descends to all boxes within the radius,
    and takes them by rising bound while the bound is within its shrinking radius. own: ids that queries may not find.
    Where the queries so far had to compare more than DENSE of the points, as in one bucket, in many dimensions, or without a
    radius and the farthest box first, the rest compares all of them.
    """
    r2 = np.broadcast_to(np.asarray(r2, dtype=float), (len(q),))
    look = _looked(tree, k, own is not None)
    every = np.flatnonzero(tree.left < 0)
    total, parts, at = int(look[every].sum()), [], 0
    dense = len(every) == 1 or order != "near_first" and bool(np.isinf(r2).all())
    while at < len(q):
        to = min(len(q), at + (min(chunk, PROBE) if not at and not dense else chunk))
        args = tree, q[at:to], k, r2[at:to].copy(), None if own is None else own[at:to]
        parts.append(_dense(*args, look, metric) if dense and total else _search(*args, look, order, metric))
        dense = dense or total >= DENSE_POINTS and parts[-1].compared.mean() > DENSE * total
        at = to
    if not parts:
        return Found(np.zeros((0, k)), np.zeros((0, k), dtype=np.int64), np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int64))
    return Found(*(np.concatenate([getattr(p, f) for p in parts]) for f in ("d2", "ids", "visited", "compared")))


def _looked(tree: Tree, k: int, own: bool) -> np.ndarray:
    """Points of each node that a search compares: of points in one spot only those with the smallest ids can answer."""
    spot, size = (tree.lo == tree.hi).all(axis=1), tree.end - tree.start
    return np.where(spot, np.minimum(size, k + own), size)


def _dense(tree: Tree, q: np.ndarray, k: int, r2: np.ndarray, own: np.ndarray | None, look: np.ndarray, metric: str) -> Found:
    """All buckets looked through, whatever their boxes: as good as any order of them where the radius reaches them all."""
    leaf = np.flatnonzero(tree.left < 0)
    if (look[leaf] == (tree.end - tree.start)[leaf]).all():
        x, ids = tree.points, tree.ids
    else:
        first = np.repeat(tree.start[leaf] - np.concatenate([[0], np.cumsum(look[leaf])[:-1]]), look[leaf])
        pos = first + np.arange(len(first))
        x, ids = tree.points[pos], tree.ids[pos]
    d2, found = brute(x, ids, q, k, r2, own, metric=metric)
    return Found(d2, found, np.full(len(q), len(tree.left), dtype=np.int64), np.full(len(q), len(x), dtype=np.int64))


def _search(tree: Tree, q: np.ndarray, k: int, r2: np.ndarray, own: np.ndarray | None, look: np.ndarray, order: str, metric: str) -> Found:
    m = len(q)
    out = Found(np.full((m, k), np.inf), np.full((m, k), NO_ID), np.zeros(m, dtype=np.int64), np.zeros(m, dtype=np.int64))
    if not len(tree.points):
        return out

    def scan(at: np.ndarray, leaf: np.ndarray) -> None:
        step = max(1, min(1 << 13, SCAN // max(1, int(look[leaf].max(initial=1)))))
        for i in range(0, len(at), step):
            a, f = at[i : i + step], leaf[i : i + step]
            column = np.arange(int(look[f].max()))
            inside = column < look[f][:, None]
            pos = np.where(inside, tree.start[f][:, None] + column, 0)
            d2 = distance(tree.points[pos], q[a][:, None, :], metric)
            found = tree.ids[pos]
            inside = inside & (d2 <= r2[a][:, None])
            if own is not None:
                inside &= found != own[a][:, None]
            d2 = np.where(inside, d2, np.inf)
            out.d2[a], out.ids[a] = top_k(np.concatenate([out.d2[a], d2], axis=1), np.concatenate([out.ids[a], np.where(inside, found, NO_ID)], axis=1), k)
            out.compared[a] += look[f]
            r2[a] = np.minimum(r2[a], out.d2[a, -1])

    at, home = np.arange(m), np.zeros(m, dtype=np.int64)
    while len(at):
        out.visited[at] += 1
        inner = tree.left[home[at]] >= 0
        at = at[inner]
        node = home[at]
        right = q[at, tree.dim[node]] >= tree.split[node]
        home[at] = np.where(right, tree.right[node], tree.left[node])
    if order == "near_first":
        scan(np.arange(m), home)
    at, node, leaves = np.arange(m), np.zeros(m, dtype=np.int64), []
    while len(at):
        bound = box_distance(q[at], tree.lo[node], tree.hi[node], metric)
        keep = bound <= r2[at]
        at, node, bound = at[keep], node[keep], bound[keep]
        np.add.at(out.visited, at, 1)
        leaf = tree.left[node] < 0
        leaves.append((at[leaf], node[leaf], bound[leaf]))
        at, node = np.repeat(at[~leaf], 2), np.stack([tree.left[node[~leaf]], tree.right[node[~leaf]]], axis=1).ravel()
    at, node, bound = (np.concatenate([x[i] for x in leaves]) for i in range(3))
    if order == "near_first":
        keep = node != home[at]
        at, node, bound = at[keep], node[keep], bound[keep]
    by = np.lexsort((bound if order == "near_first" else -bound, at))
    at, node, bound = at[by], node[by], bound[by]
    first = np.searchsorted(at, np.arange(m))
    last = np.searchsorted(at, np.arange(m), side="right")
    active = np.flatnonzero(first < last)
    while len(active):
        here = first[active]
        ok = bound[here] <= r2[active]
        scan(active[ok], node[here[ok]])
        first[active] += 1
        if order == "near_first":
            active = active[ok]  # later bounds are larger still
        active = active[first[active] < last[active]]
    return out


def search_one(tree: Tree, q: np.ndarray, k: int, r2: float = np.inf, regions: bool = True) -> tuple[list[tuple[float, int]], int, int]:
    """One query by an explicit stack: (answers, nodes visited, points compared).

    regions: bounds follow the split planes, one offset for each dimension that a later plane replaces, and not the boxes.
    """
    heap: list[tuple[float, int]] = []  # (-d2, -id), worst first
    stack = [(0, np.zeros(len(q)))]
    visited = compared = 0
    while stack:
        node, offset = stack.pop()
        bound = float(squared(offset[None, :], np.zeros((1, len(q))))[0]) if regions else float(box_distance(q, tree.lo[node], tree.hi[node]))
        if bound > r2:
            continue
        visited += 1
        if tree.left[node] < 0:
            for p in range(tree.start[node], tree.end[node]):
                compared += 1
                d2 = float(squared(tree.points[p][None, :], q[None, :])[0])
                if d2 <= r2:
                    heapq.heappush(heap, (-d2, -int(tree.ids[p])))
                    if len(heap) > k:
                        heapq.heappop(heap)
                    if len(heap) == k:
                        r2 = min(r2, -heap[0][0])  # the k-th place, not the newcomer
            continue
        gap = q[tree.dim[node]] - tree.split[node]
        near, far = (tree.left[node], tree.right[node]) if gap < 0 else (tree.right[node], tree.left[node])
        beyond = offset.copy()
        beyond[tree.dim[node]] = gap
        stack += [(far, beyond), (near, offset)]
    return sorted((-a, -b) for a, b in heap), visited, compared


#: Points that all queries meet at a time, at most and at first; queries of a tile, whose pairs stay in a core's cache.
BLOCK, FIRST, TILE = 3400, 256, 64


class Nearest:
    """The k nearest of many queries among all points that they meet, by comparing all pairs, block by block.

    For l2 a matrix product in single precision gives the distances but for a bounded rounding error. Pairs that these can't rule
    out are measured as distance does, so answers and ties are the same as by measuring all; where they are many, a product in
    double precision comes first. Measured pairs wait until the points that were met are twice as many, or k a query wait.
    """

    def __init__(self, q: np.ndarray, k: int, r2: np.ndarray | float = np.inf, own: np.ndarray | None = None, metric: str = "l2") -> None:
        self.q, self.k, self.own, self.metric = q, k, own, metric
        self.r2 = np.broadcast_to(np.asarray(r2, dtype=float), (len(q),))
        self.d2, self.ids = np.full((len(q), k), np.inf), np.full((len(q), k), NO_ID)
        self.met = self.settled = self.waiting = 0
        self.wait: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        self.product = metric == "l2" and len(q) > 0 and bool(np.abs(q).max(initial=0.0) < 1e150)
        self.left = None
        if self.product:
            self.centre = q.mean(axis=0)
            a = q - self.centre
            reach = np.sqrt((a * a).sum(axis=1).max())
            if reach == 0 or reach > 1e-140:
                # a power of two brings the queries into the unit ball, so that no square leaves the range of single precision
                self.scale = 2.0 ** -np.ceil(np.log2(reach)) if reach else 1.0
                a *= self.scale
                # twice the rounding of single precision for each of the product's terms, and more than that of the distance itself
                self.unit = (q.shape[1] + 6) * float(np.finfo(np.float32).eps)
                self.left, self.a2 = np.concatenate([-2.0 * a, np.ones((len(a), 1))], axis=1).astype(np.float32), (a * a).sum(axis=1)
        self._bounded()

    def _bounded(self) -> None:
        self.bound = np.minimum(self.r2, self.d2[:, -1])
        if self.left is not None:
            with np.errstate(over="ignore"):
                self.limit = np.nextafter((self.bound * self.scale**2 - self.a2 * (1 - self.unit) + 1e-25).astype(np.float32), np.float32(np.inf))

    def meet(self, points: np.ndarray, ids: np.ndarray, block: int = BLOCK) -> None:
        if not len(self.q) or not len(points):
            return
        at, even = 0, -(-len(points) // -(-len(points) // block))
        while at < len(points):
            to = min(len(points), at + min(even, max(FIRST, self.met)))  # the first few bound what the many bring
            self._block(points[at:to], ids[at:to])
            self.met += to - at
            at = to
            if self.waiting > self.k * len(self.q) or self.met >= 2 * self.settled:
                self._settle()

    def _right(self, x: np.ndarray) -> np.ndarray | None:
        """A block's side of the product in single precision; none if that can't hold it."""
        if self.left is None:
            return None
        with np.errstate(over="ignore"):
            b = (x - self.centre) * self.scale
            b2 = (b * b).sum(axis=1)
        return np.ascontiguousarray(np.concatenate([b, b2[:, None] * (1 - self.unit)], axis=1).T.astype(np.float32)) if b2.max() < 1e12 else None

    def _block(self, x: np.ndarray, ids: np.ndarray) -> None:
        product = self.product and np.abs(x).max() < 1e150
        right = self._right(x) if product else None
        rest = np.arange(len(self.q)) if right is None else self._looked(x, ids, right)
        one = len(rest) and (_block_product(x, ids) if product else _block_measured(x, ids, self.metric))
        for j in range(0, len(rest), TILE):
            row = rest[j : j + TILE]
            of, col, far = one(self.q[row], self.k, self.bound[row], None if self.own is None else self.own[row])
            self._keep(row[of], ids[col], far)

    def _looked(self, x: np.ndarray, ids: np.ndarray, right: np.ndarray) -> np.ndarray:
        """The block by the product in single precision; returns the queries for which that leaves too many points open."""
        near, least, rows, cols, rest = np.empty((TILE, len(x)), dtype=np.float32), np.empty(len(self.left), dtype=np.float32), [], [], []
        for j in range(0, len(least), TILE):
            np.matmul(self.left[j : j + TILE], right, out=near[: len(least) - j])
            np.minimum.reduce(near[: len(least) - j], axis=1, out=least[j : j + TILE])
        hit = np.flatnonzero(least <= self.limit)
        for j in range(0, len(hit), TILE):  # again, as keeping all products would cost more
            row = hit[j : j + TILE]
            np.matmul(self.left[row], right, out=near[: len(row)])
            found = _set(near[: len(row)] <= self.limit[row, None])
            if len(found) > 4 * self.k * len(row):
                rest.append(row)
                continue
            of, col = np.divmod(found, len(x))
            rows.append(row[of])
            cols.append(col)
        if rows:
            row, col = np.concatenate(rows), np.concatenate(cols)
            far = squared(x[col], self.q[row])
            ok = (far <= self.bound[row]) & np.isfinite(far)
            if self.own is not None:
                ok &= ids[col] != self.own[row]
            self._keep(row[ok], ids[col[ok]], far[ok])
        return np.concatenate(rest) if rest else np.zeros(0, dtype=np.int64)

    def _keep(self, row: np.ndarray, ids: np.ndarray, far: np.ndarray) -> None:
        if len(row):
            self.wait.append((row, ids, far))
            self.waiting += len(row)

    def _settle(self) -> None:
        """What waits is merged into the answers of its queries."""
        self.settled = self.met
        if not self.waiting:
            return
        row, ids, far = (np.concatenate(x) for x in zip(*self.wait, strict=True))
        self.wait, self.waiting = [], 0
        each = np.bincount(row, minlength=len(self.q))
        met = np.flatnonzero(each)
        row = np.concatenate([np.repeat(met, self.k), row])
        far, ids = np.concatenate([self.d2[met].ravel(), far]), np.concatenate([self.ids[met].ravel(), ids])
        by, many = np.lexsort((ids, far, row)), each[met] + self.k
        by = by[(np.cumsum(many) - many)[:, None] + np.arange(self.k)]
        self.d2[met], self.ids[met] = far[by], ids[by]
        self._bounded()

    def answers(self) -> tuple[np.ndarray, np.ndarray]:
        """(d2, ids) by rising distance, then id; infinite and NO_ID where there are fewer."""
        self._settle()
        return self.d2, self.ids


def brute(points: np.ndarray, ids: np.ndarray, q: np.ndarray, k: int, r2: np.ndarray | float = np.inf, own: np.ndarray | None = None, block: int = BLOCK, metric: str = "l2") -> tuple[np.ndarray, np.ndarray]:
    """(d2, ids) of the k nearest by comparing all pairs, block by block."""
    best = Nearest(q, k, r2, own, metric)
    best.meet(points, ids, block)
    return best.answers()


def _set(within: np.ndarray) -> np.ndarray:
    """Places of the few true values, looked for by words of eight."""
    flat = within.ravel()
    if len(flat) % 8:
        return np.flatnonzero(flat)
    word = np.flatnonzero(flat.view(np.uint64))
    at = (word[:, None] * 8 + np.arange(8)).ravel()
    return at[flat[at]]


def _block_product(x: np.ndarray, ids: np.ndarray):
    """(query, point, d2) of a query block's pairs within the bound, and at least of the k nearest of them."""
    centre = x.mean(axis=0)
    b = x - centre
    b2 = (b * b).sum(axis=1)
    right, reach = np.ascontiguousarray(np.concatenate([b, b2[:, None]], axis=1).T), np.sqrt(b2.max())
    # more than the rounding of the centred places, of the product and of the distance itself
    unit = 8 * (x.shape[1] + 8) * np.finfo(float).eps

    def one(q: np.ndarray, k: int, bound: np.ndarray, own: np.ndarray | None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        a = q - centre
        a2 = (a * a).sum(axis=1)
        near = np.concatenate([-2.0 * a, np.ones((len(a), 1))], axis=1) @ right
        slack = unit * (np.sqrt(a2) + reach) ** 2 + 1e-290
        if own is not None:
            near[ids[None, :] == own[:, None]] = np.inf
        limit = bound - a2 + slack
        within = near <= limit[:, None]
        if len(ids) > k and np.count_nonzero(within) > 4 * k * len(q):
            limit = np.minimum(limit, np.partition(near, k - 1, axis=1)[:, k - 1] + 2 * slack)
            within = near <= limit[:, None]
        row, col = np.divmod(_set(within), len(ids))
        far = squared(x[col], q[row])
        ok = (far <= bound[row]) & np.isfinite(far)
        if own is not None:
            ok &= ids[col] != own[row]
        return row[ok], col[ok], far[ok]

    return one


def _block_measured(x: np.ndarray, ids: np.ndarray, metric: str):
    """The same, every pair measured."""

    def one(q: np.ndarray, k: int, bound: np.ndarray, own: np.ndarray | None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        far = distance(x[None, :, :], q[:, None, :], metric)
        if own is not None:
            far = np.where(ids[None, :] == own[:, None], np.nan, far)
        limit = bound
        if len(ids) > k:  # all that tie with the k-th stay
            kth = np.partition(far, k - 1, axis=1)[:, k - 1]
            limit = np.where(np.isnan(kth), bound, np.minimum(bound, kth))
        row, col = np.nonzero((far <= limit[:, None]) & np.isfinite(far))
        return row, col, far[row, col]

    return one
