"""Sphere summarizer: a one-pass weighted summary by spheres in a feature tree.

Plain NumPy state, no Spark: points come in blocks, features keep a running mean and
cost (no cancellation), and the whole state has a fixed capacity of ``m`` features.
"""

from __future__ import annotations

import numpy as np

ROOT = -1
DEEPEST = 48
#: Features taken in at once by a rebuild; share of references that the first threshold reaches.
BLOCK, FIRST_QUANTILE = 1024, 0.1
#: Pairs of points and children of one node from which on a product takes them; pairs a point up to which a list does.
PRODUCT_PAIRS, LISTED_PAIRS, CACHED_PAIRS = 256, 8, 1 << 17


def runs(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """First places and lengths of the runs of equal neighbours."""
    head = np.ones(len(values), bool)
    np.not_equal(values[1:], values[:-1], out=head[1:])
    first = head.nonzero()[0]
    size = np.empty_like(first)
    size[:-1] = first[1:] - first[:-1]
    size[-1] = len(values) - first[-1]
    return first, size


def closest(x: np.ndarray, r: np.ndarray) -> np.ndarray:
    """Place of the row of ``r`` closest to each row of ``x``: one product, by parts that stay in the cache."""
    if len(r) == 1:
        return np.zeros(len(x), np.int64)
    sides = np.empty((r.shape[1] + 1, len(r)))
    np.multiply(r.T, -2.0, out=sides[:-1])
    np.einsum("ij,ij->i", r, r, out=sides[-1])
    rows = np.empty((len(x), x.shape[1] + 1))
    rows[:, :-1], rows[:, -1] = x, 1.0
    out, step = np.empty(len(x), np.int64), max(64, CACHED_PAIRS // len(r))
    for a in range(0, len(x), step):
        (rows[a : a + step] @ sides).argmin(axis=1, out=out[a : a + step])
    return out


def copies_that_fit(w: int, s: int, c: float, dist2: float, limit: float) -> int:
    """Most of ``w`` copies that join ``s`` members of cost ``c`` within ``limit``."""
    slack = s * dist2 - limit + c
    if slack <= 0:
        return w
    return int(max(0, min(w, (s * limit - s * c) // slack)))


class SphereTree:
    """Features with a reference point each; a point inside a sphere joins its feature or goes below it.

    ``finder`` (points one by one): ``full`` compares with all references of a level,
    ``band`` first cuts them to those whose one-dimensional projection is near enough,
    ``auto`` chooses. ``block``: points taken in at once, level by level (1: in order,
    one by one). A block may pass ``m`` until it is done; then the tree is rebuilt.

    Every feature also carries the inner cost that its points brought along from earlier
    summaries. It moves with the copies and does not count against the threshold.
    """

    def __init__(self, m: int, d: int, seed=0, finder: str = "auto", block: int = 1024, naive: bool = False, growth: float = 1.1):
        if m < 1 or d < 1:
            raise ValueError("a summary needs room for one feature of one dimension")
        if growth <= 1:
            raise ValueError("the threshold must grow")
        self.growth = growth
        if finder not in ("full", "band", "auto"):
            raise ValueError("finder must be full, band or auto")
        self.m, self.d, self.block, self.naive = int(m), int(d), int(block), naive
        self.finder = finder
        self.axis = np.random.default_rng(seed).standard_normal(d)
        self.axis /= np.linalg.norm(self.axis)
        self.limit = 0.0
        self.counters = {"n_in": 0, "w_in": 0, "rebuilds": 0, "dist_evals": 0, "splits": 0, "opened": 0}
        self._clear()

    def _clear(self) -> None:
        size = self.m + max(self.block, 1)
        self.n = 0
        self.ref, self.mean = np.empty((size, self.d)), np.empty((size, self.d))
        self.along, self.w, self.within, self.carried = np.empty(size), np.zeros(size, np.int64), np.zeros(size), np.zeros(size)
        self.parent, self.depth = np.full(size, ROOT), np.zeros(size, np.int64)
        self.kids: dict[int, list[int]] = {}
        self.held: dict[int, np.ndarray] = {}

    def _room(self, more: int) -> None:
        """Space for ``more`` features beyond those there are."""
        size = self.n + more
        if size <= len(self.w):
            return
        size = max(size, 2 * len(self.w))
        for name in ("ref", "mean", "along", "w", "within", "carried", "parent", "depth"):
            old = getattr(self, name)
            new = np.zeros((size, *old.shape[1:]), old.dtype)
            new[: self.n] = old[: self.n]
            setattr(self, name, new)

    def radius2(self, depth: int) -> float:
        return self.limit / 2.0 ** (depth + 3)

    def _children(self, node: int) -> np.ndarray:
        if node not in self.held:
            self.held[node] = np.array(self.kids.get(node, ()), np.int64)
        return self.held[node]

    def locate(self, x: np.ndarray, node: int) -> tuple[int, float]:
        """Closest reference below ``node`` and its squared distance; -1 where the level is empty."""
        at = self._children(node)
        if not len(at):
            return -1, np.inf
        if self.finder == "band" or self.finder == "auto" and len(at) > 256:
            depth = int(self.depth[at[0]])
            near = np.abs(self.along[at] - x @ self.axis) <= np.sqrt(self.radius2(depth)) * (1 + 1e-12)
            at = at[near]
            if not len(at):
                return -1, np.inf
        diff = self.ref[at] - x
        d2 = np.einsum("ij,ij->i", diff, diff)
        self.counters["dist_evals"] += len(at)
        k = int(d2.argmin())
        return int(at[k]), float(d2[k])

    def open(self, ref: np.ndarray, mean: np.ndarray, w: int, within: float, node: int, carried: float = 0.0) -> int:
        """A new feature below ``node``."""
        i = self.n
        self._room(1)
        self.n += 1
        self.ref[i], self.mean[i], self.w[i], self.within[i], self.carried[i] = ref, mean, w, within, carried
        self.along[i] = ref @ self.axis
        self.parent[i] = node
        self.depth[i] = 0 if node == ROOT else self.depth[node] + 1
        self.kids.setdefault(node, []).append(i)
        self.held.pop(node, None)
        self.counters["opened"] += 1
        return i

    def join(self, i: int, mean: np.ndarray, w: int, within: float = 0.0, carried: float = 0.0) -> None:
        """Add a point's copies, or a whole feature, to feature ``i``."""
        s = int(self.w[i])
        diff = mean - self.mean[i]
        self.within[i] += within + s * w / (s + w) * float(diff @ diff)
        self.mean[i] += diff * (w / (s + w))
        self.w[i] = s + w
        self.carried[i] += carried

    def insert(self, x: np.ndarray, w: int, node: int = ROOT, carried: float = 0.0) -> None:
        """Put ``w`` copies of a point into the tree below ``node``; copies that do not fit go deeper."""
        while True:
            i, d2 = self.locate(x, node)
            depth = 0 if node == ROOT else int(self.depth[node]) + 1
            if i < 0 or d2 > self.radius2(depth) or depth >= DEEPEST:
                self.open(x, x, w, 0.0, node, carried)
                if self.n > self.m:
                    self.rebuild()
                return
            diff = x - self.mean[i]
            gap = float(diff @ diff)
            if self.naive:
                fit = w if gap == 0 else int(max(0, min(w, (self.limit - self.within[i]) // gap)))
            else:
                fit = copies_that_fit(w, int(self.w[i]), float(self.within[i]), gap, self.limit)
            if fit:
                share = carried * (fit / w)
                self.join(i, x, fit, 0.0, share)
                if fit == w:
                    return
                self.counters["splits"] += 1
                w, carried = w - fit, carried - share
            node = i

    def _absorb(self, ref: np.ndarray, mean: np.ndarray, w: np.ndarray, within: np.ndarray, carried: np.ndarray, split: bool) -> None:
        """Take in points (``split``: copies may part) or whole features, all at once on each level."""
        w, carried = w.copy(), carried.copy()
        todo, node = np.arange(len(ref)), np.full(len(ref), ROOT)
        for depth in range(DEEPEST + 1):
            if not len(todo):
                return
            r2 = self.radius2(depth) if depth < DEEPEST else -1.0
            child, d2 = self._nearest(ref[todo], node, depth)
            out = np.flatnonzero((child < 0) | (d2 > r2))
            if len(out):
                child[out], own = self._cover(todo[out], node[out], r2, ref, mean, w, within, carried)
                stay = np.ones(len(todo), bool)
                stay[out[own]] = False
                todo, child = todo[stay], child[stay]
            rest = self._join_all(todo, child, mean, w, within, carried, split)
            todo, node = todo[rest], child[rest]

    def _nearest(self, x: np.ndarray, node: np.ndarray, depth: int) -> tuple[np.ndarray, np.ndarray]:
        """Closest child reference of each point's node (-1: none) and its exact squared distance."""
        n = len(x)
        best, d2 = np.full(n, -1), np.full(n, np.inf)
        if depth == 0:
            at = self._children(ROOT)
            if len(at):
                best = at[closest(x, self.ref[at])]
                diff = x - self.ref[best]
                d2 = np.einsum("ij,ij->i", diff, diff)
                self.counters["dist_evals"] += n * len(at)
            return best, d2
        first, size = runs(node)  # points come grouped by node, as they were joined
        kids = [self._children(k) for k in node[first].tolist()]
        count = np.fromiter(map(len, kids), np.int64, len(kids))
        product = (size * count >= PRODUCT_PAIRS).tolist()
        few = np.zeros(len(kids), bool)
        for g, (a, z, c) in enumerate(zip(first.tolist(), (first + size).tolist(), count.tolist())):
            if c == 1:
                best[a:z] = kids[g][0]
            elif product[g]:
                best[a:z] = kids[g][closest(x[a:z], self.ref[kids[g]])]
            else:
                few[g] = c > 0
        if few.any():
            p = np.flatnonzero(np.repeat(few, size))
            self._nearest_few(x, p, size[few], count[few], [kids[g] for g in np.flatnonzero(few).tolist()], best)
        self.counters["dist_evals"] += int(size @ count)
        some = slice(None) if count.all() else np.flatnonzero(best >= 0)
        diff = x[some] - self.ref[best[some]]
        d2[some] = np.einsum("ij,ij->i", diff, diff)
        return best, d2

    def _nearest_few(self, x, p, size, count, kids, best) -> None:
        """Closest child of the points ``p``, which lie in runs of ``size`` points below nodes of ``count`` children: pair by pair."""
        flat, start = np.concatenate(kids), np.repeat(np.cumsum(count) - count, size)
        c = np.repeat(count, size)
        ends = np.cumsum(c)
        a = 0
        while a < len(p):  # so many pairs at once that they take some MB
            base = ends[a - 1] if a else 0
            z = max(a + 1, int(np.searchsorted(ends, base + (1 << 16), "right")))
            q, n = p[a:z], c[a:z]
            first = np.cumsum(n) - n
            pair = flat[np.repeat(start[a:z] - first, n) + np.arange(int(n.sum()))]
            diff = self.ref[pair] - np.repeat(x[q], n, axis=0)
            far = np.einsum("ij,ij->i", diff, diff)
            hit = np.flatnonzero(far == np.repeat(np.minimum.reduceat(far, first), n))
            owner = np.repeat(np.arange(len(q)), n)[hit]
            best[q] = pair[hit[np.append(True, owner[1:] != owner[:-1])]]
            a = z

    def _cover(self, todo, node, r2, ref, mean, w, within, carried) -> tuple[np.ndarray, np.ndarray]:
        """Open features for points that no sphere holds: the feature of each, and which points became one."""
        feature, own = np.full(len(todo), -1), np.zeros(len(todo), bool)
        x = ref[todo]
        if node[0] == ROOT:
            sq = np.einsum("ij,ij->i", x, x)
            reach = r2 * (1 + 1e-9) + 1e-9 * float(sq.max())
            product = x @ x.T
            product -= 0.5 * sq
            near = product >= 0.5 * (sq[:, None] - reach)
            self.counters["dist_evals"] += near.size
            lead = self._lead_listed if np.count_nonzero(near) <= (LISTED_PAIRS + 1) * len(x) else self._lead
            head = lead(x, near, r2)
            own = head == np.arange(len(head))
            feature = self.n + (np.cumsum(own) - 1)[head]
            self._open_all(todo[own], node[own], ref, mean, w, within, carried)
            return feature, own
        active = np.arange(len(todo))
        while len(active):  # one more feature a node
            first, size = runs(node[active])
            heads, inverse = active[first], np.repeat(np.arange(len(first)), size)
            base = self.n
            self._open_all(todo[heads], node[heads], ref, mean, w, within, carried)
            own[heads] = True
            if len(heads) == len(active):
                feature[heads] = base + inverse
                break
            diff = x[active] - x[heads][inverse]
            inside = np.einsum("ij,ij->i", diff, diff) <= r2
            inside[first] = True
            self.counters["dist_evals"] += len(active)
            feature[active[inside]] = base + inverse[inside]
            active = active[~inside]
        return feature, own

    @staticmethod
    def _lead(x, near, r2) -> np.ndarray:
        """Every point in turn that none before it leads, leads itself and those within the radius that are still free."""
        head = np.where(near.sum(axis=1) <= 1, np.arange(len(x)), -1)
        for i in np.flatnonzero(head < 0).tolist():
            if head[i] >= 0:
                continue
            there = np.flatnonzero(near[i] & (head < 0))
            diff = x[there] - x[i]
            head[there[np.einsum("ij,ij->i", diff, diff) <= r2]] = i
            head[i] = i
        return head

    @staticmethod
    def _lead_listed(x, near, r2) -> np.ndarray:
        """The same from a list of the pairs, where they are few."""
        i, j = np.divmod(np.flatnonzero(near), len(x))
        later = i < j
        i, j = i[later], j[later]
        diff = x[j] - x[i]
        within = np.einsum("ij,ij->i", diff, diff) <= r2
        head = list(range(len(x)))
        for a, b in zip(i[within].tolist(), j[within].tolist()):
            if head[a] == a and head[b] == b:
                head[b] = a
        return np.array(head)

    def _open_all(self, todo, node, ref, mean, w, within, carried) -> None:
        a, z = self.n, self.n + len(todo)
        self._room(len(todo))
        self.n = z
        self.ref[a:z], self.mean[a:z], self.w[a:z], self.within[a:z], self.carried[a:z] = ref[todo], mean[todo], w[todo], within[todo], carried[todo]
        self.along[a:z] = self.ref[a:z] @ self.axis
        self.parent[a:z] = node
        self.depth[a:z] = np.where(node == ROOT, 0, self.depth[np.maximum(node, 0)] + 1)
        if len(node) and node[0] == ROOT:
            self.kids.setdefault(ROOT, []).extend(range(a, z))
            self.held.pop(ROOT, None)
        else:
            for i, k in enumerate(node.tolist(), a):
                self.kids.setdefault(k, []).append(i)
                self.held.pop(k, None)
        self.counters["opened"] += z - a

    def _join_all(self, todo, feature, mean, w, within, carried, split: bool) -> np.ndarray:
        """Add to every feature the nearest of its points that fit its threshold; places of the others in ``todo``."""
        if not len(todo):
            return todo
        gap = mean[todo] - self.mean[feature]
        far = np.einsum("ij,ij->i", gap, gap)
        order = np.lexsort((far, feature))
        todo, feature, far = todo[order], feature[order], far[order]
        first, size = runs(feature)
        c = w[todo].astype(float)
        ss = c * far + within[todo]
        most = self.limit * (1 + 1e-12) + 1e-14 * float(ss.sum())
        alone = self.within[feature[first]] + ss[first] - c[first] ** 2 * far[first] / (self.w[feature[first]] + c[first])
        takes = alone <= most  # a feature that its nearest point does not fit takes none
        kept, fits = np.zeros(len(first), np.int64), np.zeros(len(todo), bool)
        if takes.any():
            at = slice(None) if takes.all() else np.flatnonzero(np.repeat(takes, size))
            kept[takes], fits[at] = self._join_nearest(todo[at], feature[at], gap[order[at]], c[at], ss[at], most, carried)
        if split:
            part = (first + kept)[(kept < size)]
            part = part[w[todo[part]] > 1]
            if len(part):
                self._part(todo[part], feature[part], mean, w, carried)
        return order[~fits]

    def _join_nearest(self, todo, feature, gap, c, ss, most, carried) -> tuple[np.ndarray, np.ndarray]:
        """Join the nearest points of each feature, given in this order, as long as they fit: how many, and which."""
        first, size = runs(feature)

        def running(v):
            total = np.cumsum(v, axis=0)
            before = total[first] - v[first]
            return total - np.repeat(before, size, axis=0)

        total = self.w[feature] + running(c)
        ls = running(c[:, None] * gap)
        cost = self.within[feature] + running(ss) - np.einsum("ij,ij->i", ls, ls) / total
        fits = running((cost > most).astype(np.int64)) == 0
        kept = np.add.reduceat(fits.astype(np.int64), first)
        some = kept > 0
        last = (first + kept - 1)[some]
        f = feature[last]
        self.within[f] = np.maximum(cost[last], 0.0)
        self.mean[f] += ls[last] / total[last, None]
        self.w[f] = np.rint(total[last]).astype(np.int64)
        self.carried[f] += np.add.reduceat(np.where(fits, carried[todo], 0.0), first)[some]
        return kept, fits

    def _part(self, todo, f, mean, w, carried) -> None:
        """As many copies of one point a feature as fit; the others stay with the point."""
        gap = mean[todo] - self.mean[f]
        far = np.einsum("ij,ij->i", gap, gap)
        s, copies = self.w[f].astype(float), w[todo]
        slack = s * far - self.limit + self.within[f]
        with np.errstate(divide="ignore", invalid="ignore"):
            fit = np.where(slack <= 0, copies - 1, np.floor(s * (self.limit - self.within[f]) / slack))
        fit = np.clip(np.nan_to_num(fit), 0, copies - 1).astype(np.int64)
        go = fit > 0
        todo, f, gap, far, s, fit = todo[go], f[go], gap[go], far[go], s[go], fit[go]
        share = carried[todo] * (fit / w[todo])
        self.within[f] += s * fit / (s + fit) * far
        self.mean[f] += gap * (fit / (s + fit))[:, None]
        self.w[f] += fit
        self.carried[f] += share
        carried[todo] -= share
        w[todo] -= fit
        self.counters["splits"] += len(todo)

    def rebuild(self) -> None:
        """Raise the threshold and take the features in again, top down, until they fit with some room to spare.

        Small steps keep the summary full where distances hardly differ (many dimensions):
        doubling can take a level from no merges to nearly all. The room (a sixteenth)
        keeps the next rebuild some blocks away.
        """
        while self.n > self.m - self.m // 16:
            self.counters["rebuilds"] += 1
            self.limit = self.growth * self.limit if self.limit > 0 else self._first_limit()
            n = self.n
            order = np.argsort(self.depth[:n], kind="stable")
            old = [v[order] for v in (self.ref, self.mean, self.w, self.within, self.carried)]
            self._clear()
            for a in range(0, n, BLOCK):
                self._absorb(*(v[a : a + BLOCK] for v in old), split=False)

    def _first_limit(self) -> float:
        """Eight times a low quantile of the squared gaps to the nearest other reference: the top radius then reaches it.

        All features are still on the top level, and one can only go where another
        reference lies within the top radius. So where more have to go than the quantile
        has, it is the gap that as many lie within: no lower threshold makes them fit.
        """
        r = self.ref[: self.n]
        sq = np.einsum("ij,ij->i", r, r)
        tiny = 1e-12 * max(1.0, float(sq.max()))
        gaps = []
        step = max(64, CACHED_PAIRS // max(self.n, 1))
        for a in range(0, self.n, step):
            d2 = (-2.0 * r[a : a + step]) @ r.T
            d2 += sq
            d2 += sq[a : a + step, None]
            d2[np.arange(len(d2)), np.arange(a, a + len(d2))] = np.inf
            d2[d2 <= tiny] = np.inf
            gaps.append(d2.min(axis=1))
        gap = np.sort(np.concatenate(gaps))
        gap = gap[np.isfinite(gap)]
        if not len(gap):
            return 1e-12
        surplus = min(self.n - (self.m - self.m // 16) - (self.n - len(gap)), len(gap))
        return 8.0 * max(float(np.quantile(gap, FIRST_QUANTILE)), float(gap[surplus - 1]) if surplus > 0 else 0.0)

    def offer(self, x: np.ndarray, w: np.ndarray | None = None, carried: np.ndarray | None = None) -> None:
        """Take in a block of points with integral weights (default 1) and the inner costs they bring along (default 0)."""
        x = np.ascontiguousarray(x, dtype=np.float64)
        if x.ndim != 2 or x.shape[1] != self.d:
            raise ValueError(f"points of dimension {self.d} expected")
        if not np.isfinite(x).all():
            raise ValueError("a coordinate is not finite")
        w = np.ones(len(x), np.int64) if w is None else np.asarray(w)
        if len(w) and ((w < 1).any() or (w != np.floor(w)).any()):
            raise ValueError("weights must be positive whole numbers")
        w = w.astype(np.int64)
        carried = np.zeros(len(x)) if carried is None else np.asarray(carried, float)
        self.counters["n_in"] += len(x)
        self.counters["w_in"] += int(w.sum())
        if self.block == 1 or self.naive:
            for p, c, e in zip(x, w.tolist(), carried.tolist()):
                self.insert(p, c, ROOT, e)
            return
        for a in range(0, len(x), self.block):
            at = slice(a, a + self.block)
            self._absorb(x[at], x[at], w[at], np.zeros(len(w[at])), carried[at], split=True)
            if self.n > self.m:
                self.rebuild()

    def rows(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Centroid, weight and inner cost (that brought along included) of each feature."""
        n = self.n
        return self.mean[:n].copy(), self.w[:n].copy(), self.within[:n] + self.carried[:n]

    def merged(self) -> float:
        """The inner cost that this tree's own joins made."""
        return float(self.within[: self.n].sum())

    def features(self) -> list[dict]:
        """The tree itself, one record a feature."""
        inner = self.within + self.carried
        return [
            {"feature_id": i, "parent_id": int(self.parent[i]), "depth": int(self.depth[i]), "ref": self.ref[i].tolist(), "radius": float(np.sqrt(self.radius2(int(self.depth[i])))), "w": int(self.w[i]), "ls": (self.mean[i] * self.w[i]).tolist(), "ss": float(inner[i] + self.w[i] * (self.mean[i] @ self.mean[i]))}
            for i in range(self.n)
        ]

    def snapshot(self) -> dict:
        """State for a checkpoint."""
        n = self.n
        arrays = {name: getattr(self, name)[:n].copy() for name in ("ref", "mean", "w", "within", "carried", "parent")}
        return {"m": self.m, "d": self.d, "limit": self.limit, "block": self.block, "finder": self.finder, "growth": self.growth, "axis": self.axis, "counters": dict(self.counters), **arrays}

    @classmethod
    def restore(cls, state: dict) -> SphereTree:
        tree = cls(state["m"], state["d"], finder=state["finder"], block=state["block"], growth=state["growth"])
        tree.axis = state["axis"]
        for i in range(len(state["w"])):
            tree.open(state["ref"][i], state["mean"][i], int(state["w"][i]), float(state["within"][i]), int(state["parent"][i]), float(state["carried"][i]))
        tree.limit, tree.counters = state["limit"], dict(state["counters"])
        return tree


class _Page:
    """A node of the feature tree: entries with weight, mean and inner cost, and a page below each unless it is a leaf."""

    __slots__ = ("n", "w", "mean", "within", "below")

    def __init__(self, room: int, d: int, leaf: bool):
        self.n, self.w, self.mean, self.within = 0, np.zeros(room + 1), np.zeros((room + 1, d)), np.zeros(room + 1)
        self.below: list[_Page] | None = None if leaf else []

    def nearest(self, x: np.ndarray) -> tuple[int, float]:
        diff = self.mean[: self.n] - x
        d2 = np.einsum("ij,ij->i", diff, diff)
        i = int(d2.argmin())
        return i, float(d2[i])

    def add(self, i: int, mean: np.ndarray, w: float, within: float, d2: float) -> None:
        s = self.w[i]
        self.within[i] += within + s * w / (s + w) * d2
        self.mean[i] += (mean - self.mean[i]) * (w / (s + w))
        self.w[i] = s + w

    def append(self, mean: np.ndarray, w: float, within: float, below: _Page | None = None) -> None:
        i = self.n
        self.mean[i], self.w[i], self.within[i] = mean, w, within
        if self.below is not None:
            self.below.append(below)
        self.n += 1

    def sums(self) -> tuple[np.ndarray, float, float]:
        w = self.w[: self.n]
        mean = w @ self.mean[: self.n] / w.sum()
        diff = self.mean[: self.n] - mean
        return mean, float(w.sum()), float(self.within[: self.n].sum() + w @ np.einsum("ij,ij->i", diff, diff))


class FeatureTree:
    """Baseline: a height-balanced tree of clustering features with an absorption radius.

    Each point follows the nearest centroid down; every feature on its way counts it. A
    leaf's feature absorbs it where the radius allows, else it is a new entry. Pages
    above ``branching`` entries split at their farthest pair, up to the root, so all
    leaves stay at one height. With more than ``m`` leaf entries the tree is rebuilt
    from them with a larger radius.
    """

    def __init__(self, m: int, d: int, threshold: float = 0.0, branching: int = 50):
        self.m, self.d, self.threshold, self.branching = m, d, threshold, max(2, branching)
        self.rebuilds = 0
        self._clear()

    def _clear(self) -> None:
        self.root, self.entries, self.height = _Page(self.branching, self.d, True), 0, 1

    def insert(self, mean: np.ndarray, w: int, within: float = 0.0) -> None:
        page, path = self.root, []
        while page.below is not None:
            i, d2 = page.nearest(mean)
            page.add(i, mean, w, within, d2)
            path.append((page, i))
            page = page.below[i]
        if page.n:
            i, d2 = page.nearest(mean)
            s = page.w[i]
            if (page.within[i] + within + s * w / (s + w) * d2) / (s + w) <= self.threshold**2:
                page.add(i, mean, w, within, d2)
                return
        page.append(mean, w, within)
        self.entries += 1
        while page.n > self.branching:
            one, two = self._split(page)
            if not path:
                self.root = _Page(self.branching, self.d, False)
                self.root.append(*one.sums(), one)
                self.root.append(*two.sums(), two)
                self.height += 1
                break
            page, i = path.pop()
            page.mean[i], page.w[i], page.within[i] = one.sums()
            page.below[i] = one
            page.append(*two.sums(), two)
        if self.entries > self.m:
            self._rebuild()

    def _split(self, page: _Page) -> tuple[_Page, _Page]:
        x = page.mean[: page.n]
        a = int(((x - x.mean(0)) ** 2).sum(1).argmax())
        far = ((x - x[a]) ** 2).sum(1)
        b = int(far.argmax())
        left = far <= ((x - x[b]) ** 2).sum(1)
        if left.all():  # equal centroids
            left = np.arange(page.n) < page.n // 2
        made = []
        for side in (left, ~left):
            new = _Page(self.branching, self.d, page.below is None)
            for i in np.flatnonzero(side).tolist():
                new.append(page.mean[i], page.w[i], page.within[i], page.below[i] if page.below is not None else None)
            made.append(new)
        return made[0], made[1]

    def _leaves(self) -> list[_Page]:
        level = [self.root]
        while level[0].below is not None:
            level = [p for page in level for p in page.below]
        return level

    def _rebuild(self) -> None:
        """Take the leaf entries in again with a radius that joins the closest of them."""
        while self.entries > self.m:
            self.rebuilds += 1
            if self.threshold == 0:
                least = np.inf
                for page in self._leaves():
                    x = page.mean[: page.n]
                    d2 = ((x[:, None] - x[None]) ** 2).sum(2)
                    least = min(least, float(d2[d2 > 0].min()) if (d2 > 0).any() else np.inf)
                self.threshold = float(np.sqrt(least)) if np.isfinite(least) else 1e-9
            else:
                self.threshold *= 2**0.5
            old = self.rows()
            self._clear()
            m, self.m = self.m, len(old[1]) + 1  # no rebuild inside of this one
            for mean, w, within in zip(*old):
                self.insert(mean, float(w), float(within))
            self.m = m

    def offer(self, x: np.ndarray, w: np.ndarray | None = None, within: np.ndarray | None = None) -> None:
        x = np.asarray(x, float)
        w = np.ones(len(x)) if w is None else np.asarray(w, float)
        within = np.zeros(len(x)) if within is None else within
        for p, c, e in zip(x, w.tolist(), within.tolist()):
            self.insert(p, c, e)

    def rows(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        pages = self._leaves()
        return (np.concatenate([p.mean[: p.n] for p in pages]), np.rint(np.concatenate([p.w[: p.n] for p in pages])).astype(np.int64), np.concatenate([p.within[: p.n] for p in pages]))


def sampled_heads(x: np.ndarray, w: np.ndarray, m: int, seed) -> np.ndarray:
    """Places of ``m`` points drawn by squared-distance sampling; ``x`` has more than ``m`` points.

    Sampling runs down a binary tree over the points: each leaf holds the points nearest
    to its representative and what they cost. A draw descends by the children's costs,
    picks a point of the leaf by its cost and parts the leaf between the two
    representatives, so a draw looks at one leaf and not at all points.
    """
    n = len(x)
    rng = np.random.default_rng(seed)
    head = int(rng.choice(n, p=w / w.sum()))
    d2 = ((x - x[head]) ** 2).sum(1)
    members, heads, left, right = [np.arange(n)], [head], [-1], [-1]
    costs, parent, leaves = [float((w * d2).sum())], [-1], 1
    while leaves < m and costs[0] > 0:
        v = 0
        while left[v] >= 0:
            a, b = costs[left[v]], costs[right[v]]
            v = left[v] if rng.random() * (a + b) < a else right[v]
        at = members[v]
        p = d2[at] * w[at]
        total = p.sum()
        if total > 0:
            new = int(at[rng.choice(len(at), p=p / total)])
            far = ((x[at] - x[new]) ** 2).sum(1)
            goes = far < d2[at]
            d2[at[goes]] = far[goes]
            for side, who in ((~goes, heads[v]), (goes, new)):
                members.append(at[side])
                heads.append(who)
                left.append(-1)
                right.append(-1)
                costs.append(float((d2[at[side]] * w[at[side]]).sum()))
                parent.append(v)
            left[v], right[v], members[v] = len(costs) - 2, len(costs) - 1, None
            leaves += 1
            new_cost = costs[-2] + costs[-1]
        else:  # what rounding left
            new_cost = 0.0
        while v >= 0:
            costs[v] = new_cost
            v = parent[v]
            new_cost = costs[left[v]] + costs[right[v]] if v >= 0 else 0.0
    return np.array([heads[v] for v in range(len(costs)) if left[v] < 0])


def _nearest_of(x: np.ndarray, chosen: np.ndarray):
    """Blocks of rows and the nearest representative of each: the leaves only decide what is drawn."""
    sq = (chosen * chosen).sum(1)
    for a in range(0, len(x), 4096):
        yield slice(a, a + 4096), (sq - 2.0 * (x[a : a + 4096] @ chosen.T)).argmin(axis=1)


def sampling_coreset(x: np.ndarray, w: np.ndarray, m: int, seed) -> tuple[np.ndarray, np.ndarray]:
    """Baseline: ``m`` representatives by squared-distance sampling, each with the weight of the points nearest to it."""
    if len(x) <= m:
        return x, w.astype(np.int64)
    chosen = x[sampled_heads(x, w, m, seed)]
    weight = np.zeros(len(chosen))
    for at, near in _nearest_of(x, chosen):
        weight += np.bincount(near, w[at], len(chosen))
    keep = weight > 0
    return chosen[keep], np.rint(weight[keep]).astype(np.int64)


def sampled_cells(x: np.ndarray, w: np.ndarray, m: int, seed, within: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The same draw, but a representative stands at the centroid of the points nearest to it: centroids, weights, inner costs.

    Weight, vector sum and energy stay those of the input. In many dimensions a drawn point
    brings its own noise into every center; a centroid does not.
    """
    within = np.zeros(len(x)) if within is None else within
    if len(x) <= m:
        return x, w.astype(np.int64), within
    chosen = x[sampled_heads(x, w, m, seed)]
    weight, moved, inner = np.zeros(len(chosen)), np.zeros_like(chosen), np.zeros(len(chosen))
    for at, near in _nearest_of(x, chosen):
        diff = x[at] - chosen[near]  # from the drawn point, so that nothing cancels
        weight += np.bincount(near, w[at], len(chosen))
        inner += np.bincount(near, within[at] + w[at] * np.einsum("ij,ij->i", diff, diff), len(chosen))
        np.add.at(moved, near, diff * w[at, None])
    keep = weight > 0
    step = moved[keep] / weight[keep, None]
    inner = np.maximum(inner[keep] - weight[keep] * np.einsum("ij,ij->i", step, step), 0.0)
    return chosen[keep] + step, np.rint(weight[keep]).astype(np.int64), inner
