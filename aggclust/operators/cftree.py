"""A height-balanced tree of cluster features, built inside one task.

Nodes are rows of flat arrays.  Inserting goes to the nearest child on each level, then absorbs
into the nearest leaf entry if the criterion stays within the threshold, or opens an entry; an
overfull node splits at its two farthest children.  With a cap on entries, reaching it raises the
threshold and builds a smaller tree from the entries, so memory stays bounded.

Points come in blocks that grow with the tree.  A block is routed level by level for all points at
once; then, round by round, the first waiting point of every leaf is absorbed or opens an entry,
again for all leaves at once, and inner nodes follow from their children.  Within a leaf, points
keep their order and see what came before them; ``block=1`` is insertion one by one.
"""

from __future__ import annotations

import numpy as np

from aggclust.functions.cfdist import squared_rows

#: Points routed together: at most so many, and about two for each leaf node.
BLOCK = 8192


class CFTree:
    """``route`` chooses the way down and ``absorb`` decides at the leaf; they are best the same.

    ``threshold`` is compared squared.  ``growth`` is how the threshold rises at the cap: by the
    median or mean distance of an entry to the nearest in its node (at least a tenth), or twofold.
    """

    def __init__(self, d: int, threshold: float = 0.0, max_leaves: int | None = None, route: str = "D4", absorb: str | None = None, width: int = 32, growth: str = "mean", block: int | None = None):
        if growth not in ("median", "mean", "double"):
            raise ValueError(f"unknown growth {growth}")
        self.d, self.width, self.route, self.absorb = d, width, route, absorb or route
        self.t2, self.max_leaves, self.growth, self.block = float(threshold) ** 2, max_leaves, growth, block
        self.rebuilds = self.inserted = 0
        self._clear(64)

    def _clear(self, room: int) -> None:
        w = self.width + 1  # one slot more, until an overfull node splits
        self.n, self.mu, self.sse = np.zeros((room, w)), np.zeros((room, self.d, w)), np.zeros((room, w))
        self.child = np.full((room, w), -1, np.int64)
        self.k, self.parent, self.slot = np.zeros(room, np.int64), np.full(room, -1, np.int64), np.zeros(room, np.int64)
        self.nodes, self.root, self.depth, self.entries, self.leaf_nodes = 1, 0, 1, 0, 1

    def _node(self) -> int:
        if self.nodes == len(self.k):
            for name in ("n", "mu", "sse", "child", "k", "parent", "slot"):
                old = getattr(self, name)
                setattr(self, name, np.concatenate([old, np.full_like(old, -1 if name in ("child", "parent") else 0)]))
        self.nodes += 1
        return self.nodes - 1

    @property
    def threshold(self) -> float:
        return self.t2**0.5

    def raise_to(self, threshold: float) -> None:
        """Go on with at least this threshold; entries stay as they are."""
        self.t2 = max(self.t2, float(threshold) ** 2)

    def insert(self, n: float, mu: np.ndarray, sse: float) -> None:
        self.insert_many(np.array([n], float), np.asarray(mu, float)[None, :], np.array([sse], float))

    def insert_points(self, points: np.ndarray, weights: np.ndarray | None = None) -> None:
        w = np.ones(len(points)) if weights is None else np.asarray(weights, float)
        self.insert_many(w, np.asarray(points, float), np.zeros(len(points)))

    def insert_many(self, n: np.ndarray, mu: np.ndarray, sse: np.ndarray) -> None:
        """Insert features (n, mu (m, d), sse) in their order."""
        self.inserted += len(n)
        self._insert(n, mu, sse, self.max_leaves)

    def _insert(self, n: np.ndarray, mu: np.ndarray, sse: np.ndarray, cap: int | None) -> None:
        at = 0
        while at < len(n):
            size = self.block or min(BLOCK, 2 * self.leaf_nodes - 1)
            self._insert_block(n[at : at + size], mu[at : at + size], sse[at : at + size], cap)
            at += size

    def _distances(self, kind: str, v: np.ndarray, n: np.ndarray, mu: np.ndarray, sse: np.ndarray) -> np.ndarray:
        """Squared distances of one feature each to the children of a node each; unused slots are infinite."""
        with np.errstate(divide="ignore", invalid="ignore"):
            out = squared_rows(kind, n, mu, sse, self.n[v], self.mu[v], self.sse[v])
        out[np.arange(out.shape[1])[None, :] >= self.k[v][:, None]] = np.inf
        return out

    def _leaf_of(self, n: np.ndarray, mu: np.ndarray, sse: np.ndarray) -> np.ndarray:
        v = np.full(len(n), self.root)
        for _ in range(self.depth - 1):
            v = self.child[v, self._distances(self.route, v, n, mu, sse).argmin(1)]
        return v

    def _insert_block(self, n: np.ndarray, mu: np.ndarray, sse: np.ndarray, cap: int | None) -> None:
        leaf = self._leaf_of(n, mu, sse)
        wait = np.arange(len(n))
        while len(wait):
            _, first = np.unique(leaf[wait], return_index=True)
            now = wait[first]
            wait = np.delete(wait, first)
            broken = self._place(leaf[now], n[now], mu[now], sse[now])
            if cap is not None and self.entries > cap:
                self.rebuild()
                again = wait
            else:
                again = wait[np.isin(leaf[wait], broken)] if broken else wait[:0]
            if len(again):
                leaf[again] = self._leaf_of(n[again], mu[again], sse[again])

    def _place(self, v: np.ndarray, n: np.ndarray, mu: np.ndarray, sse: np.ndarray) -> list[int]:
        """One feature into each of the different leaves ``v``; the leaves that split."""
        d = self._distances(self.route, v, n, mu, sse)
        at = d.argmin(1)
        row = np.arange(len(v))
        near = d[row, at] if self.absorb == self.route else self._distances(self.absorb, v, n, mu, sse)[row, at]
        ok = near <= self.t2
        self._merge(v[ok], at[ok], n[ok], mu[ok], sse[ok])
        x, new = v[~ok], ~ok
        s = self.k[x]
        self.n[x, s], self.mu[x, :, s], self.sse[x, s] = n[new], mu[new], sse[new]
        self.k[x] += 1
        self.entries += len(x)
        if self.depth > 1:
            self._merge(self.parent[v], self.slot[v], n, mu, sse)
        broken = x[self.k[x] > self.width].tolist()
        for node in broken:
            self._split(node)
        if self.depth > 2:
            self._refresh(np.unique(self.parent[v]))
        return broken

    def _merge(self, x: np.ndarray, s: np.ndarray, n: np.ndarray, mu: np.ndarray, sse: np.ndarray) -> None:
        """Union of the children in different slots with a feature each."""
        na = self.n[x, s]
        share = n / (na + n)
        delta = mu - self.mu[x, :, s]
        self.n[x, s] = na + n
        self.mu[x, :, s] += delta * share[:, None]
        self.sse[x, s] += sse + na * share * (delta * delta).sum(1)

    def _totals(self, v: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """The union of each node's children; unused slots weigh nothing."""
        n, mu = self.n[v], self.mu[v]
        n = np.where(np.arange(n.shape[1])[None, :] < self.k[v][:, None], n, 0.0)
        w = n.sum(1)
        gap = mu - mu[:, :, :1]
        mean = np.einsum("rdw,rw->rd", gap, n) / w[:, None]
        gap -= mean[:, :, None]
        return w, mu[:, :, 0] + mean, np.where(n > 0, self.sse[v], 0.0).sum(1) + np.einsum("rdw,rdw,rw->r", gap, gap, n)

    def _refresh(self, v: np.ndarray) -> None:
        """What the ancestors of the nodes ``v`` of one level know of their children."""
        while len(v) and not (len(v) == 1 and v[0] == self.root):
            p, s = self.parent[v], self.slot[v]
            self.n[p, s], self.mu[p, :, s], self.sse[p, s] = self._totals(v)
            v = np.unique(p)

    def _split(self, node: int) -> None:
        k = int(self.k[node])
        n, mu, sse, child = self.n[node, :k].copy(), self.mu[node, :, :k].copy(), self.sse[node, :k].copy(), self.child[node, :k].copy()
        d = squared_rows(self.route, n, mu.T, sse, n[None, :], mu[None, :, :], sse[None, :])
        np.fill_diagonal(d, -1.0)
        a, b = divmod(int(d.argmax()), k)
        to_a = d[a] <= d[b]
        to_a[a], to_a[b] = True, False
        leaf = child[0] < 0
        right = self._node()
        if leaf:
            self.leaf_nodes += 1
        for x, side in ((node, to_a), (right, ~to_a)):
            m = int(side.sum())
            self.n[x, :m], self.mu[x, :, :m], self.sse[x, :m], self.child[x, :m], self.k[x] = n[side], mu[:, side], sse[side], child[side], m
            self.child[x, m:] = -1
            if not leaf:
                self.parent[child[side]], self.slot[child[side]] = x, np.arange(m)
        if node == self.root:
            self.root = p = self._node()
            self.child[p, 0], self.parent[node], self.slot[node], self.k[p] = node, p, 0, 1
            self.depth += 1
        p, s = int(self.parent[node]), int(self.k[self.parent[node]])
        self.child[p, s], self.parent[right], self.slot[right], self.k[p] = right, p, s, s + 1
        both = np.array([node, right])
        at = self.slot[both]
        self.n[p, at], self.mu[p, :, at], self.sse[p, at] = self._totals(both)
        if self.k[p] > self.width:
            self._split(p)

    def _leaf_ids(self) -> np.ndarray:
        """Leaf nodes from left to right."""
        v = np.array([self.root])
        for _ in range(self.depth - 1):
            c = self.child[v]
            v = c[c >= 0]
        return v

    def leaves(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Weights, means (m, d) and sums of squares of the leaf entries, from left to right."""
        v = self._leaf_ids()
        used = np.arange(self.width + 1)[None, :] < self.k[v][:, None]
        return self.n[v][used], self.mu[v].transpose(0, 2, 1)[used], self.sse[v][used]

    def next_threshold(self) -> float:
        """The squared threshold after a rebuild; always at least 1.21 times the squared one before."""
        if self.growth == "double" and self.t2 > 0:
            return 4 * self.t2
        near, w = [], self.width + 1
        ids = self._leaf_ids()
        for lo in range(0, len(ids), 64):
            v = ids[lo : lo + 64]
            rep = np.repeat(v, w)
            d = self._distances(self.absorb, rep, self.n[v].reshape(-1), self.mu[v].transpose(0, 2, 1).reshape(-1, self.d), self.sse[v].reshape(-1))
            own = np.tile(np.arange(w), len(v))
            d[np.arange(len(rep)), own] = np.inf
            near.append(d.min(1)[own < self.k[rep]])
        near = np.concatenate(near)
        near = near[(near > 0) & np.isfinite(near)]
        step = 0.0
        if len(near):
            step = float(np.median(near)) if self.growth != "mean" else float(np.sqrt(near).mean() ** 2)
        return max(step, 1.21 * self.t2, np.finfo(float).tiny)

    def rebuild(self) -> None:
        while True:
            self.t2 = self.next_threshold()
            found = self.leaves()
            # Neighbours in the old tree would wait for each other in the new one's leaves.
            order = np.random.default_rng(len(found[0])).permutation(len(found[0]))
            self._clear(max(64, self.nodes))
            self._insert(*(x[order] for x in found), None)
            self.rebuilds += 1
            if self.entries <= self.max_leaves:
                return

    def levels(self) -> list[tuple]:
        """(node_id, parent_id, level, is_leaf, n, mu, sse): the tree's own hierarchy; entries are leaves."""
        w, mu, sse = self._totals(np.array([self.root])) if self.entries else (np.zeros(1), np.zeros((1, self.d)), np.zeros(1))
        out = [(0, -1, 0, False, float(w[0]), mu[0].tolist(), float(sse[0]))]
        queue = [(self.root, 0, 1)]
        for node, parent, level in queue:
            leaf = level == self.depth
            for i in range(int(self.k[node])):
                me = len(out)
                out.append((me, parent, level, leaf, float(self.n[node, i]), self.mu[node, :, i].tolist(), float(self.sse[node, i])))
                if not leaf:
                    queue.append((int(self.child[node, i]), me, level + 1))
        return out

    def stats(self) -> dict:
        return {"leaves": self.entries, "rebuilds": self.rebuilds, "threshold": self.threshold, "depth": self.depth, "inserted": self.inserted}
