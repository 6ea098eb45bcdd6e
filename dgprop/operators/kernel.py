"""The same rounds and repairs on numpy arrays, for graphs that fit in one task."""

from __future__ import annotations

import numpy as np

from dgprop.operators.filters import FilterSpec


def _sums(to: np.ndarray, of: np.ndarray, w: np.ndarray, values: np.ndarray) -> np.ndarray:
    """At each node the sum of the weights times the values at the other ends, column by column."""
    n, dim = values.shape
    return np.stack([np.bincount(to, w * np.ascontiguousarray(values[:, c])[of], n) for c in range(dim)], axis=1) if dim else np.zeros_like(values)


def _different(keys: np.ndarray) -> np.ndarray:
    """Each number once, in order; sorting takes less than the hashing of ``np.unique``."""
    keys = np.sort(keys)
    return keys[np.concatenate((np.ones(min(1, len(keys)), bool), keys[1:] != keys[:-1]))]


class Flow:
    """What a round moves along the edges of one graph: at each node the sum of weights times the values at the sources.

    Edges of hubs (nodes with so many neighbours that a row of weights is at most ``THIN`` times their number) are
    products of matrices; the others are summed up one by one, only those of the active nodes where these are few.
    """

    THIN = 8

    def __init__(self, n: int, src: np.ndarray, dst: np.ndarray, w: np.ndarray) -> None:
        self.n, self.counts = n, np.bincount(src, minlength=n)
        hub = self.hubs_among(n, self.counts, np.bincount(dst, minlength=n))
        self.hubs = np.flatnonzero(hub)
        if len(self.hubs):
            place = np.zeros(n, np.int64)
            place[self.hubs] = np.arange(len(self.hubs))
            out, into = hub[src], hub[dst]
            self.out, self.into = np.zeros((len(self.hubs), n)), np.zeros((len(self.hubs), n))
            self.out[place[src[out]], dst[out]] = w[out]
            into &= ~out
            self.into[place[dst[into]], src[into]] = w[into]
            rest = ~(out | into)
            src, dst, w = src[rest], dst[rest], w[rest]
        self.src, self.dst, self.w = src, dst, w
        self.start = np.concatenate(([0], np.cumsum(np.bincount(src, minlength=n))))

    @classmethod
    def hubs_among(cls, n: int, out: np.ndarray, into: np.ndarray) -> np.ndarray:
        return (out * cls.THIN >= n) & (into * cls.THIN >= n) & (out > 64)

    @classmethod
    def without_hubs(cls, n: int, src: np.ndarray, dst: np.ndarray, w: np.ndarray, start: np.ndarray, counts: np.ndarray) -> Flow:
        """Of edges in order, those of node i from ``start[i]`` on, of which ``counts[i]`` have a weight."""
        flow = cls.__new__(cls)
        flow.n, flow.counts, flow.hubs, flow.start = n, counts, np.zeros(0, np.int64), start
        flow.src, flow.dst, flow.w = src, dst, w
        return flow

    def sums(self, values: np.ndarray, active: np.ndarray) -> np.ndarray:
        """Of ``values`` (nodes, columns), which are 0 but at the ``active`` nodes."""
        src, dst, w = self.src, self.dst, self.w
        many = self.start[active + 1] - self.start[active]
        total = int(many.sum())
        if total * 4 < len(src):
            at = np.repeat(self.start[active] - np.cumsum(many) + many, many) + np.arange(total)
            src, dst, w = src[at], dst[at], w[at]
        got = _sums(dst, src, w, values) if len(src) else np.zeros_like(values)
        if len(self.hubs):
            got += self.out.T @ values[self.hubs]
            got[self.hubs] += self.into @ values
        return got


class LocalGraph:
    """Nodes 0..n-1, edges in both directions, and the push state of several filters."""

    def __init__(self, nodes: np.ndarray, x: np.ndarray, specs: list[FilterSpec]) -> None:
        order = np.argsort(nodes)
        self.nodes, self.x, self.specs = nodes[order], x[order].astype(float), specs
        n, dim = self.x.shape
        # Edges by ``a * n + b``, in order; those with a weight of 0 are places for edges to come.
        self.keys, self.weights = np.zeros(0, np.int64), np.zeros(0)
        self._placed()
        self.degree = np.zeros(n)
        self.y = np.zeros((len(specs), n, dim))
        self.q = np.stack([self.x.copy() for _ in specs]) if specs else np.zeros((0, n, dim))

    @property
    def safe(self) -> np.ndarray:
        return np.where(self.degree > 1e-12, self.degree, 1.0)

    @property
    def weight(self) -> dict[tuple[int, int], float]:
        src, dst, w = self.arrays()
        return dict(zip(zip(src.tolist(), dst.tolist(), strict=True), w.tolist(), strict=True))

    def arrays(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        there = self.weights > 0
        return self.src[there], self.dst[there], self.weights[there]

    def _at(self, nodes: np.ndarray) -> np.ndarray:
        """Places of nodes."""
        numbered = len(self.nodes) and self.nodes[0] == 0 and self.nodes[-1] == len(self.nodes) - 1
        return np.asarray(nodes) if numbered else np.searchsorted(self.nodes, nodes)

    def _placed(self) -> None:
        """What follows from the keys."""
        n = len(self.nodes)
        self.src, self.dst = np.divmod(self.keys, max(1, n))
        out = np.bincount(self.src, minlength=n)
        self.start = np.concatenate(([0], np.cumsum(out)))
        self.hubs = bool(Flow.hubs_among(n, out, np.bincount(self.dst, minlength=n)).any())
        self.counts = np.bincount(self.src[self.weights > 0], minlength=n)

    def expect(self, src: np.ndarray, dst: np.ndarray) -> None:
        """Make places for edges that are going to be changed, so that a change of few moves none of the others."""
        a, b = self._at(src), self._at(dst)
        self._make_places(_different(a.astype(np.int64) * len(self.nodes) + b))

    def _make_places(self, keys: np.ndarray) -> None:
        there = self.weights > 0
        if not there.all():
            self.keys, self.weights = self.keys[there], self.weights[there]
        at = np.searchsorted(self.keys, keys)
        new = at == len(self.keys)
        new[~new] = self.keys[at[~new]] != keys[~new]
        self.keys, self.weights = np.insert(self.keys, at[new], keys[new]), np.insert(self.weights, at[new], 0.0)
        self._placed()

    def _add(self, keys: np.ndarray, dw: np.ndarray) -> None:
        """Changed weights; an edge whose weight is used up is gone, and later changes of it in the same batch start anew."""
        order = np.argsort(keys, kind="stable")
        keys, dw = keys[order], dw[order]
        at = np.searchsorted(self.keys, keys)
        if not (at < len(self.keys)).all() or (self.keys[at] != keys).any():
            self._make_places(_different(keys))
            at = np.searchsorted(self.keys, keys)
        turn = np.arange(len(keys)) - np.searchsorted(keys, keys)
        places = at[turn == 0]
        before = self.weights[places] > 0
        for k in range(int(turn.max(initial=-1)) + 1):
            now = at[turn == k]
            weight = self.weights[now] + dw[turn == k]
            self.weights[now] = np.where(weight > 1e-12, weight, 0.0)
        np.add.at(self.counts, self.src[places], (self.weights[places] > 0).astype(np.int64) - before)

    def reset(self) -> None:
        """Cold start on the present graph."""
        for s, spec in enumerate(self.specs):
            self.y[s] = 0
            self.q[s] = self.x * self.safe[:, None] ** (spec.beta - 1)

    def apply(self, src: np.ndarray, dst: np.ndarray, dw: np.ndarray, new_x: dict[int, np.ndarray] | None = None) -> int:
        """Change edges (both directions given) and features and repair the residuals; the number of touched nodes."""
        a, b = self._at(src), self._at(dst)
        old, x_old = self.safe.copy(), self.x.copy()
        np.add.at(self.degree, a, dw)
        self._add(a.astype(np.int64) * len(self.nodes) + b, np.asarray(dw, float))
        for node, x in (new_x or {}).items():
            self.x[np.searchsorted(self.nodes, node)] = x
        touched = np.zeros(len(self.nodes), bool)
        touched[a], touched[np.searchsorted(self.nodes, np.array(list(new_x or {}), np.int64))] = True, True
        hit = np.flatnonzero(touched)
        new = self.safe
        for s, spec in enumerate(self.specs):
            y, q = self.y[s], self.q[s]
            moved = _sums(a, b, dw, y)
            held = (y[hit] + spec.g0 * q[hit] - spec.g0 * x_old[hit] * old[hit, None] ** (spec.beta - 1)) * old[hit, None]
            right = spec.g0 * self.x[hit] * new[hit, None] ** (spec.beta - 1) + (held + spec.ratio * moved[hit]) / new[hit, None]
            q[hit] = (right - y[hit]) / spec.g0
        return len(hit)

    def push(self, rmax: float, max_rounds: int | None = None, apart: bool = False) -> dict:
        """Rounds until no residual is above ``rmax``, of all columns together or of each alone, which gives the same states."""
        n = len(self.nodes)
        flow = Flow(n, *self.arrays()) if self.hubs else Flow.without_hubs(n, self.src, self.dst, self.weights, self.start, self.counts)
        ranges = [slice(c, c + 1) for c in range(self.x.shape[1])] if apart else [slice(None)]
        done = [self._rounds(flow, at, rmax, max_rounds) for at in ranges]
        return {"rounds": max((d[0] for d in done), default=0), "pushes": sum(d[1] for d in done), "edges_touched": sum(d[2] for d in done), "max_abs_q": float(np.abs(self.q).max(initial=0.0))}

    def _rounds(self, flow: Flow, at: slice, rmax: float, max_rounds: int | None) -> tuple[int, int, int]:
        safe, y, q = self.safe[:, None], self.y[:, :, at].copy(), self.q[:, :, at].copy()
        (many, n, dim), edges, pushes, rounds = q.shape, 0, 0, 0
        while max_rounds is None or rounds < max_rounds:
            on = np.abs(q) > rmax
            active = np.flatnonzero(on.any(axis=(0, 2)))
            if not len(active):
                break
            rounds += 1
            pushes += int(on.sum())
            edges += int(flow.counts[active].sum())
            a = np.where(on, q, 0.0)
            got = flow.sums(a.transpose(1, 0, 2).reshape(n, many * dim), active).reshape(n, many, dim)
            for s, spec in enumerate(self.specs):
                y[s] += spec.g0 * a[s]
                q[s] += spec.ratio * got[:, s] / safe - a[s]
        self.y[:, :, at], self.q[:, :, at] = y, q
        return rounds, pushes, edges

    def push_in_turn(self, rmax: float) -> int:
        """One active cell after the other, in the order of nodes; for comparison only."""
        src, dst, w = self.arrays()
        by_node: dict[int, list[tuple[int, float]]] = {}
        for i, j, v in zip(src.tolist(), dst.tolist(), w.tolist(), strict=True):
            by_node.setdefault(i, []).append((j, v))
        n, safe = 0, self.safe
        for s, spec in enumerate(self.specs):
            while True:
                on = np.argwhere(np.abs(self.q[s]) > rmax)
                if not len(on):
                    break
                for i, c in on.tolist():
                    v = self.q[s, i, c]
                    if abs(v) <= rmax:
                        continue
                    n += 1
                    self.y[s, i, c] += spec.g0 * v
                    self.q[s, i, c] = 0.0
                    for j, weight in by_node.get(i, []):
                        self.q[s, j, c] += spec.ratio * weight / safe[j] * v
        return n

    def read(self) -> np.ndarray:
        """Representations of all filters, side by side."""
        return np.concatenate([y * self.safe[:, None] ** (1 - spec.beta) for y, spec in zip(self.y, self.specs, strict=True)], axis=1)

    def potential(self) -> float:
        return float((np.abs(self.q) * self.safe[None, :, None]).sum())

    def identity_gap(self) -> float:
        src, dst, w = self.arrays()
        gap, safe = 0.0, self.safe[:, None]
        for y, q, spec in zip(self.y, self.q, self.specs, strict=True):
            sums = _sums(dst, src, w, y)
            gap = max(gap, float(np.abs(y + spec.g0 * q - spec.g0 * self.x * safe ** (spec.beta - 1) - spec.ratio * sums / safe).max(initial=0.0)))
        return gap

    def exact(self) -> np.ndarray:
        """Dense solution of every filter, side by side."""
        n = len(self.nodes)
        src, dst, w = self.arrays()
        a = np.zeros((n, n))
        a[src, dst] = w
        safe, out = self.safe, []
        for spec in self.specs:
            p = safe[:, None] ** -spec.beta * a * safe[None, :] ** (spec.beta - 1)
            out.append(np.linalg.solve(np.eye(n) - spec.ratio * p, spec.g0 * self.x))
        return np.concatenate(out, axis=1)
