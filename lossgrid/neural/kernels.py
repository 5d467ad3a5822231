"""Graph layers, the partition objective and their gradients on arrays."""

from __future__ import annotations

import os
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass
from functools import cache, cached_property

import numpy as np

from ..plans.spec import TrainConfig

#: Rows that one thread works on at a time; fixed, so that results do not depend on the number of cores.
CHUNK = 4096
#: Neighbours of a node that are added one position after the other; those beyond it are summed by node.
SLOTS = 24


@cache
def _pool() -> ThreadPoolExecutor:
    return ThreadPoolExecutor(max(1, len(os.sched_getaffinity(0))))


def _each_chunk(n: int, work: Callable[[int, int], None]) -> None:
    """``work(from, to)`` for all rows, on threads if there are many."""
    if n <= 2 * CHUNK:
        work(0, n)
    else:
        list(_pool().map(lambda a: work(a, min(n, a + CHUNK)), range(0, n, CHUNK)))


def by_rows(f: Callable[..., np.ndarray], first: np.ndarray, *more: np.ndarray) -> np.ndarray:
    """f of matrices of equal shape, whose rows do not depend on each other, in place of the first."""

    def work(a: int, b: int) -> None:
        first[a:b] = f(first[a:b], *[x[a:b] for x in more])

    _each_chunk(len(first), work)
    return first


class RowSums:
    """Weighted sums of the rows ``of`` by ``to`` (sorted), laid out for many products with one graph.

    Nodes stand in order of their number of neighbours, so that those with a k-th one are the first
    of them.
    """

    def __init__(self, to: np.ndarray, of: np.ndarray, w: np.ndarray, n: int):
        first = np.searchsorted(to, np.arange(n + 1))
        count = np.diff(first)
        self.n, self.order = n, np.argsort(-count, kind="stable")
        count, first, unit = count[self.order], first[:-1][self.order], bool((w == 1).all())
        self.slots = []
        for k in range(min(SLOTS, int(count.max(initial=0)))):
            at = first[: np.searchsorted(-count, -k, side="left")] + k
            self.slots.append((of[at], None if unit else w[at][:, None]))
        self.more = []
        for v in range(int(np.searchsorted(-count, -SLOTS, side="left"))):
            at = slice(first[v] + SLOTS, first[v] + count[v])
            self.more.append((of[at], w[at]))

    def __call__(self, x: np.ndarray) -> np.ndarray:
        out = np.zeros((self.n, x.shape[1]))

        def work(a: int, b: int) -> None:
            total = np.zeros((b - a, x.shape[1]))
            room = np.empty((b - a, x.shape[1]))
            for of, w in self.slots:
                part = room[: max(0, min(b, len(of)) - a)]
                if not len(part):
                    break
                x.take(of[a:b], axis=0, out=part, mode="clip")
                if w is not None:
                    part *= w[a:b]
                total[: len(part)] += part
            for v in range(a, min(b, len(self.more))):
                of, w = self.more[v]
                total[v - a] += w @ x[of]
            out[self.order[a:b]] = total

        _each_chunk(self.n, work)
        return out


@dataclass
class ArrayGraph:
    """Edges in both directions sorted by source; ``whole`` has the nodes' degrees where the edges here
    are not all they have."""

    src: np.ndarray
    dst: np.ndarray
    w: np.ndarray
    n: int
    whole: np.ndarray | None = None

    @staticmethod
    def of(src: np.ndarray, dst: np.ndarray, w: np.ndarray, n: int, whole: np.ndarray | None = None) -> ArrayGraph:
        by = np.lexsort((dst, src))
        return ArrayGraph(src[by], dst[by], w[by].astype(float), n, whole)

    @property
    def deg(self) -> np.ndarray:
        return np.bincount(self.src, self.w, self.n) if self.whole is None else self.whole

    @cached_property
    def _forth(self) -> RowSums:
        return RowSums(self.src, self.dst, self.w, self.n)

    @cached_property
    def _back(self) -> RowSums:
        by = np.argsort(self.dst, kind="stable")
        return RowSums(self.dst[by], self.src[by], self.w[by], self.n)

    @cached_property
    def unit(self) -> ArrayGraph:
        """The same edges, each with weight 1."""
        return ArrayGraph(self.src, self.dst, np.ones(len(self.src)), self.n)

    def times(self, x: np.ndarray) -> np.ndarray:
        """A x."""
        return self._forth(x)

    def times_transposed(self, x: np.ndarray) -> np.ndarray:
        return self._back(x)

    def sampled(self, fanout: int, seed: int) -> ArrayGraph:
        """At most ``fanout`` neighbours of each node, each with weight 1."""
        key = np.random.default_rng(seed).random(len(self.src))
        by = np.lexsort((key, self.src))
        rank = np.arange(len(by)) - np.searchsorted(self.src[by], self.src[by])
        pick = np.sort(by[rank < fanout])
        return ArrayGraph(self.src[pick], self.dst[pick], np.ones(len(pick)), self.n)


def _gather(keys: np.ndarray, rows: np.ndarray, n: int) -> np.ndarray:
    """Sums of rows by sorted key."""
    out = np.zeros((n, rows.shape[1]))
    if len(keys):
        first = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]]))
        out[keys[first]] = np.add.reduceat(rows, first, axis=0)
    return out


def act(x: np.ndarray, kind: str) -> np.ndarray:
    return np.maximum(x, 0) if kind == "relu" else by_rows(np.tanh, x) if kind == "tanh" else x


def act_back(grad: np.ndarray, y: np.ndarray, kind: str) -> np.ndarray:
    """Gradient before the activation whose values are y."""
    return grad * (y > 0) if kind == "relu" else by_rows(lambda d, v: d * (1 - v * v), grad, y) if kind == "tanh" else grad


class Propagation:
    """(A + I) scaled on both sides (sym), by rows (rw), or not."""

    def __init__(self, graph: ArrayGraph, norm: str):
        self.graph, self.norm, self.deg = graph, norm, graph.deg + 1

    def __call__(self, x: np.ndarray) -> np.ndarray:
        if self.norm == "sym":
            s = 1 / np.sqrt(self.deg)[:, None]
            x = s * x
            out = self.graph.times(x)
            out += x
            out *= s
            return out
        out = self.graph.times(x) + x
        return out / self.deg[:, None] if self.norm == "rw" else out

    def transposed(self, x: np.ndarray) -> np.ndarray:
        if self.norm == "rw":
            x = x / self.deg[:, None]
            return self.graph.times(x) + x
        return self(x)


class Aggregation:
    """Neighbourhood of each node: mean, largest (pool), or mean with the node itself (gcn)."""

    def __init__(self, graph: ArrayGraph, kind: str):
        self.graph, self.kind = graph, kind
        count = np.bincount(graph.src, graph.w, graph.n)
        self.count = np.where(count > 0, count, 1) if kind != "gcn" else count + 1

    def __call__(self, x: np.ndarray) -> np.ndarray:
        g = self.graph
        if self.kind == "pool":
            out = np.zeros_like(x)
            if len(g.src):
                first = np.flatnonzero(np.concatenate([[True], g.src[1:] != g.src[:-1]]))
                out[g.src[first]] = np.maximum.reduceat(x[g.dst], first, axis=0)
            self.x, self.out = x, out
            return out
        total = g.times(x) + (x if self.kind == "gcn" else 0)
        return total / self.count[:, None]

    def transposed(self, grad: np.ndarray) -> np.ndarray:
        g = self.graph
        if self.kind == "pool":
            hit = (self.x[g.dst] == self.out[g.src]).astype(float)
            ways = _gather(g.src, hit, g.n)
            flow = hit * (grad / np.where(ways > 0, ways, 1))[g.src]
            by = np.argsort(g.dst, kind="stable")
            return _gather(g.dst[by], flow[by], g.n)
        grad = grad / self.count[:, None]
        return g.times_transposed(grad) + (grad if self.kind == "gcn" else 0)


def softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(axis=1, keepdims=True))
    return e / e.sum(axis=1, keepdims=True)


def part_sums(graph: ArrayGraph, load: np.ndarray, y: np.ndarray, own: np.ndarray | slice = slice(None), ay: np.ndarray | None = None) -> np.ndarray:
    """Sums over the own nodes that the objective is made of, by part: of Y, Y D, Y A Y, Y F and, the same
    for all parts, of F / g."""
    y1, ay = y[own], graph.times(y) if ay is None else ay
    return np.stack([y1.sum(axis=0), y1.T @ graph.deg[own], (y1 * ay[own]).sum(axis=0), y1.T @ load[own], np.full(y.shape[1], load[own].sum() / y.shape[1])])


def terms(sums: np.ndarray, form: str = "cut", scale: str = "mean") -> tuple[float, float]:
    """Expected normalized cut and balance term of the sums over all nodes."""
    s, vol, inner, loads, (mean, *_) = sums
    g, vol = len(s), np.maximum(vol, 1e-12)
    over = mean * mean if scale == "mean" and mean > 0 else 1.0
    cut = g - (inner / vol).sum() if form == "cut" else ((s * s - inner) / vol).sum()
    return float(cut), float(((loads - mean) ** 2).sum() / over)


def slope(graph: ArrayGraph, load: np.ndarray, y: np.ndarray, sums: np.ndarray, form: str = "cut", scale: str = "mean", alpha: float = 1.0, beta: float = 1.0, ay: np.ndarray | None = None) -> np.ndarray:
    """Gradient by y of beta times the cut and alpha times the balance term, given the sums over all nodes."""
    s, vol, inner, loads, (mean, *_) = sums
    deg, ay, vol = graph.deg, graph.times(y) if ay is None else ay, np.maximum(vol, 1e-12)
    over = mean * mean if scale == "mean" and mean > 0 else 1.0
    if form == "cut":
        grad = -2 * ay / vol + (inner / vol**2)[None, :] * deg[:, None]
    else:
        grad = (2 * s[None, :] - 2 * ay) / vol - ((s * s - inner) / vol**2)[None, :] * deg[:, None]
    return beta * grad + alpha * 2 * load[:, None] * (loads - mean)[None, :] / over


def objective(graph: ArrayGraph, load: np.ndarray, y: np.ndarray, form: str = "cut", scale: str = "mean", alpha: float = 1.0, beta: float = 1.0) -> tuple[float, float, np.ndarray]:
    """Expected normalized cut, balance term, and the gradient of their weighted sum by y."""
    ay = graph.times(y)
    sums = part_sums(graph, load, y, ay=ay)
    return *terms(sums, form, scale), slope(graph, load, y, sums, form, scale, alpha, beta, ay)


class Network:
    """Two graph convolutions, one neighbourhood aggregation, a dense layer and a softmax."""

    def __init__(self, features: int, cfg: TrainConfig):
        rng = np.random.default_rng(cfg.seed)
        wide = cfg.hidden if cfg.agg == "gcn" else 2 * cfg.hidden
        shapes = {"w0": (features, cfg.hidden), "w1": (cfg.hidden, cfg.hidden), "wn": (wide, cfg.embed), "wo": (cfg.embed, cfg.g)}
        self.cfg, self.seen = cfg, None
        self.weights = {k: rng.normal(0, np.sqrt(2 / a), (a, b)) for k, (a, b) in shapes.items()} | {"bo": np.zeros((1, cfg.g))}

    def forward(self, graph: ArrayGraph, x: np.ndarray, sample: int = 0) -> np.ndarray:
        c, w = self.cfg, self.weights
        self.prop = Propagation(graph, c.norm)
        near = graph.sampled(c.fanout, c.seed + sample) if c.fanout else graph.unit
        self.agg = Aggregation(near, c.agg)
        if self.seen is None or self.seen[0] is not graph or self.seen[1] is not x:
            self.seen, self.x0 = (graph, x), self.prop(x)
        self.h1 = act(self.x0 @ w["w0"], c.act)
        self.x1 = self.prop(self.h1)
        self.h2 = act(self.x1 @ w["w1"], c.act)
        around = self.agg(self.h2)
        self.x2 = around if c.agg == "gcn" else np.concatenate([self.h2, around], axis=1)
        self.h3 = act(self.x2 @ w["wn"], c.act)
        return by_rows(softmax, self.h3 @ w["wo"] + w["bo"])

    def backward(self, y: np.ndarray, grad_y: np.ndarray) -> dict[str, np.ndarray]:
        c, w, out = self.cfg, self.weights, {}
        dz = y * (grad_y - (grad_y * y).sum(axis=1, keepdims=True))
        out["wo"], out["bo"] = self.h3.T @ dz, dz.sum(axis=0, keepdims=True)
        d3 = act_back(dz @ w["wo"].T, self.h3, c.act)
        out["wn"] = self.x2.T @ d3
        dx2 = d3 @ w["wn"].T
        h = c.hidden
        dh2 = self.agg.transposed(dx2) if c.agg == "gcn" else dx2[:, :h] + self.agg.transposed(dx2[:, h:])
        d2 = act_back(dh2, self.h2, c.act)
        out["w1"] = self.x1.T @ d2
        d1 = act_back(self.prop.transposed(d2 @ w["w1"].T), self.h1, c.act)
        out["w0"] = self.x0.T @ d1
        return out


class Step:
    """Adam or plain gradient descent."""

    def __init__(self, cfg: TrainConfig):
        self.cfg, self.t, self.m, self.v = cfg, 0, {}, {}

    def __call__(self, weights: dict, grads: dict) -> None:
        self.t += 1
        for k, g in grads.items():
            if self.cfg.optimizer == "sgd":
                weights[k] -= self.cfg.lr * g
                continue
            self.m[k] = 0.9 * self.m.get(k, 0) + 0.1 * g
            self.v[k] = 0.999 * self.v.get(k, 0) + 0.001 * g * g
            weights[k] -= self.cfg.lr * (self.m[k] / (1 - 0.9**self.t)) / (np.sqrt(self.v[k] / (1 - 0.999**self.t)) + 1e-8)


def descend(net: Network, look, back) -> list[dict]:
    """Leaves the weights with the lowest objective seen in ``net``; ends after ``patience`` epochs without
    a better one.  ``look(epoch)`` gives cut and balance, ``back()`` the gradients after it."""
    cfg, step, trace = net.cfg, Step(net.cfg), []
    best, kept, since = np.inf, None, 0
    for epoch in range(cfg.epochs):
        cut, balance = look(epoch)
        total = cfg.beta * cut + cfg.alpha * balance
        trace.append({"epoch": epoch, "cut": cut, "balance": balance, "objective": total})
        if total < best - 1e-6:
            best, kept, since = total, {k: v.copy() for k, v in net.weights.items()}, 0
        else:
            since += 1
            if since > cfg.patience:
                break
        step(net.weights, back())
    net.weights = kept or net.weights
    return trace


def fit(graph: ArrayGraph, x: np.ndarray, load: np.ndarray, cfg: TrainConfig) -> tuple[Network, list[dict]]:
    """A network trained on a graph in memory."""
    net, now = Network(x.shape[1], cfg), {}

    def look(epoch: int) -> tuple[float, float]:
        now["y"] = net.forward(graph, x, epoch)
        cut, balance, now["grad"] = objective(graph, load, now["y"], cfg.form, cfg.balance_scale, cfg.alpha, cfg.beta)
        return cut, balance

    trace = descend(net, look, lambda: net.backward(now["y"], now["grad"]))
    return net, trace


def harden(y: np.ndarray, load: np.ndarray, graph: ArrayGraph, slack: float | None = None, rounds: int = 30) -> np.ndarray:
    """Most probable part.  With ``slack`` parts above (1 + slack) of the mean hand their least
    certain nodes to the most probable part with room, nodes beside that part first, then others,
    until no part is above it or no node fits anywhere."""
    part = y.argmax(axis=1)
    if slack is None:
        return part
    g, most = y.shape[1], (1 + slack) * load.sum() / y.shape[1]
    loads = np.bincount(part, load, g)
    mean = loads.mean()
    for _ in range(rounds):
        over = np.flatnonzero(loads > most)
        if not len(over):
            break
        moved = False
        beside = _gather(graph.src, np.eye(g)[part[graph.dst]], graph.n) > 0
        for k in over:
            mine = np.flatnonzero(part == k)
            # Nodes without a part to go to have none later on: this part only gives, the others only take.
            then = loads[None, :] + load[mine][:, None]
            fits = beside[mine] & (then < loads[k]) & ((then <= most) | (loads < mean))
            fits[:, k] = False
            mine = mine[fits.any(axis=1)]
            score = np.where(beside[mine], y[mine], y[mine] - 1)
            score[:, k] = -np.inf
            for i in mine[np.argsort(-score.max(axis=1), kind="stable")]:
                if loads[k] <= most:
                    break
                for to in np.argsort(-np.where(beside[i], y[i], y[i] - 1)):
                    if to != k and beside[i, to] and loads[to] + load[i] < loads[k] and (loads[to] + load[i] <= most or loads[to] < mean):
                        part[i], moved = to, True
                        loads[k] -= load[i]
                        loads[to] += load[i]
                        break
        if not moved:
            break
    # What is still over hands its least certain nodes to the part with the most room, beside it or not.
    for k in np.argsort(-loads):
        by = np.argsort(y[:, k], kind="stable")
        for i in by[part[by] == k]:
            if loads[k] <= most:
                break
            to = int(np.argmin(loads))
            if load[i] > 0 and loads[to] + load[i] <= most:
                part[i] = to
                loads[k] -= load[i]
                loads[to] += load[i]
    return part
