"""The learnable layers on sentence groups in numpy: forward with caches, backward by hand.

A group is several sentence graphs laid side by side: states ``x`` (nodes x width), edges as receiver and sender numbers sorted
by receiver, and for each edge the number of its distinct relation set. Everything that depends on edge vectors is computed once
per relation set, never once per edge.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

Params = dict[str, np.ndarray]


@dataclass
class Graph:
    n: int
    receiver: np.ndarray
    sender: np.ndarray
    relset: np.ndarray
    #: Indicator of relations in each distinct set: sets x relations.
    sets: np.ndarray


def relu(x: np.ndarray) -> np.ndarray:
    return np.maximum(x, 0.0)


def mlp(p: Params, name: str, x: np.ndarray) -> tuple[np.ndarray, tuple]:
    z = x @ p[f"{name}.w1"] + p[f"{name}.b1"]
    h = relu(z)
    return h @ p[f"{name}.w2"] + p[f"{name}.b2"], (x, z, h)


def mlp_back(p: Params, name: str, cache: tuple, dy: np.ndarray, g: Params) -> np.ndarray:
    x, z, h = cache
    put(g, f"{name}.w2", h.T @ dy)
    put(g, f"{name}.b2", dy.sum(axis=0))
    dz = (dy @ p[f"{name}.w2"].T) * (z > 0)
    put(g, f"{name}.w1", x.T @ dz)
    put(g, f"{name}.b1", dz.sum(axis=0))
    return dz @ p[f"{name}.w1"].T


def put(g: Params, name: str, value: np.ndarray) -> None:
    g[name] = g[name] + value if name in g else value


def mlp_params(rng: np.random.Generator, name: str, a: int, h: int, b: int, out_scale: float = 1.0) -> Params:
    return {
        f"{name}.w1": rng.normal(0, (2 / a) ** 0.5, (a, h)), f"{name}.b1": np.zeros(h),
        f"{name}.w2": rng.normal(0, out_scale * (1 / h) ** 0.5, (h, b)), f"{name}.b2": np.zeros(b),
    }


def segment_softmax(z: np.ndarray, seg: np.ndarray, n: int) -> np.ndarray:
    top = np.full(n, -np.inf)
    np.maximum.at(top, seg, z)
    e = np.exp(z - top[seg])
    return e / np.bincount(seg, e, n)[seg]


def gather_sum(seg: np.ndarray, values: np.ndarray, n: int) -> np.ndarray:
    out = np.zeros((n, values.shape[1]))
    np.add.at(out, seg, values)
    return out


class Layer:
    """``forward(p, x, graph) -> (y, cache)`` and ``backward(p, cache, dy, graph, g) -> dx``; parameters start with ``self.name``."""

    def __init__(self, name: str, width: int, edge_width: int, hidden: int = 32) -> None:
        self.name, self.width, self.edge_width, self.hidden = name, width, edge_width, hidden

    def params(self, rng: np.random.Generator) -> Params:
        return mlp_params(rng, f"{self.name}.theta", self.width, self.hidden, self.width)

    def own(self, p: Params, x: np.ndarray) -> tuple[np.ndarray, tuple]:
        return mlp(p, f"{self.name}.theta", x)


class Identity(Layer):
    def params(self, rng):
        return {}

    def forward(self, p, x, graph):
        return x, None

    def backward(self, p, cache, dy, graph, g):
        return dy


class EdgeSoftmax(Layer):
    """Own state through theta plus a convex mixture of the senders, whose weights are a softmax over each receiver's edges of
    psi(edge vector)."""

    def __init__(self, name, width, edge_width, hidden=32, psi: str | None = None, self_loop: bool = False) -> None:
        super().__init__(name, width, edge_width, hidden)
        self.psi, self.self_loop = psi or f"{name}.psi", self_loop

    def params(self, rng):
        return super().params(rng) | mlp_params(rng, self.psi, self.edge_width, self.hidden, 1)

    def edges(self, graph):
        if not self.self_loop:
            return graph.receiver, graph.sender, graph.relset
        own = np.arange(graph.n)
        return np.concatenate([graph.receiver, own]), np.concatenate([graph.sender, own]), np.concatenate([graph.relset, np.full(graph.n, len(graph.sets))])

    def forward(self, p, x, graph):
        own, c1 = self.own(p, x)
        r, s, k = self.edges(graph)
        vec = graph.sets @ p["relations"]
        if self.self_loop:
            vec = np.vstack([vec, np.zeros(self.edge_width)])
        z, c2 = mlp(p, self.psi, vec)
        a = segment_softmax(z[k, 0], r, graph.n) if len(r) else np.zeros(0)
        y = own + gather_sum(r, a[:, None] * x[s], graph.n)
        return y, (x, c1, c2, a, r, s, k)

    def backward(self, p, cache, dy, graph, g):
        x, c1, c2, a, r, s, k = cache
        dx = mlp_back(p, f"{self.name}.theta", c1, dy, g)
        dx += gather_sum(s, a[:, None] * dy[r], graph.n)
        c = np.einsum("ed,ed->e", dy[r], x[s])
        dz = a * (c - np.bincount(r, a * c, graph.n)[r])
        dset = np.bincount(k, dz, len(c2[0]))[:, None]
        dvec = mlp_back(p, self.psi, c2, dset, g)
        put(g, "relations", graph.sets.T @ dvec[: len(graph.sets)])
        return dx


class EdgeConv(Layer):
    """Own state through theta plus all senders, each through a gate made from its edge vector: a scalar, a vector or a matrix."""

    def __init__(self, name, width, edge_width, hidden=32, gate: str = "matrix") -> None:
        super().__init__(name, width, edge_width, hidden)
        self.gate, self.out = gate, {"scalar": 1, "diagonal": width, "matrix": width * width}[gate]

    def params(self, rng):
        scale = 0.3 if self.gate == "matrix" else 1.0
        return super().params(rng) | mlp_params(rng, f"{self.name}.psi", self.edge_width, self.hidden, self.out, scale / self.width**0.5)

    def forward(self, p, x, graph):
        own, c1 = self.own(p, x)
        gates, c2 = mlp(p, f"{self.name}.psi", graph.sets @ p["relations"])
        y = own.copy()
        if self.gate != "matrix":
            np.add.at(y, graph.receiver, x[graph.sender] * gates[graph.relset])
        else:
            for k in np.unique(graph.relset):  # one product a relation set
                e = graph.relset == k
                np.add.at(y, graph.receiver[e], x[graph.sender[e]] @ gates[k].reshape(self.width, self.width))
        return y, (x, c1, c2, gates)

    def backward(self, p, cache, dy, graph, g):
        x, c1, c2, gates = cache
        dx = mlp_back(p, f"{self.name}.theta", c1, dy, g)
        dg = np.zeros_like(gates)
        dr, xs = dy[graph.receiver], x[graph.sender]
        if self.gate == "matrix":
            for k in np.unique(graph.relset):
                e = graph.relset == k
                m = gates[k].reshape(self.width, self.width)
                np.add.at(dx, graph.sender[e], dr[e] @ m.T)
                dg[k] = (xs[e].T @ dr[e]).ravel()
        else:
            np.add.at(dx, graph.sender, dr * gates[graph.relset])
            d = dr * xs
            np.add.at(dg, graph.relset, d.sum(axis=1, keepdims=True) if self.gate == "scalar" else d)
        put(g, "relations", graph.sets.T @ mlp_back(p, f"{self.name}.psi", c2, dg, g))
        return dx


class NodeAttention(Layer):
    """Weights from the two states, edge vectors unused: heads of width / heads dimensions, a self loop, ELU-free output."""

    def __init__(self, name, width, edge_width, hidden=32, heads: int = 4, slope: float = 0.2) -> None:
        super().__init__(name, width, edge_width, hidden)
        self.heads, self.slope = heads, slope

    def params(self, rng):
        d = self.width // self.heads
        one = lambda *s: rng.normal(0, (1 / s[-1]) ** 0.5, s)
        return {f"{self.name}.w": rng.normal(0, (1 / self.width) ** 0.5, (self.width, self.width)), f"{self.name}.a1": one(self.heads, d), f"{self.name}.a2": one(self.heads, d)}

    def forward(self, p, x, graph):
        own = np.arange(graph.n)
        r, s = np.concatenate([graph.receiver, own]), np.concatenate([graph.sender, own])
        h = (x @ p[f"{self.name}.w"]).reshape(graph.n, self.heads, -1)
        u, v = np.einsum("nhd,hd->nh", h, p[f"{self.name}.a1"]), np.einsum("nhd,hd->nh", h, p[f"{self.name}.a2"])
        raw = u[r] + v[s]
        z = np.where(raw > 0, raw, self.slope * raw)
        a = np.stack([segment_softmax(z[:, k], r, graph.n) for k in range(self.heads)], axis=1)
        y = np.zeros_like(h)
        np.add.at(y, r, a[:, :, None] * h[s])
        return y.reshape(graph.n, -1), (x, h, raw, a, r, s)

    def backward(self, p, cache, dy, graph, g):
        x, h, raw, a, r, s = cache
        d = dy.reshape(graph.n, self.heads, -1)
        dh = np.zeros_like(h)
        np.add.at(dh, s, a[:, :, None] * d[r])
        c = np.einsum("ehd,ehd->eh", d[r], h[s])
        mean = np.stack([np.bincount(r, a[:, k] * c[:, k], graph.n) for k in range(self.heads)], axis=1)
        dz = a * (c - mean[r]) * np.where(raw > 0, 1.0, self.slope)
        du, dv = (np.stack([np.bincount(i, dz[:, k], graph.n) for k in range(self.heads)], axis=1) for i in (r, s))
        put(g, f"{self.name}.a1", np.einsum("nh,nhd->hd", du, h))
        put(g, f"{self.name}.a2", np.einsum("nh,nhd->hd", dv, h))
        dh += du[:, :, None] * p[f"{self.name}.a1"] + dv[:, :, None] * p[f"{self.name}.a2"]
        flat = dh.reshape(graph.n, -1)
        put(g, f"{self.name}.w", x.T @ flat)
        return flat @ p[f"{self.name}.w"].T


class MeanNeighbours(Layer):
    """Own state through theta plus the senders' mean (or their symmetrically normalised sum): no edge vectors."""

    def __init__(self, name, width, edge_width, hidden=32, norm: str = "mean") -> None:
        super().__init__(name, width, edge_width, hidden)
        self.norm = norm

    def weights(self, graph):
        deg = np.maximum(np.bincount(graph.receiver, minlength=graph.n), 1)
        return 1.0 / deg[graph.receiver] if self.norm == "mean" else 1.0 / np.sqrt(deg[graph.receiver] * deg[graph.sender])

    def forward(self, p, x, graph):
        own, c1 = self.own(p, x)
        a = self.weights(graph)
        return own + gather_sum(graph.receiver, a[:, None] * x[graph.sender], graph.n), (c1, a)

    def backward(self, p, cache, dy, graph, g):
        c1, a = cache
        return mlp_back(p, f"{self.name}.theta", c1, dy, g) + gather_sum(graph.sender, a[:, None] * dy[graph.receiver], graph.n)


LAYERS = {
    "edge_softmax": EdgeSoftmax, "edge_conv": EdgeConv, "node_attention": NodeAttention, "mean": MeanNeighbours, "identity": Identity,
}


def stack(kind: str, layers: int, width: int, edge_width: int, hidden: int = 32, **options) -> list[Layer]:
    """``layers`` layers. ``share_edge_mlp`` gives all edge-softmax layers one psi, so their weights are the same in every layer."""
    share = options.pop("share_edge_mlp", False)
    out = []
    for k in range(layers):
        more = {"psi": "psi"} if share and kind == "edge_softmax" else {}
        out.append(LAYERS[kind](f"layer{k}", width, edge_width, hidden, **options, **more))
    return out


def softmax_loss(z: np.ndarray, y: np.ndarray) -> tuple[float, np.ndarray]:
    """Mean cross-entropy and its gradient; an empty task contributes 0."""
    if not len(y):
        return 0.0, np.zeros_like(z)
    e = np.exp(z - z.max(axis=1, keepdims=True))
    q = e / e.sum(axis=1, keepdims=True)
    loss = -np.log(np.maximum(q[np.arange(len(y)), y], 1e-300)).mean()
    q[np.arange(len(y)), y] -= 1
    return float(loss), q / len(y)
