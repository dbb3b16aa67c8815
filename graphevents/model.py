"""The extractor: token vectors, graph layers, fusion, trigger and argument heads, in numpy over batches of sentences.

``Sentence`` is what one group of rows becomes on a worker. A batch lays its sentences side by side: one token matrix, one graph, one
list of pairs. ``loss_and_grads`` is one pass forward and back; ``predict`` gives triggers and arguments.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from zlib import crc32

import numpy as np

from .gnn import kernel as K

NONE = 0


@dataclass
class Config:
    """Sizes and switches. ``layer`` of ``identity`` together with ``fused=False`` is the text-only extractor."""

    dim: int = 48
    kg_dim: int = 32
    hidden: int = 48
    layers: int = 3
    layer: str = "edge_softmax"
    layer_options: dict = field(default_factory=dict)
    fused: bool = True
    context: int = 2
    ngram_dim: int = 64
    triggers: tuple[str, ...] = ("", "Accept", "Binding", "Hold", "Negative", "Positive", "Regulation", "Return")
    roles: tuple[str, ...] = ("", "Cause", "Theme")
    relations: int = 25
    node_kinds: int = 3
    seed: int = 0
    lr: float = 3e-3
    batch: int = 4
    epochs: int = 100
    patience: int = 5
    warmup: float = 0.1
    decay: float = 1e-4


@dataclass
class Sentence:
    sent_id: int
    forms: list[str]
    #: Graph nodes: names; token nodes are ``t:<place>``. Edges (receiver, sender, relations).
    nodes: list[str]
    edges: list[tuple[int, int, tuple[int, ...]]]
    #: Trigger type number of each token.
    labels: list[int]
    #: Entities (head token, id), gold pairs (trigger token, argument token, role number).
    entities: list[tuple[int, int]]
    pairs: list[tuple[int, int, int]]


def hashed_form(form: str, dim: int, n: int = 3) -> np.ndarray:
    """A fixed vector from a word's character n-grams and its shape; digits are folded, so names are alike but for their letters."""
    w = "<" + "".join("0" if c.isdigit() else c for c in form.lower()) + ">"
    v = np.zeros(dim)
    for k in (n, n + 1, len(w)):
        for i in range(max(1, len(w) - k + 1)):
            h = crc32(w[i : i + k].encode())
            v[h % dim] += 1.0 if (h >> 16) & 1 else -1.0
    return v / max(1e-9, np.linalg.norm(v))


def hashed_node(name: str, dim: int) -> np.ndarray:
    """A fixed vector of a node without a trained one: of its name if it is a type, else of its class."""
    key = name if ":" in name and not name[:2] in ("C:", "S:", "P:", "O:") else name[:2]
    rng = np.random.default_rng(crc32(key.encode()))
    return rng.normal(0, 1.0, dim)


class Extractor:
    def __init__(self, config: Config, vectors: dict[str, np.ndarray] | None = None, relation_vectors: np.ndarray | None = None) -> None:
        self.c, self.vectors = config, vectors or {}
        self.layers = K.stack(config.layer, config.layers, config.kg_dim, config.kg_dim, config.hidden, **dict(config.layer_options))
        self.start_relations = relation_vectors
        self._forms: dict[str, np.ndarray] = {}
        self._nodes: dict[str, np.ndarray] = {}

    def params(self) -> K.Params:
        c, rng = self.c, np.random.default_rng(self.c.seed)
        wide = c.ngram_dim * (2 * c.context + 1)
        p = {"enc.w": rng.normal(0, (1 / wide) ** 0.5 * 2, (wide, c.dim)), "enc.b": np.zeros(c.dim)}
        p |= K.mlp_params(rng, "tri", c.dim, c.hidden, len(c.triggers)) | K.mlp_params(rng, "arg", 2 * c.dim, c.hidden, len(c.roles))
        if c.fused:
            p |= {"in.w": rng.normal(0, (1 / c.dim) ** 0.5, (c.dim, c.kg_dim)), "in.b": np.zeros(c.kg_dim)}
            p |= {"out.w": rng.normal(0, (1 / c.kg_dim) ** 0.5, (c.kg_dim, c.dim)), "out.b": np.zeros(c.dim)}
            p["relations"] = rng.normal(0, c.kg_dim**-0.5, (c.relations, c.kg_dim)) if self.start_relations is None else self.start_relations.copy()
            for layer in self.layers:
                p |= layer.params(rng)
        return p

    def form_vector(self, form: str) -> np.ndarray:
        if form not in self._forms:
            if len(self._forms) > 200_000:
                self._forms.clear()
            self._forms[form] = hashed_form(form, self.c.ngram_dim)
        return self._forms[form]

    def node_vector(self, name: str) -> np.ndarray:
        if name not in self._nodes:
            v = self.vectors.get(name)
            self._nodes[name] = hashed_node(name, self.c.kg_dim) if v is None else v
        return self._nodes[name]

    def collate(self, batch: list[Sentence]) -> dict:
        c = self.c
        offsets = np.concatenate([[0], np.cumsum([len(s.forms) for s in batch])])
        rows = []
        zero = np.zeros((c.context, c.ngram_dim))
        for s in batch:
            padded = np.vstack([zero, np.stack([self.form_vector(f) for f in s.forms]), zero])
            n = len(s.forms)
            rows.append(np.hstack([padded[k : k + n] for k in range(2 * c.context + 1)]))
        text = np.vstack(rows)
        fixed, token_of, recv, send, sets, number = [], [], [], [], [], {}
        base = 0
        for s, o in zip(batch, offsets[:-1], strict=True):
            for name in s.nodes:
                token_of.append(o + int(name[2:]) if name.startswith("t:") else -1)
                fixed.append(np.zeros(c.kg_dim) if name.startswith("t:") else self.node_vector(name))
            for i, j, rels in s.edges:
                recv.append(base + i)
                send.append(base + j)
                sets.append(number.setdefault(rels, len(number)))
            base += len(s.nodes)
        matrix = np.zeros((max(1, len(number)), c.relations))
        for rels, k in number.items():
            for r in rels:
                matrix[k, r] = 1.0
        graph = K.Graph(base, np.array(recv, np.int64), np.array(send, np.int64), np.array(sets, np.int64), matrix)
        labels = np.concatenate([np.array(s.labels, np.int64) for s in batch])
        pairs = np.array([(o + a, o + b, r) for s, o in zip(batch, offsets, strict=False) for a, b, r in s.pairs], np.int64).reshape(-1, 3)
        return {"text": text, "graph": graph, "fixed": np.array(fixed).reshape(base, c.kg_dim), "token_of": np.array(token_of, np.int64), "labels": labels, "pairs": pairs, "offsets": offsets}

    def states(self, p: K.Params, b: dict) -> tuple[np.ndarray, tuple]:
        z = b["text"] @ p["enc.w"] + p["enc.b"]
        h = np.tanh(z)
        at = np.flatnonzero(b["token_of"] >= 0)
        if not self.c.fused or not len(at):
            return h, (h, None, None, at)
        x = b["fixed"].copy()
        tok = b["token_of"][at]
        x[at] = h[tok] @ p["in.w"] + p["in.b"]
        caches = []
        for layer in self.layers:
            x, cache = layer.forward(p, x, b["graph"])
            caches.append(cache)
        out = h.copy()
        # A token with several nodes does not occur: its node is named by its place. Unmapped tokens stay as they are.
        out[tok] = out[tok] + x[at] @ p["out.w"] + p["out.b"]
        return out, (h, x, caches, at)

    def states_back(self, p: K.Params, b: dict, cache: tuple, d: np.ndarray, g: K.Params) -> None:
        h, x, caches, at = cache
        dh = d.copy()
        if caches is not None:
            tok = b["token_of"][at]
            K.put(g, "out.w", x[at].T @ d[tok])
            K.put(g, "out.b", d[tok].sum(axis=0))
            dx = np.zeros_like(x)
            dx[at] = d[tok] @ p["out.w"].T
            for layer, cached in zip(reversed(self.layers), reversed(caches), strict=True):
                dx = layer.backward(p, cached, dx, b["graph"], g)
            K.put(g, "in.w", h[tok].T @ dx[at])
            K.put(g, "in.b", dx[at].sum(axis=0))
            dh[tok] += dx[at] @ p["in.w"].T
        dz = dh * (1 - h * h)
        K.put(g, "enc.w", b["text"].T @ dz)
        K.put(g, "enc.b", dz.sum(axis=0))

    def pair_features(self, h: np.ndarray, i: np.ndarray, j: np.ndarray) -> tuple[np.ndarray, tuple]:
        """Both tokens' vectors side by side."""
        return np.hstack([h[i], h[j]]), (i, j)

    def pair_back(self, cache: tuple, dx: np.ndarray, d: np.ndarray) -> None:
        w = d.shape[1]
        np.add.at(d, cache[0], dx[:, :w])
        np.add.at(d, cache[1], dx[:, w : 2 * w])

    def loss_and_grads(self, p: K.Params, batch: list[Sentence]) -> tuple[float, K.Params]:
        b = self.collate(batch)
        g: K.Params = {}
        h, cache = self.states(p, b)
        zt, ct = K.mlp(p, "tri", h)
        lt, dt = K.softmax_loss(zt, b["labels"])
        d = K.mlp_back(p, "tri", ct, dt, g)
        la = 0.0
        if len(b["pairs"]):
            i, j, r = b["pairs"].T
            x, seen = self.pair_features(h, i, j)
            za, ca = K.mlp(p, "arg", x)
            la, da = K.softmax_loss(za, r)
            self.pair_back(seen, K.mlp_back(p, "arg", ca, da, g), d)
        self.states_back(p, b, cache, d, g)
        return lt + la, g

    def predict(self, p: K.Params, batch: list[Sentence]) -> list[dict]:
        """Triggers by token, then roles of pairs of a predicted trigger and an entity or another predicted trigger."""
        b = self.collate(batch)
        h, _ = self.states(p, b)
        labels = K.mlp(p, "tri", h)[0].argmax(axis=1)
        out = []
        for s, o in zip(batch, b["offsets"], strict=False):
            trig = [(t, int(labels[o + t])) for t in range(len(s.forms)) if labels[o + t] != NONE]
            pairs = candidate_pairs([t for t, _ in trig], [t for t, _ in s.entities])
            args = []
            if pairs:
                i, j = np.array(pairs).T + o
                roles = K.mlp(p, "arg", self.pair_features(h, i, j)[0])[0].argmax(axis=1)
                args = [(a, c, int(r)) for (a, c), r in zip(pairs, roles, strict=True) if r != NONE]
            out.append({"sent_id": s.sent_id, "triggers": trig, "arguments": args})
        return out


def candidate_pairs(triggers: list[int], entities: list[int]) -> list[tuple[int, int]]:
    """(trigger token, argument token): each trigger with each entity and each other trigger of the sentence."""
    return [(t, a) for t in triggers for a in [*entities, *[u for u in triggers if u != t]]]


def adam_warmup(params: K.Params, grads: K.Params, state: dict, lr: float, step: int, total: int, warmup: float = 0.1, decay: float = 0.0, clip: float = 5.0) -> None:
    """Adam with decoupled decay, linear warm-up and linear descent, without bias correction; in place."""
    rate = lr * min(step / max(1.0, warmup * total), max(0.0, (total - step) / max(1.0, total * (1 - warmup))))
    norm = np.sqrt(sum(float((g * g).sum()) for g in grads.values()))
    scale = min(1.0, clip / max(norm, 1e-12))
    for k, g in grads.items():
        m, v = state.setdefault(k, (np.zeros_like(g), np.zeros_like(g)))
        m += 0.1 * (scale * g - m)
        v += 0.001 * ((scale * g) ** 2 - v)
        params[k] -= rate * (m / (np.sqrt(v) + 1e-6) + (decay * params[k] if g.ndim > 1 else 0.0))
