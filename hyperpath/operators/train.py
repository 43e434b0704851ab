"""The extrapolation model: edge scores from a perceptron over pseudo-coordinates, node features and edge features.

All windows with one current node share a ball: the edges that h transitions from it can use, and around their ends the nodes and edges
that the layers of the coordinates can see, in both directions. Balls are numbered and packed once, as arrays, one row each.
An epoch is one pass: every partition computes losses and gradients of its balls, all windows of a ball and several models at a
time, partial gradients are summed, and the driver, which holds only the parameters, takes a step. Equal windows are one with a count.

A ball grows with the degrees to the power of h + layers; where hubs make it too large, coords="none" needs the walk's edges only.
"""

from __future__ import annotations

import json
import pickle
from collections.abc import Iterator
from dataclasses import asdict, dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import metrics
from .store import stored

EPSILON = 1e-12
#: Prefix positions that the coordinates see.
MEMORY = 4
#: Up to so many nodes a ball averages by matrix products, beyond by sums over sorted edges.
DENSE_NODES = 1024
#: Numbers of a pass over a ball; sums over balls, and the parameters, are in double.
PRECISION = np.float32
#: Numbers in one array of edges (or nodes) by windows; more windows go in parts.
BATCH_NUMBERS = 2_500_000
#: Numbers in one array of hidden units by edges by windows: what a core's cache holds. Edges go in blocks, and no array has all of them.
BLOCK_NUMBERS = 60_000
#: From so many edges a tail and groups of windows on, hidden units of one sign in all groups are summed by matrix products.
RUN_EDGES, RUN_GROUPS = 8, 16


@dataclass
class ModelConfig:
    """columns: which edge features the model sees (None: all edge_width). readout: pinv, tail or head, as walk.readout has them."""

    edge_width: int = 2
    node_width: int = 2
    layers: int = 2
    width: int = 8
    hidden: int = 16
    h: int = 2
    coords: str = "gnn"  # or "none": weights don't depend on the prefix
    objective: str = "target"  # or "path"
    readout: str = "pinv"
    optimizer: str = "adam"  # or "lbfgs"
    epochs: int = 50
    lr: float = 0.01
    l2: float = 1e-4
    seed: int = 42
    columns: list[int] | None = None


@dataclass
class Model:
    config: ModelConfig
    params: np.ndarray
    history: list[tuple[int, float]] = field(default_factory=list)


def shapes(config: ModelConfig) -> dict[str, tuple[int, ...]]:
    out: dict[str, tuple[int, ...]] = {}
    wide = MEMORY
    if config.coords == "gnn":
        for layer in range(config.layers):
            out |= {f"own{layer}": (wide, config.width), f"in{layer}": (wide, config.width), f"out{layer}": (wide, config.width), f"bias{layer}": (config.width,)}
            wide = config.width
    coords = wide if config.coords == "gnn" else 0
    inputs = 2 * coords + 2 * config.node_width + config.edge_width
    return out | {"w1": (inputs, config.hidden), "b1": (config.hidden,), "w2": (config.hidden,), "b2": (1,)}


def unpack(vector: np.ndarray, config: ModelConfig) -> dict[str, np.ndarray]:
    out, at = {}, 0
    for name, shape in shapes(config).items():
        size = int(np.prod(shape))
        out[name] = vector[at : at + size].reshape(shape)
        at += size
    return out


def initial(config: ModelConfig) -> np.ndarray:
    rng = np.random.default_rng(config.seed)
    parts = []
    for name, shape in shapes(config).items():
        flat = name.startswith("b")
        parts.append(np.zeros(shape).ravel() if flat else rng.normal(0, 1 / np.sqrt(shape[0]), shape).ravel())
    return np.concatenate(parts)


# ---------------------------------------------------------------- balls


def _runs(sorted_values: np.ndarray) -> np.ndarray:
    """Where runs of equal values start."""
    return np.flatnonzero(np.concatenate(([True], sorted_values[1:] != sorted_values[:-1]))) if len(sorted_values) else np.empty(0, dtype=np.int64)


def _places(ascending: np.ndarray, values: np.ndarray) -> np.ndarray:
    """Where each of values is among distinct ascending ones, or -1."""
    if not len(ascending):
        return np.full(values.shape, -1, dtype=np.int64)
    at = np.minimum(np.searchsorted(ascending, values), len(ascending) - 1)
    return np.where(ascending[at] == values, at, -1)


class Sums:
    """Sums of rows by a key: rows are ordered once, each call is one reduceat."""

    def __init__(self, key: np.ndarray, size: int) -> None:
        self.order = np.argsort(key, kind="stable")
        ranked = key[self.order]
        self.starts, self.size = _runs(ranked), size
        self.at = ranked[self.starts]

    def __call__(self, rows: np.ndarray) -> np.ndarray:
        out = np.zeros((self.size, *rows.shape[1:]), dtype=rows.dtype)
        if len(self.order):
            out[self.at] = np.add.reduceat(rows[self.order], self.starts, axis=0)
        return out


@dataclass
class Block:
    """Edges at a slice of a ball's, with the ends (places in Ball.ends) of all; tail: of one tail only, else where the runs of equal tails start.
    stretches: of one tail, the heads as few slices (of the block, of the ends)."""

    at: slice
    src: np.ndarray
    dst: np.ndarray
    tail: int | None
    starts: np.ndarray
    by_dst: tuple[np.ndarray, np.ndarray] | None  # order by heads and where their runs start, if a head is there twice
    stretches: list[tuple[slice, slice]] | None

    def preactivation(self, u: np.ndarray, v: np.ndarray, score: np.ndarray) -> np.ndarray:
        """Hidden units (units, edges, windows) before the rectifier of its edges, from what tails, heads and features add."""
        if self.stretches is not None:
            out = np.empty((len(u), len(self.src), u.shape[2]), dtype=u.dtype)
            for own, ends in self.stretches:
                np.add(v[:, ends], u[:, self.tail, None], out=out[:, own])
        else:
            out = np.take(v, self.dst, axis=1, mode="clip")
            out += np.take(u, self.src, axis=1, mode="clip")
        out += score[:, self.at, None]
        return out

    def add_ends(self, x: np.ndarray, tails: np.ndarray, heads: np.ndarray) -> None:
        """Add x (units, edges, windows) to its edges' tails and heads."""
        if self.tail is not None:
            tails[:, self.tail] += (np.ones((1, len(self.src)), dtype=x.dtype) @ x)[:, 0]
        else:
            tails[:, self.src[self.starts]] += np.add.reduceat(x, self.starts, axis=1)
        if self.stretches is not None:
            for own, ends in self.stretches:
                heads[:, ends] += x[:, own]
        elif self.by_dst is None:
            heads[:, self.dst] += x
        else:
            order, starts = self.by_dst
            heads[:, self.dst[order[starts]]] += np.add.reduceat(np.take(x, order, axis=1, mode="clip"), starts, axis=1)


class Marked:
    """Of a dense ball and a part of its groups, the same for all models: (edge, group) whose tail or head is marked itself in this group and
    seldom in others. Their hidden units are far from those of other groups and are computed one by one."""

    def __init__(self, ball: "Ball", own: np.ndarray) -> None:
        """own: what the ends have of marks themselves (ends, groups, slots)."""
        seldom = (own != 0).any(axis=2)
        seldom &= (2 * seldom.sum(axis=1) <= seldom.shape[1])[:, None]
        self.seldom, n = np.nonzero(seldom), seldom.shape[1]
        self.usual = np.argmin(seldom, axis=1)[self.seldom[0]]  # a group of the same end where it isn't so marked
        edges, groups = [], []
        self.runs: list[tuple[int, int, slice | np.ndarray, int, bool]] = []  # rows from, to (by group, then edge), edges, groups, if the end is their tail
        at = 0
        for spans, order, tail in ((ball.tail_runs, None, True), (ball.head_runs, ball.head_order, False)):
            for a, b, end in spans:
                where = np.flatnonzero(seldom[end])
                if len(where):
                    edges.append(np.tile(np.arange(a, b) if order is None else order[a:b], len(where)))
                    groups.append(np.repeat(where, b - a))
                    self.runs.append((at, at + len(edges[-1]), slice(a, b) if order is None else order[a:b], len(where), tail))
                    at += len(edges[-1])
        self.edge, group = (np.concatenate(x) if x else np.empty(0, dtype=np.int64) for x in (edges, groups))
        self.at, self.tail, self.head = self.edge * n + group, ball.end_src[self.edge] * n + group, ball.end_dst[self.edge] * n + group
        # An edge that is marked at both ends is there twice; the second time counts nothing.
        self.once = ~(seldom[ball.end_src[self.edge], group] & (np.arange(at) >= max((r[1] for r in self.runs if r[4]), default=0)))
        self.blocks = [slice(a, a + BLOCK_NUMBERS // 16) for a in range(0, at, BLOCK_NUMBERS // 16)]

    def add(self, flow: np.ndarray, du: np.ndarray, dv: np.ndarray, each: np.ndarray) -> None:
        """Add flow (rows, units) to du and dv (ends and groups, units) and each (edges, units). Rows of a run share an end, so its other ends differ."""
        ones = np.ones((1, max((b - a for a, b, *_ in self.runs), default=0)), dtype=flow.dtype)
        for a, b, edges, groups, tail in self.runs:
            rows = flow[a:b]
            by_group = rows.reshape(groups, -1, rows.shape[1])
            n = by_group.shape[1]
            own, others, mine, theirs = (du, dv, self.tail, self.head) if tail else (dv, du, self.head, self.tail)
            own[mine[a:b:n]] += (ones[:, :n] @ by_group)[:, 0]
            others[theirs[a:b]] += rows
            each[edges] += by_group.sum(axis=0)


@dataclass
class Units:
    """What the backward pass needs of the hidden units of a dense ball: fixed (edge, unit), 1 where above zero in all usual groups; of the units that
    change sign (edges, where above zero); of marked edges, where above zero."""

    fixed: np.ndarray
    changing: list[tuple[np.ndarray, np.ndarray]]
    above: np.ndarray


def _range(x: np.ndarray, marked: Marked) -> tuple[np.ndarray, np.ndarray]:
    """Least and largest of x (ends, units, groups) over the groups where an end isn't seldom marked: there is one at least."""
    x, (end, group) = x.copy(), marked.seldom
    x[end, :, group] = x[end, :, marked.usual]
    return x.min(axis=2), x.max(axis=2)


def _dense_scores(ball: "Ball", u: np.ndarray, v: np.ndarray, score: np.ndarray, w2: np.ndarray, marked: Marked, z: np.ndarray) -> Units:
    """z (edges, groups): sums of w2 times the rectified u[tail] + v[head] + score, of u, v (ends, groups, units) and score (edges, units).

    A unit of an edge that is above zero in all groups adds what its ends do, which are products of matrices; one that is below in all adds nothing. Signs
    follow from the ranges of what the ends add, by the same roundings. Units that change sign, and marked edges, are computed one by one."""
    ends, groups, units = u.shape
    up, vp = (np.ascontiguousarray(x.transpose(0, 2, 1)) for x in (u, v))
    (u_low, u_high), (v_low, v_high) = _range(up, marked), _range(vp, marked)
    low, high = (a[ball.end_src] + b[ball.end_dst] + score for a, b in ((u_low, v_low), (u_high, v_high)))
    fixed = low > 0
    change = ~fixed & (high > 0)
    fixed = fixed.astype(u.dtype)
    weighed = fixed * w2
    turned = weighed[ball.head_order]
    for a, b, end in ball.tail_runs:
        np.matmul(weighed[a:b], u[end].T, out=z[a:b])
    heads = np.empty_like(z)
    for a, b, end in ball.head_runs:
        np.matmul(turned[a:b], v[end].T, out=heads[a:b])
    z += np.take(heads, ball.head_place, axis=0, mode="clip", out=np.empty_like(z))
    z += (weighed * score).sum(axis=1)[:, None]
    changing = []
    for k in range(units):
        edges = np.flatnonzero(change[:, k])
        hidden = up[ball.end_src[edges], k]
        hidden += vp[ball.end_dst[edges], k]
        hidden += score[edges, k, None]
        changing.append((edges, hidden > 0))
        np.maximum(hidden, 0, out=hidden)
        hidden *= w2[k]
        z[edges] += hidden
    above = np.empty((len(marked.edge), units), dtype=bool)
    u, v, flat = u.reshape(-1, units), v.reshape(-1, units), z.reshape(-1)
    for block in marked.blocks:
        hidden = np.take(u, marked.tail[block], axis=0, mode="clip")
        hidden += np.take(v, marked.head[block], axis=0, mode="clip")
        hidden += np.take(score, marked.edge[block], axis=0, mode="clip")
        np.greater(hidden, 0, out=above[block])
        flat[marked.at[block]] = np.maximum(hidden, 0, out=hidden) @ w2
    return Units(fixed, changing, above)


def _dense_flows(ball: "Ball", units: Units, dz: np.ndarray, marked: Marked) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """What dz gives, where hidden units are above zero, to tails and heads (ends, groups, units) and edges (edges, units)."""
    shape = len(ball.ends), dz.shape[1], units.fixed.shape[1]
    du, dv, dz = np.zeros(shape, dtype=dz.dtype), np.zeros(shape, dtype=dz.dtype), dz.copy()
    flat = dz.reshape(-1)
    flow = np.where(units.above, (flat[marked.at] * marked.once)[:, None], dz.dtype.type(0))
    flat[marked.at] = 0
    turned, heads = units.fixed[ball.head_order], np.take(dz, ball.head_order, axis=0, mode="clip")
    for a, b, end in ball.tail_runs:
        du[end] = np.dot(dz[a:b].T, units.fixed[a:b])  # matmul has no fast way for the turned
    for a, b, end in ball.head_runs:
        dv[end] = np.dot(heads[a:b].T, turned[a:b])
    each = units.fixed * (dz @ np.ones(shape[1], dtype=dz.dtype))[:, None]
    marked.add(flow, du.reshape(-1, shape[2]), dv.reshape(-1, shape[2]), each)
    for k, (edges, above) in enumerate(units.changing):
        if len(edges):
            rows = np.take(dz, edges, axis=0, mode="clip")
            rows *= above
            each[edges, k] += rows.sum(axis=1)
            for ends, out in ((ball.end_src[edges], du), (ball.end_dst[edges], dv)):
                order = np.argsort(ends, kind="stable")
                starts = _runs(ends[order])
                out[ends[order[starts]], :, k] += np.add.reduceat(rows[order], starts, axis=0)
    return du, dv, each


class Ball:
    """Local numbers of a ball's nodes, of all its edges (near) and of the walk's edges, which are in the order of their tails."""

    def __init__(
        self, nodes: np.ndarray, features: np.ndarray, near: np.ndarray, edges: np.ndarray, edge_features: np.ndarray, start: int, h: int,
        marks: list[list[tuple[int, int, float]]], suffixes: list[list[int]], counts: list[int],
    ) -> None:
        """near, edges: rows (src, dst) of node ids; marks: (node id, slot, weight) of each window."""
        order = np.argsort(nodes)
        self.nodes, self.features = nodes[order], features[order]
        place = {n: i for i, n in enumerate(self.nodes.tolist())}
        self.near, local = (_places(self.nodes, x).astype(np.int32).reshape(-1, 2) for x in (near, edges))
        if (self.near < 0).any() or (local < 0).any():
            raise KeyError("an edge whose end is no node of the ball")
        order = np.lexsort((local[:, 1], local[:, 0]))
        self.src, self.dst, self.edge_features = local[order, 0], local[order, 1], edge_features[order]
        self.start, self.h = place.get(start, -1), h
        keys = self.src.astype(np.int64) * len(self.nodes) + self.dst  # ascending
        self.back = _places(keys, self.dst.astype(np.int64) * len(self.nodes) + self.src).astype(np.int32)
        self.first = np.flatnonzero(self.src == self.start)
        self.steps = []
        live = self.src == self.start
        for _ in range(h):  # edges on which a walk from the start can be after each transition: those that another than their way back leads to
            ways = np.bincount(self.dst[live], minlength=len(self.nodes))[self.src] - (live[self.back] & (self.back >= 0))
            live = ways > 0
            self.steps.append(live)
        # Windows of equal marks are neighbours and share their weights: a group.
        groups: dict[tuple, int] = {}
        shown = [tuple(sorted((place[n], s, x) for n, s, x in m if n in place)) for m in marks]
        group = np.array([groups.setdefault(g, len(groups)) for g in shown], dtype=np.int64)
        self.order = np.argsort(group, kind="stable")
        self.group = group[self.order]
        flat = [(g, n, s, x) for m, g in groups.items() for n, s, x in m]
        self.marks = tuple(np.array(c) for c in zip(*flat, strict=True)) if flat else (np.empty(0, dtype=np.int64),) * 4
        suffixes, counts = [suffixes[i] for i in self.order], [counts[i] for i in self.order]
        self.suffixes = _places(self.nodes, np.array(suffixes, dtype=np.int64)).astype(np.int32).reshape(len(suffixes), -1)
        before = np.concatenate((np.full((len(suffixes), 1), self.start), self.suffixes[:, :-1]), axis=1).astype(np.int64)
        self.path = _places(keys, np.where((before >= 0) & (self.suffixes >= 0), before * len(self.nodes) + self.suffixes, -1)).astype(np.int32)
        self.counts = np.array(counts, dtype=np.float64)

    def prepare(self) -> "Ball":
        """Sorted orders, made where the ball is used: smaller to store than to keep."""
        n, m = len(self.nodes), len(self.src)
        self.tails, self.segment = _runs(self.src), np.cumsum(np.concatenate(([0], self.src[1:] != self.src[:-1]))) if m else np.empty(0, dtype=np.int64)
        self.by_src, self.by_dst = Sums(self.src, n), Sums(self.dst, n)
        self.ends = np.unique(np.concatenate((self.src, self.dst)))
        self.end_src, self.end_dst = np.searchsorted(self.ends, self.src), np.searchsorted(self.ends, self.dst)
        self.head_order = np.argsort(self.end_dst, kind="stable")
        self.head_place = np.argsort(self.head_order)
        self.tail_runs, self.head_runs = self._spans(self.end_src), self._spans(self.end_dst[self.head_order])
        self.dense = len(self.src) >= RUN_EDGES * max(len(self.tail_runs), len(self.head_runs), 1)
        self.known: dict[tuple, tuple] = {}
        self.rare: dict[tuple, Marked] = {}
        self.cut: dict[int, list[Block]] = {}
        self.paired: tuple[tuple, Pairs] | None = None
        self.in_degree = np.maximum(np.bincount(self.near[:, 1], minlength=n), 1)[:, None]
        self.out_degree = np.maximum(np.bincount(self.near[:, 0], minlength=n), 1)[:, None]
        if n <= DENSE_NODES:
            link = np.zeros((n, n))
            link[self.near[:, 0], self.near[:, 1]] = 1
            self.mean_in, self.mean_out = link.T / self.in_degree, link / self.out_degree
        else:
            self.mean_in = self.mean_out = None
            self.near_src, self.near_dst = Sums(self.near[:, 0], n), Sums(self.near[:, 1], n)
        return self

    @staticmethod
    def _spans(ends: np.ndarray) -> list[tuple[int, int, int]]:
        starts = _runs(ends).tolist()
        return [(a, b, int(ends[a])) for a, b in zip(starts, [*starts[1:], len(ends)], strict=bool(starts))] if starts else []

    def marked(self, groups: np.ndarray, own: np.ndarray) -> Marked:
        key = int(groups[0]), int(groups[-1])
        if key not in self.rare:
            self.rare = {key: Marked(self, own)}
        return self.rare[key]

    def average(self, x: np.ndarray, into: bool, turned: bool = False) -> np.ndarray:
        """Means of x (nodes, ...) over in-neighbours (into) or out-neighbours of each node; turned: the transposed map."""
        flat = x.reshape(len(x), -1)
        if self.mean_in is not None:
            m = self.mean_in if into else self.mean_out
            out = (m.T if turned else m) @ flat
        else:
            degree = self.in_degree if into else self.out_degree
            take, add = (0, self.near_dst) if into != turned else (1, self.near_src)
            out = add((flat / degree if turned else flat)[self.near[:, take]])
            out = out if turned else out / degree
        return out.reshape(x.shape)

    def seen(self, groups: np.ndarray, layers: int, kind: np.dtype) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """What the first layer sees, its means over in- and out-neighbours: the same for all models. For one layer, of the edges' ends only."""
        key = int(groups[0]), int(groups[-1]), layers == 1
        if key not in self.known:
            group, node, slot, weight = self.marks
            own = (group >= groups[0]) & (group <= groups[-1])
            c = np.zeros((len(self.nodes), len(groups), MEMORY))
            np.add.at(c, (node[own].astype(np.int64), (group[own] - groups[0]).astype(np.int64), slot[own].astype(np.int64)), weight[own])
            found = c, self.average(c, True), self.average(c, False)
            self.known = {key: tuple((x[self.ends] if layers == 1 else x).astype(kind) for x in found)}
        return self.known[key]

    def blocks(self, numbers: int) -> list[Block]:
        """Edges in blocks of so many numbers an edge: whole runs of equal tails, or parts of one."""
        room = max(1, BLOCK_NUMBERS // max(1, numbers))
        if room not in self.cut:
            edges = [0]
            for low, high in zip(self.tails.tolist(), [*self.tails[1:].tolist(), len(self.src)], strict=True):
                if high - edges[-1] > room and low > edges[-1]:
                    edges.append(low)
                pieces = -(-(high - low) // room)
                edges += [low + (high - low) * i // pieces for i in range(1, pieces + (pieces > 1))]
            edges = sorted({*edges, len(self.src)})
            self.cut[room] = [self._block(slice(a, b)) for a, b in zip(edges, edges[1:], strict=False)]
        return self.cut[room]

    def _block(self, at: slice) -> Block:
        src, dst = self.end_src[at], self.end_dst[at]
        order = np.argsort(dst, kind="stable")
        heads, tail, stretches = _runs(dst[order]), int(src[0]) if src[0] == src[-1] else None, None
        cuts = [0, *(np.flatnonzero(np.diff(dst) != 1) + 1).tolist(), len(dst)]
        if tail is not None and (len(cuts) - 1) * 4 <= len(dst):
            stretches = [(slice(a, b), slice(int(dst[a]), int(dst[a]) + b - a)) for a, b in zip(cuts, cuts[1:], strict=False)]
        return Block(at, src, dst, tail, _runs(src), None if len(heads) == len(dst) else (order, heads), stretches)

    def parts(self, hidden: int) -> Iterator[np.ndarray]:
        """Windows in parts of bounded size."""
        step = max(1, min(BATCH_NUMBERS // max(1, max(len(self.src), len(self.nodes))), 2 * BATCH_NUMBERS // max(1, len(self.nodes) * hidden)))
        for at in range(0, len(self.counts), step):
            yield np.arange(at, min(at + step, len(self.counts)))


def _features(ball: Ball, config: ModelConfig) -> np.ndarray:
    nodes = np.log1p(np.maximum(ball.features, 0))
    edges = ball.edge_features if config.columns is None else ball.edge_features[:, config.columns]
    return np.concatenate([nodes[ball.src], nodes[ball.dst], edges], axis=1)


def forward(ball: Ball, p: dict[str, np.ndarray], config: ModelConfig, windows: np.ndarray, keep: bool = True) -> dict:
    """Latent weights w (edges, groups of windows; one column if they don't depend on the window), the column of each window, and
    what the backward pass needs (keep: where hidden units are above zero, too). The last layer is that of the edges' ends only."""
    x = _features(ball, config).astype(p["w1"].dtype)
    tape: dict = {"layers": [], "x": x}
    score = x @ p["w1"][-x.shape[1] :] + p["b1"]
    if config.coords == "gnn":
        groups = np.arange(ball.group[windows[0]], ball.group[windows[-1]] + 1)
        c, a, b = (v.astype(x.dtype, copy=False) for v in ball.seen(groups, config.layers, x.dtype))
        own = c if config.layers == 1 else c[ball.ends]
        for layer in range(config.layers):
            if layer:
                a, b = ball.average(c, True), ball.average(c, False)
                if layer == config.layers - 1:
                    c, a, b = c[ball.ends], a[ball.ends], b[ball.ends]
            new = np.tanh(c @ p[f"own{layer}"] + a @ p[f"in{layer}"] + b @ p[f"out{layer}"] + p[f"bias{layer}"])
            tape["layers"].append((c, a, b, new))
            c = new
        if not config.layers:
            c = c[ball.ends]
        k = c.shape[2]
        u, v = c @ p["w1"][:k], c @ p["w1"][k : 2 * k]
        z = np.empty((len(ball.src), len(groups)), dtype=x.dtype)
        if ball.dense and len(groups) >= RUN_GROUPS:
            tape["marked"] = ball.marked(groups, own)
            tape["units"] = _dense_scores(ball, u, v, score, p["w2"], tape["marked"], z)
        else:
            u, v, score = np.ascontiguousarray(u.transpose(2, 0, 1)), np.ascontiguousarray(v.transpose(2, 0, 1)), np.ascontiguousarray(score.T)
            tape["above"] = []
            for block in ball.blocks(u.shape[0] * len(groups)):
                hidden = block.preactivation(u, v, score)
                if keep:
                    tape["above"].append(hidden > 0)
                # Twice the rectified is the value and its size: sizes are summed here, and the values below from tails, heads and features.
                z[block.at] = (p["w2"] @ np.abs(hidden, out=hidden).reshape(len(hidden), -1)).reshape(-1, len(groups))
            z += np.tensordot(p["w2"], u, 1)[ball.end_src]
            z += np.tensordot(p["w2"], v, 1)[ball.end_dst]
            z += (p["w2"] @ score)[:, None]
            z *= 0.5
        z += p["b2"][0]
        tape |= {"c": c, "added": (u, v, score), "column": ball.group[windows] - groups[0]}
    else:
        tape["hidden"], tape["column"] = np.maximum(score, 0)[:, None, :], np.zeros(len(windows), dtype=np.int64)
        z = tape["hidden"] @ p["w2"] + p["b2"][0]
    if not len(z):
        return tape | {"w": z}
    if ball.dense:  # a run of edges at a time stays in the cache
        for a, b, _ in ball.tail_runs:
            run = z[a:b]
            run -= run.max(axis=0)
            np.exp(run, out=run)
            run /= run.sum(axis=0)
        return tape | {"w": z}
    e = np.exp(z - np.maximum.reduceat(z, ball.tails, axis=0)[ball.segment])
    return tape | {"w": e / np.add.reduceat(e, ball.tails, axis=0)[ball.segment]}


def backward(ball: Ball, p: dict[str, np.ndarray], config: ModelConfig, tape: dict, dw: np.ndarray) -> dict[str, np.ndarray]:
    """Gradients of the parameters from those of the weights."""
    w, x = tape["w"], tape["x"]
    grads = {}
    if ball.dense:
        dz = np.empty_like(w)
        for a, b, _ in ball.tail_runs:
            run = np.multiply(w[a:b], dw[a:b], out=dz[a:b])
            run -= w[a:b] * run.sum(axis=0)
    else:
        dz = w * (dw - np.add.reduceat(w * dw, ball.tails, axis=0)[ball.segment])
    grads["b2"] = np.array([dz.sum()])
    if config.coords == "gnn":
        # The gradient of a hidden unit is w2 times dz where it is above zero: w2 joins the sums. There it is a sum of what tail, head and features
        # add, so that the gradient of w2 follows from the sums, too.
        u, v, score = tape["added"]
        if "units" in tape:
            du, dv, each = _dense_flows(ball, tape["units"], dz, tape["marked"])
            grads["w2"] = (du * u).sum(axis=(0, 1)) + (dv * v).sum(axis=(0, 1)) + (each * score).sum(axis=0)
        else:
            du, dv, each, ones = np.zeros_like(u), np.zeros_like(v), np.empty_like(score), np.ones(w.shape[1], dtype=w.dtype)
            for block, above in zip(ball.blocks(u.shape[0] * w.shape[1]), tape["above"], strict=True):
                flow = above * dz[block.at]
                each[:, block.at] = (flow.reshape(-1, w.shape[1]) @ ones).reshape(len(flow), -1)
                block.add_ends(flow, du, dv)
            grads["w2"] = (du * u).sum(axis=(1, 2)) + (dv * v).sum(axis=(1, 2)) + (each * score).sum(axis=1)
            du, dv, each = np.ascontiguousarray(du.transpose(1, 2, 0)), np.ascontiguousarray(dv.transpose(1, 2, 0)), each.T
        du, dv, each = du * p["w2"], dv * p["w2"], each * p["w2"]
    else:
        hidden = tape["hidden"]
        grads["w2"] = np.tensordot(hidden, dz, ([0, 1], [0, 1]))
        each = (dz[:, :, None] * p["w2"] * (hidden > 0)).sum(axis=1)
    grads["w1"], grads["b1"] = np.zeros_like(p["w1"]), each.sum(axis=0)
    grads["w1"][-x.shape[1] :] = x.T @ each
    if config.coords == "gnn":
        c = tape["c"]
        k = c.shape[2]
        grads["w1"][:k], grads["w1"][k : 2 * k] = np.tensordot(c, du, ([0, 1], [0, 1])), np.tensordot(c, dv, ([0, 1], [0, 1]))
        dc = du @ p["w1"][:k].T + dv @ p["w1"][k : 2 * k].T
        for layer in range(config.layers - 1, -1, -1):
            c, a, b, new = tape["layers"][layer]
            da = dc * (1 - new**2)
            for name, value in (("own", c), ("in", a), ("out", b)):
                grads[f"{name}{layer}"] = np.tensordot(value, da, ([0, 1], [0, 1]))
            grads[f"bias{layer}"] = da.sum(axis=(0, 1))
            if layer:
                if layer == config.layers - 1:  # back from the edges' ends to all nodes
                    full = np.zeros((len(ball.nodes), *da.shape[1:]), dtype=da.dtype)
                    full[ball.ends] = da
                    da = full
                dc = da @ p[f"own{layer}"].T + ball.average(da @ p[f"in{layer}"].T, True, True) + ball.average(da @ p[f"out{layer}"].T, False, True)
    return grads


# ---------------------------------------------------------------- walks


def _rooms(ball: Ball, w: np.ndarray) -> np.ndarray:
    return 1 - np.where((ball.back >= 0)[:, None], w[ball.back], 0)


def transitions_of(config: ModelConfig) -> int:
    """head reads the ends of the edges after h - 1 transitions, tail and pinv their origins after h."""
    return config.h - 1 if config.readout == "head" else config.h


def walk_mass(ball: Ball, w: np.ndarray, transitions: int) -> list[np.ndarray]:
    """Edge mass after 0.. transitions from the start, for each column of weights; mass at dead ends is dropped."""
    mass = [np.zeros_like(w)]
    mass[0][ball.first] = w[ball.first]
    room = _rooms(ball, w)
    for live in ball.steps[:transitions]:
        mass.append(w * _arriving(ball, mass[-1], room, live))
    return mass


def _arriving(ball: Ball, mass: np.ndarray, room: np.ndarray, live: np.ndarray) -> np.ndarray:
    """What a step brings to the tail of each edge, but for what would go back: all that comes there less the edge's own way back, a sum per
    node instead of a term per pair of edges. Edges that only their way back leads to get exactly nothing."""
    ready = np.where(room > EPSILON, mass / np.maximum(room, EPSILON), 0)
    out = ball.by_dst(ready)[ball.src] - _turned(ball, ready)
    return np.where(live[:, None], np.maximum(out, 0), 0)


def _turned(ball: Ball, x: np.ndarray) -> np.ndarray:
    """Of each edge what x has for its way back, 0 without one."""
    return np.where((ball.back >= 0)[:, None], x[ball.back], 0)


def _pairs(key: np.ndarray, targets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(edge, window) with the key of the edge equal to the target of the window."""
    order = np.argsort(key, kind="stable")
    low, high = np.searchsorted(key[order], targets, "left"), np.searchsorted(key[order], targets, "right")
    edges = np.concatenate([order[a:b] for a, b in zip(low.tolist(), high.tolist(), strict=True)] or [np.empty(0, dtype=np.int64)]).astype(np.int64)
    return edges, np.repeat(np.arange(len(targets)), high - low)


@dataclass
class Pairs:
    """Of windows in two transitions: edges out of a window's target, and edges into it which a first edge leads to, as (edge, window)."""

    edge: np.ndarray
    window: np.ndarray
    into: np.ndarray
    into_window: np.ndarray
    lead: np.ndarray  # the first edge to the tail of each of into
    turned: np.ndarray  # of each edge out of the target, the place in into of its way back, or -1
    live: np.ndarray


def _two_steps(ball: Ball, windows: np.ndarray) -> Pairs:
    """The same for all models; kept for the part of the windows in turn."""
    key = int(windows[0]), int(windows[-1])
    if ball.paired is None or ball.paired[0] != key:
        target, n = ball.suffixes[windows, -1], len(ball.src)
        edge, window = _pairs(ball.src, target)
        into, into_window = _pairs(ball.dst, target)
        leading = np.full(len(ball.nodes), -1)
        leading[ball.dst[ball.first]] = ball.first
        lead = leading[ball.src[into]]
        on = (lead >= 0) & (ball.back[into] != lead)
        into, into_window, lead = into[on], into_window[on], lead[on]
        known, asked = into_window * n + into, window * n + ball.back[edge]
        order = np.argsort(known)
        place = np.minimum(np.searchsorted(known[order], asked), max(0, len(known) - 1))
        turned = np.where((ball.back[edge] >= 0) & (known[order][place] == asked), order[place], -1) if len(known) else np.full(len(edge), -1)
        ball.paired = key, Pairs(edge, window, into, into_window, lead, turned, ball.steps[1][edge])
    return ball.paired[1]


def _totals(place: np.ndarray, value: np.ndarray, n: int) -> np.ndarray:
    """n sums in double; NumPy's own are of integers where there is nothing to sum."""
    return np.bincount(place, value, n).astype(np.float64)


def _near_target_loss(ball: Ball, tape: dict, config: ModelConfig, windows: np.ndarray, dw: np.ndarray) -> float:
    """_target_loss for two transitions read at their origins, from the edges at each window's target alone; dw has all that the loss gives."""
    w, n, counts, at = tape["w"], len(windows), ball.counts[windows], _two_steps(ball, windows)
    columns = w.shape[1]
    flat, column = w.ravel(), tape["column"]

    def room_of(edges: np.ndarray, own: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        back = ball.back[edges]
        room = 1 - np.where(back >= 0, flat[np.maximum(back, 0) * columns + own], 0)
        return back, room > EPSILON, np.maximum(room, EPSILON)

    def add(edges: np.ndarray, own: np.ndarray, value: np.ndarray) -> None:
        on = edges >= 0
        np.add.at(dw.reshape(-1), edges[on] * columns + own[on], value[on].astype(dw.dtype))

    c, d = column[at.window], column[at.into_window]
    own, entering, leading = flat[at.edge * columns + c], flat[at.into * columns + d], flat[at.lead * columns + d]
    back_lead, open_lead, room_lead = room_of(at.lead, d)
    back_into, open_into, room_into = room_of(at.into, d)
    first = np.where(open_lead, leading / room_lead, 0)
    mass = entering * first
    ready = np.where(open_into, mass / room_into, 0)
    turns = at.turned >= 0
    arriving = _totals(at.into_window, ready, n)[at.window]
    arriving[turns] -= ready[at.turned[turns]]
    arriving = np.where(at.live, np.maximum(arriving, 0), 0)
    m = own * arriving
    if config.readout == "pinv":
        squares = _totals(at.window, own * own, n)
        q = _totals(at.window, m * own, n) / np.maximum(squares, EPSILON)
        dq = -counts / (q + EPSILON)
        dm = dq[at.window] * own / squares[at.window]
        add(at.edge, c, dq[at.window] * (m - 2 * own * q[at.window]) / squares[at.window])
    else:
        q = _totals(at.window, m, n)
        dq = -counts / (q + EPSILON)
        dm = dq[at.window]
    add(at.edge, c, dm * arriving)
    flow = np.where(at.live, dm * own, 0)
    dready = _totals(at.window, flow, n)[at.into_window]
    dready[at.turned[turns]] -= flow[turns]  # an edge is the way back of one other at most
    dmass = np.where(open_into, dready / room_into, 0)
    add(back_into, d, dmass * mass / room_into)
    add(at.into, d, dmass * first)
    dfirst = np.where(open_lead, dmass * entering / room_lead, 0)
    add(back_lead, d, dfirst * leading / room_lead)
    add(at.lead, d, dfirst)
    return float((counts * -np.log(q + EPSILON)).sum())


def _target_loss(ball: Ball, tape: dict, config: ModelConfig, windows: np.ndarray, dw: np.ndarray, droom: np.ndarray) -> float:
    w, n, counts, steps = tape["w"], len(windows), ball.counts[windows], transitions_of(config)
    mass = walk_mass(ball, w, steps)
    edge, window = _pairs(ball.dst if config.readout == "head" else ball.src, ball.suffixes[windows, -1])
    at = edge, tape["column"][window]
    m, dm = mass[-1][at], np.zeros_like(w)
    if config.readout == "pinv":
        own = w[at]
        squares = np.bincount(window, own * own, n)
        q = np.bincount(window, m * own, n) / np.maximum(squares, EPSILON)
        dq = -counts / (q + EPSILON)
        np.add.at(dm, at, dq[window] * own / squares[window])
        np.add.at(dw, at, dq[window] * (m - 2 * own * q[window]) / squares[window])
    else:
        q = np.bincount(window, m, n)
        dq = -counts / (q + EPSILON)
        np.add.at(dm, at, dq[window])
    room = _rooms(ball, w)
    free = np.maximum(room, EPSILON)
    for live, before in zip(ball.steps[:steps][::-1], mass[-2::-1], strict=True):
        dw += dm * _arriving(ball, before, room, live)
        flow = np.where(live[:, None], dm * w, 0)
        dm = np.where(room > EPSILON, ball.by_src(flow)[ball.dst] - _turned(ball, flow), 0) / free
        droom -= dm * before / free
    dw[ball.first] += dm[ball.first]
    return float((counts * -np.log(q + EPSILON)).sum())


def _path_loss(ball: Ball, tape: dict, windows: np.ndarray, dw: np.ndarray, droom: np.ndarray) -> float:
    w, loss = tape["w"], 0.0
    counts, room, column, going = ball.counts[windows], _rooms(ball, tape["w"]), tape["column"], np.ones(len(windows), dtype=bool)
    for i in range(ball.path.shape[1]):
        e = ball.path[windows, i]
        loss += float(counts[going & (e < 0)].sum()) * -np.log(EPSILON)
        going = going & (e >= 0)
        at = np.flatnonzero(going)
        where = e[at], column[at]
        p = np.maximum(w[where], EPSILON)
        loss -= float((counts[at] * np.log(p)).sum())
        np.add.at(dw, where, -counts[at] / p)
        if i:
            last = ball.path[windows[at], i - 1], column[at]
            r = np.maximum(room[last], EPSILON)
            loss += float((counts[at] * np.log(r)).sum())
            np.add.at(droom, last, counts[at] / r)
    return loss


def loss_and_gradient(ball: Ball, vector: np.ndarray, config: ModelConfig) -> tuple[float, np.ndarray]:
    """Negative log likelihood of all windows' targets (or suffixes), and its gradient."""
    p = unpack(vector, config)
    total = {k: np.zeros(s) for k, s in shapes(config).items()}
    if not len(ball.first):
        return -np.log(EPSILON) * float(ball.counts.sum()), np.concatenate([g.ravel() for g in total.values()])
    loss = 0.0
    for windows in ball.parts(config.hidden):
        tape = forward(ball, p, config, windows)
        dw = np.zeros(tape["w"].shape, dtype=tape["w"].dtype)
        if config.objective == "target" and config.readout != "head" and transitions_of(config) == 2:
            loss += _near_target_loss(ball, tape, config, windows, dw)
        else:
            droom, has = np.zeros_like(dw), ball.back >= 0
            loss += _path_loss(ball, tape, windows, dw, droom) if config.objective == "path" else _target_loss(ball, tape, config, windows, dw, droom)
            dw[ball.back[has]] -= droom[has]  # an edge is the way back of one other at most
        for name, g in backward(ball, p, config, tape, dw).items():
            total[name] += g
    return loss, np.concatenate([total[k].ravel() for k in shapes(config)])


# ---------------------------------------------------------------- balls from tables


def _ids(rows: pa.StructArray | None, *names: str) -> np.ndarray:
    """Fields of structs as columns, without an object per value."""
    return np.stack([np.asarray(rows.field(n), dtype=np.int64) for n in names], axis=1) if rows is not None else np.empty((0, len(names)), dtype=np.int64)


def _vectors(rows: pa.StructArray | None, name: str) -> np.ndarray:
    """A field of lists of one length as a matrix."""
    return np.asarray(rows.field(name).flatten(), dtype=float).reshape(len(rows), -1) if rows is not None and len(rows) else np.empty((0, 0))


def ego_graphs(
    windows: DataFrame, edges: DataFrame, nodes: DataFrame, *, h: int, layers: int = 2, readout: str = "pinv", whole: bool = False,
    observations: DataFrame | None = None, memory: int = MEMORY,
) -> DataFrame:
    """(cur, n_windows, ball): a row per current node of windows(prefix, suffix, cur, target), ball packed.

    edges(src, dst, f), nodes(node_id, f: in- and out-degree). observations(node_id, seen, weight): what the coordinates see of an agent at a node
    (default: the node itself). For training, of the edges after h transitions only those at targets are taken; whole takes all, which
    predictions need. Only the last nodes of a prefix matter.
    """
    cut = F.slice("prefix", F.greatest(F.lit(1), F.size("prefix") - memory + 1), F.lit(memory))
    grouped = stored(windows.select(cut.alias("prefix"), "suffix", "cur").groupBy("cur", "prefix", "suffix").agg(F.count("*").cast("int").alias("count")), "windows")
    links = edges.select(F.col("src").alias("at"), F.col("dst").alias("to"))

    def spread(reached: DataFrame, by: DataFrame, tag: str) -> DataFrame:
        return stored(reached.unionByName(reached.join(by, "at").select("cur", F.col("to").alias("at"))).distinct(), tag)

    tails = grouped.select("cur", F.col("cur").alias("at")).distinct()
    for i in range(h - 1 if readout == "head" or not whole else h):
        tails = spread(tails, links, f"tails{i}")
    if readout != "head" and not whole:
        tails = tails.unionByName(grouped.select("cur", F.element_at("suffix", -1).alias("at"))).distinct()
    walked = stored(tails.join(edges.withColumnRenamed("src", "at"), "at").select("cur", F.col("at").alias("src"), "dst", "f"), "walked")
    ball = walked.select("cur", F.explode(F.array("src", "dst")).alias("at")).unionByName(tails).distinct()
    both = links.unionByName(links.select(F.col("to").alias("at"), F.col("at").alias("to"))).distinct()
    for i in range(layers):
        ball = spread(ball, both, f"ball{i}")
    inside = ball.join(links, "at").join(ball.select("cur", F.col("at").alias("to")), ["cur", "to"])
    per_near = inside.groupBy("cur").agg(F.collect_list(F.struct("at", "to")).alias("near"))
    per_edge = walked.groupBy("cur").agg(F.collect_list(F.struct("src", "dst", "f")).alias("edges"))
    per_node = ball.join(nodes.withColumnRenamed("node_id", "at"), "at").groupBy("cur").agg(F.collect_list(F.struct("at", "f")).alias("nodes"))
    if observations is None:
        marked = grouped.withColumn("marks", F.transform(F.reverse("prefix"), lambda n, i: F.struct(n.alias("seen"), i.cast("int").alias("slot"), F.lit(1.0).alias("weight"))))
    else:
        slots = grouped.select("prefix").distinct().select("prefix", F.posexplode(F.reverse("prefix")).alias("slot", "node_id"))
        seen = slots.join(observations, "node_id").groupBy("prefix").agg(F.collect_list(F.struct("seen", "slot", "weight")).alias("marks"))
        marked = grouped.join(seen, "prefix", "left")
    per_window = marked.groupBy("cur").agg(F.sort_array(F.collect_list(F.struct("prefix", "suffix", "count", "marks"))).alias("windows"))
    rows = per_window.join(per_node, "cur", "left").join(per_edge, "cur", "left").join(per_near, "cur", "left")

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for i, (cur, found) in enumerate(zip(batch.column("cur").to_pylist(), batch.column("windows").to_pylist(), strict=True)):
                nodes, edges, near = (batch.column(c)[i].values for c in ("nodes", "edges", "near"))
                ball = Ball(
                    _ids(nodes, "at")[:, 0], _vectors(nodes, "f"), _ids(near, "at", "to"), _ids(edges, "src", "dst"), _vectors(edges, "f"),
                    cur, h, [[(m["seen"], m["slot"], m["weight"]) for m in x["marks"] or ()] for x in found], [x["suffix"] for x in found], [x["count"] for x in found],
                )
                ball.prefixes, ball.raw_suffixes = [found[i]["prefix"] for i in ball.order], [found[i]["suffix"] for i in ball.order]
                out.append((cur, len(found), pickle.dumps(ball, protocol=5)))
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True) if out else [()] * 3, (pa.int64(), pa.int32(), pa.binary()), strict=True)], names=["cur", "n_windows", "ball"])

    return rows.select("cur", "windows", "nodes", "edges", "near").mapInArrow(pack, "cur long, n_windows int, ball binary")


def _balls(batch: pa.RecordBatch) -> Iterator[Ball]:
    for blob in batch.column("ball"):
        yield pickle.loads(blob.as_buffer()).prepare()


# ---------------------------------------------------------------- training


def evaluate(rows: DataFrame, vectors: list[np.ndarray], configs: list[ModelConfig]) -> list[tuple[float, np.ndarray]]:
    """Mean loss and gradient over all windows, of each model; one row of parameters' size per partition and model reaches the driver."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        losses, n, grads = [0.0] * len(vectors), 0.0, [np.zeros(len(v)) for v in vectors]
        for batch in batches:
            for ball in _balls(batch):
                n += float(ball.counts.sum())
                for i, (vector, config) in enumerate(zip(vectors, configs, strict=True)):
                    one, g = loss_and_gradient(ball, vector.astype(PRECISION), config)
                    losses[i] += one
                    grads[i] += g
        yield pa.RecordBatch.from_arrays(
            [pa.array(range(len(vectors)), pa.int32()), pa.array(losses), pa.array([n] * len(vectors)), pa.array([g.tolist() for g in grads], pa.list_(pa.float64()))], names=["model", "loss", "n", "grad"]
        )

    parts = rows.mapInArrow(run, "model int, loss double, n double, grad array<double>").collect()
    out = []
    for i, (vector, config) in enumerate(zip(vectors, configs, strict=True)):
        own = [p for p in parts if p["model"] == i]
        n = max(1.0, sum(p["n"] for p in own))
        grad = np.sum([p["grad"] for p in own], axis=0) / n + config.l2 * vector
        out.append((sum(p["loss"] for p in own) / n + 0.5 * config.l2 * float(vector @ vector), grad))
    return out


def fit_many(rows: DataFrame, configs: list[ModelConfig]) -> list[Model]:
    """Train models together on ego_graphs() rows, which should be stored: one pass per epoch for all. Same optimizer and epochs."""
    if configs[0].optimizer == "lbfgs":
        return [Model(c, *_lbfgs(lambda v, c=c: evaluate(rows, [v], [c])[0], initial(c), c)) for c in configs]
    x = [initial(c) for c in configs]
    m, v = [np.zeros_like(a) for a in x], [np.zeros_like(a) for a in x]
    history: list[list[tuple[int, float]]] = [[] for _ in x]
    even = rows.repartition(4 * rows.sparkSession.sparkContext.defaultParallelism).persist()  # a scan packs files into few uneven tasks
    for epoch in range(1, configs[0].epochs + 1):
        for i, (loss, g) in enumerate(evaluate(even, x, configs)):
            history[i].append((epoch, loss))
            m[i], v[i] = 0.9 * m[i] + 0.1 * g, 0.999 * v[i] + 0.001 * g * g
            x[i] = x[i] - configs[i].lr * (m[i] / (1 - 0.9**epoch)) / (np.sqrt(v[i] / (1 - 0.999**epoch)) + 1e-8)
    even.unpersist()
    return [Model(c, a, h) for c, a, h in zip(configs, x, history, strict=True)]


def fit(rows: DataFrame, config: ModelConfig) -> Model:
    return fit_many(rows, [config])[0]


def _lbfgs(f, x: np.ndarray, config: ModelConfig, memory: int = 8) -> tuple[np.ndarray, list[tuple[int, float]]]:
    pairs: list[tuple[np.ndarray, np.ndarray]] = []
    loss, g = f(x)
    history = [(0, loss)]
    for epoch in range(1, config.epochs + 1):
        q, alphas = g.copy(), []
        for s, y in reversed(pairs):
            alphas.append((s @ q) / (y @ s))
            q -= alphas[-1] * y
        if pairs:
            q *= (pairs[-1][0] @ pairs[-1][1]) / (pairs[-1][1] @ pairs[-1][1])
        for (s, y), a in zip(pairs, reversed(alphas), strict=True):
            q += (a - (y @ q) / (y @ s)) * s
        step = 1.0 if pairs else 1.0 / max(1.0, float(np.abs(g).sum()))
        for _ in range(20):
            new_loss, new_g = f(x - step * q)
            if new_loss <= loss - 1e-4 * step * float(g @ q):
                break
            step /= 2
        else:
            break
        s, y = -step * q, new_g - g
        if s @ y > 1e-12:
            pairs = [*pairs[1 - memory :], (s, y)] if len(pairs) >= memory else [*pairs, (s, y)]
        x, loss, g = x + s, new_loss, new_g
        history.append((epoch, loss))
        if np.abs(g).max() < 1e-6:
            break
    return x, history


# ---------------------------------------------------------------- prediction


def node_mass(ball: Ball, w: np.ndarray, config: ModelConfig) -> np.ndarray:
    """(nodes, columns of w): where the walk is after h steps, by the model's readout."""
    mass = walk_mass(ball, w, transitions_of(config))[-1]
    if config.readout == "pinv":
        return ball.by_src(mass * w) / np.maximum(ball.by_src(w * w), EPSILON)
    return (ball.by_dst if config.readout == "head" else ball.by_src)(mass)


def best_suffixes(ball: Ball, w: np.ndarray, h: int, k: int) -> list[tuple[float, list[int]]]:
    """The k likeliest walks of h moves from the start, for the weights w of one window; exact."""
    room = _rooms(ball, w[:, None])[:, 0]
    found = [(float(w[e]), [int(e)]) for e in ball.first]
    leaving: dict[int, list[int]] = {}
    for e, a in enumerate(ball.src.tolist()):
        leaving.setdefault(a, []).append(e)
    for _ in range(h - 1):
        found = [(p * float(w[f]) / float(room[e[-1]]), [*e, f]) for p, e in found if room[e[-1]] > EPSILON for f in leaving.get(int(ball.dst[e[-1]]), ()) if ball.dst[f] != ball.src[e[-1]]]
    names = [(p, [int(ball.nodes[ball.dst[e]]) for e in es]) for p, es in found]
    return sorted(names, key=lambda x: (-round(x[0], 9), x[1]))[:k]


_PREDICTED = (
    "model int, cur long, prefix array<long>, suffix array<long>, count long, p_target double, rank long, p_path double, "
    "top array<struct<node:long,p:double>>, choices array<struct<degree:long,hit:boolean>>, rivals array<struct<p:double,suffix:array<long>>>"
)


def predict_many(rows: DataFrame, models: list[Model], *, k: int = 5, suffixes: int = 0) -> DataFrame:
    """For every window of ego_graphs(whole=True) rows and every model: model, cur, prefix, suffix, count, p_target, rank, p_path, top, choices, rivals.

    top: the k likeliest nodes after h steps. choices: at each node of the suffix its degree and whether the heaviest exit that
    doesn't lead back is the true one; the moves after a miss are judged, too. rivals: the likeliest suffixes, if asked for.
    """
    known = [(m.params, m.config) for m in models]

    def judge(ball: Ball, i: int, vector: np.ndarray, config: ModelConfig) -> Iterator[tuple]:
        p = unpack(vector, config)
        for windows in ball.parts(config.hidden):
            dead = not len(ball.first)
            tape = None if dead else forward(ball, p, config, windows, keep=False)
            at = None if dead else node_mass(ball, tape["w"], config)
            for j, window in zip([0] * len(windows) if dead else tape["column"].tolist(), windows.tolist(), strict=True):
                suffix, pt, rank, pp, top, choices, rivals = ball.suffixes[window], 0.0, None, 0.0, [], [], []
                own = None if dead else tape["w"][:, j]
                if not dead:
                    order = np.lexsort((ball.nodes, -np.round(at[:, j], 9)))
                    order = order[at[order, j] > 0]
                    top = [{"node": int(ball.nodes[x]), "p": float(at[x, j])} for x in order[:k]]
                    if suffix[-1] >= 0:
                        pt = float(at[suffix[-1], j])
                        where = np.flatnonzero(order == suffix[-1])
                        rank = int(where[0]) + 1 if len(where) else None
                    room = _rooms(ball, own[:, None])[:, 0]
                    pp = 1.0
                    for step, e in enumerate(ball.path[window].tolist()):
                        last = ball.path[window, step - 1] if step else -1
                        bad = e < 0 or (step and last < 0) or (step and ball.dst[e] == ball.src[last]) or (step and room[last] <= EPSILON)
                        pp *= 0.0 if bad else float(own[e]) / (float(room[last]) if step else 1.0)
                    rivals = [{"p": x, "suffix": s} for x, s in best_suffixes(ball, own, len(suffix), suffixes)] if suffixes else []
                walk = [ball.start, *suffix.tolist()]
                for step in range(len(suffix)):
                    here, there, before = walk[step], walk[step + 1], walk[step - 1] if step else -1
                    exits = [] if dead or here < 0 else [e for e in range(np.searchsorted(ball.src, here), np.searchsorted(ball.src, here, "right")) if ball.dst[e] != before]
                    best = min(exits, key=lambda e: (-round(float(own[e]), 12), ball.nodes[ball.dst[e]]), default=None)
                    choices.append({"degree": int(ball.features[here].sum()) if here >= 0 else 0, "hit": best is not None and int(ball.dst[best]) == there})
                yield i, int(ball.nodes[ball.start]) if ball.start >= 0 else None, ball.prefixes[window], ball.raw_suffixes[window], int(ball.counts[window]), pt, rank, pp, top, choices, rivals

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for ball in _balls(batch):
                out = [r for i, (vector, config) in enumerate(known) for r in judge(ball, i, vector, config)]
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*out, strict=True) if out else [()] * len(schema), schema, strict=True)], schema=schema)

    schema = pa.schema([
        ("model", pa.int32()), ("cur", pa.int64()), ("prefix", pa.list_(pa.int64())), ("suffix", pa.list_(pa.int64())), ("count", pa.int64()), ("p_target", pa.float64()),
        ("rank", pa.int64()), ("p_path", pa.float64()), ("top", pa.list_(pa.struct([("node", pa.int64()), ("p", pa.float64())]))),
        ("choices", pa.list_(pa.struct([("degree", pa.int64()), ("hit", pa.bool_())]))), ("rivals", pa.list_(pa.struct([("p", pa.float64()), ("suffix", pa.list_(pa.int64()))]))),
    ])
    return rows.mapInArrow(run, _PREDICTED)


def predict(rows: DataFrame, model: Model, *, k: int = 5, suffixes: int = 0) -> DataFrame:
    return predict_many(rows, [model], k=k, suffixes=suffixes)


def top_nodes(predictions: DataFrame) -> DataFrame:
    """(model, cur, prefix, suffix, place, node_id, p): the predicted nodes as rows."""
    rows = predictions.select("model", "cur", "prefix", "suffix", F.posexplode("top").alias("place", "t"))
    return rows.select("model", "cur", "prefix", "suffix", (F.col("place") + 1).alias("place"), F.col("t.node").alias("node_id"), F.col("t.p").alias("p"))


def measure(predictions: DataFrame, *, min_degree: int = 3) -> DataFrame:
    """The four measures over predict_many() rows: model, metric, value, support."""
    n = F.sum("count")
    found = predictions.groupBy("model").agg(
        n.alias("support"), (F.sum(F.col("count") * F.col("p_target")) / n).alias("target_probability"),
        *((F.sum(F.when(F.col("rank") <= k, F.col("count")).otherwise(0)) / n).alias(f"precision_top{k}") for k in (1, 5)),
    )
    found = found.unpivot(["model", "support"], ["target_probability", "precision_top1", "precision_top5"], "metric", "value").select("model", "metric", "value", "support")
    chosen = predictions.select("model", "count", F.explode("choices").alias("c")).where(F.col("c.degree") >= min_degree)
    return found.unionByName(metrics.hit_share(chosen.select("model", F.col("c.hit").cast("double").alias("hit"), F.col("count").alias("weight")), "model"))


def weights_table(rows: DataFrame, model: Model) -> DataFrame:
    """latent(src, dst, w) of a trained model whose weights don't depend on the prefix (coords="none"), as walk.* take it."""
    if model.config.coords != "none":
        raise ValueError("weights depend on the prefix: there is no one table of them")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        p = unpack(model.params, model.config)
        for batch in batches:
            for ball in _balls(batch):
                own = ball.first
                w = forward(ball, p, model.config, np.arange(1))["w"][own, 0] if len(own) else np.empty(0)
                yield pa.RecordBatch.from_arrays([pa.array(ball.nodes[ball.src[own]]), pa.array(ball.nodes[ball.dst[own]]), pa.array(w)], names=["src", "dst", "w"])

    return rows.mapInArrow(run, "src long, dst long, w double")


def save_model(spark: SparkSession, model: Model, path: str) -> None:
    """Parameters as a small table, with the configuration in JSON beside each."""
    rows = [(i, float(v), json.dumps(asdict(model.config))) for i, v in enumerate(model.params)]
    spark.createDataFrame(rows, "i int, value double, config string").coalesce(1).write.mode("overwrite").parquet(path)


def load_model(spark: SparkSession, path: str) -> Model:
    rows = spark.read.parquet(path).orderBy("i").collect()
    return Model(ModelConfig(**json.loads(rows[0]["config"])), np.array([r["value"] for r in rows]))
