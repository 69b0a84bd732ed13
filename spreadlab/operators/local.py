"""In-memory engine: one run (seed, rep) at a time on a graph that fits an executor, 64 draws to a word."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

from spreadlab.functions.coins import bernoulli_words, key_of, md5_coins, mixed_coins


class ShortOrder(Exception):
    """A stratum tree goes further than the edges of a random order that are known."""


@dataclass
class Graph:
    """Edges sorted by (src, dst), with node numbers.

    ``orders`` holds the ids of the first edges of each run's random order in a graph of ``total`` edges, of which
    these edges are those that matter; without it all edges are here.
    """

    edge_id: np.ndarray
    src: np.ndarray
    dst: np.ndarray
    p: np.ndarray
    orders: dict[int, np.ndarray] | None = None
    total: int = 0
    nodes: np.ndarray = field(init=False)
    start: np.ndarray = field(init=False)
    walked: tuple[int | None, np.ndarray] | None = field(init=False, default=None)

    def __post_init__(self) -> None:
        order = np.lexsort((self.dst, self.src))
        self.edge_id, self.p = self.edge_id[order], self.p[order]
        self.nodes = np.union1d(np.unique(self.src), np.unique(self.dst))
        self.src, self.dst = np.searchsorted(self.nodes, self.src)[order], np.searchsorted(self.nodes, self.dst)[order]
        self.start = np.searchsorted(self.src, np.arange(len(self.nodes) + 1))
        if self.orders is None:
            self.total = len(self.edge_id)
        else:
            by_id = np.argsort(self.edge_id)
            self.orders = {rep: by_id[np.searchsorted(self.edge_id, ids, sorter=by_id)] for rep, ids in self.orders.items()}

    def number(self, node: int) -> int | None:
        at = int(np.searchsorted(self.nodes, node))
        return at if at < len(self.nodes) and self.nodes[at] == node else None

    def out_edges(self, nodes: np.ndarray) -> np.ndarray:
        lengths = self.start[nodes + 1] - self.start[nodes]
        return np.repeat(self.start[nodes] - np.concatenate([[0], np.cumsum(lengths)[:-1]]), lengths) + np.arange(lengths.sum())

    def bfs_order(self, seed: int | None) -> np.ndarray:
        """Edge positions in visiting order, kept for the next run of the same seed; none for a node that is not there."""
        if self.walked is None or self.walked[0] != seed:
            self.walked = seed, self._walk(seed) if seed is not None else np.zeros(0, np.int64)
        return self.walked[1]

    def _walk(self, seed: int) -> np.ndarray:
        """A level at a time, discovery order by (parent, dst)."""
        seen, level, out = np.zeros(len(self.nodes), bool), np.array([seed]), []
        seen[seed] = True
        while len(level):
            e = self.out_edges(level)
            out.append(e)
            _, first = np.unique(self.dst[e], return_index=True)
            level = self.dst[e][np.sort(first)]
            level = level[~seen[level]]
            seen[level] = True
        return np.concatenate(out) if out else np.zeros(0, np.int64)


class Coins:
    """The run's coins in either kind."""

    def __init__(self, salt: int, rep: int, kind: str):
        self.salt, self.rep, self.kind = salt, rep, kind

    def slots(self, path: str, n: int) -> np.ndarray:
        if self.kind == "md5":
            u = md5_coins(f"{self.salt}|{self.rep}|{path}", np.arange(n))
        else:
            u = mixed_coins(key_of(self.salt, self.rep, path), np.arange(n))
        return (np.arange(n) + u) / n

    def permutation(self, tag: str, edge_id: np.ndarray) -> np.ndarray:
        if self.kind == "md5":
            u = md5_coins(f"{self.salt}|{tag}|{self.rep}", edge_id)
        else:
            u = mixed_coins(key_of(self.salt, tag, self.rep), edge_id)
        return np.lexsort((edge_id, u))

    def live(self, edge_id: np.ndarray, p: np.ndarray, words: np.ndarray, asked: np.ndarray) -> np.ndarray:
        """uint64[edges, words]: bit b of word w is draw 64 w + b; md5 coins are thrown for the bits asked for only."""
        if self.kind != "md5":
            return bernoulli_words(key_of(self.salt, self.rep, "edge"), edge_id, p, words)
        bits = np.unpackbits(np.ascontiguousarray(asked).view(np.uint8), axis=1, bitorder="little").view(bool)
        for lane in np.flatnonzero(bits.any(0)).tolist():
            at = np.flatnonzero(bits[:, lane])
            bits[at, lane] = md5_coins(f"{self.salt}|{self.rep}|{int(words[lane // 64]) * 64 + lane % 64}", edge_id[at]) < p[at]
        return np.packbits(bits, axis=1, bitorder="little").view(np.uint64)


def masses(p: np.ndarray, scheme: str) -> tuple[np.ndarray, np.ndarray]:
    """(pi, consumed) of the strata of edges with probabilities p."""
    r = len(p)
    if scheme == "cube":
        bits = (np.arange(1 << r)[:, None] >> np.arange(r)) & 1
        return np.where(bits == 1, p, 1 - p).prod(1), np.full(1 << r, r)
    absent = np.concatenate([[1.0], np.cumprod(1 - p)])
    return np.concatenate([[absent[r]], absent[:r] * p]), np.concatenate([[r], np.arange(1, r + 1)])


def statuses(scheme: str, child: int, r: int) -> np.ndarray:
    if scheme == "cube":
        return (child >> np.arange(r)) & 1
    return np.zeros(r, int) if child == 0 else np.concatenate([np.zeros(child - 1, int), [1]])


@dataclass
class Leaf:
    draws: np.ndarray
    edges: np.ndarray
    status: np.ndarray
    weight: float
    depth: int
    path: str = ""


def leaves_of(graph: Graph, seed: int | None, coins: Coins, scheme: str | None, selector: str, r: int, tau: int, n: int, recursive: bool, allocation: str = "grid_points", random_mode: str = "per_run") -> tuple[list[Leaf], int]:
    """Leaves of the stratum tree of one run, and the number of tree nodes."""
    none = np.zeros(0, np.int64)
    if scheme is None or r == 0:
        return [Leaf(np.arange(n), none, none, 1.0, 0)], 1
    if scheme == "cube" and r > 16:
        raise ValueError(f"a cube of {r} edges has too many strata")
    per_node = selector == "random" and random_mode == "per_node"
    if selector == "bfs":
        order = graph.bfs_order(seed)
    else:
        order = coins.permutation("order", graph.edge_id) if graph.orders is None else graph.orders[coins.rep]
    total = len(order) if selector == "bfs" else graph.total
    found, fresh, count = [], n, 0
    open_ = [("", np.arange(n), 0, none, none, 1.0, 0)]
    while open_:
        path, draws, cursor, edges, status, weight, depth = open_.pop()
        count += 1
        left = len(graph.edge_id) - len(edges) if per_node else total - cursor
        if left < r or (recursive and len(draws) < tau) or (not recursive and depth == 1):
            found.append(Leaf(draws, edges, status, weight, depth, path))
            continue
        if per_node:
            shuffled = coins.permutation(f"order{path}", graph.edge_id)
            pick = shuffled[~np.isin(shuffled, edges)][:r]
        else:
            if cursor + r > len(order):
                raise ShortOrder
            pick = order[cursor : cursor + r]
        pi, consumed = masses(graph.p[pick], scheme)
        if allocation == "grid_points":
            cuts = np.cumsum(pi)
            cuts[np.flatnonzero(pi > 0)[-1] :] = 2.0
            child = np.searchsorted(cuts, coins.slots(path, len(draws)), "right")
            shares = [(int(c), draws[child == c]) for c in np.unique(child)]
        else:
            shares = []
            for c in np.flatnonzero(pi > 0):
                size = round(pi[c] * len(draws))
                size = max(1, size) if allocation == "nearest_min1" else size
                if size:
                    shares.append((int(c), np.arange(fresh, fresh + size)))
                    fresh += size
        for c, own in shares:
            k = int(consumed[c])
            open_.append((f"{path}.{c}", own, cursor + k, np.concatenate([edges, pick[:k]]), np.concatenate([status, statuses(scheme, c, r)[:k]]), weight * pi[c], depth + 1))
    return found, count


class LazyWorlds:
    """Edge states of words of draws; an edge's coins are thrown when its source is first reached.

    md5 coins are thrown for the draws that reach it only, each once since a draw reaches a node once; others by the word.
    """

    def __init__(self, graph: Graph, coins: Coins, words: np.ndarray, valid: np.ndarray, leaves: list[tuple[Leaf, np.ndarray]]):
        """leaves: each with the bits (as words) of its draws."""
        self.graph, self.coins, self.words, self.valid = graph, coins, words, valid
        self.kept = coins.kind != "md5"
        if self.kept:
            self.live = np.zeros((len(graph.edge_id), len(words)), np.uint64)
            self.known = np.zeros(len(graph.edge_id), bool)
        self.fixed = np.unique(np.concatenate([x.edges for x, _ in leaves])) if leaves else np.zeros(0, np.int64)
        self.on = np.zeros((len(self.fixed), len(words)), np.uint64)
        self.off = np.zeros_like(self.on)
        for leaf, mask in leaves:
            at = np.searchsorted(self.fixed, leaf.edges)
            self.on[at[leaf.status == 1]] |= mask
            self.off[at[leaf.status == 0]] |= mask

    def of(self, edges: np.ndarray, fresh: np.ndarray) -> np.ndarray:
        """uint64[edges, words]: live edges of the draws that have newly reached their sources."""
        new = edges[~self.known[edges]] if self.kept else edges
        out = self.live if self.kept else np.zeros((len(edges), len(self.words)), np.uint64)
        step = max(1, (1 << 16) // max(1, len(self.words)))  # a block's temporaries stay in cache
        for i in range(0, len(new), step):
            ids = new[i : i + step]
            words = self.coins.live(self.graph.edge_id[ids], self.graph.p[ids], self.words, fresh[self.graph.src[ids]])
            if len(self.fixed):
                at = np.minimum(np.searchsorted(self.fixed, ids), len(self.fixed) - 1)
                hit = self.fixed[at] == ids
                words[hit] = (words[hit] & ~self.off[at[hit]]) | self.on[at[hit]]
            out[ids if self.kept else slice(i, i + step)] = words
        if self.kept:
            self.known[new] = True
            out = out[edges]
        return out & fresh[self.graph.src[edges]]

    def thrown(self, active: np.ndarray, fresh: np.ndarray) -> int:
        """Coins that the newly reached (draw, node) pairs throw: one per out-edge whose status is not fixed."""
        total = int(np.bitwise_count(fresh[active]).sum(1, dtype=np.int64) @ (self.graph.start[active + 1] - self.graph.start[active]))
        if len(self.fixed):
            source = self.graph.src[self.fixed]
            hit = np.isin(source, active)
            total -= int(np.bitwise_count(fresh[source[hit]] & (self.on[hit] | self.off[hit])).sum())
        return total


STATE_BYTES = 64 << 20  # of edge states held at a time


def outcomes(graph: Graph, seed: int | None, coins: Coins, leaves: list[Leaf], statistic: tuple = ("spread",)) -> tuple[np.ndarray, int]:
    """(f of every draw of the leaves in their order, coins thrown)."""
    draws = np.concatenate([x.draws for x in leaves])
    kind, *args = statistic
    spans = np.cumsum([0] + [len(x.draws) for x in leaves])
    if seed is None:  # a node without edges reaches nothing
        return np.full(len(draws), float(args[1]) if kind == "distance" else 0.0), 0
    out, spent = np.zeros(len(draws)), 0
    every = np.unique(draws >> 6)
    step = max(1, STATE_BYTES // (8 * max(1, len(graph.edge_id))))
    for i in range(0, len(every), step):
        words = every[i : i + step]
        here = np.flatnonzero((draws >> 6 >= words[0]) & (draws >> 6 <= words[-1]))
        lanes = np.searchsorted(words, draws[here] >> 6) * 64 + (draws[here] & 63)
        mask_of = lambda some, n=len(words): np.packbits(np.bincount(some, minlength=64 * n).astype(bool), bitorder="little").view(np.uint64)
        cut = np.searchsorted(here, spans)
        fixed = [(x, mask_of(lanes[a:b])) for x, a, b in zip(leaves, cut, cut[1:], strict=False) if b > a and len(x.edges)]
        worlds = LazyWorlds(graph, coins, words, mask_of(lanes), fixed)
        f, thrown = _measure(graph, seed, worlds, kind, args)
        out[here] = f[lanes]
        spent += thrown
    return out, spent


def _measure(graph: Graph, seed: int, worlds: LazyWorlds, kind: str, args: list) -> tuple[np.ndarray, int]:
    words = len(worlds.words)
    width = 64 * words
    reached = np.zeros((len(graph.nodes), words), np.uint64)
    reached[seed] = worlds.valid
    fresh, active, hop, spent = np.zeros_like(reached), np.array([seed]), 0, 0
    fresh[seed] = reached[seed]
    touched = [active]
    target = graph.number(args[0]) if kind in ("reaches", "reaches_within", "distance") else None
    limit = args[1] if kind == "reaches_within" else None
    cap = float(args[1]) if kind == "distance" else 0.0
    distance = np.full(width, cap)
    if target == seed:
        distance[:] = 0
    while len(active) and (limit is None or hop < limit):
        hop += 1
        e = graph.out_edges(active)
        if not len(e):
            break
        go = worlds.of(e, fresh)
        spent += worlds.thrown(active, fresh)
        order = np.argsort(graph.dst[e], kind="stable")
        ends = graph.dst[e][order]
        heads = np.flatnonzero(np.concatenate([[True], ends[1:] != ends[:-1]]))
        nodes = ends[heads]
        new = np.bitwise_or.reduceat(go[order], heads, axis=0) & ~reached[nodes]
        some = new.any(1)
        active = nodes[some]
        fresh[active] = new[some]
        reached[active] |= new[some]
        touched.append(active)
        if kind == "distance" and target is not None and (active == target).any():
            hit = np.unpackbits(fresh[target].view(np.uint8), bitorder="little").astype(bool)
            distance[hit] = np.minimum(distance[hit], hop)
    if kind == "distance":
        return distance, spent
    if kind in ("reaches", "reaches_within"):
        return np.zeros(width) if target is None else np.unpackbits(reached[target].view(np.uint8), bitorder="little").astype(float), spent
    if kind == "connects":
        hit = np.full(words, 0xFFFFFFFFFFFFFFFF, np.uint64)
        for t in args[0]:
            at = graph.number(t)
            hit = hit & reached[at] if at is not None else hit & np.uint64(0)
        return np.unpackbits(hit.view(np.uint8), bitorder="little").astype(float), spent
    total, nodes = np.zeros(width), np.unique(np.concatenate(touched))
    for i in range(0, len(nodes), 4096):
        total += np.unpackbits(reached[nodes[i : i + 4096]].view(np.uint8), axis=1, bitorder="little").sum(0)
    return total - 1, spent


def stratified_variance(f: np.ndarray, leaves: list[Leaf], f_hat: float, by_share: bool = True) -> float:
    """Estimated variance of the mean: leaves' sample variances, weighted by their shares of the draws (or their masses).

    Leaves of one draw have no variance of their own: they are pooled in pairs in the order of their paths,
    the last odd one with the pair before it; a single one takes its distance from the mean.
    """
    spans = np.cumsum([0] + [len(x.draws) for x in leaves])
    total, lone = 0.0, []
    for x, a, b in zip(leaves, spans, spans[1:], strict=False):
        if b - a == 1:
            lone.append((x.path, f[a], 1 / len(f) if by_share else x.weight))
        else:
            total += ((b - a) / len(f) if by_share else x.weight) ** 2 * f[a:b].var(ddof=1) / (b - a)
    lone.sort()
    pairs = len(lone) // 2
    for i in range(max(1, pairs) if lone else 0):
        some = lone[2 * i : 2 * i + 2] if i < pairs - 1 else lone[2 * i :]
        value, weight = np.array([v for _, v, _ in some]), sum(w for *_, w in some)
        total += weight**2 * (value.var(ddof=1) / len(some) if len(some) > 1 else (value[0] - f_hat) ** 2)
    return float(total)
