"""NumPy kernels of one worker: graph traversal over a shard, graph construction and inserts.

Nodes are local numbers; `ids` maps them to global ids, by which ties are broken. Exact vectors come from `fetch(local numbers)`,
which reads stored vectors or calls the encoder; cheap distances come from `cheap(local numbers)`.
"""

from __future__ import annotations

import bisect
import heapq
import math
from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np

from .exact import direct_distances


@dataclass
class Shard:
    """Adjacency in compressed sparse rows, and what is known of each node."""

    ids: np.ndarray
    offsets: np.ndarray
    nbrs: np.ndarray
    codes: np.ndarray | None = None
    vectors: np.ndarray | None = None
    texts: list | None = None

    @classmethod
    def build(cls, ids: np.ndarray, lists: list[np.ndarray], **more) -> Shard:
        """lists: global ids of each node's neighbours; those outside the shard are left out."""
        order = np.argsort(ids, kind="stable")
        ids = ids[order]
        local = []
        for i in order:
            x = np.asarray(lists[i], np.int64)
            at = np.searchsorted(ids, x)
            at[at == len(ids)] = 0
            local.append(at[ids[at] == x] if len(ids) else x)
        off = np.cumsum([0, *map(len, local)])
        pick = lambda v: None if v is None else (v[order] if isinstance(v, np.ndarray) else [v[i] for i in order])
        return cls(ids, off, np.concatenate([np.empty(0, np.int64), *local]).astype(np.int64), **{k: pick(v) for k, v in more.items()})

    def of(self, u: int) -> np.ndarray:
        return self.nbrs[self.offsets[u] : self.offsets[u + 1]]

    def hub(self) -> int:
        """Entry: the node of highest degree, smallest id first."""
        return int(np.argmax(np.diff(self.offsets))) if len(self.ids) else -1


@dataclass
class Trace:
    steps: list = field(default_factory=list)  # (step, node id, cheap distances, exact distances, batch)
    batches: list = field(default_factory=list)  # objects in each encoder call
    exact: int = 0
    cheap: int = 0


class Bounded:
    """The `ef` nearest (distance, id, node), sorted, with visited marks."""

    def __init__(self, ef: int):
        self.ef, self.rows, self.visited = ef, [], set()
        self.todo: list[tuple[float, int, int]] = []  # heap of rows to visit; those that fell out since are skipped

    def offer(self, d: float, key: int, node: int) -> None:
        if len(self.rows) < self.ef or (d, key) < self.rows[-1][:2]:
            bisect.insort(self.rows, (d, key, node))
            heapq.heappush(self.todo, (d, key, node))
            del self.rows[self.ef :]

    def next(self):
        while self.todo:
            r = self.todo[0]
            if r[2] not in self.visited and r <= self.rows[-1]:
                return r
            heapq.heappop(self.todo)
        return None

    def take(self, n: int) -> list[tuple[float, int, int]]:
        """The n nearest that are not visited yet; from now on they are."""
        out = []
        while len(out) < n and (r := self.next()) is not None:
            self.visited.add(r[2])
            out.append(r)
        return out


def waves(offsets: np.ndarray, nbrs: np.ndarray, entry: int) -> list[np.ndarray]:
    """Nodes by the round that reaches them from the entry. A queue with room for all nodes drops none and visits each, whatever
    the query: so queries with the same entry go through these rounds together."""
    seen = np.zeros(len(offsets) - 1, bool)
    seen[entry] = True
    wave, out = np.array([entry]), []
    while len(wave):
        out.append(wave)
        size = offsets[wave + 1] - offsets[wave]
        at = np.repeat(offsets[wave] - np.cumsum(size) + size, size) + np.arange(size.sum())
        wave = np.unique(nbrs[at])
        wave = wave[~seen[wave]]
        seen[wave] = True
    return out


def _exact(metric: str, q: np.ndarray, x: np.ndarray) -> np.ndarray:
    d = direct_distances(metric, x, q)
    return np.where(np.isnan(d), np.inf, d) if metric == "cosine" else d


def traverse(g: Shard, q: np.ndarray, entry: int, k: int, ef: int, fetch: Callable, *, metric: str = "l2", alpha: float | None = None, cheap: Callable | None = None, alpha_base: str = "queue", min_fresh: int = 0, aq_cap: int | None = None, batch_target: int | None = None) -> tuple[list[tuple[float, int]], Trace]:
    """Best-first search; with `alpha` the interleaved form, with `batch_target` batched over steps.

    alpha None: every new neighbour gets an exact distance. Otherwise new neighbours get a cheap distance and join a
    queue; of its nearest share alpha, those without exact distance are chosen. alpha_base: the share is of the whole
    queue (`queue`), of its nodes without exact distance (`fresh`), or of this step's new neighbours (`step`).
    batch_target None: one fetch a step; 1: one fetch an object; n: steps go on until n objects wait.
    """
    if ef < k:
        raise ValueError("ef must be at least k")
    if alpha is not None and not 0 < alpha <= 1:
        raise ValueError("alpha must be in (0, 1]")
    t, eq = Trace(), Bounded(ef)
    if entry < 0 or k == 0:
        return [], t
    aq: list[tuple[float, int, int]] = []
    known, seen, waiting = {entry}, {entry}, []

    def admit(nodes: list[int]) -> None:
        if not nodes:
            return
        groups = [[n] for n in nodes] if batch_target == 1 else [nodes]
        for group in groups:
            for n, d in zip(group, _exact(metric, q, fetch(np.array(group))).tolist(), strict=True):
                eq.offer(d, int(g.ids[n]), n)
            t.batches.append(len(group))
        t.exact += len(nodes)

    admit([entry])
    step = 0
    while True:
        top = eq.next()
        if top is None:
            if not waiting:
                break
            admit(waiting)
            waiting = []
            continue
        u = top[2]
        eq.visited.add(u)
        new = [v for v in dict.fromkeys(g.of(u).tolist()) if v not in seen]
        seen.update(new)
        if alpha is None:
            chosen = new
        else:
            fresh = []
            if new:
                fresh = sorted((d, int(g.ids[v]), v) for v, d in zip(new, cheap(np.array(new)).tolist(), strict=True))
                for r in fresh:
                    bisect.insort(aq, r)
                t.cheap += len(new)
            if alpha_base == "fresh":
                pool = [r for r in aq if r[2] not in known]
                chosen = [v for _, _, v in pool[: math.ceil(round(alpha * len(pool), 9))]]
            elif alpha_base == "step":
                chosen = [v for _, _, v in fresh[: math.ceil(round(alpha * len(fresh), 9))]]
            else:
                chosen = [v for _, _, v in aq[: math.ceil(round(alpha * len(aq), 9))] if v not in known]
            if len(chosen) < min_fresh:
                chosen = [v for _, _, v in aq if v not in known][:min_fresh]
            if aq_cap:
                del aq[aq_cap:]
        known.update(chosen)
        waiting += chosen
        t.steps.append((step, int(g.ids[u]), len(new), len(chosen), len(t.batches)))
        step += 1
        if batch_target is None or batch_target == 1 or len(waiting) >= batch_target:
            admit(waiting)
            waiting = []
    return [(d, i) for d, i, _ in eq.rows[:k]], t


def cheap_then_exact(g: Shard, q: np.ndarray, entry: int, k: int, ef: int, cheap: Callable, fetch: Callable | None, rerank_n: int = 0, metric: str = "l2") -> tuple[list[tuple[float, int]], Trace]:
    """Traversal by cheap distances alone; with rerank_n the nearest of them get exact distances at the end."""
    t, eq = Trace(), Bounded(max(ef, rerank_n))
    if entry < 0 or k == 0:
        return [], t
    seen = {entry}
    eq.offer(float(cheap(np.array([entry]))[0]), int(g.ids[entry]), entry)
    while (top := eq.next()) is not None:
        eq.visited.add(top[2])
        new = [v for v in dict.fromkeys(g.of(top[2]).tolist()) if v not in seen]
        seen.update(new)
        if new:
            for v, d in zip(new, cheap(np.array(new)).tolist(), strict=True):
                eq.offer(d, int(g.ids[v]), v)
            t.cheap += len(new)
        t.steps.append((len(t.steps), int(g.ids[top[2]]), len(new), 0, 0))
    if not rerank_n:
        return [(d, i) for d, i, _ in eq.rows[:k]], t
    nodes = np.array([n for _, _, n in eq.rows[:rerank_n]])
    t.exact, t.batches = len(nodes), [len(nodes)]
    return sorted(zip(_exact(metric, q, fetch(nodes)).tolist(), g.ids[nodes].tolist(), strict=True))[:k], t


ALL_PAIRS = 1 << 25  # pairs of nodes whose distances are taken at once, at most


def all_distances(x: np.ndarray, q: np.ndarray, rows: int = 512) -> np.ndarray:
    """Squared distances of rows of q to rows of x, by products."""
    out = np.empty((len(q), len(x)))
    xx, qq = np.einsum("ij,ij->i", x, x), np.einsum("ij,ij->i", q, q)
    for a in range(0, len(q), rows):
        part = np.matmul(q[a : a + rows], x.T, out=out[a : a + rows])
        part *= -2
        part += xx
        part += qq[a : a + rows, None]
        np.maximum(part, 0, out=part)
    return out


def select(x: np.ndarray, u: np.ndarray, cand: list[tuple[float, int]], cap: int, rule: str = "closest", relax: float = 1.2, pairs: np.ndarray | None = None) -> list[tuple[float, int]]:
    """Neighbours out of candidates (distance, node): the nearest, or those not hidden behind a kept one. pairs: distances of
    all nodes, where known."""
    cand = sorted(cand)
    if rule == "closest":
        return cand[:cap]
    factor = relax if rule == "relaxed" else 1.0
    if not cand:
        return []
    at, dist = np.array([v for _, v in cand]), np.array([d for d, _ in cand])
    open_ = np.ones(len(cand), bool)
    y = x[at] if pairs is None else None
    few = pairs is not None and len(at) <= 2 * cap  # most rows are asked for
    apart = pairs[at[:, None], at] if few else None
    kept: list[tuple[float, int]] = []
    for i in range(len(cand)):
        if open_[i]:
            kept.append(cand[i])
            if len(kept) == cap:
                break
            open_ &= (apart[i] if few else pairs[at[i]].take(at) if pairs is not None else ((y - y[i]) ** 2).sum(1)) * factor > dist
    return kept


@dataclass
class Built:
    """Layers of adjacency lists (local numbers): layer 0 has all nodes."""

    layers: list[list[dict[int, float]]]
    levels: np.ndarray
    entry: int


def _search_layer(x: np.ndarray, q: np.ndarray, links: list[dict[int, float]], entry: list[int], ef: int, far: np.ndarray | None = None) -> list[tuple[float, int]]:
    """far: distances of q to all nodes, where known."""
    eq = Bounded(ef)
    seen = set(entry)
    away = (lambda nodes: ((x[nodes] - q) ** 2).sum(1)) if far is None else far.take
    for e, d in zip(entry, away(entry).tolist(), strict=True):
        eq.offer(d, e, e)
    while (top := eq.next()) is not None:
        eq.visited.add(top[2])
        new = [v for v in links[top[2]] if v not in seen]
        seen.update(new)
        if new:
            most = eq.rows[-1][0] if len(eq.rows) == ef else math.inf
            for v, d in zip(new, away(new).tolist(), strict=True):
                if d <= most:
                    eq.offer(d, v, v)
    return [(d, n) for d, _, n in eq.rows]


def node_levels(ids: np.ndarray, cap: int, seed: int) -> np.ndarray:
    """Layer of each node by a hash of its id: geometric with ratio 1 / cap."""
    with np.errstate(over="ignore"):
        h = (ids.astype(np.uint64) + np.uint64(seed)) * np.uint64(0x9E3779B97F4A7C15)
        h = (h ^ (h >> np.uint64(31))) * np.uint64(0xBF58476D1CE4E5B9)
    u = ((h >> np.uint64(11)).astype(np.float64) + 1) / (1 << 53)
    return np.floor(-np.log(u) / math.log(max(cap, 2))).astype(np.int64)


def link(links: list[dict[int, float]], x: np.ndarray, u: int, chosen: list[tuple[float, int]], cap: int, rule: str, pairs: np.ndarray | None = None) -> None:
    """Both directions; whoever has more than `cap` afterwards is cut back."""
    for d, v in chosen:
        links[u][v] = d
        links[v][u] = d
        for n in (u, v):
            if len(links[n]) > cap:
                links[n] = {w: e for e, w in select(x, x[n], [(e, w) for w, e in links[n].items()], cap, rule, pairs=pairs)}


def layered_build(ids: np.ndarray, x: np.ndarray, cap: int = 16, ef: int = 100, seed: int = 7, rule: str = "closest", caps: np.ndarray | None = None) -> Built:
    """Incremental construction: descend from the top layer, search with `ef`, link, cut back to `cap`.

    caps: first-link limit of each node (hub-preserving rebuild); default cap.
    """
    n = len(ids)
    x = x.astype(np.float64)
    levels = node_levels(ids, cap, seed)
    pairs = all_distances(x, x) if n * n <= ALL_PAIRS else None
    layers = [[{} for _ in range(n)] for _ in range(int(levels.max()) + 1 if n else 1)]
    entry = -1
    for u in range(n):
        if entry < 0:
            entry = u
            continue
        near = [entry]
        for layer in range(int(levels[entry]), -1, -1):
            up = layer > levels[u]
            found = _search_layer(x, x[u], layers[layer], near, 1 if up else ef, None if pairs is None else pairs[u])
            if not up:
                first = int(caps[u]) if caps is not None and layer == 0 else cap
                link(layers[layer], x, u, select(x, x[u], [(d, v) for d, v in found if v != u], first, rule, pairs=pairs), cap, rule, pairs)
            near = [v for _, v in found]
        if levels[u] > levels[entry]:
            entry = u
    return Built(layers, levels, entry)


def hub_rebuild(ids: np.ndarray, x: np.ndarray, lists: list[list[int]], cap: int, low: int, beta: float, ef: int, candidates: str = "original", rule: str = "closest") -> list[dict[int, float]]:
    """Hub-preserving pruning node by node: candidates come from a search of the full graph or of the growing one."""
    n = len(ids)
    x = x.astype(np.float64)
    deg = np.array([len(a) for a in lists])
    hub = np.zeros(n, bool)
    hub[np.lexsort((ids, -deg))[: math.ceil(round(beta * n, 9))]] = True
    if candidates == "incremental":
        return layered_build(ids, x, cap, ef, rule=rule, caps=np.where(hub, cap, low)).layers[0]
    full = [dict.fromkeys(a, 0.0) for a in lists]
    out: list[dict[int, float]] = [{} for _ in range(n)]
    for u in range(n):
        found = _search_layer(x, x[u], full, [u], ef)
        link(out, x, u, select(x, x[u], [(d, v) for d, v in found if v != u], cap if hub[u] else low, rule), cap, rule)
    return out


@dataclass
class Ledger:
    """Encoder calls of one insert, by what they were for."""

    search: int = 0
    select: int = 0
    repair: int = 0
    cheap: int = 0

    @property
    def encodes(self) -> int:
        return self.search + self.select + self.repair


def insert(links: list[list[int]], u: int, own: np.ndarray, encode: Callable[[list[int]], np.ndarray], entry: int, cap: int, ef: int, mode: str, approx: np.ndarray | None = None) -> Ledger:
    """Link node u, whose vector is `own`, into the graph; lists are changed in place. `encode` is called for nodes whose
    vectors are needed, and for no others; the ledger counts the objects of its calls.

    naive: vectors are encoded again whenever they are needed, in search, pairwise selection and repair of the neighbours'
    lists; cached: at most once each within the insert; light: selection and repair go by `approx`, what the stored codes
    stand for; simple: the nearest are taken without pairwise selection, and repair drops the farthest by the codes.
    """
    if mode in ("light", "simple") and approx is None:
        raise ValueError("light and simple inserts need the stored codes")
    led, have = Ledger(), {u: own.astype(np.float64)}

    def vectors(nodes: list[int], what: str) -> np.ndarray:
        miss = [v for v in nodes if v != u] if mode == "naive" else [v for v in dict.fromkeys(nodes) if v not in have]
        if miss:
            setattr(led, what, getattr(led, what) + len(miss))
            have.update(zip(miss, encode(miss).astype(np.float64), strict=True))
        return np.array([have[v] for v in nodes])

    q = have[u]
    eq, seen = Bounded(ef), {entry}
    eq.offer(float(((vectors([entry], "search")[0] - q) ** 2).sum()), entry, entry)
    while (top := eq.next()) is not None:
        eq.visited.add(top[2])
        new = [v for v in links[top[2]] if v not in seen]
        seen.update(new)
        if new:
            for v, d in zip(new, ((vectors(new, "search") - q) ** 2).sum(1).tolist(), strict=True):
                eq.offer(d, v, v)

    def apart(a: int, others: list[int], what: str) -> np.ndarray:
        """Squared distances of node a to others, by codes or by vectors."""
        if mode in ("light", "simple"):
            led.cheap += len(others)
            return ((approx[others] - approx[a]) ** 2).sum(1)
        got = vectors([a, *others], what)
        return ((got[1:] - got[0]) ** 2).sum(1)

    def choose(rows: list[tuple[float, int]], what: str) -> list[int]:
        if mode == "simple":
            return [v for _, v in sorted(rows)[:cap]]
        kept: list[int] = []
        for d, v in sorted(rows):
            if len(kept) == cap:
                break
            if not kept or (apart(v, kept, what) > d).all():
                kept.append(v)
        return kept

    links[u] = choose([(d, v) for d, _, v in eq.rows if v != u], "select")
    for v in links[u]:
        links[v].append(u)
        if len(links[v]) > cap:
            mine = links[v]
            links[v] = choose(list(zip(apart(v, mine, "repair").tolist(), mine, strict=True)), "repair")
    return led
