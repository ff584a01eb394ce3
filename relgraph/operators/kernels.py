"""Local solvers in numpy, for graphs whose edges fit in a worker, and how Spark runs them.

A kernel answers one (pair, repeat) at a time; Spark deals these tasks out. Within a kernel a block of worlds
advances together: a step takes every (node, world) that is new, meets their edges at once, and keeps the
(node, world) not seen before. Memory is that of the graph and of nodes times a block; the bitmap index adds a bit for
each edge and world. Cost is counted in edge probes, of which draws are part.
"""

from __future__ import annotations

import time
import tracemalloc
from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relgraph.model import UncertainGraph
from relgraph.plans.iterate import written
from relgraph.plans.reach import relevant

#: Most edges that are sent to every worker (24 bytes each); larger graphs are cut to each pair's relevant edges.
MOST_EDGES = 2_000_000
RUNS = "method string, pair_id int, s long, t long, rep int, k int, k_used long, hits double, r_hat double, probes long, depth int, ms double, bytes long"
FREE, IN, OUT = 0, 1, -1


def once(found: np.ndarray, place: np.ndarray) -> np.ndarray:
    """Each value once; `place` has room for an entry a possible value, whatever it holds."""
    i = np.arange(len(found))
    place[found] = i
    return found[place[found] == i]


@dataclass
class Local:
    """A graph in arrays: edges sorted by source, nodes numbered."""

    names: np.ndarray
    first: np.ndarray
    dst: np.ndarray
    prob: np.ndarray
    src: np.ndarray = field(default=None)
    turned: Local | None = field(default=None, repr=False)

    @staticmethod
    def of(src: np.ndarray, dst: np.ndarray, prob: np.ndarray) -> Local:
        return Local.placed(src, dst, prob)[0]

    @staticmethod
    def placed(src: np.ndarray, dst: np.ndarray, prob: np.ndarray) -> tuple[Local, np.ndarray]:
        """The graph, and which of the given edges stands at each of its places."""
        names, flat = np.unique(np.concatenate([src, dst]), return_inverse=True)
        a, b = flat[: len(src)], flat[len(src) :]
        order = np.lexsort((b, a))
        first = np.searchsorted(a[order], np.arange(len(names) + 1))
        return Local(names, first, b[order], prob[order].astype(float), a[order]), order

    def at(self, node: int) -> int:
        i = int(np.searchsorted(self.names, node))
        return i if i < len(self.names) and self.names[i] == node else -1

    def edges_of(self, nodes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Edges that leave the nodes, and which of the nodes each leaves."""
        count = self.first[nodes + 1] - self.first[nodes]
        which = np.repeat(np.arange(len(nodes)), count)
        return self.first[nodes][which] + np.arange(len(which)) - np.repeat(np.cumsum(count) - count, count), which

    def spread(self, start: int, open_: np.ndarray) -> np.ndarray:
        """Nodes reached over open edges, as a mask."""
        seen, place = np.zeros(len(self.names), bool), np.empty(len(self.names), np.int64)
        seen[start] = True
        fresh = np.array([start])
        while len(fresh):
            e, _ = self.edges_of(fresh)
            found = self.dst[e[open_[e]]]
            fresh = once(found[~seen[found]], place)
            seen[fresh] = True
        return seen

    def kept(self, which: np.ndarray) -> Local:
        """The same nodes with some of the edges."""
        src = self.src[which]
        return Local(self.names, np.searchsorted(src, np.arange(len(self.names) + 1)), self.dst[which], self.prob[which], src)

    def back(self) -> Local:
        """The graph with all edges turned round, made once."""
        if self.turned is None:
            order = np.argsort(self.dst, kind="stable")
            src = self.dst[order]
            self.turned = Local(self.names, np.searchsorted(src, np.arange(len(self.names) + 1)), self.src[order], self.prob[order], src)
        return self.turned

    def cut(self, s: int, t: int) -> Local:
        """Only edges on some way from s to t; the ends keep a place even if none is left."""
        every = np.ones(len(self.dst), bool)
        keep = self.spread(s, every)[self.src] & self.back().spread(t, every)[self.dst]
        on = np.zeros(len(self.names), bool)
        on[self.src[keep]] = on[self.dst[keep]] = on[[s, t]] = True
        number = np.cumsum(on) - 1
        src = number[self.src[keep]]
        return Local(self.names[on], np.searchsorted(src, np.arange(int(on.sum()) + 1)), number[self.dst[keep]], self.prob[keep], src)


@dataclass
class Answer:
    value: float
    used: int = 0
    probes: int = 0
    depth: int = 0


#: Most worlds that advance side by side, and most (node, world) that are held for them.
BLOCK, HELD = 1024, 1 << 26


def block_of(g: Local) -> int:
    return max(64, min(BLOCK, HELD // max(1, len(g.names))))


@dataclass
class Fixed:
    """Edges that groups of worlds fix: the group of each world, whether any group fixes an edge, and (group, edge) in order
    with whether it exists there."""

    owner: np.ndarray
    any: np.ndarray
    keys: np.ndarray
    exists: np.ndarray

    @staticmethod
    def of(sizes: list[int], edges: list[np.ndarray], exists: list[np.ndarray], m: int) -> Fixed:
        every = np.concatenate(edges)
        touched = np.zeros(m, bool)
        touched[every] = True
        group = np.repeat(np.arange(len(edges)), [len(e) for e in edges])
        keys = group * m + every
        order = np.argsort(keys)
        return Fixed(np.repeat(np.arange(len(sizes)), sizes), touched, keys[order], np.concatenate(exists)[order])

    def settle(self, hit: np.ndarray, e: np.ndarray, worlds: np.ndarray) -> None:
        """Put what is fixed in place of the coins `hit` of edges e in worlds."""
        at = np.flatnonzero(self.any[e])
        if len(at):
            keys = self.owner[worlds[at]] * len(self.any) + e[at]
            i = np.minimum(np.searchsorted(self.keys, keys), len(self.keys) - 1)
            own = self.keys[i] == keys
            hit[at[own]] = self.exists[i[own]]


def reached(
    g: Local, s: int, t: int, k: int, rng: np.random.Generator, max_hops: int | None = None, early: bool = True, bits: np.ndarray | None = None, fixed: Fixed | None = None,
) -> tuple[np.ndarray, int, int]:
    """(whether t is reached in each of k worlds, probes, depth); coins fall as edges are met. `bits` (edge, world) are worlds drawn before."""
    out = np.zeros(k, bool)
    probes = depth = 0
    block = block_of(g)
    for base in range(0, k, block):
        size = min(block, k - base)
        seen = np.zeros((len(g.names), size), bool)
        seen[s] = True
        nodes, worlds, n = np.full(size, s), np.arange(size), 0
        while len(nodes) and (max_hops is None or n < max_hops):
            n += 1
            e, which = g.edges_of(nodes)
            probes += len(e)
            if bits is not None:
                hit = bits[e, base + worlds[which]]
            else:
                hit = rng.random(len(e)) < g.prob[e]
                if fixed is not None:
                    fixed.settle(hit, e, base + worlds[which])
            d, w = g.dst[e[hit]], worlds[which[hit]]
            flat = d * size + w
            flat = np.unique(flat[~seen.ravel()[flat]])
            seen.ravel()[flat] = True
            nodes, worlds = flat // size, flat % size
            if early:
                on = ~seen[t][worlds]
                nodes, worlds = nodes[on], worlds[on]
        out[base : base + size], depth = seen[t], max(depth, n)
    return out, probes, depth


def sample(g: Local, s: int, t: int, k: int, rng: np.random.Generator, max_hops: int | None = None, early: bool = True, bits: np.ndarray | None = None) -> Answer:
    """Plain sampling."""
    if s == t:
        return Answer(1.0)
    found, probes, depth = reached(g, s, t, k, rng, max_hops, early, bits)
    return Answer(int(found.sum()) / k, k, probes, depth)


def drawn_bits(g: Local, words: int, rng: np.random.Generator, k: int, block: int = 1 << 22) -> np.ndarray:
    """The packed index of k worlds: bit i of word w of an edge's row is world 64 w + i. A coin is a byte, and more where that does not decide."""
    out = np.zeros((len(g.dst), words), np.uint64)
    step = max(1, block // max(1, 64 * words))
    for a in range(0, len(g.dst), step):
        chance = g.prob[a : a + step] * 256
        low = np.minimum(chance, 255).astype(np.uint8)
        byte = np.frombuffer(rng.bytes(len(low) * 64 * words), np.uint8).reshape(len(low), -1)
        on = byte < low[:, None]
        at = np.flatnonzero(byte == low[:, None])  # one in 256 needs more than its first byte
        on.ravel()[at] = rng.random(len(at)) < (chance - low)[at // on.shape[1]]
        on[:, k:] = False
        out[a : a + step] = np.packbits(on, axis=1, bitorder="little").view(np.uint64)
    return out


_INDEX: dict[tuple, np.ndarray] = {}


def shared_bits(g: Local, k: int, *seed: int) -> np.ndarray:
    """The index of a graph, drawn once in a process and shared by all pairs of a repeat; only the last one is kept."""
    key = (id(g.dst), k, seed)
    if key not in _INDEX:
        _INDEX.clear()
        _INDEX[key] = drawn_bits(g, -(-k // 64), np.random.default_rng(seed), k)
    return _INDEX[key]


def bitmap_search(g: Local, s: int, t: int, k: int, rng: np.random.Generator, max_hops: int | None = None, index: np.ndarray | None = None, early: bool = True) -> Answer:
    """One traversal for all worlds on packed words: a (node, word) with worlds that are new to it sends those on, until
    nothing is new; `early` drops worlds that reach t. Probes count the words that are read."""
    if s == t:
        return Answer(1.0)
    if index is None:
        index = drawn_bits(g, -(-k // 64), rng, k)
    words = index.shape[1]
    full = np.packbits(np.arange(64 * words) < k, bitorder="little").view(np.uint64)
    held, place = np.zeros(len(g.names) * words, np.uint64), np.empty(len(g.names) * words, np.int64)
    flat, at_t = index.ravel(), slice(t * words, (t + 1) * words)
    at, fresh = s * words + np.flatnonzero(full), full[full != 0]
    held[at] = fresh
    probes = n = 0
    while len(at) and (max_hops is None or n < max_hops):
        n += 1
        word = at % words
        e, which = g.edges_of(at // words)
        probes += len(e)
        word = word[which]
        to, sent = g.dst[e] * words + word, flat[e * words + word] & fresh[which]
        sent &= ~held[to]
        on = np.flatnonzero(sent)
        to, sent = to[on], sent[on]
        at = once(to, place)
        before = held[at]
        np.bitwise_or.at(held, to, sent)
        fresh = held[at] ^ before
        if early:
            fresh &= ~held[at_t][at % words]
            on = fresh != 0
            at, fresh = at[on], fresh[on]
    return Answer(int(np.bitwise_count(held[at_t]).sum()) / k, k, probes, n)


def skip(g: Local, s: int, t: int, k: int, rng: np.random.Generator, max_hops: int | None = None) -> Answer:
    """Skip sampling: an edge holds the visit of its source at which it fires next, and a gap is drawn only when it has fired.

    Worlds go in blocks; the visits that a node gets in a step, one for each world, are numbered on. An edge that is
    not due within them costs one look; each firing costs one draw. Probes count looks and draws.
    """
    if s == t:
        return Answer(1.0)
    m = len(g.dst)
    due, visits = np.full(m, -1, np.int64), np.zeros(len(g.names), np.int64)
    hits = probes = depth = 0
    block = block_of(g)
    for base in range(0, k, block):
        size = min(block, k - base)
        seen = np.zeros((len(g.names), size), bool)
        seen[s] = True
        nodes, worlds, n = np.full(size, s), np.arange(size), 0
        while len(nodes) and (max_hops is None or n < max_hops):
            n += 1
            active, first, count = np.unique(nodes, return_index=True, return_counts=True)
            e, which = g.edges_of(active)
            probes += len(e)
            never = e[due[e] < 0]
            due[never] = rng.geometric(g.prob[never]) - 1
            probes += len(never)
            end = visits[active] + count
            live = np.flatnonzero(due[e] < end[which])
            d, w = [], []
            while len(live):
                own = e[live]
                d.append(g.dst[own])
                w.append(worlds[first[which[live]] + due[own] - visits[active[which[live]]]])
                due[own] += rng.geometric(g.prob[own])
                probes += len(own)
                live = live[due[own] < end[which[live]]]
            visits[active] = end
            flat = np.concatenate(d) * size + np.concatenate(w) if d else np.zeros(0, np.int64)
            flat = np.unique(flat[~seen.ravel()[flat]])
            seen.ravel()[flat] = True
            nodes, worlds = flat // size, flat % size
            on = ~seen[t][worlds]
            nodes, worlds = nodes[on], worlds[on]
        hits, depth = hits + int(seen[t].sum()), max(depth, n)
    return Answer(hits / k, k, probes, depth)


def firing_list(prob: np.ndarray, k: int, rng: np.random.Generator) -> tuple[np.ndarray, np.ndarray]:
    """(edge, world) of all firings among k worlds, by gaps; in order of edges, then worlds."""
    at = np.full(len(prob), -1, np.int64)
    steps, live, count = [], np.arange(len(prob)), np.zeros(len(prob), np.int64)
    while len(live):
        now = at[live] + rng.geometric(prob[live])
        on = now < k
        live, now = live[on], now[on]
        at[live] = now
        count[live] += 1
        steps.append((live, now))
    first = np.cumsum(count) - count
    worlds = np.empty(int(count.sum()), np.int64)
    for n, (live, now) in enumerate(steps):
        worlds[first[live] + n] = now
    return np.repeat(np.arange(len(prob)), count), worlds


def skip_sequential(g: Local, s: int, t: int, k: int, rng: np.random.Generator, corrected: bool = True, loop: str = "retest") -> Answer:
    """Skip sampling world by world with counters at nodes, in the corrected form and in three readings of the one
    without the added one: 'retest' tests an edge again after it fired in this visit, 'once' tests it once a
    visit, and 'count_all' counts every firing into t. Certain edges always fire once."""
    if s == t:
        return Answer(1.0)
    visits: dict[int, int] = {}
    due: dict[int, np.ndarray] = {}
    hits = probes = 0
    step = 1 if corrected else 0
    for _ in range(k):
        seen, queue, hit = {s}, [s], False
        while queue and not (hit and loop != "count_all"):
            v = queue.pop()
            e = np.arange(g.first[v], g.first[v + 1])
            if v not in due:
                visits[v], due[v] = 0, rng.geometric(g.prob[e]).astype(np.int64) - 1
            c = visits[v]
            for i, edge in enumerate(e.tolist()):
                fired = 0
                while due[v][i] == c and not (fired and loop == "once"):
                    probes += 1
                    fired += 1
                    gap = int(rng.geometric(g.prob[edge])) - 1
                    if not corrected and g.prob[edge] >= 1:
                        gap = 1
                    due[v][i] = c + step + gap
                u = int(g.dst[edge])
                if fired and loop == "count_all" and u == t:
                    hits += fired
                if fired and u == t:
                    hit = True
                if fired and u not in seen:
                    seen.add(u)
                    queue.append(u)
            visits[v] = c + 1
        hits += hit and loop != "count_all"
    return Answer(hits / k, k, probes)


def split(
    g: Local, s: int, t: int, k: int, rng: np.random.Generator, r: int = 1, leaf: int | None = 5, edge_order: str = "depth",
    allocation: str = "proportional", leaf_rule: str = "at_most", max_hops: int | None = None,
) -> Answer:
    """Recursive sampling: choose r undecided edges and part the worlds by the first of them that exists; r = 1 is
    splitting on one edge, larger r stratified splitting. Edges come from the border of what certain edges
    reach ('depth', 'random'), or in the order of a breadth-first search over all that is possible ('breadth').

    Groups with few samples ('at_most' or 'below' the leaf size) or with fewer edges to choose from than r are sampled plainly:
    they wait until their graph is divided and are then sampled side by side, in one search. Of the others, one whose
    certain edges hold a way is 1 and one whose possible edges hold none is 0. leaf
    None never samples, so the answer is exact. allocation 'proportional' gives each branch its share,
    at least one sample; 'random' deals samples by chance; 'pooled' lets branches with less than one sample
    share what is left, chosen in proportion to their weight.
    """
    if s == t:
        return Answer(1.0)
    names = g.names[s], g.names[t]
    g = g.cut(s, t)
    s, t = (g.at(x) for x in names)
    out = Answer(0.0)

    def small(n: int) -> bool:
        return leaf is not None and (n <= leaf if leaf_rule == "at_most" else n < leaf)

    def shares(n: int, weights: np.ndarray) -> np.ndarray:
        if leaf is None:
            return np.where(weights > 0, n, 0)
        if allocation == "random":
            return rng.multinomial(n, weights)
        whole = np.floor(n * weights + 1e-9).astype(np.int64)
        if allocation == "pooled":
            low = (weights > 0) & (whole == 0)
            if low.any():
                whole[low] = rng.multinomial(max(0, n - int(whole.sum())), weights[low] / weights[low].sum())
            return whole
        return np.where(weights > 0, np.maximum(1, whole), 0)

    def enter(g: Local, base: np.ndarray, n: int, depth: int, weight: float) -> None:
        """Divide a graph of which `base` is known, then sample what waits."""
        waiting = []

        def divide(status: np.ndarray, known: np.ndarray, way: np.ndarray | None, n: int, depth: int, weight: float) -> np.ndarray | None:
            """Returns a possible way, which saves the next branch a search."""
            out.depth = max(out.depth, depth)
            if small(n):
                waiting.append((n, known, status[known] == IN, weight))
                return way
            if 10 * len(known) >= len(status):
                less, left = simplified(g, s, t, status, max_hops is None)
                if less is not g:
                    enter(less, left, n, depth, weight)
                    return way
            sure = _within(g, s, status, max_hops, t)
            reach = np.flatnonzero(sure >= 0)
            out.probes += len(reach)
            if sure[t] >= 0:
                out.value += weight
                return way
            if way is None or (status[way] == OUT).any():  # a way stays possible until one of its edges is excluded
                way = _way(g, s, t, status, max_hops)
                if way is None:
                    return None
            if edge_order == "breadth":  # not only at the border of what is certain
                border = _first_free(g, s, status, r)
            else:
                certain, _ = g.edges_of(reach)
                border = certain[(status[certain] == FREE) & (sure[g.dst[certain]] < 0 if max_hops is None else True)]
                far = sure[g.src[border]]
                border = border[rng.permutation(len(border))] if edge_order == "random" else border[np.lexsort((border, -far))]
            if leaf is not None and len(border) < r:
                waiting.append((n, known, status[known] == IN, weight))
                return way
            chosen = border[:r]
            if not len(chosen):
                return way
            weights = stratum_weights(g.prob[chosen])
            each = shares(n, weights)
            factor = weights.copy()
            if leaf is not None and allocation == "random":
                factor = each / n
            elif leaf is not None and allocation == "pooled":
                low = (weights > 0) & (np.floor(n * weights + 1e-9) == 0)
                if low.any():
                    drawn = int(each[low].sum())
                    if not drawn:  # no sample is left for these branches: one of them speaks for all, drawn by weight
                        each[rng.choice(np.flatnonzero(low), p=weights[low] / weights[low].sum())] = drawn = 1
                    factor[low] = weights[low].sum() * each[low] / drawn
            found = way
            for i in (*range(1, len(factor)), 0):  # from few to many excluded edges
                share, count = factor[i], each[i]
                if not count:
                    continue
                now = chosen[:i] if i else chosen
                own = status.copy()
                own[now] = OUT
                if i:
                    own[now[-1]] = IN
                found = divide(own, np.concatenate([known, now]), found, int(count), depth + 1, weight * share)
            return way

        divide(base, np.flatnonzero(base), None, n, depth, weight)
        if waiting:
            sizes, edges, exists, shares_ = zip(*waiting, strict=True)
            found, probes, _ = reached(g, s, t, sum(sizes), rng, max_hops, fixed=Fixed.of(sizes, edges, exists, len(g.dst)) if any(map(len, edges)) else None)
            hits = np.bincount(np.repeat(np.arange(len(sizes)), sizes), found, len(sizes))
            out.value += float((np.array(shares_) * hits / np.array(sizes)).sum())
            out.used += len(found)
            out.probes += probes

    enter(g, np.zeros(len(g.dst), np.int8), k, 0, 1.0)
    return out


def simplified(g: Local, s: int, t: int, status: np.ndarray, contract: bool = True, least: int = 64) -> tuple[Local, np.ndarray]:
    """The graph without edges that are excluded, that lead back to what certain edges reach, or that no possible way
    from s to t holds; done where a tenth of the edges is excluded."""
    gone = int((status == OUT).sum())
    if len(status) < least or 10 * gone < len(status):
        return g, status
    open_ = status != OUT
    keep = open_ & g.spread(s, open_)[g.src]
    part, held = g.kept(keep), status[keep]
    on = part.back().spread(t, np.ones(len(part.dst), bool))[part.dst]
    if contract:  # with a bound on hops a shorter way to a node that is certain can matter
        on &= ~part.spread(s, held == IN)[part.dst] | (held == IN)
    return part.kept(on), held[on]


def stratum_weights(prob: np.ndarray) -> np.ndarray:
    """Chance that no edge exists, then for each edge that it is the first to exist; they sum to one."""
    none = np.concatenate([[1.0], np.cumprod(1 - prob)])
    return np.concatenate([[none[-1]], prob * none[:-1]])


def _within(g: Local, a: int, status: np.ndarray, limit: int | None, until: int) -> np.ndarray:
    """Hop distances over certain edges, up to the limit or the level that holds `until`; -1 beyond."""
    far, place = np.full(len(g.names), -1), np.empty(len(g.names), np.int64)
    far[a] = 0
    fresh, n = np.array([a]), 0
    while len(fresh) and (limit is None or n < limit) and far[until] < 0:
        n += 1
        e, _ = g.edges_of(fresh)
        found = g.dst[e[status[e] == IN]]
        fresh = once(found[far[found] < 0], place)
        far[fresh] = n
    return far


def _way(g: Local, a: int, b: int, status: np.ndarray, limit: int | None) -> np.ndarray | None:
    """The edges of a shortest way from a to b on which none is excluded, if there is one within the limit."""
    unseen, start = -1, -2
    via = np.full(len(g.names), unseen)
    via[a] = start
    fresh, n = np.array([a]), 0
    while len(fresh) and (limit is None or n < limit) and via[b] == unseen:
        n += 1
        e, _ = g.edges_of(fresh)
        e = e[(status[e] != OUT) & (via[g.dst[e]] == unseen)]
        via[g.dst[e]] = e
        fresh = g.dst[e[via[g.dst[e]] == e]]
    if via[b] == unseen:
        return None
    out = []
    while b != a:
        out.append(via[b])
        b = g.src[via[b]]
    return np.array(out)


def _first_free(g: Local, a: int, status: np.ndarray, enough: int) -> np.ndarray:
    """Undecided edges in the order of a breadth-first search over all that is possible, by whole levels until there are enough."""
    seen, place = np.zeros(len(g.names), bool), np.empty(len(g.names), np.int64)
    seen[a] = True
    fresh, out, had = np.array([a]), [], 0
    while len(fresh) and had < enough:
        e, _ = g.edges_of(fresh)
        free = np.sort(e[status[e] == FREE])
        out.append(free)
        had += len(free)
        found = g.dst[e[status[e] != OUT]]
        fresh = once(found[~seen[found]], place)
        seen[fresh] = True
    return np.concatenate([*out, np.zeros(0, np.int64)]).astype(np.int64)


def enumerate_exact(g: Local, s: int, t: int, most: int = 20) -> Answer:
    """Sum over all worlds of a small graph."""
    if s == t:
        return Answer(1.0)
    m = len(g.dst)
    if m > most:
        raise ValueError(f"{m} edges are too many to enumerate")
    worlds = np.arange(1 << m)
    bits = (worlds[None, :] >> np.arange(m)[:, None] & 1).astype(bool)
    weight = np.prod(np.where(bits, g.prob[:, None], 1 - g.prob[:, None]), axis=0)
    seen = np.zeros((len(g.names), 1 << m), bool)
    seen[s] = True
    while True:
        before = int(seen.sum())
        for e in range(m):
            seen[g.dst[e]] |= seen[g.src[e]] & bits[e]
        if int(seen.sum()) == before:
            break
    return Answer(float(weight[seen[t]].sum()), 1 << m)


#: Names of methods for `solve`; each takes (graph, s, t, k, rng) and the method's own parameters.
METHODS: dict[str, Callable[..., Answer]] = {
    "mc": sample,
    "bitmap": bitmap_search,
    "skip": skip,
    "skip_sequential": skip_sequential,
    "split": split,
    "strata": lambda g, s, t, k, rng, r=50, **p: split(g, s, t, k, rng, r, **{"edge_order": "breadth", "leaf_rule": "below"} | p),
    "factor": lambda g, s, t, k, rng, **p: split(g, s, t, 1, rng, 1, None, **p),
    "enumerate": lambda g, s, t, k, rng, **p: enumerate_exact(g.cut(s, t), *_ends(g, s, t), **p),
}


def _ends(g: Local, s: int, t: int) -> tuple[int, int]:
    own = g.cut(s, t)
    return own.at(g.names[s]), own.at(g.names[t])


def answer(g: Local, method: str, s: int, t: int, k: int, seed: tuple[int, ...], params: dict) -> Answer:
    """One estimate; a pair with an end outside the graph has reliability 0, or 1 if both ends are the same."""
    if s == t:
        return Answer(1.0)
    a, b = g.at(s), g.at(t)
    if a < 0 or b < 0:
        return Answer(0.0)
    if method == "bitmap":  # one index for all pairs of a repeat
        params = {"index": shared_bits(g, k, seed[0], seed[-1])} | params
    return METHODS[method](g, a, b, k, np.random.default_rng(seed), **params)


def solve(g: UncertainGraph, pairs: DataFrame, method: str, k: int, reps: int = 1, seed: int = 1, name: str | None = None, **params) -> DataFrame:
    """A run for every pair and repeat, as (method, pair_id, s, t, rep, k, k_used, hits, r_hat, probes, depth, ms, bytes).

    ms is the time of a run in its worker. With watch=True the first repeat has in bytes the most memory that it held beside the
    interpreter, the graph and a shared index included, and no ms, as watching takes time itself.

    A graph of up to MOST_EDGES edges, counted first, is sent to the workers; of a larger one each pair gets
    the edges that matter to it, which must fit in a worker.
    """
    spark = g.edges.sparkSession
    if method not in METHODS:
        raise ValueError(f"unknown method {method}")
    label = name or method
    if g.edges.count() <= MOST_EDGES:
        columns = g.edges.select("src", "dst", "prob").toArrow()
        local = Local.of(*(c.to_numpy() for c in columns.columns))
        shared = spark.sparkContext.broadcast(local)
        tasks = pairs.select("pair_id", "s", "t").crossJoin(spark.range(reps).select(F.col("id").cast("int").alias("rep")))
        tasks = tasks.repartition(spark.sparkContext.defaultParallelism * 2, F.xxhash64("pair_id", "rep"))

        def run(batches):
            for batch in batches:
                yield _runs(shared.value, batch.to_pydict(), label, method, k, seed, params)

        return tasks.mapInArrow(run, RUNS)
    return solve_apart(relevant(g, pairs), pairs, method, k, reps, seed, name, **params)


def solve_apart(edges: DataFrame, pairs: DataFrame, method: str, k: int, reps: int = 1, seed: int = 1, name: str | None = None, **params) -> DataFrame:
    """As `solve`, where each pair has a graph of its own: edges (pair_id, src, dst, prob), which must fit in a worker."""
    label = name or method
    ends = written(pairs.select("pair_id", "s", "t"), "ends")  # apart from the pairs that the edges derive from

    def one(task: pa.Table, edges: pa.Table) -> pa.Table:
        local = Local.of(*(edges.column(c).to_numpy() for c in ("src", "dst", "prob")))
        rows = [{**r, "rep": i} for r in task.to_pylist() for i in range(reps)]
        return pa.Table.from_batches([_runs(local, {c: [r[c] for r in rows] for c in ("pair_id", "s", "t", "rep")}, label, method, k, seed, params)])

    return ends.groupBy("pair_id").cogroup(edges.groupBy("pair_id")).applyInArrow(one, RUNS)


def _watched(g: Local, *query) -> tuple[Answer, int]:
    """An answer and the most bytes held for it."""
    had = sum(x.nbytes for x in _INDEX.values()) + sum(x.nbytes for x in (g.names, g.first, g.dst, g.prob, g.src))
    tracemalloc.start()
    try:
        found = answer(g, *query)
        return found, had + tracemalloc.get_traced_memory()[1]
    finally:
        tracemalloc.stop()


def _runs(g: Local, rows: dict, label: str, method: str, k: int, seed: int, params: dict) -> pa.RecordBatch:
    watch, params = params.get("watch", False), {name: v for name, v in params.items() if name != "watch"}
    found, ms, held = [], [], []
    for p, s, t, rep in zip(rows["pair_id"], rows["s"], rows["t"], rows["rep"], strict=True):
        began = time.perf_counter()
        query = (method, s, t, k, (seed, p, rep), params)
        one, most = _watched(g, *query) if watch and rep == 0 else (answer(g, *query), None)
        found.append(one)
        held.append(most)
        ms.append((time.perf_counter() - began) * 1000 if most is None else None)
    n = len(found)
    columns = [
        pa.array([label] * n), pa.array(rows["pair_id"], pa.int32()), pa.array(rows["s"], pa.int64()), pa.array(rows["t"], pa.int64()), pa.array(rows["rep"], pa.int32()),
        pa.array([k] * n, pa.int32()), pa.array([a.used for a in found], pa.int64()), pa.array([a.value * k for a in found], pa.float64()),
        pa.array([a.value for a in found], pa.float64()), pa.array([a.probes for a in found], pa.int64()), pa.array([a.depth for a in found], pa.int32()),
        pa.array(ms, pa.float64()), pa.array(held, pa.int64()),
    ]
    return pa.RecordBatch.from_arrays(columns, [x.split()[0] for x in RUNS.split(", ")])
