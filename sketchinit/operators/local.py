"""Array versions for graphs of a bounded size (abstract graphs, coarsest levels, training graphs): one task, numpy."""

from __future__ import annotations

import heapq
import time
from collections.abc import Iterable, Iterator

import numpy as np

from ..functions.rng import draw_np


def alias_table(weights: np.ndarray | list[float]) -> tuple[np.ndarray, np.ndarray]:
    """(keep probability, alias position) of each element, by two stacks of deficient and surplus slots."""
    w = np.asarray(weights, float)
    n = len(w)
    keep, alias = np.ones(n), np.arange(n)
    if not n or w.sum() <= 0:
        return keep, alias
    scaled = w * n / w.sum()
    low, high = [i for i in range(n) if scaled[i] < 1], [i for i in range(n) if scaled[i] > 1]
    while low and high:
        a, b = low.pop(), high[-1]
        keep[a], alias[a] = scaled[a], b
        scaled[b] -= 1 - scaled[a]
        if scaled[b] <= 1:
            high.pop()
            if scaled[b] < 1:
                low.append(b)
    return keep, alias  # what rounding leaves over keeps 1


class Csr:
    """Adjacency of an undirected weighted graph on 0..n-1; ids are the nodes' names, in growing order."""

    def __init__(self, n: int, src: np.ndarray, dst: np.ndarray, w: np.ndarray | None = None, ids: np.ndarray | None = None) -> None:
        self.n, m = n, len(src)
        self.ids = np.arange(n) if ids is None else ids
        key = np.empty(2 * m, np.int64)
        key[:m], key[m:] = src, dst
        key <<= 32
        key[:m] |= dst
        key[m:] |= src
        if w is None:  # arcs are numbers that need no order of their own, and weights take no room
            key.sort()
            self.w, self.weight = np.broadcast_to(1.0, 2 * m), np.broadcast_to(1.0, m)
        else:
            order = np.argsort(key, kind="stable")
            key, self.weight = key[order], np.asarray(w, float)
            self.w = np.concatenate([self.weight, self.weight])[order]
        self.ptr = np.searchsorted(key, np.arange(n + 1) << 32)
        self.deg = np.diff(self.ptr)
        key &= 0xFFFFFFFF
        self.tail = key.astype(np.int32)
        self.src, self.dst, self.plain = src, dst, w is None
        self._alias: tuple | None = None

    @property
    def head(self) -> np.ndarray:
        return np.repeat(np.arange(self.n), self.deg)

    def alias(self) -> tuple[np.ndarray, np.ndarray]:
        if self._alias is None:
            if self.plain:
                return np.broadcast_to(1.0, len(self.tail)), np.broadcast_to(0, len(self.tail))  # no element is left for its alias
            keep, to = np.ones(len(self.tail)), np.arange(len(self.tail))
            for v in range(self.n):
                s, e = self.ptr[v], self.ptr[v + 1]
                if e > s + 1 and (self.w[s:e] != self.w[s]).any():
                    keep[s:e], a = alias_table(self.w[s:e] / self.w[s:e].sum())
                    to[s:e] = a + s
            self._alias = keep, to
        return self._alias

    def spread(self, nodes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(position in nodes, arc) of every arc that leaves one of the nodes."""
        d = self.deg[nodes]
        at = np.repeat(np.arange(len(nodes)), d)
        return at, np.arange(len(at)) - np.repeat(np.cumsum(d) - d, d) + np.repeat(self.ptr[nodes], d)


WALK_CELLS = 1 << 20  # places of the walks that go on together


def walks(g: Csr, per_node: int, length: int, seed: int = 1) -> Iterator[np.ndarray]:
    """Arrays (walks, length) of places, one walk number after the other, as many numbers together as WALK_CELLS holds; -1 after a node
    without neighbours. The draws are those of the distributed walks."""
    keep, to = g.alias()
    together = max(1, WALK_CELLS // max(1, g.n * length))
    for first in range(0, per_node, together):
        nth, cur = (a.ravel() for a in np.meshgrid(np.arange(first, min(first + together, per_node)), np.arange(g.n), indexing="ij"))
        start = g.ids[cur]
        out = np.full((len(cur), length), -1, np.int64)
        out[:, 0] = cur
        for step in range(1, length):
            live = np.flatnonzero((cur >= 0) & (g.deg[cur] > 0))
            key, here = (seed, start[live], nth[live], step), cur[live]
            slot = g.ptr[here] + np.minimum((draw_np("slot", *key) * g.deg[here]).astype(np.int64), g.deg[here] - 1)
            take = draw_np("keep", *key) >= keep[slot]
            slot[take] = to[slot[take]]
            cur = np.full(len(out), -1, np.int64)
            cur[live] = g.tail[slot]
            out[:, step] = cur
        yield out


def biased_walks(g: Csr, per_node: int, length: int, p: float, q: float, seed: int = 1, tries: int = 6) -> Iterator[np.ndarray]:
    """Second-order walks: `tries` uniform proposals are kept with weight 1/p (back), 1 (common neighbour) or 1/q; whoever is left draws from the whole distribution."""
    key = g.head * g.n + g.tail
    top = max(1 / p, 1.0, 1 / q)

    def weight(prev: np.ndarray, cand: np.ndarray) -> np.ndarray:
        k = prev * g.n + cand
        at = np.minimum(np.searchsorted(key, k), max(0, len(key) - 1))
        near = (key[at] == k) if len(key) else np.zeros(len(k), bool)
        return np.where(prev < 0, top, np.where(cand == prev, 1 / p, np.where(near, 1.0, 1 / q)))

    for nth in range(per_node):
        out = np.full((g.n, length), -1, np.int64)
        cur, prev = np.arange(g.n), np.full(g.n, -1, np.int64)
        out[:, 0] = cur
        for step in range(1, length):
            todo = np.flatnonzero((cur >= 0) & (g.deg[cur] > 0))
            nxt = np.full(g.n, -1, np.int64)
            for t in range(tries):
                c, start = cur[todo], g.ids[todo]
                slot = np.minimum((draw_np("slot", seed, start, nth, step, t) * g.deg[c]).astype(np.int64), g.deg[c] - 1)
                cand = g.tail[g.ptr[c] + slot]
                ok = draw_np("keep", seed, start, nth, step, t) * top < weight(prev[todo], cand)
                nxt[todo[ok]] = cand[ok]
                todo = todo[~ok]
                if not len(todo):
                    break
            if len(todo):
                at, arc = g.spread(cur[todo])
                run = np.cumsum(weight(prev[todo][at], g.tail[arc]))
                last = np.cumsum(g.deg[cur[todo]]) - 1
                base = np.concatenate([[0.0], run[last[:-1]]])
                goal = draw_np("rest", seed, g.ids[todo], nth, step) * (run[last] - base)
                hit = np.minimum(np.searchsorted(run, base + goal, side="right"), last)
                nxt[todo] = g.tail[arc[hit]]
            prev, cur = cur, nxt
            out[:, step] = cur
        yield out


DENSE = 1 << 20  # up to so many possible pairs are counted in a table


def count_pairs(paths: Iterable[np.ndarray], window: int, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(center, context, times) within `window` places, sorted; never more in memory than one array of walks and the distinct pairs."""
    if n * n <= DENSE:
        table = np.zeros(n * n, np.int64)
        for path in paths:
            for d in range(1, min(window, path.shape[1] - 1) + 1):
                x, y = path[:, :-d].ravel(), path[:, d:].ravel()
                ok = (x >= 0) & (y >= 0)
                table += np.bincount(x[ok] * n + y[ok], minlength=n * n)
        table = (table.reshape(n, n) + table.reshape(n, n).T).ravel()
        keys = np.flatnonzero(table)
        return keys // max(n, 1), keys % max(n, 1), table[keys]
    keys, times = np.zeros(0, np.int64), np.zeros(0, np.int64)
    held: list[np.ndarray] = []

    def merged() -> tuple[np.ndarray, np.ndarray]:
        k, c = np.unique(np.concatenate(held), return_counts=True)
        every = np.concatenate([keys, k])
        order = np.argsort(every, kind="stable")
        every, c = every[order], np.concatenate([times, c])[order]
        head = np.flatnonzero(np.concatenate([[True], every[1:] != every[:-1]]))
        return every[head], np.add.reduceat(c, head)

    for path in paths:
        for d in range(1, min(window, path.shape[1] - 1) + 1):
            x, y = path[:, :-d].ravel(), path[:, d:].ravel()
            ok = (x >= 0) & (y >= 0)
            held += [x[ok] * n + y[ok], y[ok] * n + x[ok]]
        if sum(map(len, held)) > 4_000_000:
            keys, times = merged()
            held = []
    if sum(map(len, held)):
        keys, times = merged()
    return keys // max(n, 1), keys % max(n, 1), times


class _Runs:
    """Where each batch's updates go: batches follow each other in `at`, `batch` long. A row that takes over `most` updates in one batch,
    each counting for `each`, takes their mean so many times. The sorting is done for all of the batches together; where most rows take one
    update, only the others are added up."""

    def __init__(self, at: np.ndarray, each: np.ndarray, batch: int, n: int, most: float = 20.0) -> None:
        self.batch, self.size = batch, len(at)
        of = np.arange(len(at)) // batch
        key = of * n + at
        if (of[-1] + 1) * n <= 1 << 16:
            self.order = np.argsort(key.astype(np.uint16), kind="stable")
            s = key[self.order]
        else:  # keys with their places are sorted as numbers, which gives the same order
            bits = len(at).bit_length()
            s = key << bits | np.arange(len(at))
            s.sort()
            self.order = s & ((1 << bits) - 1)
            s >>= bits
        self.head = np.flatnonzero(np.concatenate([[True], s[1:] != s[:-1]]))
        self.row = at[self.order[self.head]]
        self.first = np.searchsorted(s[self.head], np.arange(of[-1] + 2) * n)
        self.scale = np.minimum(1.0, most / np.add.reduceat(each[self.order], self.head)).astype(np.float32)[:, None]
        self.lone: np.ndarray | None = None
        if 2 * len(self.head) > len(at):
            count = np.diff(np.append(self.head, len(at)))
            self.lone = count == 1
            shared = np.repeat(~self.lone, count)
            self.rest = self.order[shared]  # updates of rows that take several
            self.starts = np.cumsum(np.where(self.lone, 0, count)) - count
            self.bounds = np.concatenate([[0], np.cumsum(shared)])[np.minimum(np.arange(of[-1] + 2) * batch, len(at))]

    def add(self, table: np.ndarray, what: np.ndarray, k: int) -> None:
        """table gets the updates `what` of batch k, repeats included."""
        lo, h = k * self.batch, slice(self.first[k], self.first[k + 1])
        head, row = self.head[h], self.row[h]
        if self.lone is None:
            order = self.order[lo : min(lo + self.batch, self.size)] - lo
            table[row] += np.add.reduceat(what.take(order, axis=0), head - lo) * self.scale[h]
            return
        sums = what.take(self.order[head] - lo, axis=0)
        several = np.flatnonzero(~self.lone[h])
        if len(several):
            first, last = self.bounds[k], self.bounds[k + 1]
            sums[several] = np.add.reduceat(what.take(self.rest[first:last] - lo, axis=0), self.starts[h][several] - first)
        sums *= self.scale[h]
        sums += table.take(row, axis=0)
        table[row] = sums


WIDE, GROUP, AHEAD = 1 << 13, 64, 1 << 14  # nodes beyond which GROUP pairs of a batch share negatives of their own; pairs that are sorted together then


def train(x: np.ndarray, y: np.ndarray, center: np.ndarray, context: np.ndarray, times: np.ndarray, negatives: int, rate: tuple[float, float], seed: int) -> None:
    """Skip-gram with negative sampling, in place, on pairs that each count `times`; y is x where both sides share one table.

    The rate falls from rate[0] to rate[1]. A batch shares one set of
    negatives, drawn by frequency ** 0.75 and weighted to `negatives` a pair;
    with over WIDE nodes each group of its pairs has a set of its own, as many
    in all, so that a pair meets fewer of them and costs less.
    No pair is copied: each pass sees the pairs that still count, and where
    all of them count often, takes up to eight times of one at once.
    """
    if not len(center):
        return
    given = x, y
    x = x.astype(np.float32)
    y = x if given[0] is given[1] else y.astype(np.float32)
    rng = np.random.default_rng(seed)
    freq = np.bincount(context, times, len(y)) ** 0.75
    cdf = np.cumsum(freq / freq.sum())
    many = np.argsort(-times, kind="stable")
    total, seen = int(times.sum()), 0
    by = min(8, max(1, total // (64 * len(times))))
    batch = max(16, min(512, 4 * len(x)) // by)  # a few updates of a node at a time
    group = batch if len(x) <= WIDE else max(16, GROUP // by)
    shared = max(8, group // 4)
    most = (1 << 16) // max(len(x), len(y)) if len(x) <= WIDE else AHEAD // batch  # batches whose updates are sorted together
    sizes = np.searchsorted(-times[many], -np.arange(0, int(times.max()), by), side="left")
    parts: list[np.ndarray] = []
    loads: list[np.ndarray] = []
    held = 0
    for k, size in enumerate(sizes.tolist()):
        some = many[rng.permutation(size)]
        parts.append(some)
        loads.append(np.minimum(times[some] - k * by, by).astype(np.float32))
        held += size
        if held < batch and k + 1 < len(sizes):
            continue
        buffer, load = np.concatenate(parts), np.concatenate(loads)
        end = len(buffer) if k + 1 == len(sizes) else len(buffer) - len(buffer) % batch
        ahead = batch * max(1, min(most, (1 << 20) // batch))
        for at in range(0, end, ahead):
            some = slice(at, min(at + ahead, end))
            i, q = buffer[some], load[some]
            if group < batch and len(i) % group:  # the last group is filled up with pairs that count nothing
                fill = group - len(i) % group
                i, q = np.concatenate([i, np.repeat(i[-1:], fill)]), np.concatenate([q, np.zeros(fill, np.float32)])
            c, o = center[i], context[i]
            here = np.add.reduceat(q, np.arange(0, len(i), batch)).astype(float)
            done = seen + np.cumsum(here) - here
            each = here if group == batch else np.add.reduceat(q, np.arange(0, len(i), group)).astype(float)
            neg = np.minimum(np.searchsorted(cdf, rng.random((len(each), shared))), len(y) - 1)
            lr = q * np.repeat((rate[0] + (rate[1] - rate[0]) * done / total).astype(np.float32), batch)[: len(q)]
            sets = batch // group
            to_o, to_c = _Runs(o, q, batch, len(y)), _Runs(c, q, batch, len(x))
            to_neg = _Runs(neg.ravel(), np.repeat(each * negatives / shared, shared), sets * shared, len(y))
            for k in range(len(here)):
                j = slice(k * batch, (k + 1) * batch)
                u, v, z, r = x.take(c[j], axis=0), y.take(o[j], axis=0), y.take(neg[k * sets : (k + 1) * sets], axis=0), lr[j]
                gp = r / (1 + np.exp(-np.clip((u * v).sum(axis=1), -20, 20))) - r
                us = u.reshape(len(z), -1, u.shape[1])
                gn = us @ z.transpose(0, 2, 1)
                np.negative(np.clip(gn, -20, 20, out=gn), out=gn)
                np.exp(gn, out=gn)
                gn += 1
                np.divide(np.float32(negatives / shared) * r.reshape(len(z), -1, 1), gn, out=gn)
                gu = gp[:, None] * v + (gn @ z).reshape(u.shape)
                to_o.add(y, -gp[:, None] * u, k)
                to_neg.add(y, -(gn.transpose(0, 2, 1) @ us).reshape(-1, u.shape[1]), k)
                to_c.add(x, -gu, k)
            seen += float(here.sum())
        parts, loads, held = [buffer[end:]], [load[end:]], len(buffer) - end
    given[0][:], given[1][:] = x, y


def skip_gram(n: int, center: np.ndarray, context: np.ndarray, times: np.ndarray, d: int, epochs: int = 1, negatives: int = 5, rate: float = 0.025, seed: int = 1) -> np.ndarray:
    """Vectors of a small graph from a random start."""
    x, y = (np.random.default_rng(seed).random((n, d)) - 0.5) / d, np.zeros((n, d))
    for e in range(epochs):
        train(x, y, center, context, times, negatives, (rate * (1 - e / epochs), max(0.05 * rate, rate * (1 - (e + 1) / epochs))), seed + e)
    return x


STRIP = 32  # neighbours of one strip of a node's list


class _Sums:
    """Sums of the neighbours' rows, for nodes in order of their degree, so that the rows that are read most lie together. A node's list is cut in
    strips; strips of a chunk lie in order of their length, so that the k-th neighbours of all of them are added at once."""

    def __init__(self, g: Csr, d: int, chunk: int) -> None:
        self.order = np.argsort(-g.deg, kind="stable")
        rank = np.empty(g.n, np.int32)
        rank[self.order] = np.arange(g.n)
        has = self.order[: np.count_nonzero(g.deg)]
        many = -(-g.deg[has] // STRIP)
        ends = np.cumsum(many)
        self.parts: list[tuple] = []
        lo, rows = 0, max(1, chunk // max(1, d))
        while lo < len(has):
            hi = max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + rows, side="right")))
            v, n = has[lo:hi], many[lo:hi]
            first = np.cumsum(n) - n
            at = np.arange(int(n.sum())) - np.repeat(first, n)
            size = np.minimum(STRIP, np.repeat(g.deg[v], n) - STRIP * at)
            begin = np.repeat(g.ptr[v], n) + STRIP * at
            order = np.argsort(-size, kind="stable")
            begin, counts = begin[order], np.searchsorted(-size[order], -np.arange(size.max()), side="left")
            lists = [rank[g.tail[begin[:c] + k]] for k, c in enumerate(counts.tolist())]
            back = None
            if len(at) > len(v):
                back = np.empty(len(order), np.int64)
                back[order] = np.arange(len(order))
            self.parts.append((slice(lo, hi), g.deg[v][:, None], first, back, lists))
            lo = hi

    def of(self, x: np.ndarray) -> Iterator[tuple[slice, np.ndarray, np.ndarray]]:
        """(places, degrees, sums of the neighbours' rows) of each chunk; x has its rows in `order`."""
        for here, deg, first, back, lists in self.parts:
            total = x.take(lists[0], axis=0)
            for at in lists[1:]:
                total[: len(at)] += x.take(at, axis=0)
            yield here, deg, total if back is None else np.add.reduceat(total.take(back, axis=0), first, axis=0)


def propagate(g: Csr, x: np.ndarray, delta: float, max_iter: int, chunk: int = 1 << 17) -> tuple[np.ndarray, list[tuple[float, float]]]:
    """Vectors and (move, seconds) of each step, until the mean move is at most delta."""
    trace: list[tuple[float, float]] = []
    sums = _Sums(g, x.shape[1], chunk)
    x = x.take(sums.order, axis=0)
    for _ in range(max_iter):
        t = time.time()
        new, moved = x.copy(), 0.0
        for here, deg, total in sums.of(x):
            old = x[here]
            total /= deg
            total += old
            total *= 0.5
            new[here] = total
            total -= old
            moved += float(np.sqrt(np.einsum("ij,ij->i", total, total)).sum())
        move = moved / len(x) if len(x) else 0.0
        x = new
        trace.append((move, time.time() - t))
        if move <= delta:
            break
    out = np.empty_like(x)
    out[sums.order] = x
    return out, trace


def reconstruction(g: Csr, emb: np.ndarray, theta: str = "euclid_distance") -> float:
    """Sum over ordered pairs of (A - theta)^2 without touching all pairs, diagonal included as theta(v, v)."""
    n = g.n
    a2 = 2 * float((g.weight**2).sum())
    if theta in ("euclid_distance", "neg_distance"):
        sign = 1.0 if theta == "euclid_distance" else -1.0
        dist = np.sqrt(((emb[g.src] - emb[g.dst]) ** 2).sum(axis=1))
        s = emb.sum(axis=0)
        return a2 - 2 * sign * 2 * float((g.weight * dist).sum()) + 2 * n * float((emb**2).sum()) - 2 * float(s @ s)
    if theta == "cosine":
        emb = emb / np.maximum(np.sqrt((emb**2).sum(axis=1, keepdims=True)), 1e-12)
    dots = (emb[g.src] * emb[g.dst]).sum(axis=1)
    gram = emb.T @ emb
    return a2 - 4 * float((g.weight * dots).sum()) + float((gram**2).sum())


SEARCHES = 4_096  # searches that go on together, a bit each
WORDS = 1 << 22  # words of 64 such bits that are looked at together


def diameter(g: Csr, sources: np.ndarray | None = None) -> int:
    """Longest shortest path in hops inside components, from the sources (default: all nodes): breadth-first searches, a bit for each."""
    sources = np.arange(g.n) if sources is None else sources
    best = 0
    for first in range(0, len(sources), SEARCHES):
        some = sources[first : first + SEARCHES]
        at = np.arange(len(some))
        front = np.zeros((g.n, -(-len(some) // 64)), np.uint64)
        front[some, at // 64] = np.uint64(1) << (at % 64).astype(np.uint64)
        seen, hops, new = front.copy(), 0, some
        rows = max(1, WORDS // front.shape[1])
        while True:
            reached = np.unique(g.tail[g.spread(new)[1]])  # no other node can be new to a search
            nxt = np.zeros_like(front)
            lo = 0
            ends = np.cumsum(g.deg[reached])
            while lo < len(reached):
                hi = max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + rows, side="right")))
                v = reached[lo:hi]
                arc = g.spread(v)[1]
                nxt[v] = np.bitwise_or.reduceat(front[g.tail[arc]], np.cumsum(g.deg[v]) - g.deg[v], axis=0) & ~seen[v]
                lo = hi
            new = reached[nxt[reached].any(axis=1)]
            if not len(new):
                break
            seen[new] |= nxt[new]
            front, hops = nxt, hops + 1
        best = max(best, hops)
    return best


def statistics(g: Csr) -> list[float]:
    """Nodes, edges, density, diameter, average and largest degree, average and largest edge weight."""
    m = len(g.src)
    return [g.n, m, 2 * m / (g.n * (g.n - 1)) if g.n > 1 else 0.0, diameter(g), 2 * m / g.n if g.n else 0.0, int(g.deg.max()) if g.n else 0, float(g.weight.mean()) if m else 0.0, float(g.weight.max()) if m else 0.0]


def random_graph(kind: str, n: int, seed: int) -> Csr:
    """A connected-enough random weighted graph: gnp, planted groups, or preferential attachment; weights are geometric."""
    rng = np.random.default_rng(seed)
    if kind == "pref_attach":
        ends, pairs = [0, 1], {(0, 1)}
        for v in range(2, n):
            for u in {ends[int(rng.integers(len(ends)))] for _ in range(3)}:
                pairs.add((u, v))
                ends += [u, v]
        src, dst = (np.array(c) for c in zip(*sorted(pairs)))
    else:
        i, j = np.triu_indices(n, 1)
        p = np.full(len(i), min(1.0, 6 / n)) if kind == "gnp" else np.where(i * 4 // n == j * 4 // n, min(1.0, 16 / n), 1 / n)
        on = rng.random(len(i)) < p
        src, dst = i[on], j[on]
    return Csr(n, src.astype(np.int64), dst.astype(np.int64), rng.geometric(0.3, len(src)))


# ---------------------------------------------------------------- a balanced cut of a bounded graph


def _grown(g: Csr, size: np.ndarray, k: int, cap: int, order: np.ndarray) -> np.ndarray:
    """Parts grown one after the other along the heaviest connection, up to the mean size."""
    part, load = np.full(g.n, -1, np.int64), np.zeros(k, np.int64)
    left, open_, nxt = int(size.sum()), k, 0
    for p in range(k):
        goal, heap, gain = left / open_, [], {}
        while load[p] < goal:
            if heap:
                w, v = heapq.heappop(heap)
                if part[v] >= 0 or gain.get(v) != -w:
                    continue
            else:
                while nxt < g.n and part[order[nxt]] >= 0:
                    nxt += 1
                if nxt == g.n:
                    break
                v = int(order[nxt])
                if load[p] and load[p] + size[v] > cap:
                    break
            if load[p] and load[p] + size[v] > cap:
                continue
            part[v] = p
            load[p] += size[v]
            s, e = g.ptr[v], g.ptr[v + 1]
            for u, x in zip(g.tail[s:e].tolist(), g.w[s:e].tolist()):
                if part[u] < 0:
                    gain[u] = gain.get(u, 0.0) + x
                    heapq.heappush(heap, (-gain[u], u))
        left, open_ = left - int(load[p]), open_ - 1
    for v in np.flatnonzero(part < 0).tolist():
        part[v] = int(np.argmin(load))
        load[part[v]] += size[v]
    return part


HUB = 48  # neighbours beyond which a table of all parts costs less than a dictionary


def _moved(g: Csr, size: np.ndarray, part: np.ndarray, k: int, cap: int, sweeps: int) -> None:
    """Moves of border nodes to the best connected part with room, in place."""
    load = np.bincount(part, size, k).astype(np.int64)
    calm = np.zeros(g.n, bool)  # no other part is better connected, and no neighbour has moved since
    for _ in range(sweeps):
        moved = 0
        border = np.unique(g.head[part[g.head] != part[g.tail]])
        for v in border.tolist():
            here, room, to = int(part[v]), cap - size[v], -1
            if calm[v] and load[here] <= cap:
                continue
            s, e = g.ptr[v], g.ptr[v + 1]
            if e - s >= HUB:  # the same choice by a table of all parts
                table = np.bincount(part[g.tail[s:e]], g.w[s:e], k)
                own = table[here] if load[here] <= cap else -1.0  # an overfull part gives nodes away
                table[here] = 0.0
                calm[v] = table.max() <= own
                table[load > room] = 0.0
                q = int(table.argmax())
                if table[q] > max(own, 0.0):
                    to = q
            else:
                sums: dict[int, float] = {}
                for q, x in zip(part[g.tail[s:e]].tolist(), g.w[s:e].tolist()):
                    sums[q] = sums.get(q, 0.0) + x
                own = sums.pop(here, 0.0)
                if load[here] > cap:
                    own = -1.0
                best = own
                calm[v] = max(sums.values(), default=0.0) <= own
                for q, x in sums.items():
                    if load[q] <= room and (x > best or (x == best and to >= 0 and q < to)):
                        best, to = x, q
            if to >= 0 and load[here] > size[v]:
                load[here] -= size[v]
                load[to] += size[v]
                part[v] = to
                calm[v], calm[g.tail[s:e]] = False, False
                moved += 1
        if not moved:
            break


def cut(g: Csr, size: np.ndarray, k: int, cap: int, seed: int = 1, small: int = 0, sweeps: int = 6) -> np.ndarray:
    """k parts of a weighted graph: match heavy edges until it is small, grow parts, then undo the matching and move border nodes."""
    rng = np.random.default_rng(seed)
    small = small or max(4 * k, 200)
    levels: list[tuple[Csr, np.ndarray, np.ndarray]] = []
    while g.n > small:
        mate = np.full(g.n, -1, np.int64)
        limit = max(1, cap // 3)
        for v in rng.permutation(g.n).tolist():
            if mate[v] >= 0 or size[v] >= limit:
                continue
            best, to = 0.0, -1
            for u, x in zip(g.tail[g.ptr[v] : g.ptr[v + 1]].tolist(), g.w[g.ptr[v] : g.ptr[v + 1]].tolist()):
                if mate[u] < 0 and x > best and size[u] + size[v] <= limit:
                    best, to = x, u
            if to >= 0:
                mate[v], mate[to] = to, v
        low = np.where(mate >= 0, np.minimum(mate, np.arange(g.n)), np.arange(g.n))
        up, parent = np.unique(low, return_inverse=True)
        if len(up) > 0.95 * g.n:
            break
        a, b = parent[g.src], parent[g.dst]
        on = a != b
        key, at = np.unique(np.minimum(a, b)[on] * len(up) + np.maximum(a, b)[on], return_inverse=True)
        levels.append((g, size, parent))
        g = Csr(len(up), key // len(up), key % len(up), np.bincount(at, g.weight[on], len(key)))
        size = np.bincount(parent, size, len(up)).astype(np.int64)
    part = _grown(g, size, k, cap, rng.permutation(g.n))
    _moved(g, size, part, k, cap, sweeps)
    for g, size, parent in reversed(levels):
        part = part[parent]
        _moved(g, size, part, k, cap, sweeps)
    return part
