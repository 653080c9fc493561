"""The simple-graph rounds in numpy, for graphs that fit one task, and exact single moves for small graphs."""

from __future__ import annotations

import itertools
import time
from collections import deque
from collections.abc import Iterator, Sequence

import numpy as np

from ..em.loop import Stop
from ..rng import decimals, portable_numpy


def g(x: np.ndarray) -> np.ndarray:
    return x * np.log(np.where(x > 0, x, 1.0))


def cost(hit: np.ndarray, miss: np.ndarray) -> np.ndarray:
    return np.where((hit >= 0) & (miss >= 0), g(hit + miss) - g(np.maximum(hit, 0)) - g(np.maximum(miss, 0)), 0.0)


class Graph:
    """A simple graph in compressed rows."""

    def __init__(self, n: int, src: np.ndarray, dst: np.ndarray) -> None:
        self.n, self.src, self.dst = n, src.astype(np.int32), dst.astype(np.int32)
        ends, others = np.concatenate((self.src, self.dst)), np.concatenate((self.dst, self.src))
        order = np.argsort(ends, kind="stable")
        self.other = others[order]
        self.start = np.concatenate(([0], np.cumsum(np.bincount(ends, minlength=n))))

    def counts(self, lab: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Block sizes, hits and misses as symmetric matrices (diagonal: pairs inside)."""
        size = np.bincount(lab, minlength=k).astype(float)
        hit = np.zeros(k * k)
        for at in range(0, len(self.src), EDGES):
            hit += np.bincount(lab[self.src[at : at + EDGES]] * k + lab[self.dst[at : at + EDGES]], minlength=k * k)
        hit = hit.reshape(k, k)
        hit = hit + hit.T - np.diag(np.diag(hit))
        return size, hit, misses(size, hit)

    def entropy(self, lab: np.ndarray, k: int) -> float:
        return entropy_of(*self.counts(lab, k)[1:])

    def links(self, chosen: np.ndarray, lab: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Row in chosen, block and number of links, for touched blocks and each vertex's own block, by row."""
        lengths = self.start[chosen + 1] - self.start[chosen]
        at = np.repeat(self.start[chosen] - np.concatenate(([0], np.cumsum(lengths)[:-1])), lengths) + np.arange(lengths.sum())
        cell = np.repeat(np.arange(len(chosen)), lengths) * k + lab[self.other[at]]
        own = np.arange(len(chosen)) * k + lab[self.named(chosen)]
        cells, x = np.unique(np.concatenate((cell, own)), return_counts=True)
        x[np.searchsorted(cells, own)] -= 1
        return cells // k, cells % k, x.astype(float)

    def named(self, chosen: np.ndarray) -> np.ndarray:
        """Positions of chosen vertices among the labels."""
        return chosen

    def pieces(self, chosen: np.ndarray, k: int) -> Iterator[slice]:
        """Runs of chosen vertices whose links and scores are about PIECE numbers."""
        cost = np.cumsum(self.start[chosen + 1] - self.start[chosen] + k)
        at = 0
        while at < len(chosen):
            upto = max(at + 1, int(np.searchsorted(cost, (cost[at - 1] if at else 0) + PIECE, "right")))
            yield slice(at, upto)
            at = upto


CELLS = 1 << 17
EDGES = 1 << 22
PIECE = 1 << 20
HELD = 1 << 22
RECENT = 4


def misses(size: np.ndarray, hit: np.ndarray) -> np.ndarray:
    pairs = np.outer(size, size)
    np.fill_diagonal(pairs, size * (size - 1) / 2)
    return pairs - hit


def entropy_of(hit: np.ndarray, miss: np.ndarray) -> float:
    return float(np.triu(cost(hit, miss)).sum())


def table_scores(graph: Graph, lab: np.ndarray, k: int, chosen: np.ndarray) -> np.ndarray:
    """chosen x blocks: table scores of vertices of a graph that is in memory."""
    size, hit, miss = graph.counts(lab, k)
    return scores_of(size, hit, miss, *graph.links(chosen, lab, k), lab[chosen])


def scores_of(size: np.ndarray, hit: np.ndarray, miss: np.ndarray, row: np.ndarray, b: np.ndarray, x: np.ndarray, own_block: np.ndarray) -> np.ndarray:
    """vertices x blocks: table scores from block statistics (size, symmetric hit and miss) and links by row: x links of
    vertex `row` into block b, touched blocks and the own block."""
    return TableScores(size, hit, miss, len(row), int(x.max(initial=0))).of(row, b, x, own_block)


class TableScores:
    """Table scores against fixed block statistics (size, symmetric hit and miss). What x links into a block b add to the
    scores is the same for all vertices, so it is computed once for small x (`links` rows are expected, x up to `most`)
    and looked up; the column of a vertex's own block is its own."""

    def __init__(self, size: np.ndarray, hit: np.ndarray, miss: np.ndarray, links: int, most: int) -> None:
        self.size, self.hit, self.miss, self.k = size, hit, miss, len(size)
        self.now = cost(hit, miss)
        enter = cost(hit, miss + size[None, :]) - self.now
        self.leave = self.now - cost(hit, miss - (size[None, :] - np.eye(self.k)))
        self.entering, self.leaving = enter.sum(axis=1), self.leave.sum(axis=1)
        whole = hit + miss + size[None, :]
        # of a pair (a, b), by b: what entering costs but for the two terms that depend on the vertex's own links
        self.base = (g(whole) - self.now - enter).T
        self.base_own = (g(whole - 1) - self.now - enter).T
        self.hit_t, self.rest_t = hit.T, (miss + size[None, :]).T
        self.upto = min(most + 1, HELD // (2 * self.k * self.k), links // (16 * self.k))
        b, x, own = (c.ravel() for c in np.meshgrid(np.arange(self.k), np.arange(self.upto), np.arange(2), indexing="ij"))
        self.held = np.empty((len(b), self.k))
        step = max(1, CELLS // self.k)
        for at in range(0, len(b), step):
            s = slice(at, at + step)
            self.held[s] = self._computed(b[s], x[s].astype(float), own[s] == 1)

    def _computed(self, b: np.ndarray, x: np.ndarray, own: np.ndarray) -> np.ndarray:
        """links x blocks: what x links into b add to the score of each block but the vertex's own one."""
        left = self.rest_t[b] - (x + own)[:, None]
        np.maximum(left, 1.0, out=left)
        part = np.where(own[:, None], self.base_own[b], self.base[b])
        part -= g(self.hit_t[b] + x[:, None])
        part -= left * np.log(left)
        return part

    def _parts(self, b: np.ndarray, x: np.ndarray, own: np.ndarray) -> np.ndarray:
        place = (b * self.upto + x.astype(np.int64)) * 2 + own
        far = np.flatnonzero(x >= self.upto)
        if len(far) == len(b):
            return self._computed(b, x, own)
        place[far] = 0
        part = self.held[place]
        if len(far):
            part[far] = self._computed(b[far], x[far], own[far])
        return part

    def of(self, row: np.ndarray, b: np.ndarray, x: np.ndarray, own_block: np.ndarray) -> np.ndarray:
        """vertices x blocks, by slices that fit a cache."""
        now, hit, miss, leave = self.now, self.hit, self.miss, self.leave
        many = len(own_block)
        y = own_block[row]
        own = b == y
        apart = self.size[b] - own - x
        mine = now[y, b] - cost(hit[y, b] - x, miss[y, b] - apart) - leave[y, b]
        scores = np.tile(self.entering, (many, 1))
        scores[np.arange(many), own_block] = self.leaving[own_block]
        starts = np.flatnonzero(np.diff(row, prepend=-1))
        step = max(1, CELLS // self.k)
        at = 0
        while at < len(starts):
            upto = int(np.searchsorted(starts, starts[at] + step, "right")) - 1
            upto = max(upto, at + 1) if upto < len(starts) - 1 else len(starts)
            e = slice(starts[at], starts[upto] if upto < len(starts) else len(row))
            part = self._parts(b[e], x[e], own[e])
            part[np.arange(len(part)), y[e]] = mine[e]
            scores[row[starts[at:upto]]] += np.add.reduceat(part, starts[at:upto] - starts[at], axis=0)
            at = upto
        return scores


def best_blocks(scores: np.ndarray, own_block: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Best block and gain: the own block unless another is better by more than 1e-9, the smallest among equals."""
    own = scores[np.arange(len(own_block)), own_block]
    gain = own - scores.min(axis=1)
    go = gain > 1e-9
    return np.where(go, np.round(scores, 9).argmin(axis=1), own_block), np.where(go, gain, 0.0)


def decided(graph: Graph, lab: np.ndarray, k: int, chosen: np.ndarray, counts: tuple[np.ndarray, np.ndarray, np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """best_blocks of chosen vertices against fixed counts, some vertices at a time."""
    degrees = graph.start[chosen + 1] - graph.start[chosen]
    table = TableScores(*counts, int(degrees.sum()), int(degrees.max(initial=0)))
    best, gain = np.empty(len(chosen), np.int64), np.empty(len(chosen))
    for s in graph.pieces(chosen, k):
        own = lab[graph.named(chosen[s])]
        best[s], gain[s] = best_blocks(table.of(*graph.links(chosen[s], lab, k), own), own)
    return best, gain


def allowed_to_leave(gain: np.ndarray, own_block: np.ndarray, ids: np.ndarray, size: np.ndarray, min_block: int) -> np.ndarray:
    """Which departures leave every block with min_block members: the best gains of each block, then the smallest ids."""
    order = np.lexsort((ids, -gain, own_block))
    first = np.searchsorted(own_block[order], own_block[order])
    out = np.zeros(len(gain), bool)
    out[order] = np.arange(len(order)) - first < np.maximum(0, size[own_block[order]] - min_block)
    return out


def rounds(graph: Graph, lab: np.ndarray, k: int, frac: float | Sequence[float], max_iter: int, seed: int, ids: np.ndarray | None = None, stop: Stop | None = None, min_block: int = 0, damping: float = 0.0) -> Iterator[tuple[np.ndarray, float, int]]:
    """Yield (labels, entropy, moved) after each round of re-deciding a random share of the vertices: the draws, shares,
    ties and stopping of the DataFrame rounds. ids: names of the vertices; frac: one share, or one a round; without
    stop there are max_iter rounds; damping: the share of moves that are held back. Rounds of all vertices that come back
    to the labels of one of the last RECENT rounds go on as they did then, without computing it again: they draw nothing. Nor is a
    vertex decided again that was found to stay with the same labels."""
    lab, began = lab.copy(), time.monotonic()
    ids = np.arange(graph.n) if ids is None else ids
    digits = decimals(ids)
    fracs = [frac] * max_iter if np.isscalar(frac) else frac
    counts = graph.counts(lab, k)
    entropies, recent = [entropy_of(*counts[1:])], deque(maxlen=RECENT)
    settled = np.zeros(graph.n, bool)  # found to stay where they are, with the labels as they are now
    while len(entropies) <= max_iter and not (stop and stop.reached(entropies, time.monotonic() - began)):
        number = len(entropies)
        frac = fracs[number - 1]
        drawn = frac < 1 or bool(damping)
        if met := next((r for r in recent if not drawn and np.array_equal(r[0], lab)), None):
            lab, counts, settled = met[1].astype(np.int64), None, np.zeros(graph.n, bool)
            entropies.append(met[2])
            yield lab.copy(), met[2], met[3]
            continue
        start = lab.astype(np.int32)
        counts = graph.counts(lab, k) if counts is None else counts
        chosen = np.flatnonzero(portable_numpy(seed, "choose", number, digits) < frac) if frac < 1 else np.arange(graph.n)
        chosen, moved = chosen[~settled[chosen]], 0
        if len(chosen):
            best, gain = decided(graph, lab, k, chosen, counts)
            go = np.flatnonzero(best != lab[chosen])
            settled[chosen[best == lab[chosen]]] = True
            if damping:
                go = go[portable_numpy(seed, "damp", number, digits[chosen[go]]) >= damping]
            if min_block:
                go = go[allowed_to_leave(gain[go], lab[chosen[go]], ids[chosen[go]], np.bincount(lab, minlength=k), min_block)]
            moved = len(go)
            lab[chosen[go]] = best[go]
        if moved:
            counts, settled = graph.counts(lab, k), np.zeros(graph.n, bool)
        entropies.append(entropy_of(*counts[1:]))
        if not drawn:
            recent.append((start, lab.astype(np.int32), entropies[-1], moved))
        yield lab.copy(), entropies[-1], moved


def exact_changes(graph: Graph, lab: np.ndarray, k: int) -> np.ndarray:
    """vertices x blocks: entropy change of each single move, all partners counted; 0 at the own block."""
    size, hit, miss = graph.counts(lab, k)
    everyone = np.arange(graph.n)
    row, b, x = graph.links(everyone, lab, k)
    links = np.zeros((graph.n, k))
    links[row, b] = x
    out = np.zeros((graph.n, k))
    for v in everyone:
        y, own = lab[v], links[v]
        apart = size - (np.arange(k) == y) - own
        h, m = hit.copy(), miss.copy()
        h[y] -= own
        m[y] -= apart
        h[:, y], m[:, y] = h[y], m[y]
        enter = (cost(h + own[None, :], m + apart[None, :]) - cost(h, m)).sum(axis=1)
        out[v] = enter - enter[y]
    return out


def polish(graph: Graph, lab: np.ndarray, k: int) -> tuple[np.ndarray, int]:
    """Single exact moves, best first, until none lowers the entropy: a locally optimal labeling. Each move lowers the
    entropy by more than a margin, so it ends."""
    lab, moves = lab.copy(), 0
    while True:
        change = exact_changes(graph, lab, k)
        v, a = np.unravel_index(np.round(change, 9).argmin(), change.shape)
        if change[v, a] >= -1e-9:
            return lab, moves
        lab[v], moves = a, moves + 1


class RatedPairs:
    """A rating graph in one task, for hard rounds: positions of both ends and categories."""

    def __init__(self, left_ids: np.ndarray, right_ids: np.ndarray, u: np.ndarray, v: np.ndarray, c: np.ndarray, categories: int) -> None:
        self.ids, self.ends, self.c, self.categories = (left_ids, right_ids), (u, v), c, categories

    def slices(self) -> Iterator[tuple[tuple[np.ndarray, np.ndarray], np.ndarray]]:
        for at in range(0, len(self.c), PIECE):
            s = slice(at, at + PIECE)
            yield (self.ends[0][s], self.ends[1][s]), self.c[s].astype(np.int64)

    def cells(self, left: np.ndarray, right: np.ndarray, na: int, nb: int) -> np.ndarray:
        whole = np.zeros(na * nb * self.categories, np.int64)
        for (u, v), c in self.slices():
            whole += np.bincount((left[u] * nb + right[v]) * self.categories + c, minlength=len(whole))
        return whole.reshape(na, nb, self.categories).astype(float)

    def entropy(self, left: np.ndarray, right: np.ndarray, na: int, nb: int) -> float:
        n = self.cells(left, right, na, nb)
        return float(g(n.sum(axis=2)).sum() - g(n).sum())

    def scores(self, side: int, own: np.ndarray, other: np.ndarray, k: int, k_other: int, chosen: np.ndarray) -> np.ndarray:
        """chosen x blocks: exact change of the entropy when an item of the side joins a block after leaving its own."""
        position = np.full(len(own), -1)
        position[chosen] = np.arange(len(chosen))
        found = np.zeros(len(chosen) * k_other * self.categories, np.int32)  # edges of each chosen item by block and category
        for ends, c in self.slices():
            row = position[ends[side]]
            e = np.flatnonzero(row >= 0)
            cells, x = np.unique((row[e] * k_other + other[ends[1 - side][e]]) * self.categories + c[e], return_counts=True)
            found[cells] += x.astype(np.int32)
        n = self.cells(own, other, k, k_other) if side == 0 else self.cells(other, own, k_other, k).transpose(1, 0, 2)
        taken = np.bincount(own, minlength=k) > 0
        some = max(1, PIECE // (k_other * self.categories))
        width = k_other * self.categories
        return np.concatenate([np.zeros((0, k)), *(self._scored(found[at * width : (at + some) * width], own[chosen[at : at + some]], n, taken) for at in range(0, len(chosen), some))])

    def _scored(self, found: np.ndarray, own_block: np.ndarray, n: np.ndarray, taken: np.ndarray) -> np.ndarray:
        k, k_other = n.shape[:2]
        cells = np.flatnonzero(found)
        x = found[cells].astype(np.int64)
        pairs, where = np.unique(cells // self.categories, return_inverse=True)
        sums = np.bincount(where, x)
        out = np.zeros((len(own_block), k))

        def add(rows: np.ndarray, base: np.ndarray, amount: np.ndarray, sign: int) -> None:
            step = max(1, CELLS // k)
            for at in range(0, len(rows), step):
                s = slice(at, at + step)
                before = base[:, s].T.copy()
                mine = np.arange(before.shape[0])
                before[mine, own_block[rows[s]]] -= amount[s]
                change = sign * (g(before + amount[s, None]) - g(before))
                first = np.flatnonzero(np.diff(rows[s], prepend=-1))
                out[rows[s][first]] += np.add.reduceat(change, first, axis=0)

        add(pairs // k_other, n.sum(axis=2)[:, pairs % k_other], sums.astype(float), 1)
        out[:, ~taken] = np.inf  # an empty block takes nobody, as in the DataFrame rounds
        add(cells // self.categories // k_other, n[:, cells // self.categories % k_other, cells % self.categories], x.astype(float), -1)
        return out

    def rounds(self, left: np.ndarray, right: np.ndarray, na: int, nb: int, frac, seed: int, trace, stop: Stop) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Yield both labelings at the start and after each round, one side after the other, as the DataFrame rounds do."""
        labels, sizes, digits = [left.copy(), right.copy()], (na, nb), [decimals(ids) for ids in self.ids]
        with trace.untimed():
            trace.add(self.entropy(*labels, na, nb))
        yield labels[0], labels[1]
        while not stop.reached(trace.entropies, trace.elapsed()):
            number, moved = len(trace.rows), 0
            share = frac(number) if callable(frac) else frac
            for side, name in enumerate("lr"):
                own, other = labels[side], labels[1 - side]
                chosen = np.flatnonzero(portable_numpy(seed, f"choose{name}", number, digits[side]) < share) if share < 1 else np.arange(len(own))
                if len(chosen):
                    best, _ = best_blocks(self.scores(side, own, other, sizes[side], sizes[1 - side], chosen), own[chosen])
                    moved += int((best != own[chosen]).sum())
                    labels[side] = own.copy()
                    labels[side][chosen] = best
            with trace.untimed():
                trace.add(self.entropy(*labels, na, nb), moved)
            yield labels[0], labels[1]


def brute_force(graph: Graph, k: int) -> tuple[float, tuple[int, ...]]:
    """The global optimum over all k^n labelings of a tiny graph."""
    if k**graph.n > 1_000_000:
        raise ValueError("too many labelings")
    return min((round(graph.entropy(np.array(lab), k), 12), lab) for lab in itertools.product(range(k), repeat=graph.n))
