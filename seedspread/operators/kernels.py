"""Diffusions on a graph that fits one task, as array programs; the DataFrame forms are their twins.

All functions take a ``Ball``: sorted vertex ids, true degrees and neighbour positions. A vertex whose
neighbours are not in the ball has no list; pushing from it raises ``Escaped`` so the caller can fetch more.
"""

from __future__ import annotations

import heapq
import math
from collections import deque
from dataclasses import dataclass

import numpy as np


class Escaped(Exception):
    """Mass reached a vertex whose neighbours are outside the ball."""


@dataclass
class Ball:
    ids: np.ndarray
    deg: np.ndarray
    start: np.ndarray
    to: np.ndarray

    @classmethod
    def of(cls, src: np.ndarray, dst: np.ndarray, deg_src: np.ndarray, deg_dst: np.ndarray) -> Ball:
        """From directed edges with the degrees of both ends."""
        ids, first = np.unique(np.concatenate([src, dst]), return_index=True)
        deg = np.concatenate([deg_src, deg_dst])[first].astype(np.int64)
        s, d = np.searchsorted(ids, src), np.searchsorted(ids, dst)
        order = np.lexsort((d, s))
        start = np.concatenate([[0], np.cumsum(np.bincount(s, minlength=len(ids)))])
        return cls(ids, deg, start, d[order])

    def place(self, v: int) -> int:
        k = int(np.searchsorted(self.ids, v))
        return k if k < len(self.ids) and self.ids[k] == v else -1

    def spread(self, members: np.ndarray, value: np.ndarray) -> np.ndarray:
        """Sum over members of ``value`` sent to each neighbour, as an array over the ball."""
        counts = self.start[members + 1] - self.start[members]
        if (counts != self.deg[members]).any():
            raise Escaped
        at = np.repeat(self.start[members] - np.concatenate([[0], np.cumsum(counts)[:-1]]), counts) + np.arange(counts.sum())
        return np.bincount(self.to[at], np.repeat(value, counts), len(self.ids))

    def neighbours(self, v: int) -> np.ndarray:
        if self.start[v + 1] - self.start[v] != self.deg[v]:
            raise Escaped
        return self.to[self.start[v] : self.start[v + 1]]


@dataclass
class Outcome:
    p: np.ndarray
    r: np.ndarray
    rounds: list  # (frontier, edges, mass of p, mass of r) of each round


def _seeded(ball: Ball, seeds: list[tuple[int, float]]) -> np.ndarray:
    x = np.zeros(len(ball.ids))
    for v, w in seeds:
        if (k := ball.place(v)) >= 0:
            x[k] += w
    return x


def coefficients(rule: str, alpha: float) -> tuple[float, float, float]:
    """(share kept in p, share sent to all neighbours together, share left as residual) of a push."""
    if rule == "lazy":
        return alpha, (1 - alpha) / 2, (1 - alpha) / 2
    if rule == "aggressive":
        return 2 * alpha / (1 + alpha), (1 - alpha) / (1 + alpha), 0.0
    raise ValueError(f"no push rule {rule!r}")


def push_bulk(ball, seeds, alpha, eps, rule="aggressive", beta=1.0, force_seed=True, max_rounds=100_000, blocks=1) -> Outcome:
    """All qualifying vertices of a round push at once; ``beta`` limits a round to the top share by r / deg."""
    gain, send, stay = coefficients(rule, alpha)
    p, r, rounds = np.zeros(len(ball.ids)), _seeded(ball, seeds), []
    forced = r > 0 if force_seed else np.zeros(len(r), bool)
    while len(rounds) < max_rounds:
        active = np.flatnonzero(((r >= eps * ball.deg) & (r > 0)) | forced)
        if len(active) == 0:
            break
        if beta < 1:
            ratio = np.round(r[active] / ball.deg[active], 12)
            active = active[np.lexsort((ball.ids[active], -ratio))][: math.ceil(beta * len(active))]
        forced = np.zeros(len(r), bool)
        frontier = edges = 0
        for b in range(blocks):
            mine = active if blocks == 1 else active[ball.ids[active] % blocks == b]
            value = r[mine].copy()
            p[mine] += gain * value
            r[mine] -= (1 - stay) * value if stay else value
            r += ball.spread(mine, send * value / ball.deg[mine])
            frontier += len(mine)
            edges += int(ball.deg[mine].sum())
        rounds.append((frontier, edges, float(p.sum()), float(r.sum())))
    return Outcome(p, r, rounds)


def push_queue(ball, seeds, alpha, eps, rule="aggressive", priority=False) -> Outcome:
    """One vertex at a time from a queue, or from a heap keyed by r / deg at insertion; each is pushed until it is under."""
    gain, send, stay = coefficients(rule, alpha)
    p, r = np.zeros(len(ball.ids)), _seeded(ball, seeds)
    held = deque() if not priority else []
    inside = np.zeros(len(r), bool)

    def add(v):
        if not inside[v]:
            inside[v] = True
            if priority:
                heapq.heappush(held, (-r[v] / ball.deg[v], v))
            else:
                held.append(v)

    for v in np.flatnonzero(r >= np.maximum(eps * ball.deg, 1e-300)):
        add(int(v))
    pushes = edges = 0
    while held:
        v = heapq.heappop(held)[1] if priority else held.popleft()
        inside[v] = False
        near = ball.neighbours(v)
        while r[v] >= eps * ball.deg[v] and r[v] > 0:
            value = r[v]
            p[v] += gain * value
            r[v] = stay * value
            r[near] += send * value / ball.deg[v]
            pushes += 1
            edges += len(near)
        for w in near[r[near] >= eps * ball.deg[near]]:
            add(int(w))
    return Outcome(p, r, [(pushes, edges, float(p.sum()), float(r.sum()))])


def walk_bulk(ball, seeds, steps, eps, one_by_one=False) -> Outcome:
    """Truncated lazy walk; the vector before the first one in which no vertex qualifies."""
    p, rounds = _seeded(ball, seeds), []
    for _ in range(steps):
        active = np.flatnonzero((p >= eps * ball.deg) & (p > 0)) if rounds else np.flatnonzero(p > 0)
        new = np.zeros(len(p))
        if one_by_one:
            for v in active:
                new[v] += p[v] / 2
                for w in ball.neighbours(v):
                    new[w] += p[v] / 2 / ball.deg[v]
        else:
            new[active] = p[active] / 2
            new += ball.spread(active, p[active] / 2 / ball.deg[active])
        rounds.append((len(active), int(ball.deg[active].sum()), float(new.sum()), 0.0))
        if not ((new >= eps * ball.deg) & (new > 0)).any():
            break
        p = new
    return Outcome(p, np.zeros(len(p)), rounds)


def psi(degree: int, t: float) -> list[float]:
    """Tail weights of the Taylor levels: psi_N = 1, psi_k = 1 + t / (k + 1) psi_{k+1}."""
    out = [1.0] * (degree + 1)
    for k in range(degree - 1, -1, -1):
        out[k] = 1 + t / (k + 1) * out[k + 1]
    return out


def level_floor(level: int, t: float, degree: int, eps: float, threshold: str, weights: list[float]) -> float:
    """Residual per degree at which an entry of the level is worth spreading."""
    return math.exp(t if threshold == "scaled" else -t) * eps / (2 * degree * weights[level])


def last_share(t: float, degree: int, last_level: str) -> float:
    return 1.0 if last_level == "bare" else t / degree


def heat_bulk(ball, seeds, t, degree, eps, threshold="scaled", last_level="bare") -> Outcome:
    """Taylor levels of the heat kernel, a whole level at a time; the result is e^t times the kernel."""
    weights, r, p, rounds = psi(degree, t), _seeded(ball, seeds), np.zeros(len(ball.ids)), []
    active = np.flatnonzero(r > 0)
    for j in range(degree):
        if len(active) == 0:
            break
        value = r[active]
        p[active] += value
        rounds.append((len(active), int(ball.deg[active].sum()), float(p.sum()), float(r.sum())))
        if j + 1 == degree:
            p += ball.spread(active, last_share(t, degree, last_level) * value / ball.deg[active])
            break
        r = ball.spread(active, t * value / ((j + 1) * ball.deg[active]))
        active = np.flatnonzero((r >= level_floor(j + 1, t, degree, eps, threshold, weights) * ball.deg) & (r > 0))
    return Outcome(p, r, rounds)


def heat_queue(ball, seeds, t, degree, eps, threshold="scaled", last_level="bare") -> Outcome:
    """The same by a queue of (vertex, level) entries, each enqueued when it crosses its level's floor."""
    weights, p = psi(degree, t), np.zeros(len(ball.ids))
    r: dict[tuple[int, int], float] = {}
    queue: deque[tuple[int, int]] = deque()
    for v in np.flatnonzero(_seeded(ball, seeds)):
        r[(int(v), 0)] = _seeded(ball, seeds)[v]
        queue.append((int(v), 0))
    work = edges = 0
    while queue:
        v, j = queue.popleft()
        value = r[(v, j)]
        p[v] += value
        near = ball.neighbours(v)
        work, edges = work + 1, edges + len(near)
        if j + 1 == degree:
            p[near] += last_share(t, degree, last_level) * value / ball.deg[v]
            continue
        mass, floor = t * value / ((j + 1) * ball.deg[v]), level_floor(j + 1, t, degree, eps, threshold, weights)
        for w in near:
            key = (int(w), j + 1)
            before = r.get(key, 0.0)
            r[key] = before + mass
            if before < floor * ball.deg[w] <= before + mass:
                queue.append(key)
    return Outcome(p, np.zeros(len(p)), [(work, edges, float(p.sum()), 0.0)])


def length_cdf(t: float, longest: int, overflow: str = "clamp") -> list[float]:
    """Cumulative chances of walk lengths 0..longest; the tail is clamped to the longest or renormalised away."""
    terms = [math.exp(-t) * t**k / math.factorial(k) for k in range(longest + 1)]
    total = np.cumsum(terms)
    if overflow == "clamp":
        total[-1] = 1.0
    elif overflow == "renormalize":
        total = total / total[-1]
    else:
        raise ValueError(f"no overflow rule {overflow!r}")
    return [float(x) for x in total]


def walks_one_by_one(ball, seeds, t, longest, n_walks, seed=1, overflow="clamp", run=0) -> Outcome:
    """Random walks of Poisson length, one after another; p is the share of walks that end at each vertex.

    Starts are drawn by weight among the seeds in the ball; each run has a random stream of its own.
    """
    rng, cdf, p = np.random.default_rng([seed, run & 0xFFFFFFFF]), np.array(length_cdf(t, longest, overflow)), np.zeros(len(ball.ids))
    weight = _seeded(ball, seeds)
    places = np.flatnonzero(weight > 0)
    if len(places) == 0:
        return Outcome(p, p.copy(), [])
    starts = rng.choice(places, n_walks, p=weight[places] / weight[places].sum())
    for v in starts:
        for _ in range(int(np.searchsorted(cdf, rng.random()))):
            near = ball.neighbours(v)
            v = int(near[rng.integers(len(near))])
        p[v] += 1
    return Outcome(p / n_walks, np.zeros(len(p)), [(n_walks, 0, 1.0, 0.0)])


def power_iteration(ball, seeds, alpha, tol, max_rounds) -> Outcome:
    """Fixed point of teleport with ``alpha`` and a lazy step otherwise, by repetition over all vertices."""
    start = _seeded(ball, seeds)
    everyone, x = np.arange(len(ball.ids)), start
    for _ in range(max_rounds):
        moved = ball.spread(everyone, x / np.maximum(ball.deg, 1))
        following = alpha * start + (1 - alpha) * (x + moved) / 2
        change, x = np.abs(following - x).sum(), following
        if change < tol:
            break
    return Outcome(x, np.zeros(len(x)), [])


def sweep_order(ids: np.ndarray, p: np.ndarray, deg: np.ndarray) -> np.ndarray:
    """Support of p by p / deg, largest first; ties by id."""
    held = np.flatnonzero(p > 0)
    return held[np.lexsort((ids[held], -np.round(p[held] / deg[held], 12)))]


def sweep_one_by_one(ball: Ball, p: np.ndarray, total: int) -> list[tuple[int, int, int, int, float | None]]:
    """(rank, v, volume, cut, conductance) of every prefix, inserting one vertex after another."""
    inside, vol, cut, out = np.zeros(len(ball.ids), bool), 0, 0, []
    for rank, v in enumerate(sweep_order(ball.ids, p, ball.deg), 1):
        near = ball.neighbours(v)
        met = int(inside[near].sum())
        inside[v] = True
        vol += int(ball.deg[v])
        cut += int(ball.deg[v]) - 2 * met
        low = min(vol, total - vol)
        out.append((rank, int(ball.ids[v]), vol, cut, cut / low if low > 0 else None))
    return out
