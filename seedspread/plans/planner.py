"""Choice of execution mode from the methods' a-priori work bounds."""

from __future__ import annotations

import math

#: Edges up to which a ball is handed to one task.
IN_TASK_EDGES = 5_000_000


def work_bound(method: str, **p: float) -> float:
    """Edges a run may touch at most (up to the constant): independent of the size of the graph.

    walk T / eps; push 1 / (alpha eps); heat N² + N e^t / eps; walks n_walks K; sweep is N log N + vol and needs its input.
    """
    if method == "walk":
        return p["T"] / p["eps"] if p["eps"] > 0 else math.inf
    if method == "push":
        return 1 / (p["alpha"] * p["eps"])
    if method == "heat":
        return p["N"] ** 2 + p["N"] * math.exp(p["t"]) / p["eps"]
    if method == "heat_walks":
        return p["n_walks"] * p["K"]
    if method == "sweep":
        return p["support"] * math.log2(max(2, p["support"])) + p["vol"]
    raise ValueError(f"no method {method!r}")


def depth_proxy(rounds: list[dict]) -> float:
    """Rounds weighted by the logarithm of their size: the parallel depth of the cost model."""
    return sum(math.log2(2 + r["edges"]) for r in rounds)


def brent_time(work: float, depth: float, cores: int) -> float:
    """Running time W / P + D of the cost model."""
    return work / cores + depth


def choose(bound: float, volume: int) -> str:
    """``in_task`` where either the run or the whole graph is small, else rounds of DataFrames."""
    return "in_task" if min(bound, volume) <= IN_TASK_EDGES else "frames"


def default_degree(t: float, eps: float) -> int:
    """Practical upper limit of the Taylor degree."""
    return math.ceil(2 * t * math.log(1 / eps))
