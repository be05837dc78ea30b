"""How many shuffles, how many pairs, which physical plan."""

from __future__ import annotations

import math

from .variance import Components, equal_budget, var_complete, var_incomplete, var_repartitioned, var_repartitioned_incomplete


def pairs(estimator: str, n: int, m: int, workers: int = 1, rounds: int = 1, batch: int = 1) -> int:
    """Kernel evaluations of an estimator."""
    return {
        "complete": n * m,
        "incomplete": batch,
        "local": n * m // workers,
        "local_incomplete": workers * batch,
        "repartitioned": n * m * rounds // workers,
        "repartitioned_incomplete": workers * batch * rounds,
    }[estimator]


def rounds_for(c: Components, n: int, m: int, workers: int, ratio: float) -> int:
    """Fewest complete rounds whose variance is at most `ratio` (> 1) times the complete one's."""
    if ratio <= 1:
        raise ValueError("the ratio must be above one")
    excess = (workers - 1) * c.v0 / (n * m) / var_complete(c, n, m)
    return max(1, math.ceil(excess / (ratio - 1) - 1e-12))


def diagnose(c: Components, n: int, m: int, workers: int, threshold: float = 0.05) -> tuple[str, float]:
    """("shuffle", excess) where the pair effect is worth shuffles, else ("minority_limited", ..):
    the minority sample's own variance dominates and one round is enough."""
    excess = (workers - 1) * c.v0 / (n * m) / var_complete(c, n, m)
    return ("shuffle" if excess > threshold else "minority_limited"), excess


def frontier(c: Components, n: int, m: int, workers: int, rounds: tuple[int, ...], batches: tuple[int, ...]) -> list[tuple]:
    """(estimator, rounds, batch, pairs, variance) of a grid of plans, with the complete statistic and
    pairs drawn from all tuples (as many as each number of rounds evaluates) beside them."""
    out = [("complete", 0, 0, pairs("complete", n, m), var_complete(c, n, m))]
    out += [("incomplete", 0, 0, k, var_incomplete(c, n, m, k)) for k in (pairs("repartitioned", n, m, workers, t) for t in rounds)]
    out += [("repartitioned", t, 0, pairs("repartitioned", n, m, workers, t), var_repartitioned(c, n, m, workers, t)) for t in rounds]
    out += [
        ("repartitioned_incomplete", t, b, workers * b * t, var_repartitioned_incomplete(c, n, m, workers, t, b))
        for t in rounds
        for b in batches
    ]
    return out


def best_under_budget(c: Components, n: int, m: int, workers: int, most_pairs: int, most_moved: int) -> tuple[int, int, float]:
    """(rounds, batch, variance) of least variance within pairs and moved rows; batch 0 means all
    local pairs, which at equal pairs is never worse, so it is taken whenever one round fits."""
    rounds = max(1, most_moved // (n + m))
    local = n * m // workers
    if local <= most_pairs:
        t = max(1, min(rounds, most_pairs // local))
        return t, 0, var_repartitioned(c, n, m, workers, t)
    best = None
    for t in range(1, rounds + 1):
        b = most_pairs // (workers * t)
        if b < 1:
            break
        v = var_repartitioned_incomplete(c, n, m, workers, t, b)
        if best is None or v < best[2]:
            best = (t, b, v)
    if best is None:
        raise ValueError("the budget holds no pair for each worker")
    return best


def choose_plan(
    kernel_has_sorted_form: bool,
    n: int,
    m: int,
    workers: int,
    rounds: int,
    row_bytes: int = 24,
    broadcast_bytes: int = 64 << 20,
    shuffle_bytes: int = 1 << 40,
    pair_budget: int = 10**12,
) -> dict[str, str]:
    """Physical choices: complete without shuffle where the smaller sample fits a broadcast;
    sorted form before pairs; fused rounds while their copies fit the shuffle budget."""
    if kernel_has_sorted_form and min(n, m) * row_bytes <= broadcast_bytes:
        return {"estimator": "complete", "form": "broadcast_sorted", "execution": "no_shuffle"}
    execution = "fused" if rounds * (n + m) * row_bytes <= shuffle_bytes else "iterative"
    if kernel_has_sorted_form:
        return {"estimator": "repartitioned", "form": "sorted", "execution": execution}
    if n * m // workers * rounds <= pair_budget:
        return {"estimator": "repartitioned", "form": "pairs", "execution": execution}
    return {"estimator": "repartitioned_incomplete", "form": "draws", "execution": "inverse_permutation"}


def equal_budget_rounds(n: int, m: int, workers: int, rounds0: int, batch: int) -> float:
    return equal_budget(n, m, workers, rounds0, batch)


#: Iterations between shuffles of the learning methods to start from.
START_SHUFFLE_EVERY = 25
