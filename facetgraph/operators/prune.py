"""Pruning of one candidate list, nearest first."""

from __future__ import annotations

from collections.abc import Callable, Sequence

import numpy as np


def two_hop(candidates: Sequence[int], lists: Callable[[int], Sequence[int]], m_beta: int, cap: int) -> list[int]:
    """Predicate-agnostic compression.

    The nearest ``m_beta`` stay. A later candidate is dropped when a kept one already leads to it, otherwise it
    stays and its own list counts as reached; the walk ends when reached and kept together pass ``cap``.
    """
    kept = list(candidates[:m_beta])
    reached: set[int] = set()
    for c in candidates[m_beta:]:
        if c in reached:
            continue
        kept.append(c)
        reached.update(lists(c))
        if len(reached) + len(kept) > cap:
            break
    return kept


def rng(candidates: Sequence[int], dist_to_v: Sequence[float], pairwise: Callable[[int, list[int]], np.ndarray], most: int, alpha: float = 1.0) -> list[int]:
    """Relative-neighbour pruning: a candidate nearer to a kept one than to v goes. One call of ``pairwise`` for each kept one."""
    kept: list[int] = []
    nodes, far = list(candidates), np.asarray(dist_to_v, np.float64)
    beaten = np.zeros(len(nodes), bool)
    for i, c in enumerate(nodes):
        if beaten[i]:
            continue
        kept.append(c)
        if len(kept) >= most or i + 1 == len(nodes):
            break
        beaten[i + 1 :] |= pairwise(c, nodes[i + 1 :]) * alpha < far[i + 1 :]
    return kept


def rng_labelled(candidates, dist_to_v, pairwise, most: int, labels: np.ndarray | None, own, alpha: float = 1.0) -> list[int]:
    """As ``rng``; with labels, only a kept node that carries the label v and the candidate share may remove the candidate."""
    kept: list[int] = []
    for c, d in zip(candidates, dist_to_v):
        if len(kept) >= most:
            break
        rivals = kept if labels is None else ([a for a in kept if labels[a] == own] if labels[c] == own else kept)
        if rivals and bool((pairwise(c, rivals) * alpha < d).any()):
            continue
        kept.append(c)
    return kept
