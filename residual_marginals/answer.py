"""Questions to a release: counts under a predicate, conditional distributions, sub-marginals."""

from __future__ import annotations

import math

import numpy as np

from residual_marginals.mechanisms.adaptive import Release
from residual_marginals.plans.planner import expected_mse


def covering(release: Release, mask: int) -> int:
    fits = [g for g in release.state.sets if g & mask == mask]
    if not fits:
        raise ValueError("the attributes must lie in one released marginal")
    return min(fits, key=release.domain.size)


def marginal(release: Release, names: list[str]) -> np.ndarray:
    """Sub-marginal by summing a released one."""
    mask = release.domain.mask(names)
    gamma = covering(release, mask)
    drop = tuple(k for k, i in enumerate(release.domain.axes(gamma)) if not mask >> i & 1)
    return release.state.marginals[gamma].sum(axis=drop)


def answer_count(release: Release, predicate: dict[str, set[int]]) -> tuple[float, float]:
    """(count, standard deviation of its noise at most) of rows whose codes lie in the given sets."""
    mask = release.domain.mask(predicate)
    table = marginal(release, list(predicate))
    for k, i in enumerate(release.domain.axes(mask)):
        table = np.take(table, sorted(predicate[release.domain.attributes[i].name]), axis=k)
    sd = math.sqrt(expected_mse(mask, release.domain, release.state.precision))
    return float(table.sum()), sd * table.size


def conditional(release: Release, target: str, given: dict[str, int]) -> np.ndarray:
    """Distribution of one attribute given codes of others; negative estimates count as zero."""
    names = [target, *given]
    mask = release.domain.mask(names)
    table = marginal(release, names)
    for k, i in reversed(list(enumerate(release.domain.axes(mask)))):
        name = release.domain.attributes[i].name
        if name != target:
            table = np.take(table, given[name], axis=k)
    table = np.maximum(table, 0)
    return table / table.sum() if table.sum() > 0 else np.full(table.shape, 1 / table.size)
