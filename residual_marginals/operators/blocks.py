"""Array kernels: every step works on whole slices of one numpy array per marginal."""

from __future__ import annotations

from functools import reduce

import numpy as np


def axis_sum(a: np.ndarray, axis: int) -> np.ndarray:
    return a.sum(axis=axis, keepdims=True)


def _slice(a: np.ndarray, axis: int, part: slice) -> np.ndarray:
    return a[(slice(None),) * axis + (part,)]


def axis_sub(a: np.ndarray, axis: int) -> np.ndarray:
    """Drop slice 0 after taking it from the others."""
    return _slice(a, axis, slice(1, None)) - _slice(a, axis, slice(0, 1))


def axis_center(a: np.ndarray, axis: int) -> np.ndarray:
    """Put a zero slice in front, then take the axis mean from all; written in one pass."""
    shape = list(a.shape)
    shape[axis] += 1
    out = np.empty(shape)
    front = _slice(out, axis, slice(0, 1))
    np.divide(a.sum(axis=axis, keepdims=True), -shape[axis], out=front)
    np.add(a, front, out=_slice(out, axis, slice(1, None)))
    return out


def axis_smear(a: np.ndarray, axis: int, k: int) -> np.ndarray:
    """Spread a length-1 axis evenly over k slices."""
    return np.repeat(a / k, k, axis=axis)


def axis_sub_mapped(a: np.ndarray, axis: int) -> np.ndarray:
    """The difference vector by vector instead of by whole slices; for comparison only."""
    return np.apply_along_axis(lambda v: v[1:] - v[0], axis, a)


def decompose(marginal: np.ndarray, keep: tuple[int, ...]) -> np.ndarray:
    """Residual over the kept axes (summed axes stay with length 1)."""
    for axis in range(marginal.ndim):
        if axis not in keep:
            marginal = axis_sum(marginal, axis)
    for axis in keep:
        marginal = axis_sub(marginal, axis)
    return marginal


def reconstruct(residual: np.ndarray, keep: tuple[int, ...], shape: tuple[int, ...]) -> np.ndarray:
    """Component of a marginal of the given shape; ``residual`` has length 1 on the axes not kept."""
    for axis in keep:
        residual = axis_center(residual, axis)
    for axis, n in enumerate(shape):
        if axis not in keep:
            residual = axis_smear(residual, axis, n)
    return residual


def to_coords(marginal: np.ndarray) -> np.ndarray:
    """All residuals in place: per axis, slice 0 holds the total and slice k the difference to slice 0."""
    for axis in range(marginal.ndim):
        out = np.empty(marginal.shape)
        marginal.sum(axis=axis, keepdims=True, out=_slice(out, axis, slice(0, 1)))
        np.subtract(_slice(marginal, axis, slice(1, None)), _slice(marginal, axis, slice(0, 1)), out=_slice(out, axis, slice(1, None)))
        marginal = out
    return marginal


def from_coords(coords: np.ndarray) -> np.ndarray:
    """Inverse of ``to_coords``."""
    for axis, n in enumerate(coords.shape):
        out = np.empty(coords.shape)
        rest, front = _slice(coords, axis, slice(1, None)), _slice(out, axis, slice(0, 1))
        np.divide(_slice(coords, axis, slice(0, 1)) - rest.sum(axis=axis, keepdims=True), n, out=front)
        np.add(rest, front, out=_slice(out, axis, slice(1, None)))
        coords = out
    return coords


def support_slices(shape: tuple[int, ...], keep: tuple[int, ...]) -> tuple[slice, ...]:
    """Where residual coordinates of one residual stand: index 0 on the other axes."""
    return tuple(slice(1, None) if axis in keep else slice(0, 1) for axis in range(len(shape)))


def difference_matrix(n: int) -> np.ndarray:
    return np.hstack([-np.ones((n - 1, 1)), np.eye(n - 1)])


def center_matrix(n: int) -> np.ndarray:
    wide = np.vstack([np.zeros((1, n - 1)), np.eye(n - 1)])
    return wide - wide.mean(axis=0, keepdims=True)


def factors(shape: tuple[int, ...], keep: tuple[int, ...], inverse: bool = False) -> list[np.ndarray]:
    """Per-axis factors of the explicit transform."""
    if inverse:
        return [center_matrix(n) if axis in keep else np.full((n, 1), 1 / n) for axis, n in enumerate(shape)]
    return [difference_matrix(n) if axis in keep else np.ones((1, n)) for axis, n in enumerate(shape)]


def kron_by_axis(a: np.ndarray, parts: list[np.ndarray]) -> np.ndarray:
    """Explicit baseline: one matrix product per axis on the reshaped vector."""
    for axis, m in enumerate(parts):
        moved = np.moveaxis(a, axis, 0)
        product = m @ moved.reshape(moved.shape[0], -1)
        a = np.moveaxis(product.reshape(m.shape[0], *moved.shape[1:]), 0, axis)
    return a


def kron_full(a: np.ndarray, parts: list[np.ndarray]) -> np.ndarray:
    """Test oracle: the dense matrix times the flattened vector."""
    whole = reduce(np.kron, parts, np.ones((1, 1)))
    return (whole @ a.ravel()).reshape([m.shape[0] for m in parts])


def center_all(residual: np.ndarray) -> np.ndarray:
    for axis in range(residual.ndim):
        residual = axis_center(residual, axis)
    return residual


def component_direct(marginal: np.ndarray, keep: tuple[int, ...]) -> np.ndarray:
    """Component of a marginal straight from axis means."""
    for axis in range(marginal.ndim):
        mean = marginal.mean(axis=axis, keepdims=True)
        marginal = marginal - mean if axis in keep else np.broadcast_to(mean, marginal.shape)
    return np.array(marginal)
