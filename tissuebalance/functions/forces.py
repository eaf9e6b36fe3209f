"""Strength of the force between two elements, on arrays; distances are in cutoffs."""

from __future__ import annotations

import numpy as np

#: Shape only, in units of the cutoff: strengths and ranges of repulsion and attraction.
INTRA = (0.3, 0.1, 0.2, 0.4)
INTER = (0.3, 0.04, 0.2, 0.4)
OTHER_TYPE = 0.5
MEMBRANE = (0.05, 1.0)


def strength(r: np.ndarray, u: float, v: np.ndarray | float, near: float, far: float) -> np.ndarray:
    """Repulsion less attraction along the separation."""
    return u / near * np.exp(-r / near) - v / far * np.exp(-r / far)


def within_cell(r: np.ndarray) -> np.ndarray:
    return strength(r, *INTRA)


def between_cells(r: np.ndarray, same_type: np.ndarray) -> np.ndarray:
    return strength(r, INTER[0], np.where(same_type, INTER[1], INTER[1] * OTHER_TYPE), *INTER[2:])


def pair_strength(r: np.ndarray, same_cell: np.ndarray, same_type: np.ndarray) -> np.ndarray:
    return np.where(same_cell, within_cell(r), between_cells(r, same_type))


def membrane_pull(z: np.ndarray, floor: float, cutoff: float) -> np.ndarray:
    g, reach = MEMBRANE
    return -g / reach * np.exp(-(z - floor) / (reach * cutoff))
