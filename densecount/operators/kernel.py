"""The blended estimator for one unpacked sketch."""

from __future__ import annotations

import numpy as np

from ..plans.estimate import COMPONENTS, BlendSpec
from . import tensor


def components(z: np.ndarray, history: np.ndarray, registers: int, floor: int, blend: BlendSpec = BlendSpec()) -> dict[str, float]:
    """Every estimator; 0 for an empty sketch, and for components without a valid tier."""
    z, history = np.asarray(z, np.int64), np.asarray(history, np.int64)
    if not (z >= 0).any():
        return dict.fromkeys(COMPONENTS, 0.0)
    out = tensor.components(tensor.histogram(z, history)[None], registers, blend)
    return {c: float(np.nan_to_num(out[c][0])) for c in COMPONENTS}


def hybrid_of(z: np.ndarray, history: np.ndarray, registers: int, floor: int) -> float:
    return components(z, history, registers, floor)["hybrid"]
