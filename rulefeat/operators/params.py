"""Budgets from the shape of the data."""

from __future__ import annotations

import math
import warnings
from dataclasses import dataclass


@dataclass(frozen=True)
class Budgets:
    d_freq: int
    d_conf: int


def suggest(p: int, n_classes: int, scale: int = 5) -> Budgets:
    """Both grow as the root of the number of features; the frequent sets are that times the classes."""
    root = math.isqrt(p)
    return validate(Budgets(scale * n_classes * root, scale * root), n_classes)


def suggest_lean(p: int, scale: int = 1) -> Budgets:
    """The largest number of frequent sets whose square stays in the order of p, so that pair counting costs no more than the first pass."""
    root = max(1, scale * math.isqrt(p))
    return Budgets(root, root)


def validate(b: Budgets, n_classes: int) -> Budgets:
    """Warn where the frequent sets may hold fewer different antecedents than rules are asked for."""
    if b.d_conf > b.d_freq:
        raise ValueError("more rules than frequent sets")
    if b.d_freq < n_classes * b.d_conf:
        warnings.warn(f"d_freq / d_conf is below the {n_classes} classes: several rules may share an antecedent", stacklevel=2)
    return b
