"""Which exact form and miner to run."""

from __future__ import annotations

from math import comb


def choose_miner(n_attributes: int, max_len: int, limit: int = 256) -> str:
    """One pass over all subsets while a tuple has few of them, else level by level."""
    subsets = sum(comb(n_attributes, k) for k in range(1, min(max_len, n_attributes) + 1))
    return "cube" if subsets <= limit else "levelwise"


def costs(n_elements: int, n_rules: int, n_attributes: int, tau: int) -> dict[str, int]:
    """Rows each form touches, up to a constant."""
    return {
        "decomposed": n_rules * tau,
        "multi": n_rules * (tau * tau + n_attributes + n_elements * tau),
        "sequential": n_elements * n_rules * tau * (tau + 1),
    }
