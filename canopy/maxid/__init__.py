"""Largest id of every tree by balanced doubling."""

from canopy.maxid.core import absorb_light, classify_exact, contract_paths, fold, max_id, unfold

__all__ = ["absorb_light", "classify_exact", "contract_paths", "fold", "max_id", "unfold"]
