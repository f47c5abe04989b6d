"""Forests as two tables: ``nodes(id)`` and ``edges(src, dst)`` with both directions."""

from canopy.model.forest import Forest, edges_from_pairs, from_parent, from_prefix, from_sequence, literal
from canopy.model.validate import ForestError, defects, validate_forest

__all__ = ["Forest", "ForestError", "defects", "edges_from_pairs", "from_parent", "from_prefix", "from_sequence", "literal", "validate_forest"]
