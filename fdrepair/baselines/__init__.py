"""Repair algorithms to compare with; each gives a RepairResult or the repaired table."""

from .conflict_cover import conflict_cover
from .exhaustive import exact_chase, exact_minimal, exact_pattern_preserving
from .majority import majority
from .sampling import best_of, sampling
from .similarity import similarity

__all__ = ["best_of", "conflict_cover", "exact_chase", "exact_minimal", "exact_pattern_preserving", "majority", "sampling", "similarity"]
