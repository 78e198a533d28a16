"""Constraints on paths, as running summaries with a check at every hop."""
