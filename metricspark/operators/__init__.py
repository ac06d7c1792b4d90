"""The three-stage index, searches, updates, ablations and baselines."""
