"""Baseline compressors, rebuilt from public knowledge of their kinds, with the knobs of the experiments."""
