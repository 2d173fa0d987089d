"""Selections, packing, the adaptive grid, baselines, maintenance and measures."""
