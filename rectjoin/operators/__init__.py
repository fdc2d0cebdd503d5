"""Methods, baselines and measures."""
