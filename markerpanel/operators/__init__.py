"""Commands, robustness studies, baselines and measures."""
