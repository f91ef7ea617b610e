"""Cost, robustness, recovery and interpretability measures."""
