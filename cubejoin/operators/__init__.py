"""Physical operators: index, kernel, routing, executors, baselines, factorised counts."""
