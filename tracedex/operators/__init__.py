"""DataFrame operators: positions, pairs, validation, explanation, statistics, baselines, measures, workloads."""
