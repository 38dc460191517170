"""Methods: objective, half-steps, line search, conjugate recurrence, ranking, synthetic data, baselines."""
