"""Tasks, orders, samples, folds, parallel schemes, measures and baselines."""
