"""Driver-side plans: budgets, trees, training, baselines, measures, workloads."""
