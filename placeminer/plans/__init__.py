"""Discovery runs: loops, budgets, configuration, supervision, experiments."""
