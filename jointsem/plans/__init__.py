"""Methods as staged plans: joint tasks, budget cascades and baselines."""
