"""The kNN service, the budgeted clusterers, exact baselines and measures."""
