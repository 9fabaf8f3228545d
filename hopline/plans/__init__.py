"""The methods as DataFrame plans: distances, covers, shortcut sets, queries, baselines, checks."""
