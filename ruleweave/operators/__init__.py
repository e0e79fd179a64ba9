"""Physical operators: fixpoints, baselines, the local evaluator, key discovery and relational helpers."""
