"""Tasks, jobs, cost models and what-if plans."""
