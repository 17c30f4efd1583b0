"""Routing, the one exchange, local evaluation and baselines."""
