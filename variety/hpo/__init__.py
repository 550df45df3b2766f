"""Hyperparameter search: spaces, strategies, and executors that fill one ledger."""
