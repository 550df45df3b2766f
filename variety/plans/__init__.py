"""Whole experiments: what is planned from table to measure."""
