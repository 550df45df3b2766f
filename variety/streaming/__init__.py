"""Streams over the event table, each with a batch twin."""
