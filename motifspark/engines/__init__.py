"""Engines: all exact, all with the same results."""
