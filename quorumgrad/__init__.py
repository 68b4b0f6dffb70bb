"""Distributed first-order optimization under stragglers and staleness, on Spark."""
