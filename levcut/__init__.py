"""Leverage scores on matrices and cut probes on graphs, as Spark plans."""
