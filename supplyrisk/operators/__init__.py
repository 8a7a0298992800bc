"""Operators over build histories: graph, propagation, verdicts, baselines, measures."""
