"""Distributed operators: paths, unions, matching, measures, ranking."""
