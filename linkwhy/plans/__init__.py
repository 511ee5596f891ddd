"""Compositions of operators: engine, presets, workloads, work counters."""
