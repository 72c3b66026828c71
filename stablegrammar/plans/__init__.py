"""Measures, baselines, workloads and reports."""
