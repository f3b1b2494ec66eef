"""Measures, theory, workloads and physical choices."""
