"""Whole questions, workloads, and their costs."""
