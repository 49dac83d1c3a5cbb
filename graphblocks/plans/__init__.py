"""Whole methods: multilevel partitioning, baselines, evaluation, workloads, registered queries."""
