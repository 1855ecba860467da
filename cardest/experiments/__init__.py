"""Workloads, measures and the experiments that compare the estimators."""
