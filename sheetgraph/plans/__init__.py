"""Workloads: mess patterns, their truth, and the experiments over them."""
