"""Workloads and relational plans, and checks of physical plans."""
