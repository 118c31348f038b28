"""Workloads kept up to date from streams of events."""
