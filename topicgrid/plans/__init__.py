"""The published workloads on the given tables: queries, their SQL, and experiments."""
