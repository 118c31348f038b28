"""Balanced two-way partitioning of large sparse count matrices, and topic models learned on the resulting grid."""
