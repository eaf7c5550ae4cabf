"""Recommendation to ad-hoc groups, as Spark DataFrame work with Arrow kernels."""
