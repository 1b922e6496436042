"""Collision-free numbering of large static key sets on Spark."""
