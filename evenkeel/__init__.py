"""Exact distributed gradients that do not wait for slow workers, on Spark."""
