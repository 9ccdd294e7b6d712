"""Constrained sequence mining on Spark."""
