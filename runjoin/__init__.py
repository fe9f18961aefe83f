"""Summarise-then-expand n-way equi-joins for Spark."""
