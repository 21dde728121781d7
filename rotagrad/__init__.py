"""Rotated, straggler-tolerant linear regression on Spark."""
