"""Exact spatial range queries over Z-order intervals, on Spark."""
