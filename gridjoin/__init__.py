"""Multiway natural joins with a bounded load on every worker, on Spark DataFrames."""
