"""Blockmodel graph partitioning on Spark."""
