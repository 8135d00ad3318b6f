"""Distributed block-sort text indexing on Spark."""
