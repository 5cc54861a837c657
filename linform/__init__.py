"""Aggregate queries whose atoms take linear combinations of variables, planned exactly and run on Spark."""
