"""Constraint-based itemset mining on Spark DataFrames, and (in ``llm``) training-data operators."""
