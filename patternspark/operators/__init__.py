"""Operators of itemset mining."""
