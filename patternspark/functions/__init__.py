"""Column functions and table functions on itemset masks."""
