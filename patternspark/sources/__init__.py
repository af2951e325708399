"""Where itemset databases come from and go to."""
