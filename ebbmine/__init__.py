"""Frequent-itemset engine for Spark: baskets as bit masks, counted chunk by chunk."""
