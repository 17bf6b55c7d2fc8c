"""Frequent-itemset mining on vertical layouts, written for Spark."""
