"""Exact sliding medians and other sliding order statistics on Spark.

Filtering with a window of k values is no harder than sorting blocks of k
values: a linear pass over neighbouring sorted blocks gives every window.
"""
