"""Spark-native clustered-partition vector search.

Sub-packages: ``functions`` (vector expressions and kernels), ``sources`` (tables, derived vector
collections, index files), ``operators`` (clustering, search, batch, hybrid, updates, relational),
``plans`` (statistics, selectivity, planning, scratch storage), ``streaming`` (continuous ingestion).
"""
