"""Spark-native subgraph matching with packed matches, extension reuse and pruning."""
