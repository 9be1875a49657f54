"""Behavioral-pattern mining on Spark: frequent, compact, maximal process-tree patterns of event logs."""
