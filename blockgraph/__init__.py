"""Iterative graph computation over block-partitioned tables, as Spark DataFrame plans."""
