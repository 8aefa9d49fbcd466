"""Clustering of row- and column-partitioned tables on Spark, with the operators around it."""
