"""Spark-native motif counting by colour coding, with the tables, measures and baselines around it."""
