"""Vertically partitioned gradient boosting over encrypted statistics, as Spark DataFrame plans."""
