"""Balanced pairwise matching inside skewed blocks, as Spark DataFrame plans."""
