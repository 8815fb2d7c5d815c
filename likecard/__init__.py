"""Cardinality estimation for LIKE patterns on Spark: layered filters over
count tiers, with a guaranteed ratio error for patterns that match."""
