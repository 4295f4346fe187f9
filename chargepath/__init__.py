"""Recharge-aware trip planning over road networks, for Spark."""
