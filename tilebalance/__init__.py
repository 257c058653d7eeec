"""Distributing and rebalancing records with two coordinates over owners, by tiles, on Spark."""
