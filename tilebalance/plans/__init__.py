"""Rebalancing policies, whole runs, and the registered queries."""
