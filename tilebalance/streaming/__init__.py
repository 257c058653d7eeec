"""The continuous analogue: windows of loads, stateful owners, rebalancing by micro-batch."""
