"""Trials as segments, plan nodes, stages and chains: all relational."""
