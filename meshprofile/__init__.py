"""Masked, decentralised clustering of load profiles on Spark."""
