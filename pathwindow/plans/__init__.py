"""Prepared graphs and the round loop."""
