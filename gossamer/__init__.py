"""Gossamer: stochastic descent on Spark, with windowed gossip between workers."""

__version__ = "0.1.0"
