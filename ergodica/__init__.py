"""Stationary distributions of Markov chains, and what a user of them needs, on Spark DataFrames."""

__version__ = "0.1.0"
