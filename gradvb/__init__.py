"""Approximate Bayesian inference on Spark tables by stochastic natural-gradient ascent."""
